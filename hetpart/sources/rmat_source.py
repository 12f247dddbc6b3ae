"""R-MAT graphs as a batch data source: spark.read.format("hetpart_rmat").option("scale", 14).

Partitions are ranges of edge numbers; the draws are those of graphs.rmat, so both give
the same graph. Edges are neither canonical nor distinct here: graphs.as_edges makes them so."""

from __future__ import annotations

import numpy as np
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from ..functions.columns import MASK, MIX
from .graphs import EDGES_PER_VERTEX, QUADRANTS


def mixed(x: np.ndarray, salt: int) -> np.ndarray:
    x = (x * MIX[0] + salt * 97531) & MASK
    x = ((x ^ (x >> 15)) * MIX[1]) & MASK
    x = ((x ^ (x >> 13)) * MIX[2]) & MASK
    return x ^ (x >> 16)


def draw(first: int, last: int, scale: int, seed: int) -> tuple[np.ndarray, np.ndarray]:
    e = np.arange(first, last, dtype=np.int64)
    src, dst = np.zeros_like(e), np.zeros_like(e)
    a, b, c = QUADRANTS
    for level in range(scale):
        u = mixed(e, seed * 64 + level) % 1000
        src += (u >= a + b).astype(np.int64) << level
        dst += (((u >= a) & (u < a + b)) | (u >= a + b + c)).astype(np.int64) << level
    return src, dst


class Part(InputPartition):
    def __init__(self, first: int, last: int):
        self.first, self.last = first, last


class RmatReader(DataSourceReader):
    def __init__(self, options):
        self.scale, self.seed = int(options.get("scale", 10)), int(options.get("seed", 1))
        self.parts = int(options.get("partitions", 8))

    def partitions(self):
        n = EDGES_PER_VERTEX << self.scale
        cut = np.linspace(0, n, self.parts + 1).astype(np.int64).tolist()
        return [Part(a, b) for a, b in zip(cut[:-1], cut[1:], strict=True) if b > a]

    def read(self, part):
        import pyarrow as pa

        for a in range(part.first, part.last, 1 << 18):
            src, dst = draw(a, min(part.last, a + (1 << 18)), self.scale, self.seed)
            yield pa.RecordBatch.from_arrays([pa.array(src), pa.array(dst)], names=["src", "dst"])


class RmatSource(DataSource):
    @classmethod
    def name(cls):
        return "hetpart_rmat"

    def schema(self):
        return "src long, dst long"

    def reader(self, schema):
        return RmatReader(self.options)


def register(spark) -> None:
    spark.dataSource.register(RmatSource)
