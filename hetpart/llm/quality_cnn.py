"""A byte-level convolutional quality classifier in numpy.

A document is its UTF-8 bytes, all of them. Each byte has a learned vector; learned
filters span eight bytes, at every fourth byte. Their responses are max-pooled over
chunks of 256 bytes that overlap by 64 and together cover the document. The mean and
the maximum of the chunks' pooled responses give one probability.

Training is on the driver over a bounded sample: ``SAMPLE`` labelled rows of each class
(least hashes of their ids), of longer texts ``PIECES`` evenly spaced pieces of
``PIECE`` bytes, weighted back to the classes' shares. Labels are sampled before they
meet the documents, so texts aren't shuffled. Scoring is narrow and reads whole texts.

Defined results: null and empty texts are one empty chunk and get a score as any other;
without labels of both classes the score is the share of label 1 (0.5 without labels);
repeated rows each give a row; extra columns are left out.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import fold, picked, schema_of, table
from .textbuf import ragged, text_slices

STEP, SUB, CHUNK, HOP = 4, 16, 4, 3  # bytes a position, positions a strip, strips a chunk, strips between chunks
DIM, FILTERS = 8, 32
SAMPLE, PIECES, PIECE, EPOCHS, STEPS, BATCH = 1600, 8, 512, 14, 500, 64
THRESHOLD = 0.3


class Layout:
    """Documents laid out in strips of 64 bytes, an empty strip after each."""

    def __init__(self, data: np.ndarray, offsets: np.ndarray):
        size = np.diff(offsets)
        strips = np.maximum(1, -(-size // (STEP * SUB)))
        first = np.concatenate([[0], np.cumsum(strips + 1)])
        self.index = np.full(first[-1] * STEP * SUB, 256, np.int16)
        self.index[ragged(first[:-1] * STEP * SUB, size)] = data
        chunks = np.maximum(1, -(-(strips - CHUNK) // HOP) + 1)
        self.begin = np.concatenate([[0], np.cumsum(chunks)])[:-1]
        self.chunks = chunks
        self.doc = np.repeat(np.arange(len(size)), chunks)
        self.start = first[:-1][self.doc] + HOP * (np.arange(len(self.doc)) - self.begin[self.doc])
        self.end = np.minimum(self.start + CHUNK, (first[:-1] + strips)[self.doc])


class Net:
    def __init__(self, seed: int = 0):
        rng = np.random.default_rng(seed)
        draw = lambda *s, scale: (rng.standard_normal(s) * scale).astype(np.float32)
        self.p = {"emb": draw(257, DIM, scale=0.5), "near": draw(DIM * STEP, FILTERS, scale=0.18), "far": draw(DIM * STEP, FILTERS, scale=0.18), "bias": np.zeros(FILTERS, np.float32), "mean": draw(FILTERS, scale=0.1), "top": draw(FILTERS, scale=0.1), "out": np.zeros(1, np.float32)}
        self.p["emb"][256] = 0

    def strips(self, lay: Layout) -> tuple[np.ndarray, np.ndarray]:
        x = self.p["emb"][lay.index].reshape(-1, DIM * STEP)
        y = x @ self.p["near"]
        y[:-1] += (x @ self.p["far"])[1:]
        y += self.p["bias"]
        return x, y.reshape(-1, SUB, FILTERS)

    def pooled(self, lay: Layout, best: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Chunk responses, their mean and their maximum by document."""
        pairs = np.stack([lay.start, lay.end], 1).ravel()
        h = np.maximum.reduceat(np.vstack([best, best[:1]]), pairs, axis=0)[::2]
        return h, np.add.reduceat(h, lay.begin, axis=0) / lay.chunks[:, None], np.maximum.reduceat(h, lay.begin, axis=0)

    def scores(self, data: np.ndarray, offsets: np.ndarray) -> np.ndarray:
        out = []
        step = 256_000
        i, n = 0, len(offsets) - 1
        while i < n:  # small pieces stay in the cache
            j = min(n, max(i + 1, int(np.searchsorted(offsets, offsets[i] + step, "right")) - 1))
            lay = Layout(data[offsets[i] : offsets[j]], offsets[i : j + 1] - offsets[i])
            best = np.maximum(self.strips(lay)[1].max(1), 0)
            _, mean, top = self.pooled(lay, best)
            out.append(1 / (1 + np.exp(-np.clip(mean @ self.p["mean"] + top @ self.p["top"] + self.p["out"], -30, 30))))
            i = j
        return np.concatenate(out).astype(np.float64) if out else np.zeros(0)

    def gradient(self, lay: Layout, y: np.ndarray, w: np.ndarray) -> dict[str, np.ndarray]:
        p = self.p
        x, act = self.strips(lay)
        place = act.argmax(1)
        raw = np.take_along_axis(act, place[:, None], 1)[:, 0]
        best = np.maximum(raw, 0)
        h, mean, top = self.pooled(lay, best)
        z = mean @ p["mean"] + top @ p["top"] + p["out"]
        d = (1 / (1 + np.exp(-np.clip(z, -30, 30))) - y) * w / w.sum()
        dh = (d / lay.chunks)[lay.doc, None] * p["mean"][None]
        first = h == top[lay.doc]
        first = first / np.add.reduceat(first, lay.begin, axis=0, dtype=h.dtype)[lay.doc]  # equal chunks share
        dh = dh + first * d[lay.doc, None] * p["top"][None]
        dbest = np.zeros_like(best)
        for k in range(CHUNK):  # each chunk's response came from the strip that equals it
            s = np.minimum(lay.start + k, lay.end - 1)
            live = (lay.start + k < lay.end)[:, None] & (best[s] == h)
            np.add.at(dbest, s, np.where(live, dh, 0))
            dh = np.where(live, 0, dh)
        dbest *= raw > 0
        dact = np.zeros_like(act)
        np.put_along_axis(dact, place[:, None], dbest[:, None], 1)
        dy = dact.reshape(-1, FILTERS)
        dx = dy @ p["near"].T
        dx[1:] += dy[:-1] @ p["far"].T
        flat, at = dx.reshape(-1, DIM), lay.index
        emb = np.stack([np.bincount(at, flat[:, k], 257) for k in range(DIM)], 1)
        emb[256] = 0
        return {"emb": emb, "near": x.T @ dy, "far": x[1:].T @ dy[:-1], "bias": dy.sum(0), "mean": d @ mean, "top": d @ top, "out": d.sum(keepdims=True)}

    def fit(self, texts: list[bytes], y: np.ndarray, w: np.ndarray, rate: float = 0.006, seed: int = 1) -> None:
        epochs = max(EPOCHS, STEPS // -(-len(texts) // BATCH))
        rng = np.random.default_rng(seed)
        first, second, t = {k: np.zeros_like(v) for k, v in self.p.items()}, {k: np.zeros_like(v) for k, v in self.p.items()}, 0
        total = epochs * -(-len(texts) // BATCH)
        for _ in range(epochs):
            order = rng.permutation(len(texts))
            for a in range(0, len(order), BATCH):
                pick = order[a : a + BATCH]
                raw = [texts[i] for i in pick]
                lay = Layout(np.frombuffer(b"".join(raw), np.uint8), np.concatenate([[0], np.cumsum([len(r) for r in raw])]))
                t += 1
                speed = rate * (1 - t / (total + 1))
                for k, g in self.gradient(lay, y[pick], w[pick]).items():
                    g = g + 1e-4 * self.p[k]
                    first[k] = 0.9 * first[k] + 0.1 * g
                    second[k] = 0.99 * second[k] + 0.01 * g * g
                    self.p[k] = (self.p[k] - speed * (first[k] / (1 - 0.9**t)) / (np.sqrt(second[k] / (1 - 0.99**t)) + 1e-8)).astype(np.float32)


def train(docs: DataFrame, labels: DataFrame, key: str = "doc_id", text: str = "text", label: str = "quality", each: int = SAMPLE) -> Net | float:
    """A trained net, or the share of label 1 where only one class is labelled."""
    good = picked(labels, _k=key, _y=label).where("_k IS NOT NULL AND _y IS NOT NULL")
    share = {r[0]: r[1] for r in good.groupBy(F.col("_y").cast("int")).count().collect()}
    if not share.get(0) or not share.get(1):
        return float(share.get(1, 0) / sum(share.values())) if share else 0.5
    one = good.groupBy("_k").agg(F.max(F.col("_y").cast("int")).alias("_y"))
    part = [one.where(F.col("_y") == y).orderBy(F.xxhash64("_k"), "_k").limit(each) for y in (0, 1)]
    sample = F.broadcast(part[0].unionByName(part[1]))  # 2 * each rows at most
    raw, n = F.coalesce(F.col("_t"), F.lit("")).cast("binary"), F.octet_length(F.coalesce(F.col("_t"), F.lit("")))
    pieces = F.concat(*[F.substring(raw, (n * k / PIECES).cast("int") + 1, PIECE) for k in range(PIECES)])
    got = picked(docs, _k=key, _t=text).join(sample, "_k").select(F.col("_k").cast("string").alias("k"), "_y", F.when(n <= PIECES * PIECE, raw).otherwise(pieces).alias("t")).toPandas()
    got = got.sort_values("k", kind="stable")
    y = got["_y"].to_numpy(np.float32)
    if len(set(y.tolist())) < 2:
        return float(share[1] / (share[0] + share[1]))
    w = np.where(y > 0, share[1] / (y > 0).sum(), share[0] / (y == 0).sum()).astype(np.float32)
    net = Net()
    net.fit([bytes(t) for t in got["t"]], y, w)
    return net


def score(docs: DataFrame, net: Net | float, keep: list[str], text: str = "text") -> DataFrame:
    """The kept columns, score (0 to 1) and predicted (1 from the threshold on)."""
    schema = schema_of(docs, keep, "score double, predicted int")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part, data, offsets in text_slices(batches, text):
            p = net.scores(data, offsets) if isinstance(net, Net) else np.full(part.num_rows, net)
            cols = [part.column(part.schema.get_field_index(c)) for c in keep]
            yield pa.RecordBatch.from_arrays([*cols, pa.array(p), pa.array((p >= THRESHOLD).astype(np.int32))], names=[*keep, "score", "predicted"])

    return picked(docs, **{c: c for c in [*keep, text]}).mapInArrow(run, schema)


def op2_quality_cnn(spark, sf_dir: str) -> DataFrame:
    docs, labels = table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels")
    net = train(docs, labels.where(fold() != 0))
    return score(picked(docs, doc_id="doc_id", text="text").withColumn("held_out", fold() == 0), net, ["doc_id", "held_out"])
