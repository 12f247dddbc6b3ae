"""UDFs, an aggregate and table functions for users who write SQL."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql.functions import pandas_udf, udtf


@pandas_udf("long")
def shingle_code(words: pd.Series) -> pd.Series:
    """Arithmetic code of a text: sum of (place + 1) times code point, modulo 2**31 - 1."""
    return words.fillna("").map(lambda s: int((np.arange(1, len(s) + 1, dtype=np.int64) * np.frombuffer(s.encode("utf-32-le"), np.uint32).astype(np.int64)).sum() % 2147483647))


@pandas_udf("double")
def slowest(t_cal: pd.Series, t_com: pd.Series) -> float:
    """Aggregate: the largest sum of both times."""
    return float((t_cal + t_com).max())


@udtf(returnType="v long, machine int, holders int")
class ExpandReplicas:
    """One row for each holder of a vertex."""

    def eval(self, v: int, machines: list):
        for m in machines or []:
            yield v, int(m), len(machines)


@udtf(returnType="machine int, amount double")
class Waterfill:
    """Real-valued capacities: SELECT * FROM waterfill(array(cost...), array(cap...), edges)."""

    def eval(self, cost: list, cap: list, edges: int):
        from hetpart.operators.capacity import rounds

        yield from ((i, float(x)) for i, x in enumerate(rounds([float(c) for c in cost], [float(c) for c in cap], edges)))


def register(spark: SparkSession) -> None:
    spark.udf.register("shingle_code", shingle_code)
    spark.udf.register("slowest", slowest)
    spark.udtf.register("expand_replicas", ExpandReplicas)
    spark.udtf.register("waterfill", Waterfill)
