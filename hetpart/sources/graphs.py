"""Edge tables from relational data.

edges: src long, dst long with src < dst, distinct, no loops. Vertex id = key * 16 + kind
(1 customer, 2 order, 3 part, 4 supplier, 5 user, 6 bucket, 8 page, 9 term, 10 document,
12 turn). Only the columns that a graph needs are read.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.columns import mixed, vertex


def read(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def as_edges(df: DataFrame, a: str | Column = "src", b: str | Column = "dst") -> DataFrame:
    """Undirected simple edges from any pair of id columns; null ids and loops are dropped."""
    a, b = (F.col(x) if isinstance(x, str) else x for x in (a, b))
    both = df.select(a.cast("long").alias("a"), b.cast("long").alias("b")).where("a IS NOT NULL AND b IS NOT NULL AND a <> b")
    return both.select(F.least("a", "b").alias("src"), F.greatest("a", "b").alias("dst")).distinct()


def part_supplier(spark, d):
    return as_edges(read(spark, d, "lineitem"), vertex(F.col("l_partkey"), 3), vertex(F.col("l_suppkey"), 4))


def _order_lines(spark, d):
    return read(spark, d, "orders").select("o_orderkey", "o_custkey").join(read(spark, d, "lineitem").select("l_orderkey", "l_partkey", "l_suppkey"), F.col("o_orderkey") == F.col("l_orderkey"))


def customer_part(spark, d):
    return as_edges(_order_lines(spark, d), vertex(F.col("o_custkey"), 1), vertex(F.col("l_partkey"), 3))


def customer_supplier(spark, d):
    return as_edges(_order_lines(spark, d), vertex(F.col("o_custkey"), 1), vertex(F.col("l_suppkey"), 4))


def order_part(spark, d):
    return as_edges(read(spark, d, "lineitem"), vertex(F.col("l_orderkey"), 2), vertex(F.col("l_partkey"), 3))


def part_part(spark, d):
    """Parts bought together. An order's lines are few; the pairs come from its array of parts."""
    lines = read(spark, d, "lineitem").select("l_orderkey", "l_partkey").distinct()
    a, b = lines.withColumnRenamed("l_partkey", "a"), lines.withColumnRenamed("l_partkey", "b")
    return as_edges(a.join(b, "l_orderkey").where("a < b"), vertex(F.col("a"), 3), vertex(F.col("b"), 3))


def customer_order(spark, d):
    return as_edges(read(spark, d, "orders"), vertex(F.col("o_custkey"), 1), vertex(F.col("o_orderkey"), 2))


def user_bucket(spark, d):
    return as_edges(read(spark, d, "events"), vertex(F.col("user_id"), 5), vertex(F.floor("value"), 6))


def successions(spark, d) -> DataFrame:
    """(user, next_user, ts, event_id): who acts after whom in time.

    A window over all events would be one task. Hours are windows of their own; the last
    event of an hour meets the first one of the next hour that has any, found over the
    short list of hours."""
    e = read(spark, d, "events").select("ts", "event_id", "user_id").withColumn("hour", F.date_trunc("hour", "ts"))
    w = Window.partitionBy("hour").orderBy("ts", "event_id")
    first = e.groupBy("hour").agg(F.min(F.struct("ts", "event_id", "user_id")).alias("f"))
    hours = first.select("hour", F.lead("f.user_id").over(Window.orderBy("hour")).alias("after"))
    return e.withColumn("next", F.lead("user_id").over(w)).join(F.broadcast(hours), "hour").select(F.col("user_id").alias("user"), F.coalesce("next", "after").alias("next_user"), "ts", "event_id").where("next_user IS NOT NULL")


def user_succession(spark, d):
    return as_edges(successions(spark, d), vertex(F.col("user"), 5), vertex(F.col("next_user"), 5))


#: Similarities that a task holds at once, products in its exact comparison, vectors it searches for.
SIMILARITIES, PRODUCTS, VECTORS_A_TASK = 4_000_000, 1_000_000, 2_000


class Nearest:
    """The k nearest of each vector among all, by (cosine descending, id ascending).

    Copies of a vector are compared once: a group of copies gives its k + 1 least ids. The
    nearest groups are found in single precision and everything within its error bound is
    compared again, product by product in the order of the dimensions, so that equal
    vectors give equal cosines wherever they stand. What is held at once doesn't grow with
    the number of vectors, other than the vectors themselves."""

    def __init__(self, ids, vectors, k: int):
        import numpy as np

        order = np.argsort(ids, kind="stable")
        self.ids, vectors, self.k = ids[order], np.ascontiguousarray(vectors[order]), k
        rows = vectors.view([("", vectors.dtype)] * vectors.shape[1]).ravel() if vectors.shape[1] else np.zeros(len(ids), np.int8)
        _, first, self.group = np.unique(rows, return_index=True, return_inverse=True)
        self.vectors = vectors[first]
        by = np.argsort(self.group, kind="stable")  # positions of each group, least ids first
        self.members, self.start = by, np.searchsorted(self.group[by], np.arange(len(first) + 1))

    def prepare(self) -> None:
        """What a task derives from the vectors."""
        import numpy as np

        n, dims = self.vectors.shape
        self.norm, self.unit = np.empty(n), np.empty((n, dims), np.float32)
        step = max(1, PRODUCTS // max(1, dims))
        for lo in range(0, n, step):
            own = self.vectors[lo : lo + step].astype(np.float64)
            norm = np.add.accumulate(own * own, axis=1)[:, -1]
            self.norm[lo : lo + step] = norm
            self.unit[lo : lo + step] = own / np.maximum(np.sqrt(norm), 1e-300)[:, None]
        self.slack = 2 * (dims + 4) * 2.0**-23

    def _cosine(self, a, b):
        import numpy as np

        out, step = np.empty(len(a)), max(1, PRODUCTS // self.vectors.shape[1])
        for lo in range(0, len(a), step):
            x, y = a[lo : lo + step], b[lo : lo + step]
            dot = np.add.accumulate(self.vectors[x].astype(np.float64) * self.vectors[y], axis=1)[:, -1]
            out[lo : lo + step] = np.clip(dot / np.maximum(np.sqrt(self.norm[x] * self.norm[y]), 1e-300), -1, 1)
        return out

    def pairs(self, ids):
        """(a, b, cosine) of the given ids, in slices."""
        import numpy as np

        at = np.searchsorted(self.ids, ids)
        n = len(self.vectors)
        step, keep = max(1, SIMILARITIES // max(1, n)), min(n, self.k + 1)
        for lo in range(0, len(at), step):
            some = at[lo : lo + step]
            groups, back = np.unique(self.group[some], return_inverse=True)
            s = self.unit[groups] @ self.unit.T
            least = np.partition(s, n - keep, axis=1)[:, n - keep] - self.slack
            row, near = np.divmod(np.flatnonzero(s >= least[:, None]).astype(np.int32), np.int32(n))  # all where vectors hardly differ
            del s
            cosine = self._cosine(groups[row], near)
            # a row of candidates for each of the ids, each group's members beside it
            ptr = np.searchsorted(row, np.arange(len(groups) + 1))
            for me, g in zip(some, back, strict=True):
                c, w = near[ptr[g] : ptr[g + 1]], cosine[ptr[g] : ptr[g + 1]]
                size = np.minimum(self.start[c + 1] - self.start[c], self.k + 1)
                from_ = np.repeat(self.start[c] - np.cumsum(size) + size, size)
                who, w = self.members[from_ + np.arange(size.sum())], np.repeat(w, size)
                other = who != me
                who, w = who[other], w[other]
                best = np.lexsort((who, -w))[: self.k]
                yield np.full(len(best), self.ids[me]), self.ids[who[best]], w[best]


def nearest_vectors(spark, d, k: int = 8, max_vectors: int = 200_000) -> DataFrame:
    """Vectors and their k nearest by cosine, with weight. Exact search against all vectors;
    their number is checked before they go to the tasks."""
    import numpy as np
    import pyarrow as pa

    e = read(spark, d, "embeddings").select("vec_id", "embedding")
    n = e.count()
    if n > max_vectors:
        raise ValueError(f"{n} vectors; exact neighbours are for {max_vectors} at most")
    rows = e.toArrow().combine_chunks()
    flat = pa.concat_arrays([x.flatten() for x in rows.column(1).chunks]) if n else pa.array([], pa.float32())
    search = Nearest(rows.column(0).to_numpy(), flat.to_numpy(zero_copy_only=False).reshape(n, -1) if n else np.zeros((0, 1), np.float32), k)
    del rows, flat

    def run(batches):
        search.prepare()
        for b in batches:
            got = list(search.pairs(b.column(0).to_numpy()))
            if got:
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(x)) for x in zip(*got, strict=True)], names=["a", "b", "cosine"])

    tasks = max(1, -(-n // VECTORS_A_TASK))
    found = e.select("vec_id").repartition(tasks, "vec_id").mapInArrow(run, "a long, b long, cosine double")
    return found.select(vertex(F.col("a"), 7).alias("a"), vertex(F.col("b"), 7).alias("b"), F.round((1 - F.col("cosine")) * 1e6).cast("long").alias("weight"))


def vector_neighbours(spark, d):
    return as_edges(nearest_vectors(spark, d), "a", "b")


def term_id(term: Column) -> Column:
    return vertex(F.conv(F.substring(F.md5(term.cast("binary")), 1, 8), 16, 10).cast("long"), 9)


def page_terms(spark, d) -> DataFrame:
    """Directed arcs page -> href value."""
    hrefs = read(spark, d, "pages").select("page_id", F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), F.lit(1))).alias("t"))
    return hrefs.select(vertex(F.col("page_id"), 8).alias("src"), term_id(F.col("t")).alias("dst")).distinct()


def page_term_edges(spark, d):
    return as_edges(page_terms(spark, d))


def shared_shingles(spark, d, low: int = 2, high: int = 20) -> DataFrame:
    """Documents that share a five-word shingle held by low to high documents. The upper
    bound keeps pairs in proportion to shingles."""
    w = F.filter(F.split(F.coalesce("text", F.lit("")), "\\s+"), lambda x: x != "")
    grams = read(spark, d, "documents").select("doc_id", w.alias("w")).where(F.size("w") >= 5)
    grams = grams.select("doc_id", F.explode(F.array_distinct(F.transform(F.slice("w", 1, F.size("w") - 4), lambda x, i: F.xxhash64(x, F.get("w", i + 1), F.get("w", i + 2), F.get("w", i + 3), F.get("w", i + 4))))).alias("h"))
    some = grams.groupBy("h").agg(F.count(F.lit(1)).alias("n")).where(F.col("n").between(low, high)).select("h")
    held = grams.join(some, "h").groupBy("h").agg(F.sort_array(F.collect_list("doc_id")).alias("ids"))  # high ids at most
    pairs = held.select(F.explode("ids").alias("a"), "ids").select("a", F.explode("ids").alias("b")).where("a < b")
    return as_edges(pairs, vertex(F.col("a"), 10), vertex(F.col("b"), 10))


def turn_chain(spark, d, directed: bool = False) -> DataFrame:
    t = read(spark, d, "conversations").select("conv_id", "turn")
    nxt = t.withColumn("next", F.lead("turn").over(Window.partitionBy("conv_id").orderBy("turn"))).where("next IS NOT NULL")
    a, b = vertex(F.col("conv_id") * 1000 + F.col("turn"), 12), vertex(F.col("conv_id") * 1000 + F.col("next"), 12)
    return nxt.select(a.alias("src"), b.alias("dst")) if directed else as_edges(nxt, a, b)


def turn_mesh(spark, d) -> DataFrame:
    """A mesh of conversations by turns: a turn meets the next one of its conversation and
    its like in the next conversation (by id), so no turn has more than four neighbours."""
    t = read(spark, d, "conversations").select("conv_id", "turn").distinct()
    down = t.join(t.select((F.col("conv_id") - 1).alias("conv_id"), "turn", F.lit(1).alias("_next")), ["conv_id", "turn"])
    v = lambda conv: vertex(conv * 1000 + F.col("turn"), 12)
    return turn_chain(spark, d).unionByName(as_edges(down, v(F.col("conv_id")), v(F.col("conv_id") + 1)))


def grid(spark, n: int, m: int) -> DataFrame:
    """An n by m mesh; vertex = row * m + column."""
    v = spark.range(n * m)
    right = v.where(F.col("id") % m < m - 1).select(F.col("id").alias("src"), (F.col("id") + 1).alias("dst"))
    return right.unionByName(v.where(F.col("id") < (n - 1) * m).select(F.col("id").alias("src"), (F.col("id") + m).alias("dst")))


def path(spark, n: int) -> DataFrame:
    return spark.range(n - 1).select(F.col("id").alias("src"), (F.col("id") + 1).alias("dst"))


def star(spark, n: int) -> DataFrame:
    return spark.range(1, n).select(F.lit(0).cast("long").alias("src"), F.col("id").alias("dst"))


def clique(spark, n: int) -> DataFrame:
    v = spark.range(max(0, n - 1))
    return v.select(F.col("id").alias("src"), F.explode(F.sequence(F.col("id") + 1, F.lit(n - 1).cast("long"))).alias("dst"))


#: Quadrant shares of the R-MAT model in thousandths, and edges a vertex.
QUADRANTS, EDGES_PER_VERTEX = (570, 190, 190), 16


def rmat(spark, scale: int, seed: int = 1, per_vertex: int = EDGES_PER_VERTEX) -> DataFrame:
    """A power-law graph by recursive quadrant choice; every draw is a function of the edge's
    number, so the graph is the same however it is split."""
    e = spark.range(per_vertex << scale)
    src = dst = F.lit(0).cast("long")
    a, b, c = QUADRANTS
    for level in range(scale):
        u = mixed(F.col("id"), seed * 64 + level) % 1000
        src = src + F.when(u >= a + b, 1 << level).otherwise(0)
        dst = dst + F.when((u >= a) & (u < a + b) | (u >= a + b + c), 1 << level).otherwise(0)
    return as_edges(e.select(src.alias("src"), dst.alias("dst")))


GRAPHS = {
    "g1": part_supplier,
    "g2": customer_part,
    "g3": customer_supplier,
    "g4": order_part,
    "g5": part_part,
    "g6": customer_order,
    "g7": user_bucket,
    "g8": user_succession,
    "g9": vector_neighbours,
    "g10": page_term_edges,
    "g11": shared_shingles,
    "g12": turn_chain,
    "g13": turn_mesh,
}


def both_ways(edges: DataFrame) -> DataFrame:
    """Arcs (v, u) in both directions."""
    return edges.select(F.col("src").alias("v"), F.col("dst").alias("u")).unionByName(edges.select(F.col("dst").alias("v"), F.col("src").alias("u")))


def degrees(edges: DataFrame) -> DataFrame:
    return edges.select(F.explode(F.array("src", "dst")).alias("v")).groupBy("v").agg(F.count(F.lit(1)).alias("degree"))


def stats(edges: DataFrame) -> DataFrame:
    """One row: edges, vertices, largest degree, edges a vertex, mean degree."""
    d = degrees(edges).agg((F.sum("degree") / 2).cast("long").alias("n_edges"), F.count(F.lit(1)).alias("n_vertices"), F.max("degree").alias("max_degree"))
    return d.select("n_edges", "n_vertices", "max_degree", (F.col("n_edges") / F.col("n_vertices")).alias("edges_per_vertex"), (2 * F.col("n_edges") / F.col("n_vertices")).alias("mean_degree"))
