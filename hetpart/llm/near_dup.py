"""Near-duplicates: improved consistent weighted sampling over TF-IDF shingles.

A document is its five-word shingles (all its words, if fewer); a shingle weighs its
count times its IDF, ln(1 + N / max(df, N / ``RARE``)). df is the number of documents
that hold the shingle, out of a count-min sketch of fixed size over all N documents: it
exceeds the true one by about the mean load of a slot (mean shingles of a document over
2 ** ``IDF_BITS``, as a share of N), whatever N is. Weighted samples agree with
the probability of the weighted Jaccard similarity; ``ROWS`` of them make a band, and
documents that agree in a band are candidates.

Equal word sequences (by a 128-bit digest) are folded first, so copies are neither paired
nor moved. In each bucket the least document is the hub and all others meet it (a star,
not all pairs). Texts of candidates are kept compressed and travel to their hubs, a hub
with many in salted parts; weighted Jaccard similarity decides each link. Linked documents
form classes (components). What a star may miss is made up for: where a hub's members are
of several classes, those outside the hub's class meet all members of other classes, both
sides in blocks of bounded size. So each pair of different texts that shares a bucket is
compared or known to be in one class, and what moves is documents times blocks, not pairs.
Buckets and hubs with a thousandth of all rows get what belongs to them by broadcast, so
their rows aren't gathered in one task.

Defined results: a text without words is a class of its own, as is a null id (its class
is null); a class's id is its least document id; equal rows share a class; ties don't
arise, as ids decide; extra columns are ignored. Rows of one id are one document: any of
their texts may find it, the least in compressed form is compared, all are in one class.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import checkpointed, hot_join, picked, schema_of, table
from .textbuf import LOWER, WORD, give_back, joined, mix, prefix_sums, run_hashes, text_slices, word_hashes, words

SHINGLE, SIMILARITY = 5, 0.8
BANDS, ROWS = 12, 4
#: Slots of each row of the sketch (bits), and the share of documents up to which a shingle is rare.
IDF_BITS, IDF_ROWS, RARE, TABLE_BITS = 18, 2, 256, 15
SLICE = 400_000
#: Words that a hub's part compares at most in one task, about.
PART_WORDS = 400_000


# ---------------------------------------------------------------- documents' weights


def slot(h: np.ndarray, row: int) -> np.ndarray:
    """Where hashes fall in a row of the sketch: each row takes other bits."""
    return ((h >> np.uint64(64 - IDF_BITS * (row + 1))) & np.uint64((1 << IDF_BITS) - 1)).astype(np.int64)


def document_frequency(docs: DataFrame, text: str = "text") -> tuple[np.ndarray, int]:
    """Count-min sketch of the documents that hold each shingle, and the number of documents."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        df, n = np.zeros((IDF_ROWS, 1 << IDF_BITS), np.int32), 0
        for part, data, offsets in text_slices(batches, text, SLICE):
            h = Shingles(data, offsets).hash
            for row in range(IDF_ROWS):
                df[row] += np.bincount(slot(h, row), minlength=1 << IDF_BITS).astype(np.int32)
            n += part.num_rows
        flat = df.ravel()
        at = np.flatnonzero(flat)
        yield pa.RecordBatch.from_arrays([pa.array(np.append(at, -1).astype(np.int32)), pa.array(np.append(flat[at], n).astype(np.int32))], names=["slot", "n"])

    rows = picked(docs, text=text).mapInArrow(count, "slot int, n int").groupBy("slot").agg(F.sum("n").alias("n")).toArrow()  # IDF_ROWS * 2 ** IDF_BITS rows at most
    out = np.zeros(IDF_ROWS << IDF_BITS, np.int64)
    at = rows["slot"].to_numpy()
    out[at[at >= 0]] = rows["n"].to_numpy()[at >= 0]
    return out.reshape(IDF_ROWS, -1), int(rows["n"].to_numpy()[at < 0].sum())


def idf_table(df: np.ndarray, n: int) -> np.ndarray:
    """IDF by row and slot; of a shingle's slots the greatest counts."""
    return np.log1p(n / np.maximum(df, max(n / RARE, 1e-9))).astype(np.float32)


class Shingles:
    """Different shingles of each document of a slice, with weights, ordered by document and hash."""

    def __init__(self, data: np.ndarray, offsets: np.ndarray, idf: np.ndarray | None = None):
        data = LOWER[data]
        starts, ends, bounds = words(data, offsets, WORD)
        h = word_hashes(data, starts, ends)
        sums, n = prefix_sums(h), np.diff(bounds)
        self.n_words, self.data, self.starts, self.ends, self.word_bounds = n, data, starts, ends, bounds
        doc = np.repeat(np.arange(len(n)), n)
        size = np.minimum(n, SHINGLE)[doc]
        at = np.flatnonzero(bounds[1:][doc] - np.arange(len(doc)) >= size)
        size, doc = size[at], doc[at]
        h = run_hashes(sums, at, at + size)
        bits = max(1, int(len(n)).bit_length())
        key = (doc.astype(np.uint64) << np.uint64(64 - bits)) | (h >> np.uint64(bits))
        order = np.argsort(key)
        key = key[order]
        new = np.ones(len(key), np.bool_)
        new[1:] = key[1:] != key[:-1]
        first = np.flatnonzero(new)
        count = np.diff(np.append(first, len(key)))
        pick = order[first]
        self.doc, self.hash = doc[pick], h[pick]
        worth = np.ones(len(pick), np.float32) if idf is None else np.maximum.reduce([idf[row][slot(self.hash, row)] for row in range(IDF_ROWS)])
        self.weight = worth * count.astype(np.float32)
        self.bounds = np.searchsorted(self.doc, np.arange(len(n) + 1))

    def digests(self) -> np.ndarray:
        """128-bit digests of the documents' word sequences, as two words each."""
        out, first = joined(self.data, self.starts, self.ends)
        cut, whole = first[self.word_bounds].tolist(), out.tobytes()
        return np.frombuffer(b"".join(hashlib.blake2b(whole[a:b], digest_size=16).digest() for a, b in zip(cut[:-1], cut[1:], strict=True)), np.int64).reshape(-1, 2)

    def of(self, d: int) -> tuple[np.ndarray, np.ndarray]:
        """Sorted hashes and weights of one document."""
        a, b = self.bounds[d], self.bounds[d + 1]
        order = np.argsort(self.hash[a:b])
        return self.hash[a:b][order], self.weight[a:b][order]


def weighted_jaccard(hub: tuple[np.ndarray, np.ndarray], sh: Shingles) -> np.ndarray:
    """Similarity of each document of a slice to the hub."""
    key, weight = hub
    n = len(sh.bounds) - 1
    if not len(key) or not len(sh.hash):
        return np.zeros(n)
    k = np.minimum(np.searchsorted(key, sh.hash), len(key) - 1)
    both = np.where(key[k] == sh.hash, np.minimum(weight[k], sh.weight), np.float32(0)).astype(np.float64)
    least = np.bincount(sh.doc, both, n)
    total = np.bincount(sh.doc, sh.weight.astype(np.float64), n) + float(weight.sum(dtype=np.float64))
    return least / (total - least)


# ---------------------------------------------------------------- consistent samples

_draws: dict[tuple, tuple] = {}


def draws(samples: int, seed: int) -> tuple:
    """Tables of the random values of each sample: r, 1/r, beta, ln c - r; multipliers."""
    if (samples, seed) not in _draws:
        rng = np.random.default_rng(seed)
        shape = (samples, 1 << TABLE_BITS)
        r = rng.gamma(2.0, 1.0, shape)
        c = rng.gamma(2.0, 1.0, shape)
        tables = [x.astype(np.float32) for x in (r, 1 / r, rng.uniform(0, 1, shape), np.log(c) - r)]
        _draws[samples, seed] = (*tables, rng.integers(1, 1 << 63, samples, dtype=np.uint64) | np.uint64(1))
    return _draws[samples, seed]


def band_keys(sh: Shingles, bands: int = BANDS, rows: int = ROWS, seed: int = 7) -> np.ndarray:
    """Band keys by document (rows) and band; documents without shingles have zeros.

    A sample's value for a shingle and its identity share one 64-bit word, so that one
    minimum a document finds both."""
    r, inverse, beta, offset, odd = draws(bands * rows, seed)
    n = len(sh.bounds) - 1
    full = np.flatnonzero(np.diff(sh.bounds))
    out = np.zeros((n, bands), np.uint64)
    if not len(full):
        return out
    begin, log_w = sh.bounds[full], np.log(sh.weight)
    low = (sh.hash & np.uint64(0xFFFFFFFF)).astype(np.uint32)
    key = None
    for k in range(bands * rows):
        slot = ((sh.hash * odd[k]) >> np.uint64(64 - TABLE_BITS)).astype(np.int64)
        b = beta[k][slot]
        t = np.floor(log_w * inverse[k][slot] + b)
        a = offset[k][slot] - r[k][slot] * (t - b)
        u = a.view(np.uint32)
        u = np.where(u >> np.uint32(31), ~u, u | np.uint32(0x80000000))
        code = (low + t.astype(np.int32).view(np.uint32) * np.uint32(0x9E3779B1)) * np.uint32(0x85EBCA6B)
        best = np.minimum.reduceat((u.astype(np.uint64) << np.uint64(32)) | code, begin) & np.uint64(0xFFFFFFFF)
        key = best if k % rows == 0 else mix(key * np.uint64(0x9E3779B97F4A7C15) + best)
        if k % rows == rows - 1:
            out[full, k // rows] = mix(key + np.uint64(k))
    return out


def signatures(docs: DataFrame, idf: np.ndarray) -> DataFrame:
    """Of rows (id, text): id, n_words, two hashes of the word sequence (null without words) and band keys."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part, data, offsets in text_slices(batches, "text", SLICE):
            sh = Shingles(data, offsets, idf)
            none = sh.n_words == 0
            keys, whole = band_keys(sh), sh.digests()
            lists = pa.ListArray.from_arrays(pa.array((np.arange(len(none) + 1) * BANDS).astype(np.int32)), pa.array(keys.ravel().view(np.int64)))
            yield pa.RecordBatch.from_arrays([part.column(0), pa.array(sh.n_words.astype(np.int64)), pa.array(whole[:, 0], mask=none), pa.array(whole[:, 1], mask=none), lists], names=["id", "n_words", "h1", "h2", "bands"])

    return docs.mapInArrow(run, schema_of(docs, ["id"], "n_words bigint, h1 bigint, h2 bigint, bands array<bigint>"))


# ---------------------------------------------------------------- links


def squeezed(docs: DataFrame) -> DataFrame:
    """id and the compressed text of each row (id, text)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        z = zstandard.ZstdCompressor(level=3)
        for part, data, offsets in text_slices(batches, "text"):
            whole = data.tobytes()
            blobs = [z.compress(whole[a:b]) for a, b in zip(offsets[:-1].tolist(), offsets[1:].tolist(), strict=True)]
            yield pa.RecordBatch.from_arrays([part.column(0), pa.array(blobs, pa.binary())], names=["id", "z"])

    return docs.mapInArrow(run, schema_of(docs, ["id"], "z binary"))


def _texts(blobs: list[bytes], idf: np.ndarray) -> Iterator[Shingles]:
    """Shingles of documents in turn, a slice of bounded size at a time."""
    z, held, size = zstandard.ZstdDecompressor(), [], 0
    for blob in blobs:
        held.append(z.decompress(blob))
        size += len(held[-1])
        if size >= SLICE:
            yield Shingles(*_buffer(held), idf)
            held, size = [], 0
    if held:
        yield Shingles(*_buffer(held), idf)


def star_similarities(pairs: DataFrame, texts: DataFrame, idf: np.ndarray, total: int) -> DataFrame:
    """hub, id and similarity of each pair (hub, id, n_words of id).

    A hub's pairs are dealt over parts by the words they bring; its text goes to each."""
    parts = checkpointed(pairs.groupBy("hub").agg(F.ceil(F.sum("n_words") / PART_WORDS).cast("int").alias("parts"), F.count(F.lit(1)).alias("n")))
    dealt = hot_join(pairs, parts, ["hub"], "n", total).select("hub", F.pmod(F.xxhash64("id"), F.col("parts")).cast("int").alias("part"), "id")
    own = parts.select("hub", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)).alias("part"), F.col("hub").alias("id"))

    def compare(group: pa.Table) -> pa.Table:
        ids, hub, blobs = group.column("id").to_numpy(), group.column("hub")[0].as_py(), group.column("z")
        head = next(_texts([blobs[int(np.flatnonzero(ids == hub)[0])].as_py()], idf)).of(0)
        rest = np.flatnonzero(ids != hub)
        sim = [weighted_jaccard(head, sh) for sh in _texts([blobs[i].as_py() for i in rest.tolist()], idf)]
        give_back()
        return pa.Table.from_arrays([pa.array(np.full(len(rest), hub, ids.dtype)), pa.array(ids[rest]), pa.array(np.concatenate(sim) if sim else np.zeros(0))], names=["hub", "id", "sim"])

    return dealt.unionByName(own).join(texts, "id").groupBy("hub", "part").applyInArrow(compare, schema_of(pairs, ["hub", "id"], "sim double"))


def further_links(open_: DataFrame, texts: DataFrame, idf: np.ndarray, similarity: float) -> DataFrame:
    """Links (a, b) between different classes of a hub's members: hub, id, class, out, and of
    the hub the numbers of blocks of all members and of outer ones.

    Members outside the hub's class (``out``) meet all members of other classes, block by
    block. Of an outer member's links to one class in a block the first is enough."""
    block = lambda n: F.pmod(F.xxhash64("id"), F.col(n)).cast("int")
    every = lambda n: F.explode(F.sequence(F.lit(0), F.col(n) - 1))
    inner = open_.select("hub", block("blocks").alias("i"), every("outer_blocks").alias("j"), "id", "class", F.lit(False).alias("pivot"))
    outer = open_.where("out").select("hub", every("blocks").alias("i"), block("outer_blocks").alias("j"), "id", "class", F.lit(True).alias("pivot"))

    def meet(group: pa.Table) -> pa.Table:
        pivot = group.column("pivot").to_numpy(zero_copy_only=False)
        ids, cls, blobs = group.column("id").to_numpy(), group.column("class").to_numpy(), group.column("z")
        mine, other = np.flatnonzero(pivot), np.flatnonzero(~pivot)
        heads = [sh.of(d) for sh in _texts([blobs[i].as_py() for i in mine.tolist()], idf) for d in range(len(sh.n_words))]
        a, b, at = [], [], 0
        for sh in _texts([blobs[i].as_py() for i in other.tolist()], idf):
            here = other[at : at + len(sh.n_words)]
            at += len(here)
            for i, head in zip(mine.tolist(), heads, strict=True):
                apart = cls[here] != cls[i]
                if apart.any():
                    hit = np.flatnonzero(apart & (weighted_jaccard(head, sh) >= similarity))
                    hit = hit[np.unique(cls[here[hit]], return_index=True)[1]]
                    a += [ids[i]] * len(hit)
                    b += ids[here[hit]].tolist()
        return pa.Table.from_arrays([pa.array(np.array(a, ids.dtype)), pa.array(np.array(b, ids.dtype))], names=["a", "b"])

    kind = open_.select(F.col("id").alias("a"), F.col("id").alias("b"))
    return inner.unionByName(outer).join(texts, "id").groupBy("hub", "i", "j").applyInArrow(meet, kind.schema)


def _buffer(raw: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    return np.frombuffer(b"".join(raw), np.uint8), np.concatenate([[0], np.cumsum([len(x) for x in raw])]).astype(np.int64)


def components(edges: DataFrame) -> DataFrame:
    """(id, class) of the vertices of edges (a, b): least reachable id.

    Large and small stars by turns: each vertex's larger neighbours move to its least
    neighbour, then its smaller ones do; a logarithmic number of rounds in practice."""
    edges = checkpointed(edges.where("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct())
    before, total = None, 2 * edges.count()
    n = F.count(F.lit(1)).alias("n")
    while True:
        both = edges.unionByName(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))
        least = both.groupBy("a").agg(F.least(F.min("b"), F.first("a")).alias("m"), n)
        large = hot_join(both.where("b > a"), least, ["a"], "n", total).select(F.col("b").alias("a"), F.col("m").alias("b")).where("a <> b").distinct()
        large = checkpointed(large)
        small = hot_join(large, large.groupBy("a").agg(F.min("b").alias("m"), n), ["a"], "n", total)
        after = small.select("a", F.col("m").alias("b")).unionByName(small.where("b <> m").select(F.col("b").alias("a"), F.col("m").alias("b"))).distinct()
        edges = checkpointed(after)
        state = edges.agg(F.count(F.lit(1)), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first()
        if state == before:
            return edges.select(F.col("a").alias("id"), F.col("b").alias("class"))
        before = state


def near_duplicates(docs: DataFrame, key: str = "doc_id", text: str = "text", similarity: float = SIMILARITY) -> DataFrame:
    """Each row's id, the class it is in (its least id) and whether it is that one."""
    docs = picked(docs, id=key, text=text)
    df, n = document_frequency(docs)
    idf = idf_table(df, n)
    signed = checkpointed(signatures(docs, idf))
    same = signed.where("h1 IS NOT NULL AND id IS NOT NULL")
    first = checkpointed(same.groupBy("h1", "h2", "n_words").agg(F.min("id").alias("id"), F.first("bands").alias("bands")))
    rows = first.select("id", "n_words", F.posexplode("bands").alias("band", "key"))
    hubs = checkpointed(rows.groupBy("band", "key").agg(F.min("id").alias("hub"), F.count(F.lit(1)).alias("n")).where("n > 1"))
    member = hot_join(rows, hubs, ["band", "key"], "n", BANDS * first.count())
    member = checkpointed(member.groupBy("hub", "id").agg(F.max("n_words").alias("n_words")))
    total = member.count()
    texts = squeezed(docs).join(member.select("id").distinct(), "id", "left_semi").groupBy("id").agg(F.min("z").alias("z"))
    texts = checkpointed(texts)
    star = star_similarities(member.where("hub <> id"), texts, idf, total).where(F.col("sim") >= similarity)
    links = checkpointed(star.select(F.col("id").alias("a"), F.col("hub").alias("b")))
    classes = components(links)
    more = checkpointed(further_links(_open(member, classes, total), texts, idf, similarity))
    if not more.isEmpty():
        classes = components(more.unionByName(classes.select(F.col("id").alias("a"), F.col("class").alias("b"))))
    least = first.select("h1", "h2", "n_words", F.col("id").alias("rep")).join(classes.withColumnRenamed("id", "rep"), "rep", "left").select("h1", "h2", "n_words", F.coalesce("class", "rep").alias("class_id"))
    out = signed.select("id", "h1", "h2", "n_words").join(least, ["h1", "h2", "n_words"], "left")
    class_id = F.when(F.col("id").isNotNull(), F.coalesce("class_id", "id"))
    return out.select("id", class_id.alias("class_id"), F.coalesce(F.col("id") == class_id, F.lit(True)).alias("is_kept")).withColumnRenamed("id", key)


def _open(member: DataFrame, classes: DataFrame, total: int) -> DataFrame:
    """Members of the hubs whose members are of several classes, each with its class, and
    the hubs' numbers of blocks."""
    of = member.join(classes, "id", "left").withColumn("class", F.coalesce("class", "id"))
    head = classes.select(F.col("id").alias("hub"), F.col("class").alias("hub_class"))
    hubs = member.groupBy("hub").agg(F.count(F.lit(1)).alias("n")).join(head, "hub", "left").withColumn("hub_class", F.coalesce("hub_class", "hub"))
    of = checkpointed(hot_join(of, checkpointed(hubs), ["hub"], "n", total).withColumn("out", F.col("class") != F.col("hub_class")).drop("hub_class", "n"))
    blocks = lambda w: F.greatest(F.ceil(F.sum(w) / PART_WORDS), F.lit(1)).cast("int")
    several = of.groupBy("hub").agg(F.max("out").alias("several"), F.count(F.lit(1)).alias("n"), blocks("n_words").alias("blocks"), blocks(F.when(F.col("out"), F.col("n_words"))).alias("outer_blocks"))
    return hot_join(of, checkpointed(several.where("several AND n > 2").drop("several")), ["hub"], "n", total)


def op9_near_dup(spark, sf_dir: str) -> DataFrame:
    return near_duplicates(table(spark, sf_dir, "documents"))
