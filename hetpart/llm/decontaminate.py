"""Benchmark decontamination by winnowing.

Both sides are words, lower-cased. Of the hashes of all 5-word grams each window of
ten words keeps the least one, so a passage of ten words that both sides share has a
kept gram in common, at the same place. Documents' kept grams meet the benchmark's;
each meeting is extended to the ten-word windows around it, which count if they stand
in an item word by word. Items of fewer words are one window each and meet all grams
of their own length. Hashes only find where to look: what counts as equal is decided by
the words' bytes.

While the benchmark is small (``MAX_BENCHMARK_BYTES``, measured before use), its
fingerprints go to the tasks and documents aren't shuffled at all. A larger one is
joined by fingerprint; the places that meet are written out as text and joined with
the items' windows as text. Both ways give the same rows.

Defined results: null and empty texts have no words and no hits; an empty benchmark
hits nothing; an item without words has no window; a null item id reads "null"; equal
items count by their ids, once for each id; repeated rows and null document ids give a
row each, judged by its own text; extra columns, whatever their names, stay out of the
result.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import checkpointed, hot_join, picked, schema_of, table
from .textbuf import LOWER, WORD, covered, joined, prefix_sums, ragged, run_hashes, text_slices, words

WINDOW, GRAM = 10, 5
MAX_BENCHMARK_BYTES = 32 << 20
#: Bytes that one step of a comparison gathers, on each side.
COMPARED = 4 << 20


class Scan:
    """Words of a slice of texts with their hashes and places."""

    def __init__(self, data: np.ndarray, offsets: np.ndarray):
        self.data = LOWER[data]
        self.starts, self.ends, self.bounds = words(self.data, offsets, WORD)
        self.hash = run_hashes(prefix_sums(self.data), self.starts, self.ends)
        self.sums = prefix_sums(self.hash)
        self.n = np.diff(self.bounds)
        self.doc = np.repeat(np.arange(len(self.n)), self.n)
        self.room = self.bounds[1:][self.doc] - np.arange(len(self.doc))  # words from here to the document's end

    def grams(self, n: int) -> tuple[np.ndarray, np.ndarray]:
        """Places of all n-word grams, and their hashes."""
        at = np.flatnonzero(self.room >= n)
        return at, run_hashes(self.sums, at, at + n)

    def kept(self) -> tuple[np.ndarray, np.ndarray]:
        """Places and hashes of the least gram of each ten-word window, leftmost of equals."""
        at, h = self.grams(GRAM)
        full = np.full(len(self.doc), np.uint64(0xFFFFFFFFFFFFFFFF))
        full[at] = h
        s = np.flatnonzero(self.room >= WINDOW)
        if not len(s):
            return s, np.zeros(0, np.uint64)
        best, place = full[s], s.copy()
        for j in range(1, WINDOW - GRAM + 1):
            other = full[s + j]
            less = other < best
            best[less], place[less] = other[less], s[less] + j
        mark = np.zeros(len(self.doc), np.bool_)
        mark[place] = True
        place = np.flatnonzero(mark)
        return place, full[place]

    def around(self, place: np.ndarray) -> np.ndarray:
        """Starts of the ten-word windows that hold a gram at one of these places."""
        s = (place[:, None] - np.arange(WINDOW - GRAM, -1, -1)[None, :]).ravel()
        gram = np.repeat(place, WINDOW - GRAM + 1)
        ok = s >= self.bounds[self.doc[gram]]
        s = s[ok]
        return np.unique(s[self.room[s] >= WINDOW])

    def equal(self, mine: np.ndarray, other: Scan, theirs: np.ndarray) -> np.ndarray:
        """Whether words here and words there, pair by pair, are the same bytes."""
        size = self.ends[mine] - self.starts[mine]
        same = size == other.ends[theirs] - other.starts[theirs]
        left = np.flatnonzero(same)
        total = np.cumsum(size[left])
        a = 0
        while a < len(left):
            base = total[a - 1] if a else 0
            b = max(a + 1, int(np.searchsorted(total, base + COMPARED, "right")))
            k = left[a:b]
            here, there = self.data[ragged(self.starts[mine[k]], size[k])], other.data[ragged(other.starts[theirs[k]], size[k])]
            wrong = np.flatnonzero(here != there)
            if len(wrong):
                same[k[np.searchsorted(total[a:b] - base, wrong, "right")]] = False
            a = b
        return same

    def text(self, s: np.ndarray, n: np.ndarray) -> pa.Array:
        """Runs of n words from s on, as text with one blank between words."""
        w = ragged(s, n)
        out, first = joined(self.data, self.starts[w], self.ends[w])
        ends = first[np.concatenate([[0], np.cumsum(n)])]
        return pa.LargeStringArray.from_buffers(len(n), pa.py_buffer(ends.astype(np.int64).tobytes()), pa.py_buffer(out.tobytes())).cast(pa.string())


def classes(h: np.ndarray, same) -> np.ndarray:
    """For each element the first one equal to it. Equal elements have equal hashes;
    ``same(a, b)`` decides for elements a and b, pair by pair."""
    order = np.argsort(h, kind="stable")
    new = np.ones(len(h), np.bool_)
    new[1:] = h[order][1:] != h[order][:-1]
    out = np.empty(len(h), np.int64)
    out[order] = order[np.flatnonzero(new)][np.cumsum(new) - 1]
    odd = np.flatnonzero(~same(np.arange(len(h)), out))
    while len(odd):  # unequal elements of one hash: the first of each hash stands for the next class
        head = odd[np.unique(h[odd], return_index=True)[1]]
        out[odd] = head[np.searchsorted(h[head], h[odd])]
        odd = odd[~same(odd, out[odd])]
    return out


class Lookup:
    """Elements with sorted hashes; several may share a hash."""

    def __init__(self, h: np.ndarray):
        self.order = np.argsort(h, kind="stable")
        self.key, self.first, self.count = np.unique(h[self.order], return_index=True, return_counts=True)

    def pairs(self, h: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(index into h, element) of all that agree in the hash."""
        if not len(self.key) or not len(h):
            return np.zeros(0, np.int64), np.zeros(0, np.int64)
        k = np.minimum(np.searchsorted(self.key, h), len(self.key) - 1)
        at = np.flatnonzero(self.key[k] == h)
        k = k[at]
        return np.repeat(at, self.count[k]), self.order[ragged(self.first[k], self.count[k])]


class Index:
    """Fingerprints and different windows of the items; ``ids`` are sorted as strings."""

    def __init__(self, ids: list[str], texts: list[str]):
        self.ids = sorted(set(ids))
        number = {x: i for i, x in enumerate(self.ids)}
        item = np.array([number[x] for x in ids], np.int64)
        raw = [x.encode() for x in texts]
        offsets = np.concatenate([[0], np.cumsum([len(x) for x in raw])]).astype(np.int64)
        scan = self.scan = Scan(np.frombuffer(b"".join(raw), np.uint8), offsets)
        self.word = classes(scan.hash, lambda a, b: scan.equal(a, scan, b))  # equal words, equal numbers
        different = np.flatnonzero(self.word == np.arange(len(self.word)))
        self.words, self.word_at = Lookup(scan.hash[different]), different
        self.tables = {}
        long = scan.n >= WINDOW
        for n in sorted({*scan.n[(scan.n > 0) & ~long].tolist(), *([WINDOW] if long.any() else [])}):
            at, h = scan.grams(n)
            own = scan.n[scan.doc[at]] == n if n < WINDOW else np.ones(len(at), np.bool_)
            at, h = at[own], h[own]
            cls = classes(h, lambda a, b, at=at, n=n: self._same(lambda j: self.word[at[a] + j], n, at[b]))
            pair = np.unique(cls * len(self.ids) + item[scan.doc[at]])
            head, owner = np.divmod(pair, len(self.ids))
            head, first, count = np.unique(head, return_index=True, return_counts=True)
            self.tables[n] = (Lookup(h[head]), at[head], first, count, owner)
        self.prints = np.unique(scan.kept()[1])
        self.filters = {n: self._filter(t[0].key) for n, t in self.tables.items() if n < WINDOW} | {0: self._filter(self.prints)}
        del scan.hash, scan.sums, scan.doc, scan.room

    def _same(self, number, n: int, at: np.ndarray) -> np.ndarray:
        """Whether n word numbers, number(0) to number(n - 1), are the words from ``at`` on."""
        same = np.ones(len(at), np.bool_)
        for j in range(n):
            same &= number(j) == self.word[at + j]
        return same

    @staticmethod
    def _filter(keys: np.ndarray) -> np.ndarray:
        out = np.zeros(1 << 22, np.bool_)
        out[(keys >> np.uint64(42)).astype(np.int64)] = True
        return out

    def known(self, n: int, h: np.ndarray, keys: np.ndarray) -> np.ndarray:
        """Indices of the hashes that are among the keys."""
        at = np.flatnonzero(self.filters[n][(h >> np.uint64(42)).astype(np.int64)])
        k = np.minimum(np.searchsorted(keys, h[at]), len(keys) - 1)
        return at[keys[k] == h[at]]

    def numbers(self, scan: Scan, at: np.ndarray) -> np.ndarray:
        """The items' numbers of the words at some places, -1 for words that no item has."""
        i, k = self.words.pairs(scan.hash[at])
        k = self.word_at[k]
        same = scan.equal(at[i], self.scan, k)
        out = np.full(len(at), -1, np.int64)
        out[i[same]] = k[same]
        return out

    def hits(self, scan: Scan) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """(start, end) of each window of an item that stands in the texts; (document, item)."""
        starts, ends, docs, items = [], [], [], []
        for n, (lookup, at, first, count, owner) in self.tables.items():
            if n == WINDOW:
                place, h = scan.kept()
                s = scan.around(place[self.known(0, h, self.prints)]) if len(h) else place
            else:
                s, h = scan.grams(n)
                s = s[self.known(n, h, lookup.key)]
            i, k = lookup.pairs(run_hashes(scan.sums, s, s + n))
            s = s[i]
            if not len(s):
                continue
            place = s[:, None] + np.arange(n)
            different, back = np.unique(place, return_inverse=True)
            number = self.numbers(scan, different)[back.reshape(place.shape)]
            same = self._same(lambda j, number=number: number[:, j], n, at[k])
            s, k = s[same], k[same]
            starts.append(np.unique(s))
            ends.append(starts[-1] + n)
            pair = np.unique(scan.doc[s] * len(at) + k)  # a window of a document counts its items once
            doc, k = np.divmod(pair, max(1, len(at)))
            docs.append(np.repeat(doc, count[k]))
            items.append(owner[ragged(first[k], count[k])])
        return tuple(np.concatenate(x) if x else np.zeros(0, np.int64) for x in (starts, ends, docs, items))


MORE = "n_words bigint, n_hit bigint, n_items bigint, items_sha256 string, contaminated boolean"
NAMES = [x.split()[0] for x in MORE.split(", ")]


def _broadcast_form(docs: DataFrame, items: list) -> DataFrame:
    ids, texts = [str(r[0]) if r[0] is not None else "null" for r in items], [r[1] or "" for r in items]
    kept: dict = {}

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        index = kept.get("index") or kept.setdefault("index", Index(ids, texts))
        none = hashlib.sha256(b"").hexdigest()
        for part, data, offsets in text_slices(batches, "text"):
            scan = Scan(data, offsets)
            start, end, doc, item = index.hits(scan)
            hit = covered(start, end, len(scan.doc))
            n_hit = np.bincount(scan.doc[hit], minlength=len(scan.n))
            of, which = np.divmod(np.unique(doc * max(1, len(index.ids)) + item), max(1, len(index.ids)))
            n_items = np.bincount(of, minlength=len(scan.n))
            sha, at = [none] * len(scan.n), np.searchsorted(of, np.arange(len(scan.n) + 1))
            for d in np.flatnonzero(n_items).tolist():
                sha[d] = hashlib.sha256(",".join(index.ids[i] for i in which[at[d] : at[d + 1]].tolist()).encode()).hexdigest()
            yield pa.RecordBatch.from_arrays([part.column(0), pa.array(scan.n), pa.array(n_hit), pa.array(n_items), pa.array(sha, pa.string()), pa.array(n_hit > 0)], names=["key", *NAMES])

    return docs.mapInArrow(run, schema_of(docs, ["key"], MORE))


def _counts(docs: DataFrame) -> DataFrame:
    """key, sha and number of words of each row."""

    def run(batches):
        for part, data, offsets in text_slices(batches, "text"):
            yield pa.RecordBatch.from_arrays([part.column(0), part.column(1), pa.array(np.diff(words(data, offsets, WORD)[2]))], names=["key", "sha", "n_words"])

    return docs.mapInArrow(run, schema_of(docs, ["key", "sha"], "n_words bigint"))


def _grams(docs: DataFrame, lengths: list[int]) -> DataFrame:
    """Rows (key, sha, n, print, place): kept grams, and all grams of shorter items' lengths."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part, data, offsets in text_slices(batches, "text"):
            scan = Scan(data, offsets)
            for n in lengths:
                place, h = scan.kept() if n == WINDOW else scan.grams(n)
                row = pa.array(scan.doc[place])
                where = (place - scan.bounds[scan.doc[place]]).astype(np.int64)
                yield pa.RecordBatch.from_arrays([part.column(0).take(row), part.column(1).take(row), pa.array(np.full(len(place), n, np.int32)), pa.array(h.view(np.int64)), pa.array(where)], names=["key", "sha", "n", "print", "place"])

    return docs.mapInArrow(run, schema_of(docs, ["key", "sha"], "n int, print bigint, place bigint"))


def _item_windows(items: DataFrame) -> DataFrame:
    """Rows (item, n, print, window): the items' windows as text, with the print that finds
    them: of a full window its least gram, of a shorter item its own."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part, data, offsets in text_slices(batches, "text"):
            scan = Scan(data, offsets)
            place, h = scan.kept()
            full = np.full(len(scan.doc) + 1, np.uint64(0xFFFFFFFFFFFFFFFF))
            full[place] = h
            s = np.flatnonzero(scan.room >= WINDOW)
            prints = np.minimum.reduce([full[s + j] for j in range(WINDOW - GRAM + 1)]) if len(s) else np.zeros(0, np.uint64)
            short = scan.bounds[:-1][(scan.n > 0) & (scan.n < WINDOW)]
            n = np.concatenate([np.full(len(s), WINDOW), scan.n[scan.doc[short]]]).astype(np.int64)
            s = np.concatenate([s, short])
            prints = np.concatenate([prints, run_hashes(scan.sums, short, short + n[len(prints) :])])
            yield pa.RecordBatch.from_arrays([part.column(0).take(pa.array(scan.doc[s])), pa.array(n.astype(np.int32)), pa.array(prints.view(np.int64)), scan.text(s, n)], names=["item", "n", "print", "window"])

    return items.mapInArrow(run, "item string, n int, print bigint, window string")


def _written_out(met: DataFrame) -> DataFrame:
    """Rows (key, sha, n, start, window) of the windows around the places of each text."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part, data, offsets in text_slices(batches, "text"):
            scan = Scan(data, offsets)
            lists = part.column(part.schema.get_field_index("at"))
            flat, row = lists.flatten(), np.repeat(np.arange(len(lists)), lists.value_lengths().to_numpy())
            n, place = flat.field("n").to_numpy().astype(np.int64), flat.field("place").to_numpy() + scan.bounds[row]
            full = n == WINDOW
            s = np.concatenate([scan.around(place[full]), place[~full]])
            n = np.concatenate([np.full(len(s) - int((~full).sum()), WINDOW), n[~full]]).astype(np.int64)
            d = pa.array(scan.doc[s])
            yield pa.RecordBatch.from_arrays([part.column(0).take(d), part.column(1).take(d), pa.array(n.astype(np.int32)), pa.array((s - scan.bounds[scan.doc[s]]).astype(np.int64)), scan.text(s, n)], names=["key", "sha", "n", "start", "window"])

    return met.mapInArrow(run, schema_of(met, ["key", "sha"], "n int, start bigint, window string"))


def _joined_form(docs: DataFrame, bench: DataFrame) -> DataFrame:
    """For a benchmark of any size. A row is told by its key and its text's digest: rows that
    agree in both have one result."""
    rows = docs.select("key", F.sha2(F.coalesce("text", F.lit("")).cast("binary"), 256).alias("sha"), "text")
    named = bench.select(F.coalesce(F.col("item").cast("string"), F.lit("null")).alias("item"), "text")
    items = checkpointed(_item_windows(named).distinct())
    lengths = [r[0] for r in items.select("n").distinct().collect()]  # ten values at most
    counts = _counts(rows)
    none = F.sha2(F.lit("").cast("binary"), 256)
    if not lengths:
        return counts.select("key", "n_words", F.lit(0).cast("long").alias("n_hit"), F.lit(0).cast("long").alias("n_items"), none.alias("items_sha256"), F.lit(False).alias("contaminated"))
    met = _grams(rows, lengths).join(items.select("n", "print").distinct(), ["n", "print"], "left_semi")
    places = met.groupBy("key", "sha").agg(F.collect_set(F.struct("n", "place")).alias("at")).withColumnRenamed("key", "_k").withColumnRenamed("sha", "_s")
    again = rows.join(places, F.col("key").eqNullSafe(F.col("_k")) & (F.col("sha") == F.col("_s"))).groupBy("key", "sha").agg(F.first("text").alias("text"), F.first("at").alias("at"))
    windows = checkpointed(_written_out(again))
    sizes = windows.groupBy("n", "window").agg(F.count(F.lit(1)).alias("rows"))
    owners = items.groupBy("n", "window").agg(F.collect_set("item").alias("items")).join(sizes, ["n", "window"])
    hits = hot_join(windows, owners, ["n", "window"], "rows", windows.count()).groupBy("key", "sha").agg(F.collect_set(F.struct("start", "n")).alias("at"), F.sort_array(F.array_distinct(F.flatten(F.collect_set("items")))).alias("items"))
    hits = hits.select(F.col("key").alias("_k"), F.col("sha").alias("_s"), F.size(F.array_distinct(F.flatten(F.transform("at", lambda x: F.sequence(x["start"], x["start"] + x["n"] - 1))))).cast("long").alias("n_hit"), F.size("items").cast("long").alias("n_items"), F.sha2(F.array_join("items", ",").cast("binary"), 256).alias("items_sha256"))
    out = counts.join(hits, F.col("key").eqNullSafe(F.col("_k")) & (F.col("sha") == F.col("_s")), "left")
    zero = lambda c: F.coalesce(F.col(c), F.lit(0).cast("long")).alias(c)
    return out.select("key", "n_words", zero("n_hit"), zero("n_items"), F.coalesce("items_sha256", none).alias("items_sha256"), F.col("n_hit").isNotNull().alias("contaminated"))


def contamination(docs: DataFrame, bench: DataFrame, key: str = "doc_id", text: str = "text", item: str = "item_id", max_bytes: int = MAX_BENCHMARK_BYTES, bench_text: str | None = None) -> DataFrame:
    """Words, hit words and items of each document."""
    docs, bench = picked(docs, key=key, text=text), picked(bench, item=item, text=bench_text or "text")
    size = bench.agg(F.coalesce(F.sum(F.octet_length("text")), F.lit(0)) + F.count(F.lit(1)) * 16).first()[0]
    out = _joined_form(docs, bench) if size > max_bytes else _broadcast_form(docs, bench.select("item", "text").collect())
    return out.withColumnRenamed("key", key)


def op8_decontaminate(spark, sf_dir: str) -> DataFrame:
    return contamination(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))
