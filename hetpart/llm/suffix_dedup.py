"""Exact removal of repeated 50-byte strings by distributed deep-shallow suffix sorting.

A byte goes if some 50-byte string over it also starts in a document with a smaller id.
So the suffixes of all documents, each looked at to 50 bytes, must be ordered, and of
equal ones the documents compared.

Suffixes that begin alike have to meet without sending 50 bytes for each byte of text.
Every 50-byte string has an anchor: of its 16-byte grams the one with the least hash,
the leftmost of equals. Strings that overlap mostly share their anchor, so about
eighteen neighbouring suffixes travel as one segment, to the bucket of their anchor;
equal strings have equal anchors and meet there. Equal segments of one slice are folded
before they move: those of larger ids are removed at once, so a passage that a third of
all documents hold sends one segment for each slice of text, not for each document.

In a bucket, segments of anchors that only one document holds are dropped, equal ones
are folded again, and the suffixes of the others are sorted deep-shallow: multikey
quicksort by eight-byte keys to ``SHALLOW`` bytes; what is still together hangs into
blind tries, built level by level for all groups at once. At each level a member is
compared once, with its group's pivot, and branches off at the first byte that differs
or has the pivot's string. At most 34 levels follow, whatever the data.

Segments, removed ranges and texts travel as compressed blobs, one for each slice and
bucket; the numbers of buckets and of partitions follow the size of the input.

A bucket is read as a stream and holds ``HELD_BYTES`` at most. Beyond that equal segments
are folded, and if this doesn't halve it, its largest anchors give way: their segments,
those that come later as well, are taken apart into single strings, sorted in pieces, and
what no smaller id of the piece has goes on, dealt by all its 50 bytes. So an anchor that
very many different contexts share isn't one task's, and results don't depend on sizes.

Defined results: null and empty texts have nothing to remove; a null id is smaller than
all others; repeated rows (equal id and text) don't remove each other and each give a
row; texts under 50 bytes stay whole; extra columns are ignored.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import picked, plan_bytes, table
from .textbuf import covered, give_back, mix, powers, prefix_sums, ragged, run_hashes, text_slices

LENGTH, GRAM, SHALLOW = 50, 16, 16
GRAMS = LENGTH - GRAM + 1  # grams of a string
#: Text that a task gathers before it sends; input on disk for each bucket.
FLUSH_BYTES, BUCKET_BYTES = 16_000_000, 2_000_000
#: Buckets of a shuffle partition, and partitions of a shuffle: then partitions hold more buckets.
BUCKETS_A_TASK, MAX_TASKS = 2, 200_000
#: A larger estimate is none; numbers of finer buckets must be integers of four bytes.
UNKNOWN_BYTES, MAX_BUCKETS = 1 << 50, 1 << 27
#: Bytes of segments that a bucket holds; buckets of single strings for each bucket.
HELD_BYTES, FINER = 64_000_000, 8
WINDOWS_AT_ONCE = 500_000
#: Smaller blobs aren't compressed.
SMALL_BLOB = 512
NULL_ID = np.iinfo(np.int64).min


def pack(*arrays: np.ndarray) -> bytes:
    head = np.array([len(arrays), *(a.nbytes for a in arrays)], np.int64).tobytes()
    raw = head + b"".join(np.ascontiguousarray(a).tobytes() for a in arrays)
    return raw if len(raw) < SMALL_BLOB else zstandard.ZstdCompressor(level=6).compress(raw)


def unpack(blob: bytes, *types) -> list[np.ndarray]:
    raw = zstandard.ZstdDecompressor().decompress(blob) if blob[:4] == zstandard.FRAME_HEADER else blob
    sizes = np.frombuffer(raw, np.int64, 1 + len(types))[1:]
    out, at = [], 8 * (1 + len(types))
    for t, n in zip(types, sizes.tolist(), strict=True):
        out.append(np.frombuffer(raw, t, n // np.dtype(t).itemsize, at))
        at += n
    return out


def shares(bucket: np.ndarray) -> Iterator[tuple[int, np.ndarray]]:
    """Each bucket that occurs, with its rows in their order."""
    order = np.argsort(bucket, kind="stable")
    there, first = np.unique(bucket[order], return_index=True)
    for b, i, j in zip(there.tolist(), first.tolist(), [*first[1:].tolist(), len(order)], strict=True):
        yield b, order[i:j]


def gram_hashes(sums: np.ndarray) -> np.ndarray:
    h = (sums[GRAM:] - sums[:-GRAM]) * powers(len(sums) - GRAM, True)
    return mix(h)


def segments(data: np.ndarray, offsets: np.ndarray) -> dict[str, np.ndarray] | None:
    """Runs of neighbouring 50-byte strings with one anchor: document, first start, number
    of strings, anchor's place after the start, hash of the anchor and of the content."""
    n = len(data)
    if n < LENGTH:
        return None
    sums = prefix_sums(data)
    gram = gram_hashes(sums)
    low = (gram & ~np.uint64(0xFFFFFFFF)) | np.arange(len(gram), dtype=np.uint64)
    best, have = low, 1
    while 2 * have <= GRAMS:
        best, have = np.minimum(best[:-have], best[have:]), 2 * have
    if have < GRAMS:
        best = np.minimum(best[: len(best) - (GRAMS - have)], best[GRAMS - have :])
    anchor = (best & np.uint64(0xFFFFFFFF)).astype(np.int64)[: n - LENGTH + 1]
    room = np.maximum(np.diff(offsets) - LENGTH + 1, 0)
    at = ragged(offsets[:-1], room)
    if not len(at):
        return None
    doc = np.repeat(np.arange(len(room)), room)
    a = anchor[at]
    new = np.ones(len(at), np.bool_)
    new[1:] = (a[1:] != a[:-1]) | (doc[1:] != doc[:-1])
    first = np.flatnonzero(new)
    count = np.diff(np.append(first, len(at)))
    start, where = at[first], a[first]
    return {"doc": doc[first], "start": start, "count": count, "anchor": where - start, "key": gram[where], "content": run_hashes(sums, start, start + count + LENGTH - 1)}


def fold(ids: np.ndarray, content: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(larger, class, least): whether a smaller id has the same content; the content's
    class; the least id of each class."""
    _, cls = np.unique(content, return_inverse=True)
    least = np.full(cls.max() + 1 if len(cls) else 0, np.iinfo(np.int64).max)
    np.minimum.at(least, cls, ids)
    return ids > least[cls], cls, least


class Sender:
    """Gathers segments and removed ranges of a task and packs them by bucket."""

    def __init__(self, buckets: int):
        self.buckets, self.rows, self.text, self.ranges, self.size = buckets, [], [], [], 0

    def add(self, ids: np.ndarray, data: np.ndarray, offsets: np.ndarray) -> None:
        s = segments(data, offsets)
        self.size += len(data)
        if s is None:
            return
        own = ids[s["doc"]]
        begin = s["start"] - offsets[s["doc"]]
        gone, _, _ = fold(own, s["content"])
        self.ranges.append((own[gone], begin[gone].astype(np.uint32), (begin + s["count"] + LENGTH - 1)[gone].astype(np.uint32)))
        keep = np.flatnonzero(~gone)
        bucket = (s["key"][keep] % np.uint64(self.buckets)).astype(np.int32)
        order = keep[np.argsort(bucket, kind="stable")]
        self.rows.append((np.sort(bucket), own[order], begin[order].astype(np.uint32), s["count"][order].astype(np.uint8), s["anchor"][order].astype(np.uint8)))
        self.text.append(data[ragged(s["start"][order], s["count"][order] + LENGTH - 1)])

    def flush(self) -> Iterator[tuple[int, int, bytes]]:
        """(kind, bucket, blob): 0 for segments, 1 for removed ranges."""
        if self.rows:
            ends = [np.concatenate([[0], np.cumsum(r[3].astype(np.int64) + LENGTH - 1)]) for r in self.rows]
            there = np.unique(np.concatenate([r[0] for r in self.rows]))
            for k in range(0, len(there), 4096):
                some = there[k : k + 4096]
                cuts = [(np.searchsorted(r[0], some, "left").tolist(), np.searchsorted(r[0], some, "right").tolist()) for r in self.rows]
                for i, b in enumerate(some.tolist()):
                    part = [[x[lo[i] : hi[i]] for x in r[1:]] + [t[e[lo[i]] : e[hi[i]]]] for r, (lo, hi), e, t in zip(self.rows, cuts, ends, self.text, strict=True) if hi[i] > lo[i]]
                    yield 0, b, pack(*(np.concatenate(x) for x in zip(*part, strict=True)))
        if self.ranges:
            yield from send_ranges(*(np.concatenate(x) for x in zip(*self.ranges, strict=True)), self.buckets)
        self.rows, self.text, self.ranges, self.size = [], [], [], 0


def home(ids: np.ndarray, buckets: int) -> np.ndarray:
    return (mix(ids.astype(np.uint64) + np.uint64(0x9E3779B97F4A7C15)) % np.uint64(buckets)).astype(np.int64)


def send_ranges(ids: np.ndarray, start: np.ndarray, end: np.ndarray, buckets: int) -> Iterator[tuple[int, int, bytes]]:
    """Ranges by their documents' buckets; those of a document that touch become one."""
    if not len(ids):
        return
    order = np.lexsort((start, ids))
    ids, start, end = ids[order], start[order].astype(np.int64), end[order].astype(np.int64)
    _, doc = np.unique(ids, return_inverse=True)
    span = int(end.max()) + 1
    reach = np.maximum.accumulate(doc * span + end)  # ends so far, in one line of documents
    new = np.ones(len(ids), np.bool_)
    new[1:] = (doc[1:] * span + start[1:] > reach[:-1]) | (doc[1:] != doc[:-1])
    first = np.flatnonzero(new)
    last = np.append(first[1:], len(ids)) - 1
    ids, start, end = ids[first], start[first], reach[last] - doc[first] * span
    for k, o in shares(home(ids, buckets)):
        yield 1, k, pack(ids[o], start[o].astype(np.uint32), end[o].astype(np.uint32))


def groups_of(*keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Order by the keys, and where a new combination begins in it."""
    order = np.lexsort(keys[::-1])
    new = np.ones(len(order), np.bool_)
    new[1:] = False
    for k in keys:
        s = k[order]
        new[1:] |= s[1:] != s[:-1]
    return order, new


def multi(order: np.ndarray, new: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Members of groups of two and more, and their group numbers."""
    gid = np.cumsum(new) - 1
    size = np.bincount(gid)
    keep = size[gid] > 1
    return order[keep], np.cumsum(new[keep]) - 1


def first_difference(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Leading equal bytes of big-endian words, 8 if equal."""
    x = a ^ b
    out = np.full(len(x), 8, np.int64)
    for k in range(7, -1, -1):
        out[(x >> np.uint64(8 * (7 - k))) > 0] = k
        # a higher byte that differs overwrites a lower one
    return out


def sort_suffixes(buf: np.ndarray, pos: np.ndarray, group: np.ndarray, owner: np.ndarray) -> Iterator[np.ndarray]:
    """Suffixes (to 50 bytes) for which an equal one of the group has a smaller owner."""
    word = np.ndarray((len(buf) - 7,), ">u8", buf, strides=(1,))
    key = lambda at: word[at].astype(np.uint64)
    live, gid = multi(*groups_of(group))
    for depth in range(0, SHALLOW, 8):  # multikey quicksort, eight bytes a key
        if not len(live):
            return
        order, new = groups_of(gid, key(pos[live] + depth))
        live = live[order]
        keep, gid = multi(np.arange(len(live)), new)
        live = live[keep]
    while len(live):  # blind tries: one level of all groups
        order = np.lexsort((owner[live], gid))
        live, gid = live[order], gid[order]
        head = np.ones(len(live), np.bool_)
        head[1:] = gid[1:] != gid[:-1]
        pivot = live[np.flatnonzero(head)][np.cumsum(head) - 1]
        same = np.full(len(live), LENGTH, np.int64)
        left = np.flatnonzero(~head)
        for depth in (*range(SHALLOW, LENGTH - 8, 8), LENGTH - 8):
            d = first_difference(key(pos[live[left]] + depth), key(pos[pivot[left]] + depth))
            cut = d < 8
            same[left[cut]] = depth + d[cut]
            left = left[~cut]
            if not len(left):
                break
        equal = same == LENGTH
        yield live[equal & (owner[live] > owner[pivot])]
        branch = ~equal
        live, gid, same = live[branch], gid[branch], same[branch]
        order, new = groups_of(gid, same, buf[pos[live] + same] if len(live) else same)
        keep, gid = multi(order, new)
        live = live[keep]


#: Segments: document, start, number of strings, anchor's place, bytes behind each other.
SEGMENTS = (np.int64, np.uint32, np.uint8, np.uint8, np.uint8)
#: Single strings: document, start, 50 bytes each.
STRINGS = (np.int64, np.uint32, np.uint8)


def places(count: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Sizes of segments and where each begins in their bytes."""
    size = count.astype(np.int64) + LENGTH - 1
    return size, np.concatenate([[0], np.cumsum(size)[:-1]])


def anchor_keys(buf: np.ndarray, at: np.ndarray) -> np.ndarray:
    """64-bit keys of the grams that begin at these places."""
    word = np.ndarray((len(buf) - 7,), ">u8", buf, strides=(1,))
    return mix(word[at].astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15) ^ mix(word[at + 8].astype(np.uint64)))


def contents(buf: np.ndarray, at: np.ndarray, size: np.ndarray) -> np.ndarray:
    """64-bit hashes of segments."""
    out, step = np.empty(len(at), np.uint64), 1 << 14
    for a in range(0, len(at), step):
        n = size[a : a + step]
        sums, end = prefix_sums(buf[ragged(at[a : a + step], n)]), np.cumsum(n)
        out[a : a + step] = run_hashes(sums, end - n, end)
    return out


def chosen(part: list[np.ndarray], rows: np.ndarray) -> list[np.ndarray]:
    """Some of the segments, in the order given."""
    *columns, buf = part
    size, at = places(columns[2])
    return [*(c[rows] for c in columns), buf[ragged(at[rows], size[rows])]]


def in_runs(w: np.ndarray, seg: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """First and last of each run of neighbouring strings of one segment among sorted w."""
    new = np.ones(len(w), np.bool_)
    new[1:] = (w[1:] != w[:-1] + 1) | (seg[w[1:]] != seg[w[:-1]])
    first = np.flatnonzero(new)
    return w[first], w[np.append(first[1:], len(w)) - 1]


def deal_strings(ids: np.ndarray, start: np.ndarray, rows: np.ndarray, buckets: int) -> Iterator[tuple[int, int, bytes]]:
    """Single strings (rows of 50 bytes) by the bucket of all their bytes, of kind 3; these
    buckets have negative numbers."""
    word = np.ascontiguousarray(rows)[:, [*range(LENGTH), *range(LENGTH - 8, LENGTH - 2)]].reshape(-1).view(np.uint64).reshape(len(rows), -1)
    h = np.zeros(len(rows), np.uint64)
    for k in range(word.shape[1]):
        h = mix((h ^ word[:, k]) * np.uint64(0x9E3779B97F4A7C15))
    for b, o in shares((h % np.uint64(buckets * FINER)).astype(np.int64)):
        yield 3, -1 - b, pack(ids[o], start[o], rows[o].reshape(-1))


def take_apart(part: list[np.ndarray], buckets: int) -> Iterator[tuple[int, int, bytes]]:
    """The strings of segments: sorted in pieces, in the order of anchors; those that a
    smaller id of their piece has are removed, the others are dealt."""
    ids, start, count, anchor, buf = part
    size, at = places(count)
    order = np.argsort(anchor_keys(buf, at + anchor), kind="stable")
    total = np.cumsum(count[order].astype(np.int64))
    a = 0
    while a < len(order):
        b = max(a + 1, int(np.searchsorted(total, (total[a - 1] if a else 0) + WINDOWS_AT_ONCE, "right")))
        r, a = order[a:b], b
        n = count[r].astype(np.int64)
        seg, inner = np.repeat(r, n), ragged(np.zeros(len(r), np.int64), n)
        pos, left = at[seg] + inner, np.ones(len(seg), np.bool_)
        for hit in sort_suffixes(buf, pos, np.zeros(len(pos), np.int64), ids[seg]):
            left[hit] = False
        if not left.all():
            f, l = in_runs(np.flatnonzero(~left), seg)  # noqa: E741
            yield from send_ranges(ids[seg[f]], start[seg[f]] + inner[f], start[seg[f]] + inner[l] + LENGTH, buckets)
        rest = np.flatnonzero(left)
        for k in range(0, len(rest), WINDOWS_AT_ONCE // 4):
            w = rest[k : k + WINDOWS_AT_ONCE // 4]
            yield from deal_strings(ids[seg[w]], (start[seg[w]] + inner[w]).astype(np.uint32), buf[pos[w][:, None] + np.arange(LENGTH)], buckets)


class Held:
    """Segments of one bucket, within a bound."""

    def __init__(self, buckets: int, limit: int):
        self.buckets, self.limit, self.parts, self.size, self.hot = buckets, limit, [], 0, np.zeros(0, np.uint64)

    def joined(self) -> list[np.ndarray]:
        self.parts = [[np.concatenate(x) for x in zip(*self.parts, strict=True)]] if len(self.parts) > 1 else self.parts
        return self.parts[0]

    def put(self, part: list[np.ndarray]) -> None:
        self.parts.append(part)
        self.size += sum(x.nbytes for x in part)

    def add(self, part: list[np.ndarray]) -> Iterator[tuple[int, int, bytes]]:
        if len(self.hot):
            apart = np.isin(anchor_keys(part[4], places(part[2])[1] + part[3]), self.hot)
            yield from take_apart(chosen(part, np.flatnonzero(apart)), self.buckets) if apart.any() else ()
            part = chosen(part, np.flatnonzero(~apart))
        if len(part[0]):
            self.put(part)
        if self.size > self.limit:
            yield from self.relieve()

    def relieve(self) -> Iterator[tuple[int, int, bytes]]:
        """Folds equal segments; if that doesn't free a quarter of the bound, the largest
        anchors go, until half of it is free."""
        ids, start, count, anchor, buf = part = self.joined()
        self.parts, self.size = [], 0
        size, at = places(count)
        gone, _, _ = fold(ids, contents(buf, at, size))
        yield from send_ranges(ids[gone], start[gone], start[gone].astype(np.int64) + size[gone], self.buckets)
        part = chosen(part, np.flatnonzero(~gone))
        size, at = places(part[2])
        keys, of = np.unique(anchor_keys(part[4], at + part[3]), return_inverse=True)
        weight = np.bincount(of, weights=size + 14)
        order = np.argsort(-weight, kind="stable")
        rest = weight.sum() - np.concatenate([[0], np.cumsum(weight[order])])
        go = np.zeros(len(keys), np.bool_)
        if rest[0] > 0.75 * self.limit:
            go[order[: int(np.argmax(rest <= self.limit / 2))]] = True
        if go.any():
            self.hot = np.union1d(self.hot, keys[go])
            yield from take_apart(chosen(part, np.flatnonzero(go[of])), self.buckets)
            part = chosen(part, np.flatnonzero(~go[of]))
        if len(part[0]):
            self.put(part)

    def settled(self) -> Iterator[tuple[int, int, bytes]]:
        if self.parts:
            yield from send_ranges(*settle(*self.joined()), self.buckets)
        self.parts, self.size = [], 0


class HeldStrings:
    """Single strings of one bucket; beyond the bound those that are decided go."""

    def __init__(self, buckets: int, limit: int):
        self.buckets, self.limit, self.parts, self.size = buckets, limit, [], 0

    def add(self, part: list[np.ndarray]) -> Iterator[tuple[int, int, bytes]]:
        self.parts.append(part)
        self.size += sum(x.nbytes for x in part)
        if self.size > self.limit:
            yield from self.settled()
            self.limit = max(self.limit, 2 * self.size)

    def settled(self) -> Iterator[tuple[int, int, bytes]]:
        if not self.parts:
            return
        ids, start, buf = (np.concatenate(x) for x in zip(*self.parts, strict=True))
        left = np.ones(len(ids), np.bool_)
        for hit in sort_suffixes(buf, np.arange(len(ids)) * LENGTH, np.zeros(len(ids), np.int64), ids):
            left[hit] = False
        yield from send_ranges(ids[~left], start[~left], start[~left].astype(np.int64) + LENGTH, self.buckets)
        self.parts = [[ids[left], start[left], buf.reshape(-1, LENGTH)[left].reshape(-1)]]
        self.size = sum(x.nbytes for x in self.parts[0])


def settle(ids: np.ndarray, start: np.ndarray, count: np.ndarray, anchor: np.ndarray, buf: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Removed ranges (id, start, end) that these segments decide among them."""
    size, at = places(count)
    key = anchor_keys(buf, at + anchor)
    order = np.argsort(key, kind="stable")
    new = np.ones(len(order), np.bool_)
    new[1:] = key[order][1:] != key[order][:-1]
    first = np.flatnonzero(new)
    lo, hi = np.minimum.reduceat(ids[order], first), np.maximum.reduceat(ids[order], first)
    group = np.cumsum(new) - 1
    shared = (lo != hi)[group]
    mine, group = order[shared], group[shared]  # segments whose anchor several documents hold
    if not len(mine):
        return ids[:0], start[:0], start[:0]
    content = contents(buf, at[mine], size[mine])
    gone, cls, least = fold(ids[mine], content)
    out = [(ids[mine[gone]], start[mine[gone]].astype(np.int64), start[mine[gone]] + size[mine[gone]])]
    # one segment stands for each class; groups of one class are settled
    _, rep = np.unique(np.where(gone, len(least), cls), return_index=True)
    rep = rep[~gone[rep]]
    rep = rep[np.argsort(group[rep], kind="stable")]
    several = np.bincount(group[rep], minlength=group.max() + 1) > 1
    rep = rep[several[group[rep]]]
    if len(rep):
        n = count[mine[rep]].astype(np.int64)
        total, edge = np.cumsum(n), np.flatnonzero(np.append(group[rep][1:] != group[rep][:-1], True)) + 1
        members = np.flatnonzero(~gone)
        members = members[np.argsort(cls[members], kind="stable")]
        member_at = np.searchsorted(cls[members], np.arange(len(least) + 1))
        a = 0
        while a < len(rep):
            base = total[a - 1] if a else 0
            fits = edge[(edge > a) & (total[edge - 1] - base <= WINDOWS_AT_ONCE)]
            b = int(fits[-1]) if len(fits) else int(edge[edge > a][0])
            r = rep[a:b]
            seg, inner = np.repeat(np.arange(len(r)), n[a:b]), ragged(np.zeros(len(r), np.int64), n[a:b])
            pos = at[mine[r]][seg] + inner
            # equal strings have their anchor at the same distance
            g = group[r][seg] * np.int64(64) + (anchor[mine[r]].astype(np.int64)[seg] - inner)
            hit = [x for x in sort_suffixes(buf, pos, g, least[cls[r]][seg]) if len(x)]
            if hit:
                f, l = in_runs(np.sort(np.concatenate(hit)), seg)  # noqa: E741
                c = cls[r[seg[f]]]
                k = member_at[c + 1] - member_at[c]
                m = mine[members[ragged(member_at[c], k)]]
                out.append((ids[m], start[m] + np.repeat(inner[f], k), start[m] + np.repeat(inner[l] + LENGTH, k)))
            a = b
    return tuple(np.concatenate(x) for x in zip(*out, strict=True))


def _rows(rows: Iterator[tuple[int, int, bytes]]) -> Iterator[pa.RecordBatch]:
    for kind, bucket, blob in rows:
        yield pa.RecordBatch.from_arrays([pa.array([kind], pa.int32()), pa.array([bucket], pa.int32()), pa.array([blob], pa.binary())], names=["kind", "bucket", "blob"])


BLOBS = "kind int, bucket int, blob binary"


def _ids(part: pa.RecordBatch, key: str) -> np.ndarray:
    return part.column(part.schema.get_field_index(key)).cast(pa.int64()).fill_null(NULL_ID).to_numpy(zero_copy_only=False)


def _blobs(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[int, int, bytes]]:
    for b in batches:
        for kind, bucket, blob in zip(b.column("kind").to_pylist(), b.column("bucket").to_pylist(), b.column("blob"), strict=True):
            yield kind, bucket, blob.as_py()


def dealt(blobs: DataFrame, buckets: int):
    """Blobs by bucket, in as many partitions as their number asks for."""
    return blobs.repartition(min(MAX_TASKS, max(16, buckets // BUCKETS_A_TASK)), "bucket").groupBy("bucket")


def removed_ranges(docs: DataFrame, buckets: int, key: str = "doc_id", text: str = "text", held: int = HELD_BYTES) -> DataFrame:
    """Blobs of kind 1: removed ranges by their documents' buckets."""

    def send(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        out = Sender(buckets)
        for part, data, offsets in text_slices(batches, text, 1_000_000):
            out.add(_ids(part, key), data, offsets)
            if out.size >= FLUSH_BYTES:
                yield from _rows(out.flush())
        yield from _rows(out.flush())

    def solve(kind: int, here, types, batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Decides the blobs of a kind; others go on as they are."""
        for k, bucket, blob in _blobs(batches):
            yield from _rows(here.add(unpack(blob, *types)) if k == kind else [(k, bucket, blob)])
        yield from _rows(here.settled())
        give_back()

    def meet(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        yield from solve(0, Held(buckets, held), SEGMENTS, batches)

    def finish(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        yield from solve(3, HeldStrings(buckets, held), STRINGS, batches)

    met = dealt(docs.select(key, text).mapInArrow(send, BLOBS), buckets).applyInArrow(meet, BLOBS)
    return dealt(met, buckets).applyInArrow(finish, BLOBS)


def with_ranges(docs: DataFrame, ranges: DataFrame, buckets: int, key: str, text: str, schema: str, finish) -> DataFrame:
    """finish(ids, data, offsets, removed) for the documents of each bucket."""

    def send(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, size = [], 0

        def flush():
            b = np.concatenate([home(i, buckets) for i, _, _ in held]) if held else np.zeros(0, np.int64)
            if not len(b):
                return
            ids, data, n = (np.concatenate(x) for x in zip(*held, strict=True))
            first = np.concatenate([[0], np.cumsum(n)[:-1]])
            for k, o in shares(b):
                yield 2, k, pack(ids[o], n[o], data[ragged(first[o], n[o])])

        for part, data, offsets in text_slices(batches, text):
            held.append((_ids(part, key), data, np.diff(offsets)))
            size += len(data)
            if size >= FLUSH_BYTES:
                yield from _rows(flush())
                held, size = [], 0
        yield from _rows(flush())

    def meet(group: pa.Table) -> pa.Table:
        kinds = group.column("kind").to_numpy()
        blob = lambda kind, *t: [unpack(group.column("blob")[int(i)].as_py(), *t) for i in np.flatnonzero(kinds == kind)]
        texts = blob(2, np.int64, np.int64, np.uint8)
        if not texts:
            return finish(np.zeros(0, np.int64), np.zeros(0, np.uint8), np.zeros(1, np.int64), np.zeros(0, np.bool_))
        ids, n, data = (np.concatenate(x) for x in zip(*texts, strict=True))
        cuts = blob(1, np.int64, np.uint32, np.uint32)
        offsets = np.concatenate([[0], np.cumsum(n)])
        gone = np.zeros(len(data), np.bool_)
        if cuts and len(data):
            of, a, b = (np.concatenate(x).astype(np.int64) for x in zip(*cuts, strict=True))
            order = np.argsort(ids, kind="stable")
            lo, hi = np.searchsorted(ids[order], of, "left"), np.searchsorted(ids[order], of, "right")
            d = order[ragged(lo, hi - lo)]  # repeated rows of a document all lose the range
            a, b = np.minimum(np.repeat(a, hi - lo), n[d]), np.minimum(np.repeat(b, hi - lo), n[d])
            gone = covered(offsets[d] + a, offsets[d] + b, len(data))
        return finish(ids, data, offsets, gone)

    sent = docs.select(key, text).mapInArrow(send, BLOBS)
    return dealt(sent.unionByName(ranges), buckets).applyInArrow(meet, schema)


def bucket_count(docs: DataFrame, text: str = "text") -> int:
    """By the planner's estimate; where it has none (tables that aren't files), by a count.
    The number decides about speed only."""
    size = plan_bytes(docs)
    if size > UNKNOWN_BYTES:
        size = docs.agg(F.sum(F.octet_length(F.col(text)))).first()[0] or 0
    return min(MAX_BUCKETS, max(16, size // BUCKET_BYTES))


def _finish(key: str, texts: bool):
    def finish(ids, data, offsets, gone) -> pa.Table:
        n = np.diff(offsets)
        total = np.zeros(len(gone) + 1, np.int32 if len(gone) < 2**31 else np.int64)
        np.cumsum(gone, out=total[1:])
        removed = total[offsets[1:]] - total[offsets[:-1]]
        begin = gone.copy()
        begin[1:] &= ~gone[:-1]
        inner = offsets[1:-1]
        inner = inner[inner < len(gone)]
        begin[inner] = gone[inner]
        spans = np.zeros_like(total)
        np.cumsum(begin, out=spans[1:])
        spans = spans[offsets[1:]] - spans[offsets[:-1]]
        kept, at = data[~gone].tobytes(), offsets - total[offsets]
        pieces = [kept[a:b] for a, b in zip(at[:-1].tolist(), at[1:].tolist(), strict=True)]
        cols = [pa.array(ids, pa.int64(), mask=ids == NULL_ID), pa.array(n, pa.int64()), pa.array(removed, pa.int64()), pa.array(spans, pa.int64()), pa.array([hashlib.sha256(x).hexdigest() for x in pieces], pa.string())]
        return pa.Table.from_arrays([*cols, *([pa.array(pieces, pa.binary())] if texts else [])], names=[key, *NAMES, *(["kept"] if texts else [])])

    return finish


NAMES = ["n_bytes", "n_removed", "n_spans", "kept_sha256"]


def deduplicate(docs: DataFrame, key: str = "doc_id", text: str = "text", *, texts: bool = True, buckets: int | None = None, held: int = HELD_BYTES) -> DataFrame:
    """Sizes, removed bytes and runs of each document and, as wanted, the bytes kept.
    held: bytes of segments that a bucket holds at once."""
    docs, name, key, text = picked(docs, key=key, text=text), key, "key", "text"
    buckets = buckets or bucket_count(docs, text)
    schema = f"key bigint, n_bytes bigint, n_removed bigint, n_spans bigint, kept_sha256 string" + ", kept binary" * texts
    return with_ranges(docs, removed_ranges(docs, buckets, key, text, held), buckets, key, text, schema, _finish(key, texts)).withColumnRenamed("key", name)


def op6_suffix_dedup(spark, sf_dir: str) -> DataFrame:
    return deduplicate(table(spark, sf_dir, "documents"), texts=False)
