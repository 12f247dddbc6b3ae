"""Vectorised work on Arrow text columns: whole batches as one byte buffer.

Every kernel of this subpackage that must run in Python reads its texts through
these helpers, so that no per-word or per-character Python code is needed. A null
text is an empty one. Nothing here keeps more than one slice of a batch in memory.
"""

from __future__ import annotations

import ctypes
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash

#: Bytes of text that a kernel handles at once; a longer document is handled alone.
SLICE_BYTES = 2_000_000
_P = np.uint64(0x9E3779B97F4A7C15)
_PINV = np.uint64(pow(0x9E3779B97F4A7C15, -1, 1 << 64))
_powers: dict[int, np.ndarray] = {}


def buffers(col: pa.Array | pa.ChunkedArray) -> tuple[np.ndarray, np.ndarray]:
    """(bytes, offsets) of a string or binary column; nulls have no bytes."""
    if isinstance(col, pa.ChunkedArray):
        col = col.combine_chunks() if col.num_chunks != 1 else col.chunk(0)
    if col.null_count:
        col = col.fill_null(b"" if pa.types.is_binary(col.type) or pa.types.is_large_binary(col.type) else "")
    wide = pa.types.is_large_string(col.type) or pa.types.is_large_binary(col.type)
    _, off, data = col.buffers()
    if len(col) == 0 or off is None:
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    offsets = np.frombuffer(off, np.int64 if wide else np.int32)[col.offset : col.offset + len(col) + 1].astype(np.int64)
    raw = np.frombuffer(data, np.uint8) if data is not None else np.zeros(0, np.uint8)
    return raw[offsets[0] : offsets[-1]], offsets - offsets[0]


def slices(offsets: np.ndarray, limit: int = SLICE_BYTES) -> Iterator[tuple[int, int]]:
    """Row ranges [i, j) of at most ``limit`` bytes, or of one row."""
    i, n = 0, len(offsets) - 1
    while i < n:
        j = max(i + 1, int(np.searchsorted(offsets, offsets[i] + limit, "right")) - 1)
        yield i, min(j, n)
        i = j


def give_back() -> None:
    """Returns freed memory to the system: Python workers live on from task to task."""
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL(None).malloc_trim(0)
    except (AttributeError, OSError):  # not glibc
        pass


def text_slices(batches, column: str = "text", limit: int = SLICE_BYTES):
    """(record batch slice, bytes, offsets) for each slice of each Arrow batch."""
    for batch in batches:
        data, offsets = buffers(batch.column(batch.schema.get_field_index(column)))
        for i, j in slices(offsets, limit):
            yield batch.slice(i, j - i), data[offsets[i] : offsets[j]], offsets[i : j + 1] - offsets[i]
        del data, offsets, batch
    give_back()


def powers(n: int, inverse: bool = False) -> np.ndarray:
    """P**0 ... P**(n-1) modulo 2**64, or the powers of P's inverse."""
    got = _powers.get(int(inverse))
    if got is None or len(got) < n:
        size = max(1 << 16, 1 << int(n - 1).bit_length())
        step, got = int(_PINV if inverse else _P), np.empty(size, np.uint64)
        got[0], done = 1, 1
        while done < size:
            got[done : 2 * done] = got[:done] * np.uint64(step)
            step, done = step * step % (1 << 64), 2 * done
        if size <= 1 << 22:
            _powers[int(inverse)] = got
    return got[:n]


def mix(h: np.ndarray) -> np.ndarray:
    """Spreads the bits of 64-bit hashes, in place."""
    h ^= h >> np.uint64(31)
    h *= np.uint64(0xBF58476D1CE4E5B9)
    h ^= h >> np.uint64(29)
    h *= np.uint64(0x94D049BB133111EB)
    h ^= h >> np.uint64(32)
    return h


def prefix_sums(values: np.ndarray) -> np.ndarray:
    """S[i]: sum of values[j] * P**j over j < i; from it the hash of any run follows."""
    out = np.zeros(len(values) + 1, np.uint64)
    np.cumsum((values.astype(np.uint64) + np.uint64(1)) * powers(len(values)), out=out[1:])
    return out


def run_hashes(sums: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """64-bit hashes of the runs [start, end), equal for equal contents."""
    h = (sums[ends] - sums[starts]) * powers(len(sums), True)[starts]
    h ^= (ends - starts).astype(np.uint64) * np.uint64(0xD6E8FEB86659FD93)
    return mix(h)


#: Longer words are hashed by xxhash: the sums above are blind to some patterns of 2 ** 10 letters.
LONG_WORD = 64


def word_hashes(data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """64-bit hashes of words."""
    h = run_hashes(prefix_sums(data), starts, ends)
    for i in np.flatnonzero(ends - starts > LONG_WORD).tolist():
        h[i] = xxhash.xxh64_intdigest(data[starts[i] : ends[i]].tobytes())
    return h


def joined(data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The words behind each other, a blank after each, and where each begins, and the end."""
    size = ends - starts + 1
    first = np.concatenate([[0], np.cumsum(size)])
    out = np.full(int(first[-1]), 32, np.uint8)
    inner = np.ones(len(out), np.bool_)
    inner[first[1:] - 1] = False
    out[inner] = data[ragged(starts, size - 1)]
    return out, first


def words(data: np.ndarray, offsets: np.ndarray, is_word: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(starts, ends, bounds): maximal runs of bytes that is_word marks, never across
    documents; bounds[d]:bounds[d+1] are the words of document d."""
    n = len(data)
    inside = np.zeros(n + 2, np.bool_)
    inside[1:-1] = is_word[data]
    starts = inside[1:-1] & ~inside[:-2]
    ends = inside[1:-1] & ~inside[2:]
    cut = offsets[1:-1]
    cut = cut[(cut > 0) & (cut < n)]
    starts[cut] |= inside[cut + 1]
    ends[cut - 1] |= inside[cut]
    starts, ends = np.flatnonzero(starts), np.flatnonzero(ends) + 1
    return starts, ends, np.searchsorted(starts, offsets)


def ragged(starts: np.ndarray, lengths: np.ndarray) -> np.ndarray:
    """The concatenated ranges start, start+1, ... of the given lengths."""
    total = int(lengths.sum())
    if not total:
        return np.zeros(0, np.int64)
    out = np.ones(total, np.int64)
    keep = lengths > 0
    s, n = starts[keep].astype(np.int64), lengths[keep].astype(np.int64)
    at = np.concatenate([[0], np.cumsum(n)[:-1]])
    out[at] = s
    out[at[1:]] -= s[:-1] + n[:-1] - 1
    return np.cumsum(out)


def covered(starts: np.ndarray, ends: np.ndarray, n: int) -> np.ndarray:
    """Boolean of length n: positions inside any of the ranges [start, end)."""
    edge = np.zeros(n + 1, np.int32)
    np.add.at(edge, starts, 1)
    np.add.at(edge, ends, -1)
    return np.cumsum(edge[:n], dtype=np.int32) > 0


#: Lower-cased ASCII; the word bytes of the benchmark contract: digits, a-z and all of other alphabets.
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32
WORD = np.zeros(256, np.bool_)
WORD[48:58] = WORD[97:123] = WORD[65:91] = WORD[128:] = True
#: Bytes that are no white space of the quality contract.
SOLID = np.ones(256, np.bool_)
SOLID[[32, 9, 10, 11, 12, 13]] = False
