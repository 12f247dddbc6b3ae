"""Byte-level BPE encoding and decoding by segment trees over adjacent pair ranks.

Each pre-token is a row of leaves, one for each pair of neighbouring symbols, holding
the pair's merge rank. A tree of minima stands over the leaves; its root names the
lowest rank, and of equal ranks the leftmost. One merge changes three leaves at most,
each a logarithmic update, until the root holds no rank. The trees of all pre-tokens
of a batch that are about as long stand in one matrix and merge in step; pre-tokens
beyond ``WIDE`` symbols get a tree of their own, so time stays n log n.

Defined results: a null text is an empty one; an empty text has no ids and decodes
to an empty text; extra columns stay out of the result; repeated rows each give one.
The added token's string gives its id wherever it stands, as in the library.
"""

from __future__ import annotations

import hashlib
import json
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame

from .common import picked, schema_of, table
from .textbuf import ragged, text_slices

SPLIT = regex.compile(r"""'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+""")  # fixed value
WIDE, NONE = 64, np.int64(1) << 40
#: Pre-tokens whose ids a worker keeps; beyond, the store starts anew.
KEPT = 120_000


def byte_alphabet() -> dict[str, int]:
    """The printable character that stands for each byte in byte-level vocabularies."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    rest = [b for b in range(256) if b not in set(plain)]
    return {chr(b): b for b in plain} | {chr(256 + i): b for i, b in enumerate(rest)}


class Tokenizer:
    """Vocabulary, merge ranks and byte tables of one tokenizer file."""

    def __init__(self, path: str):
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        vocab, alphabet = spec["model"]["vocab"], byte_alphabet()
        self.added = {t["content"]: t["id"] for t in spec["added_tokens"]}
        size = max([*vocab.values(), *self.added.values()]) + 1
        raw: list[bytes] = [b""] * size
        for token, i in vocab.items():
            raw[i] = bytes(alphabet[c] for c in token)
        for token, i in self.added.items():
            raw[i] = token.encode()
        self.of_byte = np.zeros(256, np.int64)
        for c, b in alphabet.items():
            self.of_byte[b] = vocab[c]
        pairs = {}
        for rank, pair in enumerate(spec["model"]["merges"]):
            a, b = pair.split(" ") if isinstance(pair, str) else pair
            pairs.setdefault((vocab[a] << 20) | vocab[b], (rank, vocab[a + b]))
        self.pairs = pairs
        self.keys = np.array(sorted(pairs), np.int64)
        self.ranks = np.array([pairs[k][0] for k in self.keys.tolist()], np.int64)
        self.merged = np.zeros(len(pairs), np.int64)
        for rank, token in pairs.values():
            self.merged[rank] = token
        self.lengths = np.array([len(x) for x in raw], np.int64)
        self.starts = np.concatenate([[0], np.cumsum(self.lengths)[:-1]])
        self.bytes = np.frombuffer(b"".join(raw), np.uint8)
        self.special = regex.compile("|".join(map(regex.escape, sorted(self.added, key=len, reverse=True)))) if self.added else None
        # an open-addressed table answers a rank lookup with two or three gathers
        bits = int(len(pairs) * 4 - 1).bit_length()
        self.mask, self.shift = np.int64((1 << bits) - 1), np.uint64(64 - bits)
        slot = self._slot(self.keys)
        self.table_key, self.table_rank = np.full(1 << bits, -1, np.int64), np.full(1 << bits, NONE, np.int64)
        left = np.arange(len(slot))
        while len(left):
            free = self.table_key[slot[left]] < 0
            first = left[free][np.unique(slot[left[free]], return_index=True)[1]]
            self.table_key[slot[first]], self.table_rank[slot[first]] = self.keys[first], self.ranks[first]
            left = left[self.table_key[slot[left]] != self.keys[left]]
            slot[left] = (slot[left] + 1) & self.mask

    def _slot(self, key: np.ndarray) -> np.ndarray:
        return ((key.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) >> self.shift).astype(np.int64)

    def rank(self, left: np.ndarray, right: np.ndarray) -> np.ndarray:
        """Merge ranks of pairs; NONE where a pair doesn't merge."""
        key = (left << np.int64(20)) | right
        slot = self._slot(key)
        out = np.full(len(key), NONE, np.int64)
        todo = np.arange(len(key))
        while len(todo):
            at = self.table_key[slot[todo]]
            hit = at == key[todo]
            out[todo[hit]] = self.table_rank[slot[todo[hit]]]
            todo = todo[~hit & (at >= 0)]
            slot[todo] = (slot[todo] + 1) & self.mask
        return out

    def merge_rows(self, symbols: np.ndarray, lengths: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Ids and their number for each row of a matrix of byte symbols."""
        rows, width = symbols.shape
        size = 1 << max(1, int(width - 1).bit_length())  # leaves
        sym = np.zeros((rows, size + 1), np.int64)
        sym[:, :width] = symbols
        pos = np.arange(size + 1)
        nxt = np.broadcast_to(pos + 1, (rows, size + 1)).copy()
        prv = np.broadcast_to(pos - 1, (rows, size + 1)).copy()
        alive = pos[None, :] < lengths[:, None]
        # a leaf holds rank * size + place: the least is the leftmost of the lowest rank
        tree = np.full((rows, 2 * size), NONE * size, np.int64)
        has = pos[None, : size - 1] < (lengths[:, None] - 1)
        r, c = np.nonzero(has)
        rank = self.rank(sym[r, c], sym[r, c + 1])
        tree[r, size + c] = np.where(rank < NONE, rank * size + c, NONE * size)
        for level in range(size.bit_length() - 2, -1, -1):
            a = 1 << level
            tree[:, a : 2 * a] = np.minimum(tree[:, 2 * a : 4 * a : 2], tree[:, 2 * a + 1 : 4 * a : 2])
        active = np.flatnonzero(tree[:, 1] < NONE * size)
        while len(active):
            root = tree[active, 1]
            at, rank = root % size, root // size
            gone = nxt[active, at]
            after, before = nxt[active, gone], prv[active, at]
            sym[active, at] = self.merged[rank]
            alive[active, gone] = False
            nxt[active, at] = after
            inside = after < lengths[active]
            prv[active[inside], after[inside]] = at[inside]
            self._set(tree, size, active, gone, np.full(len(active), NONE * size))
            value = np.full(len(active), NONE * size)
            if inside.any():
                k = self.rank(sym[active[inside], at[inside]], sym[active[inside], after[inside]])
                value[inside] = np.where(k < NONE, k * size + at[inside], NONE * size)
            self._set(tree, size, active, at, value)
            has = before >= 0
            if has.any():
                a, b = active[has], before[has]
                k = self.rank(sym[a, b], sym[a, at[has]])
                self._set(tree, size, a, b, np.where(k < NONE, k * size + b, NONE * size))
            active = active[tree[active, 1] < NONE * size]
        return sym[:, : size + 1][alive], alive.sum(1)

    @staticmethod
    def _set(tree, size, rows, place, value) -> None:
        node = size + place
        tree[rows, node] = value
        while size > 1:
            node >>= 1
            tree[rows, node] = np.minimum(tree[rows, 2 * node], tree[rows, 2 * node + 1])
            size >>= 1

    def merge_long(self, token: bytes) -> list[int]:
        """The same for one very long pre-token."""
        sym = self.of_byte[np.frombuffer(token, np.uint8)].tolist()
        n, pairs = len(sym), self.pairs
        size = 1 << int(n - 1).bit_length()
        none = (1 << 60, 0)
        tree = [none] * (2 * size)
        nxt, prv = [*range(1, n + 1)], [*range(-1, n - 1)]

        def leaf(i: int):
            j = nxt[i]
            got = pairs.get((sym[i] << 20) | sym[j]) if j < n else None
            return (got[0], i) if got else none

        def put(i: int, value) -> None:
            k = size + i
            tree[k] = value
            while k > 1:
                k >>= 1
                a, b = tree[2 * k], tree[2 * k + 1]
                tree[k] = a if a <= b else b

        for i in range(n):
            tree[size + i] = leaf(i)
        for k in range(size - 1, 0, -1):
            tree[k] = min(tree[2 * k], tree[2 * k + 1])
        while tree[1] is not none and tree[1][0] < none[0]:
            rank, i = tree[1]
            j = nxt[i]
            sym[i], nxt[i] = int(self.merged[rank]), nxt[j]
            sym[j] = -1
            if nxt[i] < n:
                prv[nxt[i]] = i
            put(j, none)
            put(i, leaf(i))
            if prv[i] >= 0:
                put(prv[i], leaf(prv[i]))
        return [s for s in sym if s >= 0]

    def encode_tokens(self, tokens: list[bytes]) -> list[np.ndarray]:
        """Ids of each pre-token."""
        out: list = [None] * len(tokens)
        lengths = np.fromiter(map(len, tokens), np.int64, len(tokens))
        for i in np.flatnonzero(lengths > WIDE).tolist():
            out[i] = np.array(self.merge_long(tokens[i]), np.uint32)
        low = 0
        for width in (1, 2, 4, 8, 16, 32, WIDE):
            which = np.flatnonzero((lengths > low) & (lengths <= width))
            low = width
            for k in range(0, len(which), 32_768):
                rows = which[k : k + 32_768]
                n = lengths[rows]
                flat = self.of_byte[np.frombuffer(b"".join([tokens[i] for i in rows.tolist()]), np.uint8)]
                m = np.zeros((len(rows), width), np.int64)
                m[np.arange(width)[None, :] < n[:, None]] = flat
                ids, count = self.merge_rows(m, n) if width > 1 else (flat, n)
                for i, x in zip(rows.tolist(), np.split(ids.astype(np.uint32), np.cumsum(count)[:-1]), strict=True):
                    out[i] = x
        return out

    def decode_bytes(self, ids: np.ndarray) -> bytes:
        i = ids.astype(np.int64)
        return self.bytes[ragged(self.starts[i], self.lengths[i])].tobytes()

    def decode(self, ids: np.ndarray) -> str:
        """Bytes that are no UTF-8 become replacement characters, as in the library."""
        return self.decode_bytes(ids).decode("utf-8", "replace")


class Encoder:
    """Encodes texts; each different pre-token meets the tree once while it is kept."""

    def __init__(self, tokenizer: Tokenizer):
        self.tokenizer, self.index = tokenizer, {}
        self._reset()

    def _reset(self) -> None:
        self.index.clear()
        self.index |= {("", s): k for k, s in enumerate(self.tokenizer.added)}
        self._store([], [np.array([i], np.uint32) for i in self.tokenizer.added.values()])

    def _store(self, old: list[np.ndarray], new: list[np.ndarray]) -> None:
        """Ids of all kept pre-tokens as one array, with where each begins."""
        n = np.fromiter(map(len, new), np.int64, len(new))
        self.lengths = np.concatenate([self.lengths, n]) if old else n
        self.flat = np.concatenate([*old, *new]) if old or new else np.zeros(0, np.uint32)
        self.starts = np.concatenate([[0], np.cumsum(self.lengths)[:-1]]).astype(np.int64)

    def pieces(self, text: str) -> list:
        t = self.tokenizer
        if t.special is None or not t.special.search(text):
            return SPLIT.findall(text)
        out, at = [], 0
        for m in t.special.finditer(text):
            out += [*SPLIT.findall(text[at : m.start()]), ("", m[0])]
            at = m.end()
        return out + SPLIT.findall(text[at:])

    def encode(self, texts: list[str]) -> list[np.ndarray]:
        if len(self.index) > KEPT:
            self._reset()
        parts = [self.pieces(x) for x in texts]
        new = list(set().union(*parts).difference(self.index)) if parts else []
        if new:
            self.index |= {x: len(self.lengths) + k for k, x in enumerate(new)}
            self._store([self.flat], self.tokenizer.encode_tokens([x.encode() for x in new]))
        out = []
        for p in parts:
            k = np.fromiter(map(self.index.__getitem__, p), np.int64, len(p))
            out.append(self.flat[ragged(self.starts[k], self.lengths[k])] if len(k) else np.zeros(0, np.uint32))
        return out


def default_path() -> str:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.json")


_loaded: dict[str, Encoder] = {}


def encoder(path: str) -> Encoder:
    if path not in _loaded:
        _loaded[path] = Encoder(Tokenizer(path))
    return _loaded[path]


def encode(docs: DataFrame, path: str | None = None, text: str = "text", key: str = "doc_id", *, ids: bool = True, digests: bool = False) -> DataFrame:
    """Per document its key, n_tokens and, as wanted, ``ids``, the decoded text and digests.

    Narrow: no shuffle. Each Arrow batch is cut into slices of bounded bytes.
    """
    path = path or default_path()
    schema = schema_of(docs, [key], "n_tokens bigint" + ", ids array<int>, decoded string" * ids + ", ids_sha256 string, decoded_sha256 string" * digests)
    where = path

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc = encoder(where)
        for part, data, offsets in text_slices(batches, text):
            whole = data.tobytes()
            texts = [whole[a:b].decode("utf-8", "replace") for a, b in zip(offsets[:-1].tolist(), offsets[1:].tolist(), strict=True)]
            got = enc.encode(texts)
            cols = [part.column(part.schema.get_field_index(key)), pa.array([len(x) for x in got], pa.int64())]
            decoded = [enc.tokenizer.decode(x) for x in got]
            if ids:
                flat = np.concatenate(got) if got else np.zeros(0, np.uint32)
                cols += [pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum([len(x) for x in got])]).astype(np.int32)), pa.array(flat.astype(np.int32))), pa.array(decoded, pa.string())]
            if digests:
                cols += [pa.array([hashlib.sha256(x.astype("<u4").tobytes()).hexdigest() for x in got]), pa.array([hashlib.sha256(x.encode()).hexdigest() for x in decoded])]
            yield pa.RecordBatch.from_arrays(cols, names=names)

    names = [key, "n_tokens", *(["ids", "decoded"] * ids), *(["ids_sha256", "decoded_sha256"] * digests)]
    return picked(docs, **{key: key, text: text}).mapInArrow(run, schema)


def decode(encoded: DataFrame, path: str | None = None, ids: str = "ids", key: str = "doc_id") -> DataFrame:
    """Texts of id arrays; a null array decodes to an empty text."""
    path = path or default_path()
    schema = schema_of(encoded, [key], "text string")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tok = encoder(path).tokenizer
        for b in batches:
            got = [tok.decode(np.array(x.as_py() or [], np.int64)) for x in b.column(1)]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(got, pa.string())], names=[key, "text"])

    return picked(encoded, **{key: key, ids: ids}).mapInArrow(run, schema)


def op4_bpe(spark, sf_dir: str) -> DataFrame:
    return encode(table(spark, sf_dir, "documents"), ids=False, digests=True)
