"""Language identification by cross-parsing entropy.

For each language a suffix automaton of sample text is built. A text is parsed against
each: from where the last phrase ended, the longest string that the sample contains is
the next phrase. The language whose sample needs the fewest phrases a letter wins; the
counts are normalised by the expected gain of the samples' sizes, which are alike.

Automata are dense tables over the letter classes of the sample, so that thousands of
blocks of text walk at once: one gather a byte. A text is parsed in blocks of ``BLOCK``
bytes, all of it, each block starting a phrase. Tasks get the samples only (a stated
number of bytes a language, chosen by a hash of the text over all labelled rows) and
build the tables once a worker.

Defined results: null, empty and letterless texts are ``und`` with score 0; nothing
learned (no labelled row) gives ``und`` too; ties go to the first language by name;
rows with a null language teach nothing; repeated rows each give a row.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import regex
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import fold, picked, schema_of, table
from .textbuf import text_slices

BLOCK = 512
#: Bounded sample of labelled rows: rows a language, and bytes of their texts that are kept.
SAMPLE_ROWS, SAMPLE_BYTES, PIECE = 64, 24_000, 750
LETTER = regex.compile(r"\p{L}")
MISS = np.int32(1 << 30)


def fold_case(text: str) -> bytes:
    """Lower case; all ASCII but letters is a space."""
    return text.lower().encode().translate(_ASCII)


_ASCII = bytes(b if b >= 128 or 97 <= b <= 122 else 32 for b in range(256))


class Automaton:
    """Suffix automaton of a byte string as a dense table.

    table[state * classes + class] is the next state; with MISS set the byte begins a
    phrase: no such string is in the sample, and the state is the one after that byte
    alone (the root, if the sample lacks it)."""

    def __init__(self, sample: bytes):
        seen = sorted(set(sample))
        self.of = np.zeros(256, np.int32)
        for i, b in enumerate(seen):
            self.of[b] = i + 1
        self.classes = len(seen) + 1
        nxt, link, length, last = [{}], [-1], [0], 0
        for b in sample:
            c = int(self.of[b])
            cur = len(nxt)
            nxt.append({})
            length.append(length[last] + 1)
            link.append(0)
            p = last
            while p >= 0 and c not in nxt[p]:
                nxt[p][c] = cur
                p = link[p]
            if p >= 0:
                q = nxt[p][c]
                if length[p] + 1 == length[q]:
                    link[cur] = q
                else:
                    copy = len(nxt)
                    nxt.append(dict(nxt[q]))
                    length.append(length[p] + 1)
                    link.append(link[q])
                    while p >= 0 and nxt[p].get(c) == q:
                        nxt[p][c] = copy
                        p = link[p]
                    link[q] = link[cur] = copy
            last = cur
        again = np.zeros(self.classes, np.int32)
        for c, s in nxt[0].items():
            again[c] = s
        out = np.tile((again * self.classes) | MISS, len(nxt))
        rows = np.fromiter((i * self.classes + c for i, m in enumerate(nxt) for c in m), np.int64)
        to = np.fromiter((s for m in nxt for s in m.values()), np.int64)
        out[rows] = (to * self.classes).astype(np.int32)
        out[: self.classes] |= MISS  # at the root every byte begins a phrase
        self.table = out

    def phrases(self, blocks: np.ndarray, lengths: np.ndarray) -> np.ndarray:
        """Phrases of each block; blocks[k] has byte k of all, longest blocks first."""
        state, count = np.zeros(len(lengths), np.int32), np.zeros(len(lengths), np.int32)
        live = np.searchsorted(-lengths, -np.arange(len(blocks)), "left")
        cls, low = self.of[blocks], MISS - 1
        for k in range(len(blocks)):
            m = live[k]
            if not m:
                break
            got = self.table[state[:m] + cls[k, :m]]
            count[:m] += got >> 30
            state[:m] = got & low
        return count


class Model:
    def __init__(self, samples: dict[str, bytes]):
        self.langs = sorted(samples)
        self.automata = [Automaton(samples[x]) for x in self.langs]

    def rates(self, texts: list[bytes]) -> np.ndarray:
        """Phrases a byte of each text by language."""
        sizes = np.fromiter(map(len, texts), np.int64, len(texts))
        data = np.frombuffer(b"".join(texts), np.uint8)
        begin = np.concatenate([[0], np.cumsum(sizes)[:-1]])
        per = -(-sizes // BLOCK)
        doc = np.repeat(np.arange(len(texts)), per)
        first = np.concatenate([[0], np.cumsum(per)[:-1]])
        inner = (np.arange(len(doc)) - first[doc]) * BLOCK
        n = np.minimum(BLOCK, sizes[doc] - inner)
        order = np.argsort(-n, kind="stable")
        doc, start, n = doc[order], (begin[doc] + inner)[order], n[order]
        out = np.zeros((len(texts), len(self.langs)))
        step = 8192
        for a in range(0, len(doc), step):
            s, m, d = start[a : a + step], n[a : a + step], doc[a : a + step]
            at = np.minimum(s[None, :] + np.arange(m[0])[:, None], len(data) - 1)
            blocks = data[at]
            for j, auto in enumerate(self.automata):
                out[:, j] += np.bincount(d, auto.phrases(blocks, m), len(texts))
        return out / np.maximum(sizes, 1)[:, None]


def learn_samples(labelled: DataFrame, lang: str = "lang", text: str = "text", rows: int = SAMPLE_ROWS, size: int = SAMPLE_BYTES) -> dict[str, bytes]:
    """Sample text of each language: pieces from evenly spaced places of ``rows`` texts,
    those with the least hashes; the number of languages bounds what is collected."""
    has = picked(labelled, l=lang, t=text).where(F.col("l").isNotNull() & F.col("t").rlike(r"\p{L}"))
    n = F.char_length("t")
    piece = lambda k: F.substring(F.col("t"), (n * k / 4).cast("int") + 1, PIECE)
    top = F.xxhash64("t")
    part = has.select("l", top.alias("h"), F.array_distinct(F.when(n <= PIECE, F.array(F.col("t"))).otherwise(F.array(*[piece(k) for k in range(4)]))).alias("p"))

    def least(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        kept = None
        for f in frames:
            f["p"] = [list(x) for x in f["p"]]
            kept = f if kept is None else pd.concat([kept, f])
            kept = kept.drop_duplicates("h").sort_values("h").groupby("l").head(rows)
        if kept is not None:
            yield kept

    some = part.mapInPandas(least, "l string, h bigint, p array<string>").dropDuplicates(["l", "h"])
    rank = F.row_number().over(Window.partitionBy("l").orderBy("h"))
    best = some.withColumn("r", rank).where(F.col("r") <= rows).toPandas().sort_values(["l", "h"])
    out = {}
    for name, group in best.groupby("l"):
        pieces = [x for r in range(4) for p in group["p"] for x in list(p)[r : r + 1]]
        out[name] = b" ".join(fold_case(x) for x in pieces)[:size]
    return out


_made: dict[int, Model] = {}


def model(samples: dict[str, bytes]) -> Model:
    key = hash(tuple(sorted(samples.items())))
    if key not in _made:
        _made.clear()
        _made[key] = Model(samples)
    return _made[key]


def identify(docs: DataFrame, samples: dict[str, bytes], keep: list[str], text: str = "text") -> DataFrame:
    """The kept columns, lang_pred and score of each row. Narrow: no shuffle."""
    schema = schema_of(docs, keep, "lang_pred string, score double")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part, data, offsets in text_slices(batches, text, 4_000_000):
            whole = data.tobytes()
            raw = [whole[a:b].decode("utf-8", "replace") for a, b in zip(offsets[:-1].tolist(), offsets[1:].tolist(), strict=True)]
            m = model(samples) if samples else None
            letters = np.array([bool(m) and LETTER.search(x) is not None for x in raw], np.bool_)
            lang, score = np.full(len(raw), "und", object), np.zeros(len(raw))
            if letters.any():
                rates = m.rates([fold_case(x) if ok else b"" for x, ok in zip(raw, letters, strict=True)])
                best = rates.argmin(1)
                gain = np.exp(-25 * (rates - rates.min(1)[:, None]))
                lang[letters] = np.array(m.langs, object)[best[letters]]
                score[letters] = (1 / gain.sum(1))[letters]
            cols = [part.column(part.schema.get_field_index(c)) for c in keep]
            yield pa.RecordBatch.from_arrays([*cols, pa.array(lang.tolist(), pa.string()), pa.array(score)], names=[*keep, "lang_pred", "score"])

    return picked(docs, **{c: c for c in [*keep, text]}).mapInArrow(run, schema)


def op7_langid(spark, sf_dir: str) -> DataFrame:
    docs = picked(table(spark, sf_dir, "documents"), doc_id="doc_id", text="text", lang="lang").withColumn("held_out", fold(parts=3) == 1)
    samples = learn_samples(docs.where(~F.col("held_out")))
    return identify(docs, samples, ["doc_id", "held_out"])
