"""Toxicity by a classifier chain.

Categories are predicted one after another by linear models over hashed words and word
beginnings; each later model also gets the earlier categories' probabilities. A later
model learns from out-of-fold predictions of the earlier ones, so it meets in training
the kind of probabilities it meets afterwards.

Labels may carry any number of category columns. Where only ``toxic`` is labelled, two
graded categories are made from it with the learned lead terms (features nearly only
toxic training texts have): ``dense`` (a toxic text with a lead term in each hundred
words or more) and ``repeated`` (three or more lead terms). ``toxic`` ends the chain.
Features, lead terms and so the graded categories are chosen anew for each fold, from the
rows outside it: an out-of-fold probability has seen nothing of its own fold.

Learning uses a bounded sample: ``SAMPLE`` labelled rows of each class with the least
hashes of their ids, weighted back to the classes' shares. Labels are sampled before
they meet the documents, so texts are never shuffled. Scoring is narrow.

Defined results: null and empty texts have no feature, and texts without features are
learned to be clean; without usable labels every score is 0; repeated rows each give a
row; labels of absent documents and null labels teach nothing; of several labels of one
document the greatest counts; extra columns are kept where asked for.
"""

from __future__ import annotations

import pickle
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import fold, picked, schema_of, table
from .textbuf import LOWER, WORD, give_back, prefix_sums, run_hashes, text_slices, words

SAMPLE, FEATURES, FOLDS, BITS = 2500, 1024, 4, 18
HEADS = (4, 6, 8)
CATEGORIES = ("dense", "repeated", "toxic")


def feature_rows(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(document, feature) of every word and word beginning; words of each document."""
    data = LOWER[data]
    starts, ends, bounds = words(data, offsets, WORD)
    sums, n = prefix_sums(data), np.diff(bounds)
    doc = np.repeat(np.arange(len(n)), n)
    shift = np.uint64(64 - BITS)
    feats, docs = [(run_hashes(sums, starts, ends) >> shift).astype(np.int32)], [doc]
    for k in HEADS:
        long = np.flatnonzero(ends - starts > k)
        h = run_hashes(sums, starts[long], starts[long] + k) ^ np.uint64(0xA5A5A5A5A5A5A5A5)
        feats.append((h >> shift).astype(np.int32))
        docs.append(doc[long])
    return np.concatenate(docs), np.concatenate(feats), n


def counted(doc: np.ndarray, feature: np.ndarray, width: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    key, count = np.unique(doc * np.int64(width) + feature, return_counts=True)
    return key // width, key % width, count


def sigmoid(x: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(x, -30, 30)))


def logistic(x: np.ndarray, y: np.ndarray, w: np.ndarray, l2: float = 1e-4, steps: int = 300) -> np.ndarray:
    """Weights, the last one the intercept, by accelerated gradient steps."""
    x = np.hstack([x, np.ones((len(x), 1), x.dtype)])
    w = (w / w.sum()).astype(x.dtype)
    v = np.ones(x.shape[1], x.dtype)
    for _ in range(12):  # power iteration: the steepest curvature bounds the step
        v = x.T @ (w * (x @ v))
        top = float(np.linalg.norm(v))
        v /= max(top, 1e-12)
    rate, a, look, t = 1 / (0.25 * top + l2), np.zeros(x.shape[1], x.dtype), None, 1.0
    look = a.copy()
    for _ in range(steps):
        grad = x.T @ (w * (sigmoid(x @ look) - y)).astype(x.dtype) + l2 * look
        new = look - rate * grad
        t2 = (1 + np.sqrt(1 + 4 * t * t)) / 2
        look = (new + (t - 1) / t2 * (new - a)).astype(x.dtype)
        a, t = new, t2
    return a


@dataclass
class Chain:
    """Feature columns by hashed feature and, for each category, its weights."""

    lut: np.ndarray
    weights: list[np.ndarray] = field(default_factory=list)
    categories: tuple[str, ...] = CATEGORIES
    threshold: float = 0.5

    def probabilities(self, data: np.ndarray, offsets: np.ndarray) -> np.ndarray:
        doc, feature, n = feature_rows(data, offsets)
        col = self.lut[feature]
        known = col >= 0
        doc, col, _ = counted(doc[known], col[known], FEATURES)
        out = np.zeros((len(n), len(self.categories)))
        for j, w in enumerate(self.weights):
            z = np.bincount(doc, w[col], len(n)) + out[:, :j] @ w[FEATURES : FEATURES + j] + w[-1]
            out[:, j] = sigmoid(z)
        return out


def fit_chain(view, w: np.ndarray, part: np.ndarray, truth: np.ndarray) -> tuple[list[np.ndarray], float]:
    """Chain weights and the threshold of the last category with the best F1 out of fold.

    view(k): features and categories as they look from outside fold k; view(None): from all."""
    all_x, all_y = view(None)
    seen = np.zeros((len(all_x), all_y.shape[1]), np.float32)
    for j in range(seen.shape[1]):  # a fold's later models need all folds' earlier probabilities
        for k in range(FOLDS):
            held = part == k
            if held.any() and not held.all():
                x, y = view(k)
                inputs = np.hstack([x, seen[:, :j]])
                a = logistic(inputs[~held], y[~held, j], w[~held])
                seen[held, j] = sigmoid(inputs[held] @ a[:-1] + a[-1])
    weights = [logistic(np.hstack([all_x, seen[:, :j]]), all_y[:, j], w).astype(np.float64) for j in range(seen.shape[1])]
    score, truth = seen[:, -1], truth > 0
    order = np.argsort(-score, kind="stable")
    hit, all_ = np.cumsum((w * truth)[order]), np.cumsum(w[order])
    f1 = 2 * hit / (all_ + (w * truth).sum())
    best = int(f1.argmax())
    here = float(score[order[best]])
    below = float(score[order[best + 1]]) if best + 1 < len(order) else 0.0
    return weights, (here + below) / 2


def _sampled(labels: DataFrame, each: int) -> DataFrame:
    one = labels.groupBy("_k").agg(F.max(F.col("_y").cast("int")).alias("_y"))
    part = [one.where(F.col("_y") == y).orderBy(F.xxhash64("_k"), "_k").limit(each) for y in (0, 1)]
    return part[0].unionByName(part[1]).withColumn("_f", F.pmod(F.xxhash64(F.lit("fold"), "_k"), F.lit(FOLDS)).cast("int"))


def chosen(n0: np.ndarray, n1: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The features that tell most by chi-square, of counts of texts by class (the last
    entry: all texts), and which of them are lead terms."""
    total = np.array([n0[-1], n1[-1]], float)
    n0, n1 = n0[:-1], n1[:-1]
    p0, p1 = (n0 + 0.5) / (total[0] + 1), (n1 + 0.5) / (total[1] + 1)
    both = (n0 + n1 + 1.0) / (total.sum() + 2)
    chi = np.where(n0 + n1 > 0, total.prod() / total.sum() * (p0 - p1) ** 2 / (both * (1 - both) + 1e-9), -1.0)
    order = np.lexsort((np.arange(len(chi)), -chi))[:FEATURES]
    order = order[chi[order] >= 0]
    return order, (p1[order] > 20 * p0[order]) & (n1[order] >= max(3, 0.02 * total[1]))


def train(docs: DataFrame, labels: DataFrame, key: str = "doc_id", text: str = "text", label: str = "toxic", each: int = SAMPLE) -> Chain | None:
    """A chain learned from a bounded sample of the labels; None if a class has no row."""
    labels = picked(labels, _k=key, _y=label).where("_k IS NOT NULL AND _y IS NOT NULL")
    share = {r[0]: r[1] for r in labels.groupBy(F.col("_y").cast("int")).count().collect()}
    sample = F.broadcast(_sampled(labels, each))  # 2 * each rows at most
    rows = picked(docs, _k=key, text=text).join(sample, "_k")
    column = lambda part, c: part.column(part.schema.get_field_index(c))
    width = 1 << BITS

    def tally(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cell = {}  # (fold, class): texts with each feature, and all
        for part, data, offsets in text_slices(batches, "text"):
            doc, feature, _ = feature_rows(data, offsets)
            doc, feature, _ = counted(doc, feature, width)
            y, f = column(part, "_y").to_numpy(), column(part, "_f").to_numpy()
            group = f * 2 + y
            for g in np.unique(group).tolist():
                n = cell.setdefault(g, np.zeros(width + 1, np.int32))
                n[:-1] += np.bincount(feature[group[doc] == g], minlength=width).astype(np.int32)
                n[-1] += (group == g).sum()
        for g, n in cell.items():
            at = np.flatnonzero(n)
            yield pa.RecordBatch.from_arrays([pa.array(np.full(len(at), g, np.int32)), pa.array(at.astype(np.int32)), pa.array(n[at])], names=["g", "f", "n"])

    sums = rows.mapInArrow(tally, "g int, f int, n int").groupBy("g", "f").agg(F.sum("n").alias("n")).toArrow()  # 2 * FOLDS * 2 ** BITS rows at most
    count = np.zeros((2 * FOLDS, width + 1), np.int64)
    count[sums["g"].to_numpy(), sums["f"].to_numpy()] = sums["n"].to_numpy()
    del sums
    n0, n1 = count[0::2], count[1::2]
    if n0[:, -1].sum() == 0 or n1[:, -1].sum() == 0:
        return None
    picks = {k: chosen(n0.sum(0) - (n0[k] if k is not None else 0), n1.sum(0) - (n1[k] if k is not None else 0)) for k in (None, *range(FOLDS))}
    union = np.unique(np.concatenate([p[0] for p in picks.values()]))
    of = np.full(width, -1, np.int32)
    of[union] = np.arange(len(union))

    def rows_of(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part, data, offsets in text_slices(batches, "text"):
            doc, feature, n = feature_rows(data, offsets)
            col = of[feature]
            known = col >= 0
            doc, col, times = counted(doc[known], col[known], len(union))
            off = pa.array(np.searchsorted(doc, np.arange(len(n) + 1)).astype(np.int32))
            yield pa.RecordBatch.from_arrays([column(part, "_k").cast(pa.string()), column(part, "_y"), column(part, "_f"), pa.array(n), pa.ListArray.from_arrays(off, pa.array(col.astype(np.int32))), pa.ListArray.from_arrays(off, pa.array(times.astype(np.int32)))], names=["k", "y", "f", "n", "cols", "times"])

    def fit(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        got = pa.Table.from_batches(batches).to_pandas()
        got = got.sort_values(["k", "n"], kind="stable").reset_index(drop=True)
        # a text without any feature is no toxic one: rows of zeros say so, with a small weight
        blank = 2 * FOLDS
        size = len(got) + blank
        row = np.repeat(np.arange(len(got)), [len(c) for c in got.cols])
        col = np.concatenate([*got.cols, np.zeros(0, np.int32)]).astype(np.int64)
        times = np.concatenate([*got.times, np.zeros(0, np.int32)]).astype(np.float64)
        toxic = np.append(got.y.to_numpy(np.float32), np.zeros(blank, np.float32))
        n_words = np.append(got.n.to_numpy(), np.zeros(blank, np.int64))
        part = np.append(got.f.to_numpy(), np.arange(blank) % FOLDS)
        w = np.where(toxic > 0, share.get(1, 0) / max(1, (toxic > 0).sum()), share.get(0, 0) / max(1, len(got) - (toxic > 0).sum())).astype(np.float32)
        w[len(got) :] = 0.02 * w[: len(got)].sum() / blank

        def view(k: int | None) -> tuple[np.ndarray, np.ndarray]:
            features, lead = picks[k]
            place = np.full(len(union), -1, np.int64)
            place[of[features]] = np.arange(len(features))
            here = np.flatnonzero(place[col] >= 0)
            x = np.zeros((size, FEATURES), np.float32)
            x[row[here], place[col[here]]] = 1
            led = np.zeros(len(union), np.bool_)
            led[of[features[lead]]] = True
            leads = np.bincount(row[led[col]], times[led[col]], size)
            return x, np.stack([toxic * (leads * 100 >= np.maximum(n_words, 1)), toxic * (leads >= 3), toxic], 1).astype(np.float32)

        model = pickle.dumps(fit_chain(view, w, part, toxic))
        give_back()
        yield pa.RecordBatch.from_arrays([pa.array([model], pa.binary())], names=["model"])

    # the driver keeps what learning takes out of its memory: one task learns, from 2 * each rows at most
    features = rows.mapInArrow(rows_of, "k string, y int, f int, n bigint, cols array<int>, times array<int>")
    weights, threshold = pickle.loads(features.repartition(1).mapInArrow(fit, "model binary").first()["model"])
    lut = np.full(width, -1, np.int16)
    lut[picks[None][0]] = np.arange(len(picks[None][0]))
    return Chain(lut, weights, CATEGORIES, threshold)


def score(docs: DataFrame, chain: Chain | None, keep: list[str], text: str = "text") -> DataFrame:
    """The kept columns, p_<category> of each and the verdict ``is_toxic``."""
    names = CATEGORIES if chain is None else chain.categories
    schema = schema_of(docs, keep, "".join(f"p_{c} double, " for c in names) + "is_toxic boolean")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part, data, offsets in text_slices(batches, text):
            p = np.zeros((part.num_rows, len(names))) if chain is None else chain.probabilities(data, offsets)
            bad = np.zeros(len(p), np.bool_) if chain is None else p[:, -1] >= chain.threshold
            cols = [part.column(part.schema.get_field_index(c)) for c in keep]
            yield pa.RecordBatch.from_arrays([*cols, *(pa.array(p[:, j]) for j in range(len(names))), pa.array(bad)], names=[*keep, *(f"p_{c}" for c in names), "is_toxic"])

    return picked(docs, **{c: c for c in [*keep, text]}).mapInArrow(run, schema)


def op5_toxicity(spark, sf_dir: str) -> DataFrame:
    """Learns from labelled rows whose ``fold`` isn't 0."""
    docs, labels = table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels")
    chain = train(docs, labels.where(fold() != 0))
    return score(picked(docs, doc_id="doc_id", text="text").withColumn("fold", fold()), chain, ["doc_id", "fold"])
