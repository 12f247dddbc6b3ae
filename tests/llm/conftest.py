import random

import pytest


@pytest.fixture(scope="session")
def sample(sf):
    """(doc_id, text) of the smallest documents."""
    import pandas as pd

    d = pd.read_parquet(f"{sf}/documents.parquet")
    return dict(zip(d.doc_id.tolist(), d.text.tolist(), strict=True))


@pytest.fixture(scope="session")
def frame(spark):
    """A documents frame with clashing extra columns from {doc_id: text}."""

    def make(docs, parts=3):
        rows = [(i, t, "en", "s", len(t or ""), "x", 1, "y") for i, t in docs]
        schema = "doc_id long, text string, lang string, source string, n_chars long, _t string, id long, hub string"
        return spark.createDataFrame(rows, schema).repartition(parts) if rows else spark.createDataFrame([], schema)

    return make


EDGES = [None, "", " ", "\n\n", "a", "é😀", "x" * 3000, "the " * 3000, "1" * 2000, "\x00\x7f", "A b c d e f g h i j k"]


@pytest.fixture(scope="session")
def awkward():
    """Texts that must not crash anything, under ids from 900000."""
    return [(900_000 + k, t) for k, t in enumerate(EDGES)] + [(900_100, "same text again, word for word and more"), (900_100, "same text again, word for word and more")]


@pytest.fixture()
def edited():
    """A copy of a text with some words replaced."""

    def edit(text, share, seed):
        rng, w = random.Random(seed), text.split(" ")
        for _ in range(max(1, int(share * len(w)))):
            w[rng.randrange(len(w))] = f"zz{rng.randrange(500)}"
        return " ".join(w)

    return edit
