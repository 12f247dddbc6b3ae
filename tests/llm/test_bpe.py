import hashlib

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from hetpart.llm import bpe

tokenizers = pytest.importorskip("tokenizers")
PATH = bpe.default_path()


@pytest.fixture(scope="module")
def library():
    return tokenizers.Tokenizer.from_file(PATH)


def test_query_equals_the_library(spark, frame, sample, awkward, library):
    docs = [*sample.items(), *awkward, (5_000_000, "<|endoftext|>a <|endoftext|>"), (5_000_001, "it's they'll 12 ½ ³\r\n\t  x")]
    got = bpe.encode(frame(docs), ids=True, digests=True).collect()
    assert len(got) == len(docs)
    want = {i: library.encode(t or "", add_special_tokens=False).ids for i, t in docs}
    for r in got:
        ids = want[r["doc_id"]]
        assert r["ids"] == ids and r["n_tokens"] == len(ids)
        assert r["ids_sha256"] == hashlib.sha256(np.array(ids, "<u4").tobytes()).hexdigest()
        text = library.decode(ids, skip_special_tokens=False)
        assert r["decoded"] == text and r["decoded_sha256"] == hashlib.sha256(text.encode()).hexdigest()
    back = {r["doc_id"]: r["text"] for r in bpe.decode(bpe.encode(frame(docs))).collect()}
    assert back == {i: t or "" for i, t in docs}


@settings(max_examples=150, deadline=None)
@given(st.text(max_size=120))
def test_any_text(text):
    lib = tokenizers.Tokenizer.from_file(PATH) if not hasattr(test_any_text, "lib") else test_any_text.lib
    test_any_text.lib = lib
    enc = bpe.encoder(PATH)
    ids = enc.encode([text])[0]
    assert ids.tolist() == lib.encode(text, add_special_tokens=False).ids
    assert enc.tokenizer.decode(ids) == text


def test_ids_that_are_no_text(library):
    tok = bpe.encoder(PATH).tokenizer
    for ids in ([133], [133, 222, 5], list(range(100, 220)), []):
        assert tok.decode(np.array(ids, np.int64)) == library.decode(ids, skip_special_tokens=False)


def test_long_token_agrees_with_the_matrix(monkeypatch):
    tok = bpe.encoder(PATH).tokenizer
    word = b" international" * 4
    assert tok.merge_long(word) == tok.encode_tokens([word])[0].tolist()


def test_empty_table(frame):
    assert bpe.encode(frame([])).count() == 0
