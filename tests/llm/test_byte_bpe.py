import hashlib

import numpy as np
import public_tokenizers as P
import pytest
import tiktoken
from hypothesis import given, settings, strategies as st

from pacedfl.llm.byte_bpe import ByteBpe, bpe_documents, load_ranks

PATH = P.path("byte_bpe_50k.tiktoken")
BPE = ByteBpe(load_ranks(PATH), P.PATTERN)
LIBRARY = tiktoken.Encoding("own", pat_str=P.PATTERN, mergeable_ranks=load_ranks(PATH), special_tokens={})


@settings(max_examples=150, deadline=None)
@given(st.lists(st.text(), max_size=5))
def test_equals_library(batch):
    for text, ids in zip(batch, BPE.encode_batch(batch), strict=True):
        assert np.frombuffer(ids, "<u4").tolist() == LIBRARY.encode_ordinary(text)
        assert BPE.decode(ids) == text.encode()


@pytest.mark.parametrize("text", ["", "a" * 5000, "ab" * 200 + "!?" * 300, "é" * 400, " \n\t " * 50, "日本語🎉" * 30, "<|endoftext|>", "x" * 256, "x" * 257])
def test_odd_texts(text):
    (ids,) = BPE.encode_batch([text])
    assert np.frombuffer(ids, "<u4").tolist() == LIBRARY.encode_ordinary(text)


@pytest.mark.parametrize("seed", range(6))
def test_wide_rows_equal_library_and_matrices(seed):
    """Pieces around and far beyond the width that has a matrix of its own, in alphabets that repeat and overlap."""
    rng = np.random.default_rng(seed)
    letters = ["ab", "aab", "abcdefghijklmnopqrstuvwxyz", "tionesr", "ACGT", "x"][seed]
    for n in (255, 256, 257, 300, 2000, 20000):
        piece = "".join(rng.choice(list(letters), n)).encode()
        assert np.frombuffer(BPE._wide(piece), "<u4").tolist() == LIBRARY._core_bpe.encode_single_piece(piece)
        if n <= 300:
            assert BPE._matrix([piece], 512) == [BPE._wide(piece)]


def test_documents(spark):
    docs = spark.createDataFrame([(1, "Hello world", "x"), (2, None, "x"), (2, None, "x"), (None, "", "x")], "doc_id long, text string, n_tokens string")
    rows = bpe_documents(docs, PATH, P.PATTERN, with_ids=True).collect()
    assert len(rows) == 4
    one = next(r for r in rows if r.doc_id == 1)
    assert one.ids == LIBRARY.encode_ordinary("Hello world") and one.n_tokens == len(one.ids)
    assert one.ids_sha256 == hashlib.sha256(np.array(one.ids, "<u4").tobytes()).hexdigest()
    assert one.decoded_sha256 == hashlib.sha256(b"Hello world").hexdigest()
    assert all(r.n_tokens == 0 for r in rows if r.doc_id != 1)
    assert bpe_documents(docs.limit(0), PATH, P.PATTERN).count() == 0


def test_whole_table_equals_library(spark, small):
    from pacedfl.llm.queries import op6_bpe

    want = {r.doc_id: LIBRARY.encode_ordinary(r.text or "") for r in spark.read.parquet(f"{small}/documents.parquet").collect()}
    for r in op6_bpe(spark, small).collect():
        assert r.n_tokens == len(want[r.doc_id]) and r.ids_sha256 == hashlib.sha256(np.array(want[r.doc_id], "<u4").tobytes()).hexdigest()
