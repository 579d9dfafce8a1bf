import hashlib
import random

import numpy as np
import public_tokenizers
import pyarrow as pa
import pytest
import tiktoken
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import Row

from obljoin.llm import bpe
from obljoin.llm.common import utf8

PATH = public_tokenizers.path("byte_bpe_multi_50k.tiktoken")
RANKS = bpe.load_ranks(PATH)
REFERENCE = tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=RANKS, special_tokens={})


def encoded(texts):
    data, offsets = utf8(pa.array(texts, pa.string()))
    return [np.frombuffer(x, "<u4").tolist() for x in bpe.encode_texts(data, offsets, bpe.Pieces(RANKS))]


@settings(max_examples=300, deadline=None)
@given(st.lists(st.text(alphabet="aéZ1٣²  \n\t 　'stmdrevl!?日𝒳́😀", max_size=30), max_size=6))
def test_same_ids_as_the_reference(texts):
    assert encoded(texts) == [REFERENCE.encode_ordinary(t) for t in texts]


def test_long_and_odd_texts():
    texts = ["", "a" * 5000, "!" * 4000, " \n " * 900, "it's we're I'll 'street ''s 's's \n's  's", "<|endoftext|>", "x\0y"]
    assert encoded(texts) == [REFERENCE.encode_ordinary(t) for t in texts]


def test_scan_is_associative():
    """Block sizes do not matter: the scan gives the states of a plain walk."""
    products, effects, *_ = bpe.monoid()
    rng = np.random.default_rng(1)
    elements = rng.integers(0, len(effects), 20_000).astype(np.uint8)
    state, want = bpe.START, []
    for e in elements.tolist():
        want.append(state)
        state = effects[e, state]
    assert bpe.states_before(elements).tolist() == want
    for _ in range(200):
        a, b, c = rng.integers(0, len(effects), 3).tolist()
        left = products[int(products[a << 8 | b]) << 8 | c]
        assert left == products[a << 8 | int(products[b << 8 | c])]


@pytest.mark.parametrize("n", [3, 50, 400])
def test_long_pieces_merge_like_short_ones(n):
    rng = random.Random(n)
    for _ in range(20):
        piece = "".join(rng.choice("theaonid") for _ in range(n)).encode()
        if piece not in RANKS:
            assert bpe._merge_long(piece, RANKS) == REFERENCE.encode_ordinary(piece.decode())
            assert bpe.merge(piece, RANKS) == bpe._merge_long(piece, RANKS)


def test_cache_is_bounded_and_does_not_change_results(monkeypatch):
    monkeypatch.setattr(bpe, "CACHED_PIECES", 4)
    text = " ".join(f"w{i} the of" for i in range(50))
    pieces = bpe.Pieces(RANKS)
    data, offsets = utf8(pa.array([text]))
    assert np.frombuffer(next(bpe.encode_texts(data, offsets, pieces)), "<u4").tolist() == REFERENCE.encode_ordinary(text)
    assert len(pieces) <= 4 and len(pieces.old) <= 4


def test_operator_and_decoding(spark):
    texts = [(1, "Hello, wörld's end"), (2, None), (3, ""), (3, "again"), (None, "x" * 3000)]
    docs = spark.createDataFrame([Row(doc_id=i, text=t, ids="clash") for i, t in texts], "doc_id long, text string, ids string")
    full = bpe.encode(docs, PATH)
    for r in full.collect():
        assert len(r.ids) == len(r.offsets)
    back = bpe.decode(full, PATH).collect()
    assert sorted((r.doc_id or 0, bytes(r.data).decode()) for r in back) == sorted((i or 0, t or "") for i, t in texts)
    rows = {(r.doc_id, r.n_bytes): r for r in bpe.token_digests(docs, PATH).collect()}
    for i, t in texts:
        r = rows[i, len((t or "").encode())]
        ids = REFERENCE.encode_ordinary(t or "")
        assert r.n_tokens == len(ids) and r.ids_sha256 == hashlib.sha256(np.array(ids, "<u4").tobytes()).hexdigest()
        assert r.decoded_sha256 == hashlib.sha256((t or "").encode()).hexdigest()
    assert bpe.token_digests(docs.limit(0), PATH).collect() == []
