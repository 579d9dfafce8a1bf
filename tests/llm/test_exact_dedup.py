import hashlib
import random

import numpy as np
import pytest
from pyspark.sql import Row

from obljoin.llm.exact_dedup import BASES, CHUNK, PRIME, combine, deduplicated, exact_dedup, fingerprints

UPPER = str.maketrans({c: c.lower() for c in "ABCDEFGHIJKLMNOPQRSTUVWXYZ"})


def horner(data, base, prime):
    h = 0
    for b in data:
        h = (h * base + b) % prime
    return h


def test_fingerprints_are_the_polynomial():
    rng = random.Random(1)
    texts = [b"", b"a", bytes(CHUNK), rng.randbytes(CHUNK), rng.randbytes(CHUNK + 1), rng.randbytes(5000)]
    data = np.frombuffer(b"".join(texts), np.uint8)
    offsets = np.cumsum([0, *map(len, texts)])
    got = fingerprints(data, offsets)
    assert got.tolist() == [[horner(t, b, PRIME) for b in BASES] for t in texts]


def test_pieces_combine():
    rng = random.Random(2)
    whole = rng.randbytes(700)
    for cut in (0, 1, 350, 700):
        left, right = whole[:cut], whole[cut:]
        assert combine(horner(left, BASES[0], PRIME), horner(right, BASES[0], PRIME), len(right), BASES[0]) == horner(whole, BASES[0], PRIME)


def rows():
    texts = ["Hello World", "hello world", "HELLO WORLD", "hello  world", None, "", "É", "é", "x" * 200_000, "X" * 200_000, "tie", "tie"]
    return [(i, t) for i, t in enumerate(texts, 5)] + [(99, "same row"), (99, "same row"), (None, "no id"), (3, "no id"), (None, "alone")]


@pytest.mark.parametrize("prime", [PRIME, 3])
def test_matches_brute_force(spark, prime):
    """With a tiny prime nearly all texts of one length share a fingerprint, and the comparison has to part them."""
    docs = spark.createDataFrame([Row(doc_id=i, text=t, row=0, kept="clash") for i, t in rows()], "doc_id long, text string, row int, kept string")
    groups = {}
    for i, t in rows():
        groups.setdefault((t or "").translate(UPPER), []).append(i)
    got = exact_dedup(docs, prime=prime).collect()
    assert len(got) == len(rows())
    want = sorted((str(i), str(max((x for x in ids if x is not None), default=None)), len(ids), hashlib.sha256(t.encode()).hexdigest()) for t, ids in groups.items() for i in ids)
    assert sorted((str(r.doc_id), str(r.keep_id), r.group_size, r.text_sha256) for r in got) == want
    assert sum(r.kept for r in got) == len(groups)


def test_rows_that_stay(spark):
    docs = spark.createDataFrame([Row(doc_id=i, text=t, row=k) for k, (i, t) in enumerate(rows())], "doc_id long, text string, row int")
    stay = deduplicated(docs)
    assert stay.columns == docs.columns
    kept = [(r.text or "").translate(UPPER) for r in stay.collect()]
    assert sorted(kept) == sorted({(t or "").translate(UPPER) for _, t in rows()})


def test_empty_table(spark):
    empty = spark.createDataFrame([], "doc_id long, text string")
    assert exact_dedup(empty).collect() == [] and deduplicated(empty).collect() == []
