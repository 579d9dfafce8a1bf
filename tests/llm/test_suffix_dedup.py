import hashlib
import random
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import Row

from obljoin.llm import suffix_dedup
from obljoin.llm.suffix_dedup import LENGTH, repeated_windows, strip


def brute(texts):
    """(n_bytes, n_removed, n_spans, sha of the rest) of each text."""
    bodies = [(t or "").encode() for t in texts]
    seen = Counter(b[i : i + LENGTH] for b in bodies for i in range(len(b) - LENGTH + 1))
    out = []
    for b in bodies:
        gone = np.zeros(len(b), bool)
        for i in range(len(b) - LENGTH + 1):
            if seen[b[i : i + LENGTH]] > 1:
                gone[i : i + LENGTH] = True
        rest = np.frombuffer(b, np.uint8)[~gone].tobytes()
        spans = int(gone[:1].sum() + (gone[1:] & ~gone[:-1]).sum())
        out.append((len(b), int(gone.sum()), spans, hashlib.sha256(rest).hexdigest()))
    return out


def corpus(seed, n=60):
    rng = random.Random(seed)
    words = ["".join(rng.choice("abé日") for _ in range(rng.randint(1, 5))) for _ in range(60)]
    prose = lambda k: " ".join(rng.choice(words) for _ in range(k))
    shared = [prose(150) for _ in range(4)]
    texts = [None, "", "short", "a" * 900, "ab" * 300, "x" * LENGTH, "\0" * 450]
    for _ in range(n):
        part = rng.choice(shared)
        i = rng.randrange(len(part) // 2)
        texts.append(prose(rng.randint(0, 50)) + part[i : i + rng.randrange(60, 300)] + prose(rng.randint(0, 50)))
    return texts + [texts[-1]] * 3 + [texts[-2]]


def run(spark, texts):
    docs = spark.createDataFrame([Row(doc_id=i, text=t, h=1, start="clash") for i, t in enumerate(texts)], "doc_id long, text string, h int, start string")
    rows = {r.doc_id: tuple(r)[1:] for r in strip(docs).collect()}
    return [rows[i] for i in range(len(texts))]


def test_matches_brute_force(spark):
    texts = corpus(1)
    assert run(spark, texts) == brute(texts)


def test_split_anchors_and_pieces(spark, monkeypatch):
    """Tiny limits, so that long texts are cut in pieces."""
    monkeypatch.setattr(suffix_dedup, "SHARD_CONTEXTS", 2)
    texts = corpus(2, 40)
    assert run(spark, texts) == brute(texts)


def test_shards_tell_each_other_of_repeated_windows(spark, monkeypatch):
    """Each shard judged alone: what is repeated in one of them stands once in another, or as a context of two texts."""
    monkeypatch.setattr(suffix_dedup, "SHARD_CONTEXTS", 2)
    monkeypatch.setattr(suffix_dedup, "SHARD_BYTES", 1)
    rng = random.Random(5)
    noise = lambda n: "".join(rng.choice("abcdefgh ") for _ in range(n))
    common, part = noise(150), noise(120)
    texts = [noise(90) + common + noise(90) for _ in range(30)]
    texts += [noise(90) + common + part + noise(90) for _ in range(3)]
    texts += [noise(90) + common + noise(90)] * 2 + [noise(20) + texts[3][60:300] + noise(20), noise(20) + texts[-1][60:300] + noise(20)]
    coalesced = spark.conf.get("spark.sql.adaptive.coalescePartitions.enabled")
    spark.conf.set("spark.sql.adaptive.coalescePartitions.enabled", "false")
    try:
        assert run(spark, texts) == brute(texts)
    finally:
        spark.conf.set("spark.sql.adaptive.coalescePartitions.enabled", coalesced)


def test_a_line_in_very_many_texts(spark, monkeypatch):
    """A common line with groups of three that share more; many small shards in many partitions, that nothing joins."""
    monkeypatch.setattr(suffix_dedup, "SHARD_CONTEXTS", 16)
    monkeypatch.setattr(suffix_dedup, "SHARD_BYTES", 1)
    rng = random.Random(11)
    noise = lambda n: "".join(rng.choice("abcdefghij ") for _ in range(n))
    line, more = noise(200), [noise(40) for _ in range(20)]
    texts = [noise(60) + line + (more[i % 20] if i < 60 else "") + noise(60) for i in range(800)]
    kept = {k: spark.conf.get(k) for k in ("spark.sql.adaptive.enabled", "spark.sql.shuffle.partitions")}
    spark.conf.set("spark.sql.adaptive.enabled", "false")
    spark.conf.set("spark.sql.shuffle.partitions", "16")
    try:
        assert run(spark, texts) == brute(texts)
    finally:
        for k, v in kept.items():
            spark.conf.set(k, v)


def test_runs_are_merged_by_search():
    rng = random.Random(12)
    for n in range(1, 9):
        runs = [sorted(rng.sample(range(40), rng.randint(1, 30))) for _ in range(n)]
        marks = [np.array([b"%016d" % x for x in r], "S16") for r in runs]
        want = sorted(x for x, c in Counter(x for r in runs for x in r).items() if c > 1)
        assert suffix_dedup.met_in_two(marks).tolist() == [b"%016d" % x for x in want]


def test_repeated_ids_and_rows(spark):
    part = "".join(random.Random(13).choice("abcdef ") for _ in range(260))
    docs = spark.createDataFrame([(1, "x" + part), (1, "y" + part), (1, "x" + part), (None, part + "z"), (None, None)], "doc_id long, text string")
    rows = sorted(tuple(r)[:4] for r in strip(docs).collect() if r.doc_id is not None)
    assert rows == [(1, 261, 260, 1), (1, 261, 261, 1), (1, 261, 261, 1)]
    assert sorted(tuple(r)[1:4] for r in strip(docs).where("doc_id is null").collect()) == [(0, 0, 0), (261, 260, 1)]


def test_long_text_in_pieces(monkeypatch):
    monkeypatch.setattr(suffix_dedup, "PIECE", 300)
    monkeypatch.setattr(suffix_dedup, "BLOCK_BYTES", 256)
    data = np.frombuffer(random.Random(4).randbytes(2000), np.uint8)
    offsets = np.array([0, 2000])
    starts = []
    for part, at, _, begin in suffix_dedup._pieces(data, offsets):
        first, last, _, owner, _ = suffix_dedup.contexts(part, at)
        starts += [w + begin[o] for a, b, o in zip(first, last, owner, strict=True) for w in range(a, b + 1)]
    assert sorted(starts) == list(range(2000 - LENGTH + 1))


def test_empty_table(spark):
    assert strip(spark.createDataFrame([], "doc_id long, text string")).collect() == []


@pytest.mark.parametrize("seed", range(3))
def test_windows_of_random_strings(seed):
    rng = random.Random(seed)
    part = bytes(rng.choice(b"ab") for _ in range(600))
    texts = [part[i : i + rng.randrange(200, 400)] for i in range(0, 300, 23)] + [b"a" * 500, b"b" * 199, b"\0" * 300]
    seen = Counter(t[i : i + LENGTH] for t in texts for i in range(len(t) - LENGTH + 1))
    flags = repeated_windows(texts, np.ones(len(texts)))
    assert [f.tolist() for f in flags] == [[seen[t[i : i + LENGTH]] > 1 for i in range(len(t) - LENGTH + 1)] for t in texts]
