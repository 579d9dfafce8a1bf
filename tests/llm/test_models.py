"""Language identification and toxicity: held-out accuracy on the given tables, and edge cases."""

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import Row
from pyspark.sql import functions as F

from obljoin.llm import langid, queries, toxicity
from obljoin.llm.common import blocks, utf8

SF = "/root/testdata/sf0.1"


def test_codewords_are_apart():
    for n in (2, 3, 4, 7, 12, 40):
        code = langid.codewords(n)
        assert len(code) == n and set(np.unique(code)) <= {-1.0, 1.0}
        apart = (code.shape[1] - code @ code.T) / 2 + 10**6 * np.eye(n)
        assert apart.min() >= (1 if n == 2 else 2)


def test_language_accuracy(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    out = queries.op2_language_id(spark, SF).join(docs.select("doc_id", "lang"), "doc_id").where("held_out")
    right, n = out.agg(F.avg((F.col("lang") == F.col("lang_pred")).cast("int")), F.count("*")).first()
    assert n > 3000 and right > 0.99
    assert out.where("score < 0 or score > 1").count() == 0


def test_language_edges(spark):
    words = {"aa": "banana papaya tatata", "bb": "orokoro momolo", "cc": "xyzzy qwqw"}
    rows = [Row(doc_id=i, text=words[k] * (1 + i % 3), lang=k, score=1) for i, k in enumerate(list(words) * 12)]
    rows += [Row(doc_id=900, text=None, lang="aa", score=1), Row(doc_id=901, text="123 !?", lang=None, score=1), Row(doc_id=None, text="banana papaya", lang=None, score=1), Row(doc_id=902, text="", lang="bb", score=1)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, score int")
    model = langid.train(docs, langid.remainder("doc_id", 3) != 1)
    out = {r.doc_id: r for r in langid.identify(docs, model).collect()}
    assert out[900].lang_pred == out[901].lang_pred == out[902].lang_pred == "und" and out[900].score == 0 and out[900].ambiguous
    assert out[None].lang_pred == "aa"
    assert all(out[r.doc_id].lang_pred == r.lang for r in rows[:36])
    whole = langid.identify(docs, model, whole=True).select("row.*").collect()
    assert sorted(map(str, whole)) == sorted(map(str, docs.collect()))
    none = langid.train(docs.where("lang = 'zz'"), F.lit(True))
    assert none is None and {r.lang_pred for r in langid.identify(docs, none).collect()} == {"und"}
    one = langid.train(docs.where("lang = 'aa'"), F.lit(True))
    assert {r.score for r in langid.identify(docs.where("doc_id < 36"), one).collect()} == {1.0}
    assert langid.identify(docs.limit(0), model).collect() == []


def test_models_take_long_texts_repeated_ids_and_any_names(spark):
    long = "banana papaya tatata " * 60_000
    rows = [Row(doc_id=i % 20, text=t, lang=k, toxic=j, row="x", order=1, label=5) for i in range(30) for k, t, j in (("aa", "banana papaya", 0), ("bb", "orokoro momolo", 1))]
    rows += [Row(doc_id=100, text=long, lang="aa", toxic=0, row="x", order=1, label=5), Row(doc_id=101, text=long, lang="aa", toxic=0, row="x", order=1, label=5)]
    docs = spark.createDataFrame(rows)
    out = langid.identify(docs, langid.train(docs, F.lit(True))).where("doc_id >= 100").collect()
    assert [r.lang_pred for r in out] == ["aa", "aa"] and out[0].score == out[1].score
    labels = docs.select("doc_id", "toxic").where("doc_id < 100")
    model = toxicity.train(docs.select("doc_id", "text", "label", "order"), labels, F.lit(True))
    scored = toxicity.score(docs, model).collect()
    assert len(scored) == len(rows) and all(0 <= r.score <= 1 for r in scored)
    assert len({r.score for r in scored if r.doc_id >= 100}) == 1


def test_short_rows_make_small_blocks():
    offsets = np.arange(10_001) * 3
    sizes = [b - a for a, b in blocks(offsets, langid.BLOCK_BYTES, langid.BLOCK_ROWS)]
    assert sum(sizes) == 10_000 and max(sizes) == langid.BLOCK_ROWS


def test_bags_agree_with_scoring():
    texts = ["Some words, here!", "", "a", "ab abc", "é x " * 50, "one-two 3"]
    data, offsets = utf8(pa.array(texts))
    rng = np.random.default_rng(1)
    model = toxicity.ToxicityModel(rng.normal(size=1 << toxicity.BUCKET_BITS).astype(np.float32), 0.25)
    slow = [model.bias + float((model.buckets[c].astype(np.float64) * w).sum()) for c, w in toxicity.bags(data, offsets)]
    assert model.logits(data, offsets) == pytest.approx(slow, abs=1e-4)


def test_toxicity_accuracy(spark):
    labels = spark.read.parquet(f"{SF}/labels.parquet")
    out = queries.op9_toxicity(spark, SF).join(labels, "doc_id").where("held_out")
    got = {r.toxic: r.p for r in out.groupBy("toxic").agg(F.avg("predicted").alias("p")).collect()}
    assert got[1] - got[0] > 0.6  # about 350 documents of label 1 to learn from
    assert out.where("score < 0 or score > 1").count() == 0


def test_misspellings_share_vectors(spark):
    rng = np.random.default_rng(3)
    words = ["".join(rng.choice(list("aeioumnrst"), 5)) for _ in range(80)]
    prose = lambda: " ".join(rng.choice(words, 40))
    rows, marks = [], []
    for i in range(240):
        bad = i % 2 == 0
        rows.append((i, prose() + (" xqzblorkev xqzblorkev" if bad else "")))
        marks.append((i, int(bad)))
    rows += [(500, prose() + " xqzblorkez xqzblorkez"), (501, prose()), (502, None), (503, "")]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    labels = spark.createDataFrame(marks, "doc_id long, toxic int")
    model = toxicity.train(docs, labels, F.lit(True))
    out = {r.doc_id: r.score for r in toxicity.score(docs, model).collect()}
    assert out[500] > out[501] and out[502] == out[503]
    assert toxicity.train(docs, labels.where("toxic > 1"), F.lit(True)) is None
    assert {r.score for r in toxicity.score(docs, None).collect()} == {0.0}
