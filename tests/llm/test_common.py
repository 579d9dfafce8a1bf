import random

import numpy as np
import pyarrow as pa
from pyspark.sql import functions as F

from obljoin.llm.common import attach, blocks, in_bitmap, keep_rows, key_bitmap, utf8
from obljoin.llm.components import connected_components


def test_attach_joins_hot_and_other_keys(spark):
    rows = spark.range(3000).select(F.when(F.col("id") < 1500, -1).otherwise(F.col("id")).alias("k"), F.col("id").alias("v"))
    groups = rows.groupBy("k").agg(F.count("*").alias("n"), F.min("v").alias("first"))
    out = attach(rows, groups, ["k"], "n")
    assert out.count() == 3000 and out.where("k = -1 and first = 0").count() == 1500
    assert attach(rows.limit(0), groups.limit(0), ["k"], "n").collect() == []


def test_bitmap_never_misses(spark):
    keys = spark.range(500).select((F.xxhash64("id")).alias("h"))
    bitmap = key_bitmap(keys, F.col("h"), 17)
    assert len(bitmap) == 1 << 14
    assert in_bitmap(bitmap, np.array([r.h for r in keys.collect()], np.int64)).all()
    others = np.random.default_rng(1).integers(-(1 << 62), 1 << 62, 5000)
    assert in_bitmap(bitmap, others).mean() < 0.02
    assert not key_bitmap(keys.limit(0), F.col("h"), 16).any()


def test_components_of_chains_stars_and_cycles(spark):
    rng = random.Random(1)
    edges = [(i, i + 1) for i in range(200)] + [(500, i) for i in range(501, 560)] + [(700, 701), (701, 702), (702, 700), (9, 9)]
    rng.shuffle(edges)
    edges += [(b, a) for a, b in edges[:40]]
    found = {r.node: r.root for r in connected_components(spark.createDataFrame(edges, "a long, b long")).collect()}
    want = {i: 0 for i in range(201)} | {i: 500 for i in range(500, 560)} | {700: 700, 701: 700, 702: 700}
    assert found == want
    assert connected_components(spark.createDataFrame([], "a long, b long")).collect() == []


def test_blocks_cover_all_rows():
    _, offsets = utf8(pa.array(["a" * n for n in (0, 5, 100, 0, 3, 3)] + [None]))
    assert list(blocks(offsets, 10)) == [(0, 2), (2, 3), (3, 7)]
    assert list(blocks(np.zeros(1, np.int64), 10)) == []
    data, offsets = utf8(pa.array(["xx", "é", None, "z"]).slice(1, 3))
    assert bytes(data) == "éz".encode() and offsets.tolist() == [0, 2, 2, 3]


def test_keep_rows_tells_repeats_apart(spark):
    docs = spark.createDataFrame([(1, "a", "x"), (1, "a", "y"), (1, "b", "z"), (None, "c", "w"), (None, "c", "v")], "doc_id long, text string, more string")
    judged = docs.select("doc_id", F.xxhash64("text").alias("content"), F.row_number().over(__import__("pyspark").sql.Window.partitionBy("doc_id", "text").orderBy("more")).alias("n"))
    kept = keep_rows(docs, judged, F.col("n") == 1)
    assert kept.columns == docs.columns
    assert sorted(str(tuple(r)[:2]) for r in kept.collect()) == sorted(["(1, 'a')", "(1, 'b')", "(None, 'c')"])


def test_keep_rows_with_clashing_names(spark):
    names = ["_id", "_KEY", "_content", "_stay", "_all", "_n", "content"]
    rows = [(i, t, *range(k, k + len(names))) for k, (i, t) in enumerate([(1, "a"), (1, "a"), (2, "b"), (None, None)])]
    docs = spark.createDataFrame(rows, "doc_id long, text string, " + ", ".join(f"{n} long" for n in names))
    judged = docs.select("doc_id", F.xxhash64(F.coalesce("text", F.lit(""))).alias("content"), F.row_number().over(__import__("pyspark").sql.Window.partitionBy("doc_id", "text").orderBy("_id")).alias("n"))
    kept = keep_rows(docs, judged, F.col("n") == 1)
    assert kept.columns == docs.columns
    assert sorted(map(str, kept.collect())) == sorted(str(r) for r in docs.collect() if r["_id"] != 1)
