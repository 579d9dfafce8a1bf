import hashlib
import random
from fractions import Fraction

import numpy as np
import pytest
from pyspark.sql import Row
from pyspark.sql import functions as F

from obljoin.llm import ann, mixing


def brute(rows, k):
    good = {}
    for i, v in rows:
        if i is not None and v is not None and len(v) == 8 and all(x is not None and np.isfinite(x) for x in v) and any(v):
            good[i] = np.array(v, np.float64)
    out = {}
    for q in good:
        if q % 5 == 0:
            scored = sorted(((-float(good[q] @ v), i) for i, v in good.items() if i != q))
            out[q] = [(i, -s) for s, i in scored[:k]]
    return out


def test_search_matches_brute_force(spark, monkeypatch):
    monkeypatch.setattr(ann, "LIST_ROWS", 40)
    monkeypatch.setattr(ann, "TUNED_RECALL", 1.0)
    monkeypatch.setattr(ann, "CONFIDENCE", 50.0)
    rng = np.random.default_rng(1)
    rows = [(int(i), [float(np.float32(x)) for x in rng.normal(size=8)]) for i in range(300)]
    rows += [(300 + i, rows[10][1]) for i in range(60)] + [(400, None), (405, [0.0] * 8), (410, [1.0] * 7), (415, [float("nan")] + [1.0] * 7), (420, [None] + [1.0] * 7), (None, [1.0] * 8)]
    table = spark.createDataFrame([Row(vec_id=i, embedding=v, list=1) for i, v in rows], "vec_id long, embedding array<float>, list int")
    found = {}
    for r in ann.search(table, F.col("vec_id") % 5 == 0).collect():
        found.setdefault(r.query_id, []).append((r["rank"], r.vec_id, r.score))
    want = brute(rows, 20)
    assert set(found) == set(want)
    hits = 0
    for q, hit in found.items():
        hit.sort()
        assert [r for r, _, _ in hit] == list(range(1, 21))
        scores = {i: s for i, s in want[q]}
        hits += sum(i in scores for _, i, _ in hit)
        assert all(i != q for _, i, _ in hit)
        assert [(-s, i) for _, i, s in hit] == sorted((-s, i) for _, i, s in hit)
    assert hits == 20 * len(want)


def test_recall_of_the_scan_alone(spark, monkeypatch):
    """Far more vectors than the sample holds: what is found comes from the probed lists."""
    monkeypatch.setattr(ann, "SAMPLE", 300)
    rng = np.random.default_rng(3)
    for rows in (rng.normal(size=(3000, 32)), rng.normal(size=(40, 32))[rng.integers(0, 40, 3000)] * 2 + rng.normal(size=(3000, 32))):
        rows = rows.astype(np.float32)
        table = spark.createDataFrame([(int(i), [float(x) for x in v]) for i, v in enumerate(rows)], "vec_id long, embedding array<float>")
        exact = rows[::20].astype(np.float64) @ rows.astype(np.float64).T
        exact[np.arange(len(exact)), np.arange(0, 3000, 20)] = -np.inf
        want = {(20 * q, int(i)) for q, line in enumerate(np.argsort(-exact, axis=1)[:, :20]) for i in line}
        got = ann.search(table, F.col("vec_id") % 20 == 0).collect()
        assert len(got) == len(want)
        assert len(want & {(r.query_id, r.vec_id) for r in got}) >= 0.9 * len(want)
        assert [r.score for r in got] == pytest.approx([exact[r.query_id // 20, r.vec_id] for r in got], rel=1e-12)


def test_a_query_that_finds_too_few_scans_all_lists(spark, monkeypatch):
    monkeypatch.setattr(ann, "TUNED_RECALL", 0.0)  # one list
    rng = np.random.default_rng(4)
    rows = [(i, [float(x) for x in rng.normal(size=6)]) for i in range(30)]
    got = ann.search(spark.createDataFrame(rows, "vec_id long, embedding array<float>"), F.col("vec_id") < 5).collect()
    assert len(got) == 5 * 20 and len({(r.query_id, r.vec_id) for r in got}) == 100
    want = {q: [i for _, i in sorted((-float(np.dot(rows[q][1], v)), i) for i, v in rows if i != q)[:20]] for q in range(5)}
    assert all([r.vec_id for r in sorted(got, key=lambda r: r["rank"]) if r.query_id == q] == want[q] for q in want)


def test_one_vector_of_an_id_takes_part(spark):
    rows = [(1, [1.0, 0.0]), (1, [0.0, 1.0]), (2, [1.0, 1.0]), (3, [2.0, 1.0]), (2, [1.0, 1.0])]
    got = ann.search(spark.createDataFrame(rows, "vec_id long, embedding array<float>"), F.lit(True)).collect()
    assert sorted((r.query_id, r["rank"]) for r in got) == [(q, r) for q in (1, 2, 3) for r in (1, 2)]
    assert {(r.query_id, r.vec_id) for r in got} == {(a, b) for a in (1, 2, 3) for b in (1, 2, 3) if a != b}


def test_few_and_no_rows(spark):
    table = spark.createDataFrame([(0, [1.0, 0.0]), (1, [0.0, 1.0]), (2, [1.0, 1.0])], "vec_id long, embedding array<float>")
    assert [(r.query_id, r["rank"], r.vec_id) for r in ann.search(table, F.col("vec_id") == 0).orderBy("rank").collect()] == [(0, 1, 2), (0, 2, 1)]
    assert ann.search(table.limit(0), F.col("vec_id") == 0).collect() == []
    assert ann.search(table.limit(1), F.col("vec_id") == 0).collect() == []


def test_abandoning_saves_work_and_keeps_recall():
    rng = np.random.default_rng(2)
    rows = rng.normal(size=(30, 64))[rng.integers(0, 30, 3000)] * 2 + rng.normal(size=(3000, 64)) * 0.5
    index = ann.build(rows[:1000], float((rows**2).sum(axis=1).max()), 3000)
    queries = rows[:50]
    products = queries @ rows.T
    best = np.argsort(-products, axis=1)[:, :20]
    limits = np.einsum("nd,nd->n", queries, queries) + index.longest - 2 * np.sort(products[:, :1000], axis=1)[:, -20]
    q, v, p, read = ann.scan(index, rows, queries, limits, 20)
    assert read < 0.6 * 50 * 3000 * 65
    got = {(a, b) for a, b in zip(q.tolist(), v.tolist(), strict=True)}
    assert sum((i, j) in got for i in range(50) for j in best[i].tolist()) >= 0.9 * 50 * 20
    assert p == pytest.approx(products[q, v])


def test_shares_redistribute():
    share = lambda b, w, m: mixing.share_out(Fraction(b), [Fraction(x) for x in w], [Fraction(x) for x in m])
    assert share(100, [1, 1], [100, 100]) == [50, 50]
    assert share(100, [1, 1], [10, 100]) == [10, 90]
    assert share(100, [1, 1, 2], [10, 100, 40]) == [10, 50, 40]
    assert share(100, [1, 0], [30, 100]) == [30, 0]


def test_siblings_come_before_ancestors():
    supply = {("a", "x"): 10, ("a", "y"): 100, ("b", "x"): 500}
    given = mixing.budgets(supply, {}, 120, 1)
    assert given == {("a", "x"): 10, ("a", "y"): 50, ("b", "x"): 60}  # y takes what x lacks; b keeps its half
    assert mixing.budgets(supply, {}, 400, 1) == {("a", "x"): 10, ("a", "y"): 100, ("b", "x"): 290}
    assert mixing.budgets(supply, {("b",): 0}, 400, 2) == {("a", "x"): 20, ("a", "y"): 200, ("b", "x"): 0}


def test_window_shares_match_exact_ones(spark):
    rng = random.Random(5)
    supply = {(rng.choice("abc"), rng.choice("xyz"), str(i)): rng.choice([0, rng.randint(1, 50), rng.randint(100, 900)]) for i in range(60)}
    weights = {("a",): 0.5, ("b",): 3, ("b", "x"): 0, ("c", "y"): 2.5, ("a", "x", "3"): 7}
    leaves = spark.createDataFrame([(*k, n) for k, n in supply.items()], "p string, q string, r string, mix_held long")
    for budget, epochs in ((10, 1), (3000, 1), (3000, 2), (10**6, 3)):
        got = {(r.p, r.q, r.r): r.mix_given for r in mixing.leaf_budgets(leaves, ["p", "q", "r"], weights, budget, epochs).collect()}
        assert {k: got.get(k, 0) for k in supply} == mixing.budgets(supply, weights, budget, epochs)


def test_many_leaves_go_by_shuffle(spark, monkeypatch):
    docs = spark.range(300).select(F.col("id").alias("doc_id"), (F.col("id") % 7).cast("string").alias("source"), F.lit("a b c").alias("text"))
    levels = {"source": F.col("source")}
    run = lambda: sorted(tuple(r) for r in mixing.mix(docs, levels, {("3",): 2}, 0.5, 1).collect())
    few = run()
    monkeypatch.setattr(mixing, "BROADCAST_LEAVES", 0)
    assert run() == few and 140 <= len(few) <= 160


def test_mix_matches_brute_force(spark):
    rng = random.Random(4)
    rows = [(i, rng.choice(["en", "fr", None]), rng.choice(["s1", "s2", "s3"]), " ".join("w" * rng.randint(1, 9) for _ in range(rng.randint(0, 30)))) for i in range(400)]
    rows += [(7, "en", "s1", None), (None, "en", "s1", "a b c"), (8, "en", "s1", "a b"), (8, "en", "s1", "a b")]
    docs = spark.createDataFrame([Row(doc_id=i, lang=a, source=s, text=t, mix_key="clash", mix_0="x", copies=7) for i, a, s, t in rows], "doc_id long, lang string, source string, text string, mix_key string, mix_0 string, copies int")
    levels, weights = {"lang": F.col("lang"), "source": F.col("source")}, {("en",): 3, ("en", "s2"): 0.5}
    for budget, epochs in ((0.5, 1), (9000, 3), (10**9, 2)):
        out = mixing.mix(docs, levels, weights, budget, epochs, seed=3).collect()
        leaves, supply = {}, {}
        for i, a, s, t in rows:
            leaf = (a or "", s)
            leaves.setdefault(leaf, []).append((i, len((t or "").split()), t or ""))
            supply[leaf] = supply.get(leaf, 0) + len((t or "").split())
        total = sum(supply.values())
        given = mixing.budgets(supply, weights, int(total * budget) if isinstance(budget, float) else budget, epochs)
        want = []
        for leaf, docs_of in leaves.items():
            if not supply[leaf] or not given[leaf]:
                continue
            whole, rest = divmod(given[leaf], supply[leaf])
            key = lambda d: (int(hashlib.md5(f"3:{whole}:{'-' + hashlib.md5(d[2].encode()).hexdigest() if d[0] is None else d[0]}".encode()).hexdigest()[:15], 16), d[0] or -1, d[1])  # noqa: B023, E731
            used = 0
            for d in sorted(docs_of, key=key):
                used += d[1]
                want.append((d[0], d[1], whole + (rest > 0 and 2 * used - d[1] <= 2 * rest)))
        got = sorted((r.doc_id or -1, r.n_tokens, r.copies) for r in out)
        assert got == sorted((i or -1, n, c) for i, n, c in want if c)
        assert all(r.mix_key == "clash" and r.mix_0 == "x" for r in out)
    assert mixing.mix(docs.limit(0), levels, weights, 0.5).collect() == []
    assert mixing.repeat_copies(mixing.mix(docs, levels, weights, 10**9, 2)).count() == sum(r.copies for r in out)
