"""Every method against brute force on random instances, in both modes, with sizes checked at each step."""

import itertools
import random
from pathlib import Path

import pytest
from pyspark.sql import functions as F

from obljoin.measures import audit, leakage, tables
from obljoin.operators import baselines, padded, primitives, surface, twoway
from obljoin.operators.cover_join import cover_join
from obljoin.operators.decomposed import decomposed_join
from obljoin.operators.padded import concat, load, pad_to, real_count, reveal, where
from obljoin.operators.physical import Engine, shared_dir
from obljoin.operators.primitives import augment, compact, intersect, project, semijoin, sort
from obljoin.operators.triangle import candidates, split_choice, split_delay, triangle_choice, triangle_delay, triangle_tau
from obljoin.operators.twoway import bounded_join, nested_loop
from obljoin.operators.wcoj import hidden_wcoj, split_pair, split_single
from obljoin.plans.covers import step_bound
from obljoin.plans.hypergraph import parse_atoms
from obljoin.plans.planner import plan_order, step_slots
from obljoin.sources.workloads import WORKLOADS
from obljoin.sql import sql_join

TRIANGLE = parse_atoms("R1(b, c), R2(a, c), R3(a, b)")


def rows_of(query, seed, size=12, domain=5):
    rng = random.Random(seed)
    out = {}
    for n, attrs in query.edges:
        space = list(itertools.product(range(domain), repeat=len(attrs)))
        out[n] = rng.sample(space, min(size, len(space)))
    return out


def frames(spark, query, rows):
    return {n: spark.createDataFrame(rows[n], ", ".join(f"{x} long" for x in query.relations[n])) for n in rows}


def brute(query, rows):
    out = []
    for combo in itertools.product(*(rows[n] for n, _ in query.edges)):
        row, fits = {}, True
        for (_, attrs), values in zip(query.edges, combo, strict=True):
            for x, v in zip(attrs, values, strict=True):
                fits = fits and row.setdefault(x, v) == v
        if fits:
            out.append(tuple(row[x] for x in query.attributes))
    return sorted(set(out))


def real(table, attrs=None):
    """Checks the public invariants and returns the real rows."""
    got = table.df.collect()
    assert len(got) == table.rows
    assert sorted(r["__pos"] for r in got) == list(range(table.rows))
    assert all(r[a] is None for r in got if not r["__real"] for a in table.attrs)
    found = sorted(tuple(r[a] for a in (attrs or table.attrs)) for r in got if r["__real"])
    assert len(found) == len(set(found))
    return found


def setup(spark, query, seed, mode="padded", extra=0, **options):
    rows = rows_of(query, seed, **options)
    engine = Engine(spark, mode, 3)
    held = {n: load(engine, df, query.relations[n], len(rows[n]) + extra) for n, df in frames(spark, query, rows).items()}
    return rows, held, engine


@pytest.mark.parametrize("mode", ["padded", "hidden"])
def test_triangles(spark, mode):
    rows, held, _ = setup(spark, TRIANGLE, 1, mode, extra=2)
    args = [held[n] for n in ("R1", "R2", "R3")]
    want = brute(TRIANGLE, rows)
    for method in (triangle_choice, triangle_delay):
        out = method(*args)
        assert out.rows == triangle_tau(*args)
        assert real(out, TRIANGLE.attributes) == want


@pytest.mark.parametrize("text", ["R1(b, c), R2(a, c), R3(a, b)", "A(a, b), B(b, c), C(c, d), D(d, a)", "A(a, b, c), B(a, d), C(c)", "A(b, c, d), B(a, c, d), C(a, b, d), D(a, b, c)", "A(a), B(a), C(a)", "A(a), B(b)"])
def test_recursive_join(spark, text):
    query = parse_atoms(text)
    rows, held, engine = setup(spark, query, 3, size=10, domain=3)
    want = brute(query, rows)
    for options in ({"j": "single"}, {"j": "pair"}, {"j": "single", "fuse": True}, {"filter_all": True}, {"policy": "power"}, {"policy": "step"}):
        assert real(hidden_wcoj(query, held, **options), query.attributes) == want, options


@pytest.mark.parametrize("options", [{"j": "single", "fuse": True}, {"j": "pair"}])
def test_recursive_join_hidden(spark, options):
    rows, held, _ = setup(spark, TRIANGLE, 3, "hidden", size=5, domain=3)
    assert sorted(tuple(r) for r in reveal(hidden_wcoj(TRIANGLE, held, **options)).select(*TRIANGLE.attributes).collect()) == brute(TRIANGLE, rows)


def test_other_methods_hidden(spark):
    query = parse_atoms("R1(p, s), R2(s, n)")
    rows, held, _ = setup(spark, query, 4, "hidden", size=6, domain=4)
    want = brute(query, rows)
    assert real(cover_join(query, held), query.attributes) == want
    assert real(decomposed_join(query, held, len(want) + 3), query.attributes) == want
    r1 = held["R1"]
    assert real(surface.totals(r1, ["p"], {"n": F.lit(1).cast("long")})) == sorted((p, sum(x == p for x, _ in rows["R1"])) for p in {x for x, _ in rows["R1"]})
    assert real(surface.first_per_group(r1, ["p"], [F.desc("s")])) == sorted((p, max(s for x, s in rows["R1"] if x == p)) for p in {x for x, _ in rows["R1"]})
    for refused in (lambda: surface.aggregate(r1, ["p"], {"n": F.count("*")}), lambda: surface.grouping_sets(r1, [["p"]], {"n": F.count("*")})):
        with pytest.raises(ValueError):
            refused()


def test_keys_tighten_steps(spark):
    """Declared keys make a step as large as the table that it extends."""
    query = parse_atoms("N(n, r), C(c, n), O(o, c), R(r, o)")
    rng = random.Random(2)
    rows = {"N": [(i, i % 3) for i in range(5)], "C": [(i, rng.randrange(5)) for i in range(12)], "O": [(i, rng.randrange(12)) for i in range(20)], "R": [(rng.randrange(3), i) for i in range(20)]}
    keys = {"N": ("n",), "C": ("c",), "O": ("o",)}
    engine = Engine(spark, "padded", 3)
    held = {n: load(engine, df, query.relations[n]) for n, df in frames(spark, query, rows).items()}
    out = hidden_wcoj(query, held, j="single", policy="keys", keys=keys)
    assert out.rows <= 20 < hidden_wcoj(query, held, j="single").rows
    assert sorted(tuple(r) for r in reveal(out).select(*query.attributes).collect()) == brute(query, rows)


def test_correspondence_of_triangles_and_steps(spark):
    """Adding two attributes at once is the heavy/light triangle; adding one is the delayed triangle over the pairs that survive."""
    rows, held, _ = setup(spark, TRIANGLE, 8, size=14)
    r1, r2, r3 = (held[n] for n in ("R1", "R2", "R3"))
    want = brute(TRIANGLE, rows)
    pair = hidden_wcoj(TRIANGLE, held, order=(("b", "c"),))
    single = hidden_wcoj(TRIANGLE, held, order=(("c",), ("b",)))
    assert real(pair, TRIANGLE.attributes) == real(single, TRIANGLE.attributes) == real(triangle_choice(r1, r2, r3), TRIANGLE.attributes) == real(triangle_delay(r1, r2, r3, reduce_first=True), TRIANGLE.attributes) == want
    first, second = split_delay(r1, r2, r3, reduce_first=True)
    live = intersect(semijoin(semijoin(r3, r1), r2), r3)
    parts = split_single(augment(live, [("R1", r1, ["b"]), ("R2", r2, ["a"])]), TRIANGLE, "c")
    assert [real(p) for p in parts.values()] == [real(first), real(second)]


def test_hot_key_meets_in_blocks(spark, monkeypatch):
    """One key in all rows: no group of the join holds more than MEET rows of either side."""
    monkeypatch.setattr(twoway, "MEET", 16)
    engine = Engine(spark, "padded", 4)
    r = load(engine, spark.range(70).select((F.col("id") * 0).alias("k"), F.col("id").alias("a")), ["k", "a"])
    s = load(engine, spark.range(50).select((F.col("id") * 0).alias("k"), F.col("id").alias("b")), ["k", "b"])
    out = bounded_join(r, s, 4000)
    assert out.rows == 4000 and real(out, ("a", "b")) == [(a, b) for a in range(70) for b in range(50)]


def test_other_methods(spark):
    query = parse_atoms("R1(p, s), R2(o, s), R3(o, p), S(s, n)")
    rows, held, _ = setup(spark, query, 4)
    want = brute(query, rows)
    assert real(decomposed_join(query, held, len(want) + 7), query.attributes) == want
    assert real(decomposed_join(query, held, "exact"), query.attributes) == want
    assert real(cover_join(query, held), query.attributes) == want
    f = frames(spark, query, rows)
    take = lambda df: sorted(tuple(r[x] for x in query.attributes) for r in df.collect())
    assert take(baselines.catalyst(query, f)) == take(baselines.recursive_plain(query, f)) == want
    assert take(sql_join(spark, "R1(p, s), R2(o, s), R3(o, p), S(s, n)", tau=len(want) or 1, **f)) == want


def test_empty_and_all_dummy_inputs(spark):
    engine = Engine(spark, "padded", 2)
    none = spark.createDataFrame([], "b long, c long")
    dummies = spark.createDataFrame([(None, 1), (2, None)], "a long, c long")
    some = spark.createDataFrame([(1, 2), (2, 2)], "a long, b long")
    r1, r2, r3 = load(engine, none, ["b", "c"]), load(engine, dummies, ["a", "c"]), load(engine, some, ["a", "b"])
    assert r1.rows == 0 and real(r2) == []
    for method in (triangle_choice, triangle_delay):
        assert real(method(r1, r2, r3)) == []
    assert real(semijoin(r3, r1)) == [] and real(semijoin(r3, r1, anti=True)) == [(1, 2), (2, 2)]
    assert real(bounded_join(r3, r2, 5)) == []
    assert real(project(r2, ["a"])) == []


def test_declared_bounds_are_enforced(spark):
    query = parse_atoms("R(a, b), S(b, c)")
    rows, held, engine = setup(spark, query, 5)
    n = len(brute(query, rows))
    assert real(bounded_join(held["R"], held["S"], n), query.attributes) == brute(query, rows)
    for make in (lambda: bounded_join(held["R"], held["S"], n - 1), lambda: compact(held["R"], 3)):
        small = make()  # nothing stops before the client looks
        assert small.df.count() == small.rows
        with pytest.raises(OverflowError):
            reveal(small)
        assert engine.sizes == []
    other = load(engine, frames(spark, parse_atoms("T(d)"), {"T": [(1,), (2,)]})["T"], ["d"])
    with pytest.raises(OverflowError):
        reveal(bounded_join(held["R"], other, 5))
    with pytest.raises(ValueError):
        load(engine, frames(spark, query, rows)["R"], ["a", "b"], rows=2)
    small = Engine(spark, "padded", 2, most_rows=10)
    with pytest.raises(ValueError):
        nested_loop(*(load(small, df.limit(8), query.relations[m]) for m, df in frames(spark, query, rows).items()))


def test_grid_meets_its_bound(spark):
    rows = {n: list(itertools.product(range(3), repeat=2)) for n in ("R1", "R2", "R3")}
    engine = Engine(spark, "padded", 2)
    held = {n: load(engine, df, TRIANGLE.relations[n]) for n, df in frames(spark, TRIANGLE, rows).items()}
    out = triangle_choice(held["R1"], held["R2"], held["R3"])
    assert out.rows == 27 == len(real(out))
    assert len(real(hidden_wcoj(TRIANGLE, held))) == 27


def test_splits_partition_and_stay_in_budget(spark):
    rows, held, _ = setup(spark, TRIANGLE, 6, size=15)
    r1, r2, r3 = (held[n] for n in ("R1", "R2", "R3"))
    light, heavy = split_choice(candidates(r2, r3, "a"), r1.rows)
    assert light.rows == heavy.rows
    values = {x[0] for x in rows["R2"]} & {x[0] for x in rows["R3"]}
    d2 = {v: sum(x[0] == v for x in rows["R2"]) for v in values}
    d3 = {v: sum(x[0] == v for x in rows["R3"]) for v in values}
    assert real(light) == sorted((v,) for v in values if d2[v] * d3[v] <= 15)
    assert real(heavy) == sorted((v,) for v in values if d2[v] * d3[v] > 15)
    assert sum(min(d2[v] * d3[v], 15) for v in values) <= triangle_tau(r1, r2, r3)
    pairs = augment(r3, [("R1", r1, ["b"]), ("R2", r2, ["a"])])
    parts = split_single(pairs, TRIANGLE, "c")
    assert sorted(sum((real(p) for p in parts.values()), [])) == sorted(rows["R3"])
    ones = augment(candidates(r2, r3, "a"), [("R1", r1, []), ("R2", r2, ["a"]), ("R3", r3, ["a"])])
    both = split_pair(ones, TRIANGLE, "b", "c")
    assert set(both) == {("R1",), ("R3", "R2")}
    # the pair split of a triangle is the heavy/light split
    assert real(both[("R1",)]) == real(heavy) and real(both[("R3", "R2")]) == real(light)


def test_hidden_sort_hides_a_heavy_key(spark):
    """One key in 80 % of the rows: a hash exchange shows it, the hidden sort's partitions stay alike."""
    n = 4000
    even = spark.range(n).select(F.col("id").alias("k"), F.col("id").alias("v"))
    heavy = spark.range(n).select(F.when(F.col("id") % 5 > 0, 7).otherwise(F.col("id")).alias("k"), F.col("id").alias("v"))
    seen = []
    for df in (even, heavy):
        engine = Engine(spark, "hidden", 4)
        t = load(engine, df, ["k", "v"])
        ranked = engine.ordered(t.df, [F.col("k")], n)
        seen.append(leakage.partition_sizes(ranked.repartitionById(4, F.floor(F.col("__rank") / 1000).cast("int"))))
        assert sort(t, ["k"]).rows == n
    assert seen[0] == seen[1] == [1000] * 4
    skewed = leakage.partition_sizes(heavy.repartition(4, "k"))
    assert max(skewed) > 3000


def test_audit_finds_a_planted_join(spark):
    a = spark.range(10).withColumnRenamed("id", "k")
    found = audit.check(a.join(a.withColumn("x", F.lit(1)), "k"))
    assert any("AdaptiveSparkPlan" in v for v in found)
    engine = Engine(spark, "hidden", 2)
    k = load(engine, spark.createDataFrame([(1,), (3,)], "a long"), ["a"])
    planted = k.df.join(k.df.select("a", F.lit(1).alias("x")), "a")
    with pytest.raises(RuntimeError, match="partners meet by key"):
        engine.barrier(planted)
    with pytest.raises(RuntimeError, match="dealt by a key"):
        engine.barrier(k.df.groupBy("a").count())
    with pytest.raises(RuntimeError, match="real rows"):
        engine.barrier(k.df.where("__real"))
    assert Engine(spark).secret != Engine(spark).secret
    with pytest.raises(ValueError):
        Engine(spark, secret="")
    t = load(engine, spark.createDataFrame([(1, 2), (3, 4)], "a long, b long"), ["a", "b"])
    assert not [v for v in audit.check(t.df) if "key" in v]
    assert any("real rows" in v for v in audit.check(reveal(t)))


def test_masks_and_padding_keep_sizes(spark):
    engine = Engine(spark, "padded", 2)
    t = load(engine, spark.createDataFrame([(i, i % 3) for i in range(9)], "a long, b long"), ["a", "b"])
    cut = where(t, F.when(F.col("a") > 4, F.col("b") == 1))  # null counts as false
    assert cut.rows == 9 and real(cut) == [(7, 1)]
    wide = pad_to(cut, 12)
    assert wide.rows == 12 and real(wide) == [(7, 1)]
    assert real(intersect(t, where(t, F.col("a") < 2))) == [(0, 0), (1, 1)]
    padded = baselines.pad_only(engine, reveal(t), 20)
    assert padded.rows == 20 and len(real(padded)) == 9
    assert real(surface.with_column(cut, "c", F.col("a") * 2)) == [(7, 1, 14)]


def test_public_shapes_do_not_depend_on_the_data(spark):
    """The recorded sizes of all steps are the same for different instances of one size."""
    seen = []
    for seed in (11, 12):
        _, held, engine = setup(spark, TRIANGLE, seed)
        triangle_choice(*(held[n] for n in ("R1", "R2", "R3")))
        hidden_wcoj(TRIANGLE, held)
        seen.append(engine.steps)
    assert seen[0] == seen[1] and ("bounded_join", triangle_tau(*(held[n] for n in ("R1", "R2", "R3")))) in seen[0]


def test_interval_and_outer_joins(spark):
    engine = Engine(spark, "padded", 2)
    points = load(engine, spark.createDataFrame([(i,) for i in range(6)], "p long"), ["p"])
    spans = load(engine, spark.createDataFrame([(0, 2, "x"), (1, 4, "y")], "a long, b long, n string"), ["a", "b", "n"])
    got = surface.interval_join(points, spans, "p", "a", "b", 10)
    assert [(r[0], r[3]) for r in real(got)] == [(0, "x"), (1, "x"), (1, "y"), (2, "y"), (3, "y")]
    r = load(engine, spark.createDataFrame([(1, 1), (2, 2)], "k long, a long"), ["k", "a"])
    s = load(engine, spark.createDataFrame([(2, 5), (3, 6)], "k long, b long"), ["k", "b"])
    rows = {h: sorted(str(tuple(x)) for x in reveal(surface.outer_join(r, s, 4, h)).collect()) for h in ("left", "right", "full")}
    assert rows["left"] == ["(1, 1, None)", "(2, 2, 5)"] and rows["right"] == ["(2, 2, 5)", "(3, None, 6)"] and len(rows["full"]) == 3


def test_tiles_are_opened_in_place(spark):
    """A tiled loop deals each row once: no row is copied for each tile before the sides meet."""
    query = parse_atoms("R(a, b), S(b, c)")
    rows, held, _ = setup(spark, query, 5)
    tiled = nested_loop(held["R"], held["S"], tiling="recursive", tile=9)
    assert "sequence(" not in audit.plan_text(tiled.df)
    assert real(tiled, query.attributes) == brute(query, rows)


def test_large_tables_in_blocks(spark, monkeypatch):
    """Tables stored in blocks hold the same slots; every method finds the same, and stores rows of a public number."""
    monkeypatch.setattr(padded, "LARGE", 9)
    monkeypatch.setattr(padded, "BLOCK", 4)
    rows, held, engine = setup(spark, TRIANGLE, 3, extra=3)
    want = brute(TRIANGLE, rows)
    triangle = [held[n] for n in ("R1", "R2", "R3")]
    assert real(triangle_choice(*triangle), TRIANGLE.attributes) == want
    assert real(triangle_delay(*triangle), TRIANGLE.attributes) == want
    for options in ({"j": "single"}, {"j": "pair"}, {"j": "single", "fuse": True}):
        assert real(hidden_wcoj(TRIANGLE, held, **options), TRIANGLE.attributes) == want
    assert real(cover_join(TRIANGLE, held), TRIANGLE.attributes) == want
    assert real(project(held["R1"], ["b"])) == sorted({(b,) for b, _ in rows["R1"]})
    engine.settle()
    few, none = where(held["R1"], F.col("b") == 1).hold(), where(held["R1"], F.lit(False)).hold()
    assert few.large and real(few) == sorted(r for r in rows["R1"] if r[0] == 1) and real(none) == []
    files = [spark.read.parquet(*{f.rsplit("/", 1)[0] for f in t.df.inputFiles()}).count() for t in (few, none)]
    assert files == [-(-few.rows // 4)] * 2


def test_large_dummies_are_not_exchanged(spark, monkeypatch):
    """A semi-join of a large table moves its real rows alone: a million dummies leave no shuffle."""
    monkeypatch.setattr(padded, "LARGE", 1 << 18)
    query = parse_atoms("R(a, b), S(b, c)")
    _, held, _ = setup(spark, query, 2)
    big = semijoin(bounded_join(held["R"], held["S"], 1 << 20).hold(), held["S"])
    plan = audit.plan_text(big.df.where("__real"))
    assert "Range (" not in plan and "sequence(" not in plan and real_count(big) == real_count(bounded_join(held["R"], held["S"], 500))


def test_plain_joins_follow_keys():
    """The plain join of the cycles begins with the lines, whose orders, customers and suppliers are known; no nation meets all its suppliers."""
    for name in ("w7", "w8"):
        work = WORKLOADS[name]
        order, seen = baselines.join_order(work.query, work.keys), set()
        for n in order:
            assert not seen or set(work.keys[n]) <= seen
            seen |= set(work.query.relations[n])
        assert sorted(order) == sorted(work.relations)
    assert baselines.join_order(TRIANGLE) == ["R1", "R2", "R3"]


def test_cover_join_stores_no_pairs_at_the_end(spark):
    """The last loop is not stored, and relations that were looped over are not asked again."""
    query = parse_atoms("R(a, b), S(b, c)")
    rows, held, engine = setup(spark, query, 4)
    engine.steps.clear()
    found = cover_join(query, held)
    assert real(found, query.attributes) == brute(query, rows)
    assert found.stored is None
    assert [n for n, _ in engine.steps if n == "semijoin"] == ["semijoin"]


def test_large_hidden_join_is_not_stored(spark, monkeypatch):
    """A hidden join of very many slots that have room for all pairs loops over them by public position; none is stored."""
    monkeypatch.setattr(padded, "LARGE", 9)
    query = parse_atoms("R(a, b), S(b, c)")
    rows, held, engine = setup(spark, query, 5, "hidden", extra=2)
    n = held["R"].rows * held["S"].rows
    found = bounded_join(held["R"], held["S"], n + 3)
    assert found.rows == n + 3 and found.stored is None and ("nested_loop", n) in engine.steps
    assert sorted(r[0] for r in found.df.select("__pos").collect()) == list(range(n + 3))
    assert real(found, query.attributes) == brute(query, rows)
    engine.steps.clear()
    bounded_join(held["R"], held["S"], n - 1)
    assert ("nested_loop", n) not in engine.steps


def test_declared_keys_order_the_steps():
    """Of plans with as many slots, the one whose rows the declared keys bound: all lines, not every order with every supplier."""
    sizes = {"O": 900_000, "C": 90_000, "S": 6_000, "L": 3_600_000}
    work = WORKLOADS["w7"]
    assert set(plan_order(work.query, sizes, "pair", "keys", work.keys)[0]) == {"cust", "nat"}
    assert step_bound(work.query, sizes, ("cust", "nat"), 3_600_000, work.keys) == 3_600_000
    assert step_bound(work.query, sizes, ("cust", "nat"), 3_600_000) == 900_000 * 6_000


@pytest.mark.parametrize("options", [{"j": "single"}, {"j": "pair"}, {"j": "single", "fuse": True}, {"j": "pair", "policy": "keys"}])
def test_recursive_join_with_keys(spark, options):
    """The order follows the keys, the slots the policy; the result is that of brute force."""
    query, rng = parse_atoms("O(o, c), C(c, n), S(s, n), L(o, s)"), random.Random(13)
    rows = {"O": [(i, rng.randrange(5)) for i in range(14)], "C": [(i, rng.randrange(2)) for i in range(5)], "S": [(i, rng.randrange(2)) for i in range(4)]}
    rows["L"] = sorted({(rng.randrange(14), rng.randrange(4)) for _ in range(30)})
    engine = Engine(spark, "padded", 2)
    held = {n: load(engine, df, query.relations[n]) for n, df in frames(spark, query, rows).items()}
    keys = {"O": ("o",), "C": ("c",), "S": ("s",)}
    found = hidden_wcoj(query, held, keys=keys, **options)
    assert real(found, query.attributes) == brute(query, rows)
    engine.settle()
    if "policy" not in options:
        assert found.rows == step_slots(query, {n: len(x) for n, x in rows.items()}, ("c",), 0, "product", None)
    elif options["j"] == "pair":
        assert found.rows <= len(rows["L"])


@pytest.mark.parametrize(("name", "j", "fuse"), [("w1", "pair", False), ("w1", "single", False), ("w1", "single", True), ("w12", "auto", True)])
def test_steps_begin_with_the_finest(name, j, fuse):
    """Of plans with about as many slots: orders, which have few lines each, come before suppliers, which have many."""
    work = WORKLOADS[name]
    sizes = {n: 3_590_000 + 3_000 * i for i, n in enumerate(work.relations)} | {"S": 60_000, "N": 25}
    steps = plan_order(work.query.induced(("part", "supp", "ord")), {n: sizes[n] for n in work.relations}, j, "product", fuse=fuse, finest=work.finest)
    assert "ord" not in {x for step in steps for x in step} and (j == "pair" or steps[-1] == ("part",))


@pytest.mark.parametrize("bits", [6, 26])
def test_sieve_of_large_tables_is_exact(spark, monkeypatch, bits):
    """Most rows without a partner leave before the exchange; what stays is that of the plain semi-join, however few bits there are. Slots stay."""
    monkeypatch.setattr(padded, "LARGE", 9)
    monkeypatch.setattr(primitives, "SIEVED", 0)
    monkeypatch.setattr(primitives, "SIEVE_MOST", bits)
    engine = Engine(spark, "padded", 4)
    left = spark.range(3000).selectExpr("id % 61 AS a", "IF(id % 7 = 0, NULL, id % 53) AS b", "id AS c")
    right = spark.range(200).selectExpr("id % 20 AS a", "id % 11 AS b")
    r, s = load(engine, left, ("a", "b", "c")), load(engine, right, ("a", "b"))
    out = semijoin(r, s)
    assert {(x.a, x.b, x.c) for x in reveal(out).collect()} == {(x.a, x.b, x.c) for x in left.join(right, ["a", "b"], "left_semi").collect()}
    slots = [x[0] for x in out.df.select("__pos").collect()]
    assert sorted(slots) == list(range(r.rows)) and out.df.where("NOT __real AND (a IS NOT NULL OR c IS NOT NULL)").count() == 0
    plan = out.df.where("__real")._jdf.queryExecution().executedPlan().toString()
    assert "BroadcastNestedLoopJoin" in plan and "getbit" in plan


def _stages(engine):
    """Folders of steps on disk."""
    return {p.name for p in Path(shared_dir(engine.spark).removeprefix("file:")).iterdir() if p.name.startswith("stage-")}


@pytest.mark.parametrize("large", [9, 1 << 24])
def test_steps_that_are_done_leave_the_disk(spark, monkeypatch, large):
    """In padded mode a join keeps on disk what its result reads and its noted sizes; the sizes are still right, and so is what comes later."""
    monkeypatch.setattr(padded, "LARGE", large)
    rows, held, engine = setup(spark, TRIANGLE, 3)
    before = _stages(engine)
    for run in (lambda: hidden_wcoj(TRIANGLE, held, j="single"), lambda: hidden_wcoj(TRIANGLE, held, j="pair"), lambda: triangle_choice(*(held[n] for n in ("R1", "R2", "R3")))):
        mark, old = engine.mark(), _stages(engine)
        found = run()
        assert len(_stages(engine) - old) <= 3 and before <= _stages(engine)
        assert real(found, TRIANGLE.attributes) == brute(TRIANGLE, rows)
        engine.release(mark, found.df)
        assert real(found, TRIANGLE.attributes) == brute(TRIANGLE, rows)
    tight = triangle_delay(*(held[n] for n in ("R1", "R2", "R3")), tau=1)
    with pytest.raises(OverflowError):
        reveal(tight)


def test_step_report_leaves_no_steps(spark):
    before = _stages(Engine(spark))
    tables.step_report(spark, "/root/testdata/sf0.001", "w2")
    assert _stages(Engine(spark)) == before


def test_slots_that_are_only_numbered_are_not_refused(spark, monkeypatch):
    """The parts of a step have more slots together than a step may work on one by one, but in padded mode only their real rows are worked on."""
    monkeypatch.setattr(padded, "MOST_BLOCKS", 64)
    query = parse_atoms("R(a, b), S(b, c)")
    rows, held, engine = setup(spark, query, 5)
    grown = bounded_join(held["R"], held["S"], 1 << 39).hold()
    parts = concat(*(where(grown, F.col("a") % 3 == k) for k in range(3)))
    assert ("concat", 3 << 39) in engine.steps
    assert sorted(tuple(r) for r in reveal(compact(parts, 1 << 39)).select(*query.attributes).collect()) == brute(query, rows)
    with pytest.raises(ValueError):
        nested_loop(grown, grown)
    with pytest.raises(ValueError):
        Engine(spark, "hidden", 4).step("concat", parts.rows)


def test_tiles_are_spread_over_tasks(spark, monkeypatch):
    """A tiled loop is no single task, however small its blocks are, and a task opens a bounded number of pairs."""
    query = parse_atoms("R(a, b), S(b, c)")
    rows, held, engine = setup(spark, query, 5)
    tasks = lambda t: t.df.select(F.spark_partition_id().alias("p")).distinct().count()
    tiled = nested_loop(held["R"], held["S"], tiling="recursive", tile=9)
    assert engine.partitions > 1 and tasks(tiled) > 1
    monkeypatch.setattr(twoway, "AT_ONCE", 9)
    spread = nested_loop(held["R"], held["S"], tiling="recursive", tile=9)
    assert tasks(spread) >= 9 and real(spread, query.attributes) == brute(query, rows)


def test_sieves_of_several_partners_are_exact(spark, monkeypatch):
    """All sieves stand before the exact comparisons; slots and what stays are those of one semi-join after the other."""
    monkeypatch.setattr(padded, "LARGE", 9)
    monkeypatch.setattr(primitives, "SIEVED", 0)
    monkeypatch.setattr(primitives, "SIEVE_MOST", 6)
    engine = Engine(spark, "padded", 4)
    left = spark.range(900).selectExpr("id % 61 AS a", "IF(id % 7 = 0, NULL, id % 53) AS b", "id AS c")
    r = load(engine, left, ("a", "b", "c"))
    others = [load(engine, spark.range(n).selectExpr(f"id % {m} AS {x}", f"id % {k} AS {y}"), (x, y)) for n, m, x, k, y in ((700, 40, "a", 30, "b"), (300, 25, "b", 300, "c"))]
    one = semijoin(semijoin(r, others[0]), others[1])
    out = primitives.semijoins(r, others)
    found = {tuple(x) for x in reveal(out).collect()}
    assert found and found == {tuple(x) for x in reveal(one).collect()}
    assert sorted(x[0] for x in out.df.select("__pos").collect()) == list(range(r.rows))
    assert engine.steps.count(("semijoin", r.rows)) == 4
