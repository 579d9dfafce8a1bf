"""Measures of the workloads as tables, with their SQL."""

from __future__ import annotations

import math
from fractions import Fraction

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from obljoin.measures import cost, leakage
from obljoin.operators.physical import Engine
from obljoin.operators.primitives import project
from obljoin.operators.triangle import candidates, corner_names, split_choice, split_delay, triangle_choice, triangle_delay
from obljoin.operators.wcoj import hidden_wcoj
from obljoin.plans.covers import integer_root, minimal_covers, product_bound, rho, rho_star
from obljoin.plans.ghd import fhtw
from obljoin.sources.workloads import WORKLOADS

BUDGETED = tuple(n for n in WORKLOADS if n not in ("w9", "w21"))  # their relations are slow to build in SQL or hold texts


def widths(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Fractional and integral cover numbers and the width of every workload's query; its rows, and what the width allows a bag of them."""
    rows = []
    for name, w in WORKLOADS.items():
        n, width = sum(df.distinct().count() for df in w.frames(spark, sf_dir).values()), fhtw(w.query)
        rows.append((name, str(rho_star(w.query)), rho(w.query), str(width), n, integer_root(n**width.numerator, width.denominator)))
    return spark.createDataFrame(rows, "workload string, rho_star string, rho long, width string, n long, bag long")


#: Fractional cover, integral cover and width of each query, as derived by hand from its class.
WIDTHS = {
    "w1": ("3/2", 2, "3/2"), "w2": ("3/2", 2, "3/2"), "w3": ("3/2", 2, "3/2"), "w4": ("3/2", 2, "3/2"), "w4b": ("3/2", 2, "3/2"), "w4c": ("3/2", 2, "3/2"),
    "w5": ("3", 3, "1"), "w6": ("3", 3, "1"), "w7": ("2", 2, "2"), "w7u": ("2", 2, "2"), "w8": ("3", 3, "2"), "w8b": ("5/2", 3, "2"), "w9": ("2", 2, "2"),
    "w10": ("4/3", 2, "4/3"), "w11": ("2", 2, "2"), "w12": ("5/2", 3, "3/2"), "w13": ("5/2", 3, "3/2"), "w14": ("2", 2, "1"), "w15a": ("2", 2, "1"), "w15b": ("2", 2, "1"),
    "w16": ("3/2", 2, "3/2"), "w17": ("1", 1, "1"), "w18": ("2", 2, "1"), "w19": ("3/2", 2, "3/2"), "w20": ("3/2", 2, "3/2"), "w21": ("2", 2, "1"), "w22": ("2", 2, "1"),
}


def widths_sql() -> str:
    parts = []
    for name, (best, whole, width) in WIDTHS.items():
        w, e = WORKLOADS[name], Fraction(width)
        total = " + ".join(f"(SELECT count(*) FROM (SELECT DISTINCT * FROM {n}))" for n in w.relations)
        bag = f"CAST(floor(pow(n, {e.numerator} / {e.denominator}.0) + 1e-6) AS BIGINT)"
        parts.append(f"SELECT * FROM ({w.with_sql()}, k AS (SELECT CAST({total} AS BIGINT) AS n) SELECT '{name}' AS workload, '{best}' AS rho_star, CAST({whole} AS BIGINT) AS rho, '{width}' AS width, n, {bag} AS bag FROM k)")
    return " UNION ALL ".join(parts)


def budgets(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Input size and product bound of the workloads, from counts alone."""
    rows = []
    for name in BUDGETED:
        sizes = {n: df.distinct().count() for n, df in WORKLOADS[name].frames(spark, sf_dir).items()}
        rows.append((name, sum(sizes.values()), product_bound(WORKLOADS[name].query, sizes)))
    return spark.createDataFrame(rows, "workload string, n long, bound long")


def budgets_sql() -> str:
    """The bound as the least power product over the minimal covers of each class, in SQL."""
    parts = []
    for name in BUDGETED:
        w = WORKLOADS[name]
        names = list(w.relations)
        sizes = ", ".join(f"(SELECT count(*) FROM (SELECT DISTINCT * FROM {n})) AS c{i}" for i, n in enumerate(names))
        products = []
        for point in _vertex_list(name):
            used = [(i, p) for i, p in enumerate(point) if p]
            degree = math.lcm(*(p.denominator for _, p in used))
            inner = " * ".join(f"pow(c{i}, {int(p * degree)})" for i, p in used)
            products.append(f"pow({inner}, {1 / degree!r})" if degree > 1 else inner)
        best = f"least({', '.join(products)})" if len(products) > 1 else products[0]
        total = " + ".join(f"c{i}" for i in range(len(names)))
        parts.append(f"SELECT * FROM ({w.with_sql()} SELECT '{name}' AS workload, CAST({total} AS BIGINT) AS n, CAST(floor({best} + 1e-6) AS BIGINT) AS bound FROM (SELECT {sizes}))")
    return " UNION ALL ".join(parts)


def _vertex_list(name: str) -> list[tuple[Fraction, ...]]:
    """Minimal fractional covers of triangles, the urgent cycle and the Loomis-Whitney join, in the order of the relations; other classes by the solver."""
    half, third, one, zero = Fraction(1, 2), Fraction(1, 3), Fraction(1), Fraction(0)
    if name == "w7u":  # O, C, S, L around the cycle
        return [(one, zero, one, zero), (zero, one, zero, one)]
    if name == "w10":
        pairs = [tuple(one if i in (a, b) else zero for i in range(4)) for a in range(4) for b in range(a)]
        triples = [tuple(zero if i == a else half for i in range(4)) for a in range(4)]
        return [(third,) * 4, *pairs, *triples]
    if WIDTHS[name] == ("3/2", 2, "3/2") and len(WORKLOADS[name].relations) == 3:
        return [(half,) * 3, (one, one, zero), (one, zero, one), (zero, one, one)]
    return list(minimal_covers(WORKLOADS[name].query))


def split_sizes(spark: SparkSession, sf_dir: str, name: str = "w3") -> DataFrame:
    """Real rows of each part of both triangle splits, as the padded operators make them."""
    engine = Engine(spark, "padded", 4)
    held = WORKLOADS[name].instance(engine, sf_dir)
    r1, r2, r3 = (held[n] for n in ("R1", "R2", "R3"))
    light, heavy = split_choice(candidates(r2, r3, "a"), r1.rows)
    first, second = split_delay(r1, r2, r3)
    rows = [(n, t.df.where("__real").count()) for n, t in (("light", light), ("heavy", heavy), ("first", first), ("second", second))]
    return spark.createDataFrame(rows, "part string, n long")


_DEGREES = "d2 AS (SELECT a, count(*) AS d2 FROM R2 GROUP BY a), d3 AS (SELECT a, count(*) AS d3 FROM R3 GROUP BY a), d1 AS (SELECT b, count(*) AS d1 FROM R1 GROUP BY b), both_ AS (SELECT d2, d3, (SELECT count(*) FROM R1) AS n FROM d2 JOIN d3 USING (a)), pairs AS (SELECT coalesce(d1, 0) AS d1, coalesce(d2, 0) AS d2 FROM R3 LEFT JOIN d1 USING (b) LEFT JOIN d2 USING (a))"


def split_sizes_sql(name: str = "w3") -> str:
    return (
        f"{WORKLOADS[name].with_sql()}, {_DEGREES} SELECT 'light' AS part, count(*) AS n FROM both_ WHERE d2 * d3 <= n UNION ALL SELECT 'heavy', count(*) FROM both_ WHERE d2 * d3 > n"
        " UNION ALL SELECT 'first', count(*) FROM pairs WHERE d1 <= d2 UNION ALL SELECT 'second', count(*) FROM pairs WHERE d1 > d2"
    )


def leak_report(spark: SparkSession, sf_dir: str, name: str = "w3") -> DataFrame:
    f = WORKLOADS[name].frames(spark, sf_dir)
    return leakage.choice_report(f["R1"], f["R2"], f["R3"])


def leak_report_sql(name: str = "w3") -> str:
    items = {
        "candidates": "count(*)",
        "heavy": "coalesce(sum(CASE WHEN d2 * d3 > n THEN 1 ELSE 0 END), 0)",
        "light": "coalesce(sum(CASE WHEN d2 * d3 <= n THEN 1 ELSE 0 END), 0)",
        "longest_second": "coalesce(max(d2), 0)",
        "longest_third": "coalesce(max(d3), 0)",
        "light_pairs": "coalesce(sum(CASE WHEN d2 * d3 <= n THEN d2 * d3 ELSE 0 END), 0)",
    }
    rows = " UNION ALL ".join(f"SELECT '{m}' AS measure, CAST({x} AS BIGINT) AS value FROM both_" for m, x in items.items())
    return f"{WORKLOADS[name].with_sql()}, {_DEGREES} {rows}"


def delay_report(spark: SparkSession, sf_dir: str, name: str = "w3") -> DataFrame:
    f = WORKLOADS[name].frames(spark, sf_dir)
    return leakage.delay_report(f["R1"], f["R2"], f["R3"])


def delay_report_sql(name: str = "w3") -> str:
    return f"{WORKLOADS[name].with_sql()}, {_DEGREES} SELECT 'first' AS measure, count(*) AS value FROM pairs WHERE d1 <= d2 UNION ALL SELECT 'second', count(*) FROM pairs WHERE d1 > d2"


def padding(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Real rows against slots of the distinct keys of one relation: what padding costs."""
    engine = Engine(spark, "padded", 4)
    out = []
    for name in ("w1", "w14"):
        for relation, t in WORKLOADS[name].instance(engine, sf_dir).items():
            cut = project(t, t.attrs[:1])
            out.append((name, relation, cut.rows, cut.df.where(F.col("__real")).count()))
    return spark.createDataFrame(out, "workload string, relation string, slots long, real long")


def padding_sql() -> str:
    parts = []
    for name in ("w1", "w14"):
        w = WORKLOADS[name]
        for relation, (attrs, _) in w.relations.items():
            parts.append(f"SELECT * FROM ({w.with_sql()} SELECT '{name}' AS workload, '{relation}' AS relation, (SELECT count(*) FROM (SELECT DISTINCT * FROM {relation})) AS slots, (SELECT count(DISTINCT {attrs[0]}) FROM {relation}) AS real)")
    return " UNION ALL ".join(parts)


def _triangle_order(name: str) -> tuple[str, str, str]:
    r1, r2, r3 = (set(WORKLOADS[name].relations[n][0]) for n in ("R1", "R2", "R3"))
    return (r2 & r3).pop(), (r1 & r3).pop(), (r1 & r2).pop()


def step_report(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """Real rows against slots of every bounded join, for both triangles and the recursive join. Secret: a report for the owner."""
    rows = []
    x1, x2, x3 = _triangle_order(name)
    query = WORKLOADS[name].query
    methods = {
        "choice": (("heavy", "light"), lambda held: triangle_choice(held["R1"], held["R2"], held["R3"])),
        "delay": (("first", "second"), lambda held: triangle_delay(held["R1"], held["R2"], held["R3"])),
        "recursive": (("values_first", "values_third", "pairs_first", "pairs_second"), lambda held: hidden_wcoj(query, held, order=((x3,), (x2,)))),
    }
    for method, (labels, run) in methods.items():
        engine = Engine(spark, "padded", max(2, int(spark.conf.get("spark.sql.shuffle.partitions"))))
        run(WORKLOADS[name].instance(engine, sf_dir))
        found = [(slots, real) for step, slots, real in engine.real_sizes() if step == "bounded_join"]
        rows += [(method, label, slots, real) for label, (slots, real) in zip(labels, found, strict=True)]
        engine.sizes.clear()
        engine.release((0, 0))  # the next method loads its own
    return spark.createDataFrame(rows, "method string, step string, slots long, real long")


def _degrees(name: str) -> str:
    x1, x2, _ = _triangle_order(name)
    return (
        f"d1 AS (SELECT {x2}, count(*) AS d1 FROM R1 GROUP BY ALL), d2 AS (SELECT {x1}, count(*) AS d2 FROM R2 GROUP BY ALL), d3 AS (SELECT {x1}, count(*) AS d3 FROM R3 GROUP BY ALL),"
        f" c AS (SELECT (SELECT count(*) FROM R1) AS c1, (SELECT count(*) FROM R2) AS c2, (SELECT count(*) FROM R3) AS c3, (SELECT count(*) FROM d1) AS v1),"
        f" ones AS (SELECT * FROM d2 JOIN d3 USING ({x1}), c), pairs AS (SELECT coalesce(d1, 0) AS d1, coalesce(d2, 0) AS d2 FROM R3 LEFT JOIN d1 USING ({x2}) LEFT JOIN d2 USING ({x1})),"
        f" live AS (SELECT * FROM pairs WHERE d1 > 0 AND d2 > 0),"
        " t AS (SELECT CAST(floor(least(pow(CAST(c1 AS DOUBLE) * c2 * c3, 0.5), c1 * c2, c1 * c3, c2 * c3) + 1e-6) AS BIGINT) AS whole, least(c3, c1 * c2) AS half FROM c)"
    )


def step_report_sql(name: str) -> str:
    steps = (
        ("choice", "heavy", "whole", "count(*) * max(c1)", "ones WHERE d2 * d3 > c1"),
        ("choice", "light", "whole", "sum(d2 * d3)", "ones WHERE d2 * d3 <= c1"),
        ("delay", "first", "whole", "sum(d1)", "pairs WHERE d1 <= d2"),
        ("delay", "second", "whole", "sum(d2)", "pairs WHERE d1 > d2"),
        ("recursive", "values_first", "half", "sum(v1)", "ones WHERE v1 <= d3"),
        ("recursive", "values_third", "half", "sum(d3)", "ones WHERE v1 > d3"),
        ("recursive", "pairs_first", "whole", "sum(d1)", "live WHERE d1 <= d2"),
        ("recursive", "pairs_second", "whole", "sum(d2)", "live WHERE d1 > d2"),
    )
    rows = " UNION ALL ".join(f"SELECT '{m}' AS method, '{s}' AS step, (SELECT {t} FROM t) AS slots, CAST(coalesce({v}, 0) AS BIGINT) AS real FROM {f}" for m, s, t, v, f in steps)
    return f"{WORKLOADS[name].with_sql()}, {_degrees(name)} {rows}"


def recursive_report(spark: SparkSession, sf_dir: str, name: str = "w3") -> DataFrame:
    f = WORKLOADS[name].frames(spark, sf_dir)
    return leakage.recursive_report(f["R1"], f["R2"], f["R3"])


def recursive_report_sql(name: str = "w3") -> str:
    steps = (
        ("values", "ones"), ("values_by_first", "ones WHERE v1 <= d3"), ("values_by_third", "ones WHERE v1 > d3"),
        ("pairs", "live"), ("pairs_by_first", "live WHERE d1 <= d2"), ("pairs_by_second", "live WHERE d1 > d2"),
    )
    return f"{WORKLOADS[name].with_sql()}, {_degrees(name)} " + " UNION ALL ".join(f"SELECT '{m}' AS measure, count(*) AS value FROM {f}" for m, f in steps)


#: A memory and a block, in words, for which block moves are listed.
MEMORY, BLOCK = 1 << 20, 1 << 10
COSTED = ("w1", "w5", "w7", "w10", "w12")


def costs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Logarithms of the closed forms of time and block moves, for the input sizes of some classes."""
    out = []
    for name in COSTED:
        w = WORKLOADS[name]
        n = sum(df.distinct().count() for df in w.frames(spark, sf_dir).values())
        values = {f"time_{m}": cost.time(w.query, n, m) for m in ("nested_loop", "cover", "wcoj", "circuit", "memory_tree")}
        values |= {f"blocks_{m}": cost.blocks(w.query, n, m, MEMORY, BLOCK) for m in ("nested_loop", "cover", "wcoj", "lower_bound")}
        values |= {"time_decomposed": cost.decomposed_time(w.query, n, n), "blocks_decomposed": cost.blocks(w.query, n, "decomposed", MEMORY, BLOCK, limit=n), "time_relaxed": cost.relaxed_acyclic(n, n)}
        out += [(name, k, round(math.log2(v), 6)) for k, v in values.items()]
    return spark.createDataFrame(out, "workload string, measure string, log2 double")


def costs_sql() -> str:
    sort_time = lambda x: f"(({x}) * greatest(1, log2({x})))"
    sort_blocks = lambda x: f"(({x}) / {BLOCK} * greatest(1, ln(greatest(({x}) / {BLOCK}, 2)) / ln({MEMORY // BLOCK})))"
    parts = []
    for name in COSTED:
        w = WORKLOADS[name]
        best, whole, width = (float(Fraction(x)) for x in WIDTHS[name])
        k, cover = len(w.relations), min(whole, best + 1)
        power = lambda e: f"pow(n, {e})"
        bag = f"pow(n, {width}) + n"
        forms = {
            "time_nested_loop": power(k), "time_cover": f"{power(cover)} * log2(n)", "time_wcoj": f"{power(best)} * log2(n)", "time_circuit": f"{power(best)} * pow(log2(n), 2)",
            "time_memory_tree": f"{power(best)} * pow(log2(n), 2)", "blocks_nested_loop": f"{power(k)} / {BLOCK}", "blocks_cover": sort_blocks(power(cover)), "blocks_wcoj": sort_blocks(power(best)),
            "blocks_lower_bound": f"{power(best)} / {BLOCK}", "time_decomposed": sort_time(bag), "blocks_decomposed": sort_blocks(bag), "time_relaxed": "2 * n * log2(n)",
        }
        total = " + ".join(f"(SELECT count(*) FROM (SELECT DISTINCT * FROM {n}))" for n in w.relations)
        rows = " UNION ALL ".join(f"SELECT '{name}' AS workload, '{m}' AS measure, round(log2({x}), 6) AS log2 FROM k" for m, x in forms.items())
        parts.append(f"SELECT * FROM ({w.with_sql()}, k AS (SELECT CAST({total} AS DOUBLE) AS n) {rows})")
    return " UNION ALL ".join(parts)
