"""What the padded methods are compared with: Catalyst joins without any hiding."""

from __future__ import annotations

from collections.abc import Mapping
from functools import reduce

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from obljoin.operators.padded import PaddedTable, pad_to
from obljoin.operators.physical import Engine
from obljoin.plans.ghd import decompose
from obljoin.plans.hypergraph import JoinQuery, join_tree

Frames = Mapping[str, DataFrame]


def _natural(r: DataFrame, s: DataFrame, how: str = "inner") -> DataFrame:
    keys = [c for c in r.columns if c in s.columns]
    if keys:
        return r.join(s, keys, how)
    if how == "left_semi":
        return r.where(F.lit(bool(s.head(1))))
    return r.crossJoin(s)


def join_order(query: JoinQuery, keys: Mapping[str, tuple[str, ...]] | None = None) -> list[str]:
    """An order of binary joins that never multiplies unconnected relations if it can be helped.

    It begins where declared keys determine the most relations. Relations without new attributes come next, then those whose key is
    there, which add no rows; only then those that may.
    """
    names, keys = [n for n, _ in query.edges], keys or {}

    def following(seen: set[str], left: list[str]) -> str | None:
        filters = (m for m in left if set(query.relations[m]) <= seen)
        return next(filters, next((m for m in left if m in keys and set(keys[m]) <= seen), None))

    def closure(first: str) -> list[str]:
        out, seen = [first], set(query.relations[first])
        while (n := following(seen, [m for m in names if m not in out])) is not None:
            out.append(n)
            seen |= set(query.relations[n])
        return out

    out = max((closure(n) for n in names), key=len)  # the first of the longest
    seen = {x for n in out for x in query.relations[n]}
    while left := [n for n in names if n not in out]:
        n = following(seen, left) or next((m for m in left if seen & set(query.relations[m])), left[0])
        out.append(n)
        seen |= set(query.relations[n])
    return out


def catalyst(query: JoinQuery, frames: Frames, keys: Mapping[str, tuple[str, ...]] | None = None) -> DataFrame:
    """A plan of binary joins in the order that declared keys suggest."""
    return reduce(_natural, (frames[n] for n in join_order(query, keys))).select(*query.attributes)


def sort_merge(r: DataFrame, s: DataFrame) -> DataFrame:
    """A sort-merge join; its partitions show the degrees of the keys, its output the size."""
    return _natural(r.hint("merge"), s)


def degrees(r2: DataFrame, r3: DataFrame, x1: str) -> DataFrame:
    return r2.groupBy(x1).agg(F.count("*").alias("d2")).join(r3.groupBy(x1).agg(F.count("*").alias("d3")), x1)


def triangle_choice_plain(r1: DataFrame, r2: DataFrame, r3: DataFrame) -> DataFrame:
    """Heavy values meet R1, light ones join R2 with R3; how many there are of each is in plain sight."""
    x1 = next(c for c in r2.columns if c in r3.columns)
    found = degrees(r2, r3, x1).withColumn("light", F.col("d2") * F.col("d3") <= r1.count())
    light, heavy = found.where("light").select(x1), found.where("not light").select(x1)
    one = _natural(_natural(heavy.crossJoin(r1), r2, "left_semi"), r3, "left_semi")
    two = _natural(_natural(_natural(r2, light, "left_semi"), r3), r1, "left_semi")
    return one.unionByName(two)


def triangle_delay_plain(r1: DataFrame, r2: DataFrame, r3: DataFrame) -> DataFrame:
    """One attribute after the other: pairs with partners on both sides, then the smaller list of each."""
    x1 = next(c for c in r2.columns if c in r3.columns)
    x2 = next(c for c in r1.columns if c in r3.columns)
    d1, d2 = r1.groupBy(x2).agg(F.count("*").alias("d1")), r2.groupBy(x1).agg(F.count("*").alias("d2"))
    pairs = r3.join(d1, x2).join(d2, x1)
    one = _natural(_natural(pairs.where("d1 <= d2").drop("d1", "d2"), r1), r2, "left_semi")
    two = _natural(_natural(pairs.where("d1 > d2").drop("d1", "d2"), r2), r1, "left_semi")
    return one.unionByName(two)


def recursive_plain(query: JoinQuery, frames: Frames, order: tuple[str, ...] | None = None) -> DataFrame:
    """Attribute at a time: every partial result is extended along its smallest list and filtered by the others."""
    order = order or query.attributes
    out: DataFrame | None = None
    for i, x in enumerate(order):
        past = set(order[:i])
        cuts = {n: frames[n].select(*(a for a in query.relations[n] if a in past or a == x)).distinct() for n in query.incident(x)}
        if out is None or not any(set(c.columns) & past for c in cuts.values()):
            values = reduce(lambda a, b: a.intersect(b), [c.select(x) for c in cuts.values()])
            out = values if out is None else out.crossJoin(values)
            continue
        counted = out
        for n, c in cuts.items():
            keys = [a for a in c.columns if a != x]
            size = c.groupBy(*keys).agg(F.count("*").alias(f"d_{n}")) if keys else c.agg(F.count("*").alias(f"d_{n}"))
            counted = counted.join(size, keys) if keys else counted.crossJoin(size)
        least = F.least(*(F.col(f"d_{n}") for n in cuts)) if len(cuts) > 1 else F.col(f"d_{next(iter(cuts))}")
        parts, free = [], F.lit(True)
        for n, c in cuts.items():
            mine = counted.where(free & (F.col(f"d_{n}") == least)).select(*out.columns)
            free = free & (F.col(f"d_{n}") != least)
            grown = _natural(mine, c)
            for m, other in cuts.items():
                if m != n:
                    grown = _natural(grown, other, "left_semi")
            parts.append(grown)
        out = reduce(lambda a, b: a.unionByName(b), parts)
    return out.select(*query.attributes)


def acyclic_plain(query: JoinQuery, frames: Frames) -> DataFrame:
    """The semi-join program over a join tree, then the joins along it."""
    tree = join_tree(query)
    if tree is None:
        raise ValueError("a cyclic query")
    ghd = decompose(query)
    names = [next(n for n, a in query.edges if a == bag) for bag in ghd.bags]
    held = [frames[n] for n in names]
    for i in reversed(range(1, len(held))):
        held[ghd.parents[i]] = _natural(held[ghd.parents[i]], held[i], "left_semi")
    for i in range(1, len(held)):
        held[i] = _natural(held[i], held[ghd.parents[i]], "left_semi")
    return reduce(_natural, held).select(*query.attributes)


def pad_only(engine: Engine, df: DataFrame, rows: int) -> PaddedTable:
    """Dummies added to a plain result: its size is hidden, but not how it came about."""
    attrs = tuple(df.columns)
    real = engine.numbered(df.withColumn("__real", F.lit(True)), "__pos")
    found = real.count()
    if found > rows:
        raise OverflowError(f"the result has more than {rows} rows")
    return pad_to(PaddedTable(real, attrs, found, engine), rows)


def row_numbers(df: DataFrame, keys: list[str]) -> DataFrame:
    """Plain ranks of rows in key order, for comparison with the padded sorts."""
    return df.withColumn("rank", F.row_number().over(Window.orderBy(*keys)) - 1)
