"""The recursive worst-case optimal join: attributes are added one or two at a time, always along the smallest list."""

from __future__ import annotations

from collections.abc import Mapping, Sequence
from dataclasses import replace
from itertools import product

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from obljoin.operators.padded import PaddedTable, concat
from obljoin.operators.primitives import augment, compact, intersect, project, semijoin
from obljoin.operators.triangle import mask
from obljoin.operators.twoway import bounded_join
from obljoin.plans.hypergraph import JoinQuery
from obljoin.plans.planner import next_step, plan_order, step_slots

Instance = Mapping[str, PaddedTable]


def sizes(instance: Instance) -> dict[str, int]:
    return {n: t.rows for n, t in instance.items()}


def hidden_wcoj(
    query: JoinQuery,
    instance: Instance,
    j: str = "auto",
    fuse: bool = False,
    policy: str = "product",
    keys: Mapping[str, tuple[str, ...]] | None = None,
    order: tuple[tuple[str, ...], ...] | None = None,
    filter_all: bool = False,
    finest: Sequence[str] = (),
) -> PaddedTable:
    """The join in as many slots as the last step of the policy allows (``product``: the product bound).

    ``j``: how many attributes a step adds (``single``, ``pair``, or what costs less). ``order``: the steps, last added first, to override the
    planner, which goes by ``keys`` where some are declared: they leave the slots of the policy as they are, but fewer of these real;
    so does ``finest``, see ``plan_order``. ``fuse``: one bounded join for all parts of a step. ``filter_all``: semi-joins with relations that recursion has enforced already.
    """
    if order is None:
        order = plan_order(query, sizes(instance), j, "keys" if keys else policy, keys, fuse, finest)
    return _solve(query, dict(instance), list(order), fuse, policy, keys, filter_all)


def _solve(query: JoinQuery, instance: dict[str, PaddedTable], order: list[tuple[str, ...]], fuse: bool, policy: str, keys, filter_all: bool) -> PaddedTable:
    if len(query.attributes) == 1:
        return intersect(*(instance[n] for n, _ in query.edges)).hold()
    added, rest = order[0], order[1:]
    engine = next(iter(instance.values())).engine
    mark = engine.mark()
    next_step(query, added)  # refuses an illegal choice
    inner = tuple(x for x in query.attributes if x not in added)
    sub = query.induced(inner)
    below = {n: project(instance[n], a) if set(a) < set(query.relations[n]) else instance[n] for n, a in sub.edges}
    found = _solve(sub, {n: t.hold() for n, t in below.items()}, rest, fuse, policy, keys, filter_all).instead(mark)
    limit = step_slots(query, sizes(instance), added, found.rows, policy, keys)
    touched = [n for n, a in query.edges if set(a) & set(added)]
    lists = [(n, instance[n], [x for x in query.relations[n] if x not in added]) for n in touched]
    counted = augment(found, lists).hold().instead(mark)
    others = [n for n, _ in query.edges] if filter_all else touched
    parts = split_single(counted, query, added[0]) if len(added) == 1 else split_pair(counted, query, *added)
    if fuse and len(added) == 1:
        grown = _fused(parts, query, instance, added[0], limit)
        return compact(_filtered(grown, query, instance, others).instead(mark), limit).hold().instead(mark)
    out = []
    for names, part in parts.items():
        grown = replace(part, df=part.df.drop(*part.counts), counts=())
        for n in names:
            grown = bounded_join(grown, instance[n], limit)
        out.append(_filtered(grown, query, instance, [n for n in others if n not in names]))
    return compact((concat(*out) if len(out) > 1 else out[0]).instead(mark), limit).hold().instead(mark)


def _filtered(table: PaddedTable, query: JoinQuery, instance: Instance, names: list[str]) -> PaddedTable:
    for n in names:
        table = semijoin(table, instance[n], query.relations[n])
    return table


def _argmin(names: list[str]) -> tuple[Column, Column]:
    """The number of the first relation of least degree, and that degree."""
    degrees = [F.col(f"__deg_{n}") for n in names]
    least = F.least(*degrees) if len(degrees) > 1 else degrees[0]
    which = F.lit(len(names) - 1)
    for i in reversed(range(len(names) - 1)):
        which = F.when(degrees[i] == least, i).otherwise(which)
    return which, least


def split_single(counted: PaddedTable, query: JoinQuery, x: str) -> dict[tuple[str, ...], PaddedTable]:
    """One table per relation with x; each tuple is real in that of its smallest degree only."""
    names = query.incident(x)
    which, _ = _argmin(names)
    return {(n,): mask(counted, which == i) for i, n in enumerate(names)}


def split_pair(counted: PaddedTable, query: JoinQuery, y: str, z: str) -> dict[tuple[str, ...], PaddedTable]:
    """One table per pair of relations with only y and only z, and per relation with both.

    A tuple goes to the pair of least product unless a relation with both has strictly fewer rows.
    """
    with_y, with_z = query.incident(y), query.incident(z)
    only_y, only_z = [n for n in with_y if n not in with_z], [n for n in with_z if n not in with_y]
    both = [n for n in with_y if n in with_z]
    at_y, least_y = _argmin(only_y)
    at_z, least_z = _argmin(only_z)
    pairs = F.lit(True)
    out = {}
    if both:
        at_both, least_both = _argmin(both)
        pairs = least_y * least_z <= least_both
        out = {(n,): mask(counted, ~pairs & (at_both == i)) for i, n in enumerate(both)}
    out |= {(a, b): mask(counted, pairs & (at_y == i) & (at_z == k)) for (i, a), (k, b) in product(enumerate(only_y), enumerate(only_z))}
    return out


def _fused(parts: dict[tuple[str, ...], PaddedTable], query: JoinQuery, instance: Instance, x: str, limit: int) -> PaddedTable:
    """All parts in one bounded join: rows carry the number of their part, and attributes foreign to it are blanked on both sides."""
    first = next(iter(parts.values()))
    inner = first.attrs
    kinds = {f.name: f.dataType for f in first.df.schema.fields}
    names = [f"__key_{a}" for a in inner]

    def keyed(df: DataFrame, own: list[str], part: int, real: Column) -> DataFrame:
        blank = lambda a: F.lit("").cast(kinds[a]) if kinds[a].simpleString() == "string" else F.lit(0).cast(kinds[a])
        values = {f"__key_{a}": F.when(real, F.col(a) if a in own else blank(a)) for a in inner}
        return df.withColumns(values | {"__branch": F.when(real, F.lit(part))})

    left, right, at = None, None, 0
    for i, ((n,), part) in enumerate(parts.items()):
        own = [a for a in query.relations[n] if a != x]
        mine = keyed(part.df, own, i, F.col("__real")).select(*inner, *names, "__branch", "__real", "__pos")
        # a tuple is real in one part only, so the parts share their slots
        left = mine if left is None else left.unionByName(mine)
        table = instance[n]
        theirs = keyed(table.df.select(*own, x, "__real", "__pos", *(F.lit(None).cast(kinds[a]).alias(a) for a in inner if a not in own)), own, i, F.col("__real"))
        theirs = theirs.select(x, *names, "__branch", "__real", (F.col("__pos") + at).alias("__pos"))
        at += table.rows
        right = theirs if right is None else right.unionByName(theirs)
    keep = [*inner, *names, "__branch"]
    left = left.where("__real") if first.large else left.groupBy("__pos").agg(F.max("__real").alias("__real"), *(F.max(c).alias(c) for c in keep))
    r = PaddedTable(left.select(*keep, "__real", "__pos"), tuple(keep), first.rows, first.engine).hold()
    s = PaddedTable(right.select(x, *names, "__branch", "__real", "__pos"), (x, *names, "__branch"), at, first.engine).hold()
    grown = bounded_join(r, s, limit, on=[*names, "__branch"])
    return replace(grown, df=grown.df.select(*inner, x, "__real", "__pos"), attrs=(*inner, x))
