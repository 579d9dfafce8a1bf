"""Joins along a tree decomposition with a declared bound of the result."""

from __future__ import annotations

from collections.abc import Mapping, Sequence
from dataclasses import replace

from obljoin.operators.padded import PaddedTable, real_count
from obljoin.operators.primitives import compact, project, semijoin
from obljoin.operators.twoway import bounded_join
from obljoin.operators.wcoj import Instance, hidden_wcoj, sizes
from obljoin.plans.covers import tau as bound
from obljoin.plans.ghd import Decomposition, decompose
from obljoin.plans.hypergraph import JoinQuery


def bag_tables(query: JoinQuery, instance: Instance, ghd: Decomposition, policy: str = "product", keys: Mapping | None = None, finest: Sequence[str] = ()) -> list[PaddedTable]:
    """For every bag the join of all relations, cut to the bag; a bag that is a relation takes it as it is."""
    out = []
    for bag in ghd.bags:
        inside = query.induced(bag)
        whole = next((n for n, a in inside.edges if set(a) == set(bag) and set(query.relations[n]) == set(bag)), None)
        cut = {n: instance[n] if set(a) == set(query.relations[n]) else project(instance[n], a) for n, a in inside.edges}
        if whole is not None:
            table = cut[whole]
            for n, a in inside.edges:
                if n != whole:
                    table = semijoin(table, cut[n], a)
        else:
            table = hidden_wcoj(inside, {n: t.hold() for n, t in cut.items()}, fuse=True, policy=policy, keys=keys, finest=finest)
        out.append(table.hold())
    return out


def reduce_tree(bags: list[PaddedTable], ghd: Decomposition) -> list[PaddedTable]:
    """Semi-joins from the leaves to the root and back; then every row of every bag is part of a result."""
    bags = list(bags)
    for i in reversed(range(len(bags))):
        p = ghd.parents[i]
        if p is not None:
            bags[p] = semijoin(bags[p], bags[i]).hold()
    for i, p in enumerate(ghd.parents):
        if p is not None:
            bags[i] = semijoin(bags[i], bags[p]).hold()
    return bags


def decomposed_join(query: JoinQuery, instance: Instance, tau: int | str, ghd: Decomposition | None = None, policy: str = "product", keys: Mapping | None = None, finest: Sequence[str] = ()) -> PaddedTable:
    """The join in ``tau`` slots. ``tau`` may be a number, ``keys`` (what declared keys imply), or ``exact``, which reveals the size of the result."""
    ghd = ghd or decompose(query)
    ghd.check(query)
    bags = reduce_tree(bag_tables(query, instance, ghd, policy, keys, finest), ghd)
    if tau == "keys":
        tau = bound(query, sizes(instance), "keys", keys)
    out = bags[0]
    for i in range(1, len(bags)):
        limit = _exact(out, bags[i]) if tau == "exact" else tau
        out = bounded_join(out, bags[i], limit).hold()
    if len(bags) == 1:
        out = compact(out, real_count(out) if tau == "exact" else tau)
    return replace(out, df=out.df.select(*query.attributes, "__real", "__pos"), attrs=query.attributes)


def _exact(r: PaddedTable, s: PaddedTable) -> int:
    """The size of a join, from counts: the relaxed setting, where this number is public."""
    keys = [a for a in r.attrs if a in s.attrs]
    left, right = r.df.where("__real"), s.df.where("__real")
    if not keys:
        return left.count() * right.count()
    n = left.groupBy(*keys).count().join(right.groupBy(*keys).count().withColumnRenamed("count", "other"), keys).selectExpr("sum(count * other)").first()[0]
    return n or 0
