"""Nested loops over the relations of an edge cover, filtered by semi-joins after each step."""

from __future__ import annotations

from obljoin.operators.padded import PaddedTable
from obljoin.operators.primitives import compact, semijoins
from obljoin.operators.twoway import nested_loop
from obljoin.operators.wcoj import Instance, sizes
from obljoin.plans.covers import integral_cover
from obljoin.plans.covers import tau as bound
from obljoin.plans.hypergraph import JoinQuery


def cover_join(query: JoinQuery, instance: Instance, cover: str | tuple[str, ...] = "least", policy: str = "product") -> PaddedTable:
    """``cover``: ``least`` (an optimal integral cover), ``all`` (every relation), or names in the order of the loops."""
    rows = sizes(instance)
    if cover == "least":
        names = sorted(integral_cover(query, rows), key=lambda n: (rows[n], n))
    elif cover == "all":
        names = sorted(rows, key=lambda n: (rows[n], n))
    else:
        names = list(cover)
        if {x for n in names for x in query.relations[n]} != set(query.attributes):
            raise ValueError("not a cover")
    out, looped = None, set()
    for name in names:
        out = instance[name] if out is None else nested_loop(out, instance[name], tiling="recursive", tile=1 << 20)
        if out.engine.hidden:
            out = out.hold()
        looped.add(name)
        # pairs agree with every relation that has been looped over already
        out = semijoins(out, [instance[other] for other in query.relations if other not in looped])
        # the attributes so far bound what can be real, which keeps the next loop small
        limit = bound(query.induced(out.attrs), rows, policy)
        if limit < out.rows:
            out = compact(out, limit)
        if out.engine.hidden or name != names[-1]:
            out = out.hold()
    return out
