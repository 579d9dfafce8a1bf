"""Two triangle joins R1(x2,x3), R2(x1,x3), R3(x1,x2) that split work by the cheaper of two choices, with masks instead of filters."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import Column
from pyspark.sql import functions as F

from obljoin.operators.padded import PaddedTable, concat, masked
from obljoin.operators.primitives import augment, compact, intersect, project, semijoin
from obljoin.operators.twoway import bounded_join
from obljoin.plans.covers import tau as bound
from obljoin.plans.hypergraph import JoinQuery


def corner_names(r1: PaddedTable, r2: PaddedTable, r3: PaddedTable) -> tuple[str, str, str]:
    """x1, x2, x3: the attributes that two of the relations share."""
    pick = lambda a, b: next(x for x in a.attrs if x in b.attrs)
    names = pick(r2, r3), pick(r1, r3), pick(r1, r2)
    if len(set(names)) != 3 or any(len(r.attrs) != 2 for r in (r1, r2, r3)):
        raise ValueError("not a triangle")
    return names


def triangle_tau(r1: PaddedTable, r2: PaddedTable, r3: PaddedTable, policy: str = "product") -> int:
    query = JoinQuery.of({"R1": r1.attrs, "R2": r2.attrs, "R3": r3.attrs})
    return bound(query, {"R1": r1.rows, "R2": r2.rows, "R3": r3.rows}, policy)


def mask(table: PaddedTable, chosen: Column) -> PaddedTable:
    """The table with dummies wherever ``chosen`` does not hold; slots and counts stay."""
    keep = F.col("__real") & chosen
    return table.with_df(table.df.withColumn("__keep", keep).withColumns(masked(table.attrs, F.col("__keep")) | {"__real": F.col("__keep")}))


def candidates(r2: PaddedTable, r3: PaddedTable, x1: str) -> PaddedTable:
    """x1 values of both relations, with their numbers of rows in either."""
    values = intersect(project(r2, [x1]), project(r3, [x1]))
    return augment(values, [("r2", r2, [x1]), ("r3", r3, [x1])]).hold()


def split_choice(values: PaddedTable, limit: int) -> tuple[PaddedTable, PaddedTable]:
    """Light values (product of counts at most the limit) and heavy ones, each in a table of the full size."""
    light = F.col("__deg_r2") * F.col("__deg_r3") <= F.lit(limit)
    return mask(values, light), mask(values, ~light)


def triangle_choice(r1: PaddedTable, r2: PaddedTable, r3: PaddedTable, tau: int | None = None, policy: str = "product") -> PaddedTable:
    """Heavy values of x1 meet all of R1; light ones join R2 with R3. Both fit the bound of the query."""
    x1, x2, x3 = corner_names(r1, r2, r3)
    limit, mark = r1.rows, r1.engine.mark()
    tau = triangle_tau(r1, r2, r3, policy) if tau is None else tau
    light, heavy = (replace(t, df=t.df.drop(*t.counts), counts=()) for t in split_choice(candidates(r2, r3, x1), limit))
    one = bounded_join(heavy, r1, tau, on=())
    one = semijoin(semijoin(one, r2, (x1, x3)), r3, (x1, x2))
    two = bounded_join(semijoin(r2, light, (x1,)).hold(), semijoin(r3, light, (x1,)).hold(), tau)
    two = semijoin(two, r1, (x2, x3))
    return compact(concat(one, two).instead(mark), tau)


def split_delay(r1: PaddedTable, r2: PaddedTable, r3: PaddedTable, reduce_first: bool = False) -> tuple[PaddedTable, PaddedTable]:
    """Rows of R3 with the shorter list in R1 (ties too), and those with the shorter list in R2."""
    x1, x2, _ = corner_names(r1, r2, r3)
    counted = augment(r3, [("r1", r1, [x2]), ("r2", r2, [x1])]).hold()
    if reduce_first:
        counted = mask(counted, (F.col("__deg_r1") > 0) & (F.col("__deg_r2") > 0)).hold()
    first = F.col("__deg_r1") <= F.col("__deg_r2")
    return mask(counted, first), mask(counted, ~first)


def triangle_delay(r1: PaddedTable, r2: PaddedTable, r3: PaddedTable, tau: int | None = None, policy: str = "product", reduce_first: bool = False) -> PaddedTable:
    """Every row of R3 is extended by the shorter of its two lists of x3, then checked against the other relation."""
    x1, x2, x3 = corner_names(r1, r2, r3)
    tau, mark = triangle_tau(r1, r2, r3, policy) if tau is None else tau, r1.engine.mark()
    by_r1, by_r2 = (replace(t, df=t.df.drop(*t.counts), counts=()) for t in split_delay(r1, r2, r3, reduce_first))
    one = semijoin(bounded_join(by_r1, r1, tau), r2, (x1, x3))
    two = semijoin(bounded_join(by_r2, r2, tau), r1, (x2, x3))
    return compact(concat(one, two).instead(mark), tau)
