"""Linear scans over a ranked table, in two levels and without a single partition."""

from __future__ import annotations

from collections.abc import Mapping

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from obljoin.operators.physical import Engine


def scan(
    engine: Engine,
    ranked: DataFrame,
    n: int,
    sums: Mapping[str, Column] | None = None,
    fills: Mapping[str, Column] | None = None,
    before: Mapping[str, Column] | None = None,
) -> DataFrame:
    """Adds running values in the order of ``__rank`` (0 to n-1).

    ``sums``: totals up to and with the row. ``fills``: the last non-null value up to and with the row. ``before``: the same, but
    without the row itself. Rows go to equal buckets by rank; one row per bucket carries the state across.
    """
    sums, fills, before = dict(sums or {}), dict(fills or {}), dict(before or {})
    size = max(1, -(-n // engine.partitions))
    values = {f"__v_{k}": v for k, v in (sums | fills | before).items()}
    held = ranked.withColumns(values | {"__b": F.floor(F.col("__rank") / size).cast("int")})
    v = lambda k: F.col(f"__v_{k}")
    last = lambda k: F.max_by(v(k), F.when(v(k).isNotNull(), F.col("__rank")))
    totals = held.groupBy("__b").agg(F.count("*").alias("__n"), *(F.sum(v(k)).alias(f"__c_{k}") for k in sums), *(last(k).alias(f"__c_{k}") for k in (*fills, *before)))
    upto = Window.orderBy("__b").rowsBetween(Window.unboundedPreceding, -1)  # one row per bucket
    carry = totals.select("__b", *(F.sum(f"__c_{k}").over(upto).alias(f"__c_{k}") for k in sums), *(F.last(f"__c_{k}", True).over(upto).alias(f"__c_{k}") for k in (*fills, *before)))
    dealt = held.repartitionById(engine.partitions, F.col("__b"))
    here = Window.partitionBy("__b").orderBy("__rank")
    now, past = here.rowsBetween(Window.unboundedPreceding, 0), here.rowsBetween(Window.unboundedPreceding, -1)
    inside = dealt.withColumns({k: F.sum(v(k)).over(now) for k in sums} | {k: F.last(v(k), True).over(now) for k in fills} | {k: F.last(v(k), True).over(past) for k in before})
    joined = inside.join(F.broadcast(carry), "__b")
    zero = F.lit(0).cast("long")
    done = joined.withColumns(
        {k: F.coalesce(F.col(k), zero) + F.coalesce(F.col(f"__c_{k}"), zero) for k in sums} | {k: F.coalesce(F.col(k), F.col(f"__c_{k}")) for k in (*fills, *before)}
    )
    return done.drop("__b", *values, *(f"__c_{k}" for k in (*sums, *fills, *before)))
