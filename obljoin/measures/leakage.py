"""What an observer learns: from traces, from plain plans, and from Spark's own event log."""

from __future__ import annotations

import json
import random
from collections import Counter
from collections.abc import Hashable, Sequence
from pathlib import Path

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from obljoin.measures.trace import Memory


def same_trace(a: Memory, b: Memory) -> bool:
    return a.trace == b.trace


def tv_distance(a: Sequence[Hashable], b: Sequence[Hashable]) -> float:
    """Total variation distance of two samples."""
    p, q = Counter(a), Counter(b)
    return sum(abs(p[x] / len(a) - q[x] / len(b)) for x in p.keys() | q.keys()) / 2


def tv_bound(a: Sequence[Hashable], b: Sequence[Hashable], rounds: int = 200, seed: int = 1, level: float = 0.99) -> float:
    """What the distance would be at most, with this confidence, if both samples had one law."""
    rng, pool, out = random.Random(seed), [*a, *b], []
    for _ in range(rounds):
        rng.shuffle(pool)
        out.append(tv_distance(pool[: len(a)], pool[len(a) :]))
    return sorted(out)[min(rounds - 1, int(level * rounds))]


def choice_report(r1: DataFrame, r2: DataFrame, r3: DataFrame) -> DataFrame:
    """The numbers that the plain heavy/light triangle shows: one row of measure, value each."""
    x1 = next(c for c in r2.columns if c in r3.columns)
    n = r1.count()
    counts = r2.groupBy(x1).agg(F.count("*").alias("d2")).join(r3.groupBy(x1).agg(F.count("*").alias("d3")), x1)
    row = counts.agg(
        F.count("*").alias("candidates"),
        F.coalesce(F.sum(F.when(F.col("d2") * F.col("d3") > n, 1).otherwise(0)), F.lit(0)).alias("heavy"),
        F.coalesce(F.sum(F.when(F.col("d2") * F.col("d3") <= n, 1).otherwise(0)), F.lit(0)).alias("light"),
        F.coalesce(F.max("d2"), F.lit(0)).alias("longest_second"),
        F.coalesce(F.max("d3"), F.lit(0)).alias("longest_third"),
        F.coalesce(F.sum(F.when(F.col("d2") * F.col("d3") <= n, F.col("d2") * F.col("d3")).otherwise(0)), F.lit(0)).alias("light_pairs"),
    )
    names = row.columns
    stacked = ", ".join(f"'{c}', cast({c} AS BIGINT)" for c in names)
    return row.selectExpr(f"stack({len(names)}, {stacked}) AS (measure, value)")


def delay_report(r1: DataFrame, r2: DataFrame, r3: DataFrame) -> DataFrame:
    """How many rows of R3 take their list from R1 and how many from R2."""
    x1 = next(c for c in r2.columns if c in r3.columns)
    x2 = next(c for c in r1.columns if c in r3.columns)
    d1, d2 = r1.groupBy(x2).agg(F.count("*").alias("d1")), r2.groupBy(x1).agg(F.count("*").alias("d2"))
    both = r3.join(d1, x2, "left").join(d2, x1, "left").na.fill(0, ["d1", "d2"])
    row = both.agg(F.sum((F.col("d1") <= F.col("d2")).cast("long")).alias("first"), F.sum((F.col("d1") > F.col("d2")).cast("long")).alias("second"))
    return row.selectExpr("stack(2, 'first', first, 'second', second) AS (measure, value)")


def recursive_report(r1: DataFrame, r2: DataFrame, r3: DataFrame) -> DataFrame:
    """What the plain recursive join of a triangle shows: values and pairs that survive, and how many take which list."""
    x1 = next(c for c in r2.columns if c in r3.columns)
    x2 = next(c for c in r1.columns if c in r3.columns)
    d1, d2, d3 = (r.groupBy(x).agg(F.count("*").alias(n)) for r, x, n in ((r1, x2, "d1"), (r2, x1, "d2"), (r3, x1, "d3")))
    ones = d2.join(d3, x1).crossJoin(d1.agg(F.count("*").alias("all")))  # one row
    pairs = r3.join(d1, x2).join(d2, x1)
    count = lambda c, name: F.coalesce(F.sum(F.when(c, 1).otherwise(0)), F.lit(0)).cast("long").alias(name)
    first = ones.agg(F.count("*").alias("values"), count(F.col("all") <= F.col("d3"), "values_by_first"), count(F.col("all") > F.col("d3"), "values_by_third"))
    second = pairs.agg(F.count("*").alias("pairs"), count(F.col("d1") <= F.col("d2"), "pairs_by_first"), count(F.col("d1") > F.col("d2"), "pairs_by_second"))
    row = first.crossJoin(second)  # one row each
    return row.selectExpr(f"stack({len(row.columns)}, {', '.join(f"'{c}', `{c}`" for c in row.columns)}) AS (measure, value)")


def spark_profile(event_log: str, jobs_from: float = 0.0) -> list[tuple[int, int, int, int, int]]:
    """From an event log: (stage, task, rows read, rows written, bytes written) of every exchange, in order."""
    out = []
    paths = [p for p in Path(event_log).rglob("*") if p.is_file() and not p.name.startswith(".")] if Path(event_log).is_dir() else [Path(event_log)]
    for path in sorted(paths):
        for line in path.open(errors="replace"):
            e = json.loads(line) if line.startswith("{") else {}
            if e.get("Event") == "SparkListenerTaskEnd" and e["Task Info"]["Launch Time"] >= jobs_from:
                m = e.get("Task Metrics") or {}
                wrote, read = m.get("Shuffle Write Metrics", {}), m.get("Shuffle Read Metrics", {})
                out.append((e["Stage ID"], e["Task Info"]["Index"], read.get("Total Records Read", 0), wrote.get("Shuffle Records Written", 0), wrote.get("Shuffle Bytes Written", 0)))
    return sorted(out)


def partition_sizes(df: DataFrame) -> list[int]:
    """Rows per partition after an exchange: what an observer of block sizes sees."""
    return sorted(r["count"] for r in df.groupBy(F.spark_partition_id().alias("p")).count().collect())
