"""Reads an executed plan and names the nodes whose work depends on data."""

from __future__ import annotations

import re

from pyspark.sql import DataFrame

#: Patterns of physical nodes that a hidden plan must not have, and why. Public numbers may deal rows: __pos, __b (bucket of a rank),
#: __task (partition), __down and __across (tile of a position).
FORBIDDEN = {
    r"AdaptiveSparkPlan": "the plan may change with the data",
    r"Exchange hashpartitioning\((?!__b#|__task#|__down#|__across#|__pos#)": "rows are dealt by a key",
    r"(?:SortMergeJoin|ShuffledHashJoin)\S* \[(?!__down#)": "partners meet by key",
    r"CartesianProduct \(|BroadcastNestedLoopJoin \w+, \w+, \(": "the size of the output follows the data",
    r"InMemoryTableScan": "cached blocks have data-dependent sizes",
    r"(?:BatchEvalPython|MapInPandas|MapInArrow|FlatMapGroups\w*)": "Python may emit any number of rows",
}


def plan_text(df: DataFrame) -> str:
    return df._jdf.queryExecution().executedPlan().toString()


def check(df: DataFrame, allowed: tuple[str, ...] = ()) -> list[str]:
    """Violations found in the physical plan; empty for a plan that only moves rows by position, random tag or range."""
    text = plan_text(df)
    out = []
    for pattern, why in FORBIDDEN.items():
        if pattern not in allowed and (found := re.search(pattern, text)):
            out.append(f"{found[0]}: {why}")
    # a cut on the flag of real rows shows how many there are
    if re.search(r"Filter .*__real", text):
        out.append("Filter on __real: the number of real rows shows")
    return out


def exchanges(df: DataFrame) -> int:
    return len(re.findall(r"\bExchange\b", plan_text(df)))
