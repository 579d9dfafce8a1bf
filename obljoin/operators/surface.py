"""Operators around the joins: outer, interval and as-of joins, aggregates, windows, sets, top-k. Sizes stay public."""

from __future__ import annotations

from collections.abc import Mapping, Sequence
from dataclasses import replace

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from obljoin.operators.padded import PaddedTable, concat, masked
from obljoin.operators.primitives import antijoin, compact, intersect, merged, project, reopened
from obljoin.operators.scan import scan
from obljoin.operators.twoway import bounded_join, nested_loop


def select(t: PaddedTable, attrs: Sequence[str]) -> PaddedTable:
    """Fewer columns without removing duplicates (see ``project`` for that)."""
    return replace(t, df=t.df.select(*attrs, "__real", "__pos"), attrs=tuple(attrs), counts=())


def with_column(t: PaddedTable, name: str, value: Column) -> PaddedTable:
    """A computed column; null in dummies."""
    attrs = (*(a for a in t.attrs if a != name), name)
    return replace(t, df=t.df.withColumn(name, F.when(F.col("__real"), value)).select(*attrs, "__real", "__pos", *t.counts), attrs=attrs)


def widened(t: PaddedTable, like: PaddedTable) -> PaddedTable:
    """The attributes of ``like``, null where the table lacks them."""
    kinds = {f.name: f.dataType for f in like.df.schema.fields}
    df = t.df.select(*((F.col(a) if a in t.attrs else F.lit(None).cast(kinds[a])).alias(a) for a in like.attrs), "__real", "__pos")
    return PaddedTable(df, like.attrs, t.rows, t.engine)


def outer_join(r: PaddedTable, s: PaddedTable, tau: int, how: str = "left") -> PaddedTable:
    """tau slots of matches, and the slots of either side for what has no partner."""
    if how not in ("left", "right", "full"):
        raise ValueError(f"no outer join {how}")
    inner = bounded_join(r, s, tau)
    parts = [inner]
    if how in ("left", "full"):
        parts.append(widened(antijoin(r, s), inner))
    if how in ("right", "full"):
        parts.append(widened(antijoin(s, r), inner))
    return concat(*parts)


def interval_join(r: PaddedTable, s: PaddedTable, point: str, start: str, end: str, tau: int) -> PaddedTable:
    """Rows of r whose ``point`` lies in [start, end) of a row of s, in tau slots."""
    pairs = nested_loop(r, s, (F.col(point) >= F.col(start)) & (F.col(point) < F.col(end)))
    return compact(pairs, tau)


def asof_join(r: PaddedTable, s: PaddedTable, time: str, other_time: str, by: Sequence[str], columns: Sequence[str]) -> PaddedTable:
    """For every row of r the latest row of s at or before its time with the same ``by``; nulls if there is none."""
    by, attrs = list(by), (*r.attrs, *columns)
    t = replace(s, df=s.df.withColumn("__time", F.col(other_time)), attrs=(*s.attrs, "__time"))
    u = replace(r, df=r.df.withColumn("__time", F.col(time)), attrs=(*r.attrs, "__time"))
    both = merged(u, t, [*by, "__time"])
    order = [F.col("__dead"), *(F.col(f"__key.k{i}") for i in range(len(by) + 1)), F.col("__side")]
    n = r.rows + s.rows
    ranked = r.engine.ordered(both, order, n, "__at")
    group = F.struct(*(F.col(f"__key.k{i}").alias(f"k{i}") for i in range(len(by)))) if by else F.struct(F.lit(1).alias("k0"))
    given = F.struct(group.alias("group"), *(F.col(f"__s.{c}").alias(c) for c in columns))
    done = scan(r.engine, ranked, n, fills={"__got": F.when((F.col("__side") == 0) & ~F.col("__dead"), given)})
    hit = F.coalesce(F.col("__got.group") == group, F.lit(False))
    out = reopened(u, done, ~F.col("__dead"), {c: F.when(hit, F.col(f"__got.{c}")) for c in columns}, attrs=(*u.attrs, *columns))
    return select(out, attrs)


def aggregate(t: PaddedTable, by: Sequence[str], aggs: Mapping[str, Column]) -> PaddedTable:
    """Aggregates per group, in as many slots as the table has. ``aggs`` are Spark aggregates over real rows.

    Groups meet by key, so hidden mode refuses this; ``totals`` is the hidden form for counts and sums.
    """
    if t.engine.hidden:
        raise ValueError("hidden tables are aggregated by totals()")
    by = list(by)
    values = t.df.where("__real").groupBy(*by).agg(*(c.alias(n) for n, c in aggs.items()))
    first = t.df.where("__real").groupBy(*by).agg(F.min("__pos").alias("__pos"))
    joined = first.join(values, by) if by else first.crossJoin(values).where(F.col("__pos").isNotNull())
    slots = t.df.select("__pos").join(joined.withColumn("__in", F.lit(True)), "__pos", "left")
    attrs = (*by, *aggs)
    return PaddedTable(slots.select(*attrs, F.coalesce("__in", F.lit(False)).alias("__real"), "__pos"), attrs, t.rows, t.engine)


def grouping_sets(t: PaddedTable, sets: Sequence[Sequence[str]], aggs: Mapping[str, Column]) -> PaddedTable:
    """One aggregate per set of attributes, in as many slots each; attributes outside a set are null."""
    whole = list(dict.fromkeys(a for s in sets for a in s))
    kinds = {f.name: f.dataType for f in t.df.schema.fields}
    parts = []
    for s in sets:
        one = aggregate(t, s, aggs)
        df = one.df.withColumns({a: F.lit(None).cast(kinds[a]) for a in whole if a not in s})
        attrs = (*whole, *aggs)
        parts.append(PaddedTable(df.select(*attrs, "__real", "__pos"), attrs, one.rows, one.engine))
    return concat(*parts)


def running(t: PaddedTable, by: Sequence[str], order: Sequence[str], sums: Mapping[str, Column]) -> PaddedTable:
    """Running sums within groups (``row_number`` is the sum of 1), by one sort and one scan over all rows."""
    keys = [~F.col("__real"), *(F.col(a) for a in (*by, *order))]
    ranked = t.engine.ordered(t.df, keys, t.rows)
    own = F.when(F.col("__real"), F.struct(*(F.col(a).alias(a) for a in by)) if by else F.struct(F.lit(1).alias("one")))
    values = {f"__t_{n}": F.when(F.col("__real"), c).otherwise(0) for n, c in sums.items()}
    one = scan(t.engine, ranked.withColumn("__own", own).withColumns(values), t.rows, sums={n: F.col(f"__t_{n}") for n in sums}, before={"__past": F.col("__own")})
    new = F.col("__real") & ~F.coalesce(F.col("__past") == F.col("__own"), F.lit(False))
    start = F.when(new, F.struct(*((F.col(n) - F.col(f"__t_{n}")).alias(n) for n in sums)))
    two = scan(t.engine, one, t.rows, fills={"__from": start})
    attrs = (*t.attrs, *sums)
    df = two.withColumns({n: F.when(F.col("__real"), F.col(n) - F.col(f"__from.{n}")) for n in sums}).withColumn("__pos", F.col("__rank"))
    return PaddedTable(df.select(*attrs, "__real", "__pos"), attrs, t.rows, t.engine)


def lagged(t: PaddedTable, by: Sequence[str], order: Sequence[str], values: Mapping[str, str]) -> PaddedTable:
    """The value of the row before within a group: ``values`` maps new names to attributes."""
    keys = [~F.col("__real"), *(F.col(a) for a in (*by, *order))]
    ranked = t.engine.ordered(t.df, keys, t.rows)
    group = F.struct(*(F.col(a).alias(f"k{i}") for i, a in enumerate(by))) if by else F.struct(F.lit(1).alias("k0"))
    given = F.when(F.col("__real"), F.struct(group.alias("group"), *(F.col(a).alias(n) for n, a in values.items())))
    done = scan(t.engine, ranked, t.rows, before={"__got": given})
    hit = F.col("__real") & F.coalesce(F.col("__got.group") == group, F.lit(False))
    attrs = (*t.attrs, *values)
    df = done.withColumns({n: F.when(hit, F.col(f"__got.{n}")) for n in values}).withColumn("__pos", F.col("__rank"))
    return PaddedTable(df.select(*attrs, "__real", "__pos"), attrs, t.rows, t.engine)


def top_k(t: PaddedTable, order: Sequence[Column], k: int) -> PaddedTable:
    """The first k real rows; k is public."""
    ranked = t.engine.ordered(t.df, [~F.col("__real"), *order], t.rows)
    df = ranked.withColumn("__pos", F.col("__rank")).where(F.col("__rank") < k)
    return replace(t, df=df.select(*t.columns()), rows=min(k, t.rows))


def distinct(t: PaddedTable) -> PaddedTable:
    return project(t, t.attrs)


def union(r: PaddedTable, s: PaddedTable) -> PaddedTable:
    """Without duplicates, in the slots of both."""
    return distinct(concat(r, s).hold())


def intersection(r: PaddedTable, s: PaddedTable) -> PaddedTable:
    return intersect(r, s)


def difference(r: PaddedTable, s: PaddedTable) -> PaddedTable:
    return antijoin(r, s, r.attrs)


def payload(result: PaddedTable, source: DataFrame, key: Sequence[str]) -> DataFrame:
    """Real rows with the other columns of a source whose key the result holds (one row each)."""
    return result.df.where("__real").select(*result.attrs).join(source, list(key), "left")


def multiplicities(t: PaddedTable, source: DataFrame) -> DataFrame:
    """How often each row of a set occurs in the bag it came from."""
    return source.groupBy(*t.attrs).agg(F.count("*").alias("copies")).join(t.df.where("__real").select(*t.attrs), list(t.attrs), "left_semi")


def totals(t: PaddedTable, by: Sequence[str], sums: Mapping[str, Column]) -> PaddedTable:
    """Sums per group (a count is the sum of 1) in as many slots as the table has, by sorts and scans in either mode."""
    by = list(by)
    ran = running(t, by, [], sums).hold()
    last = _edge(ran, by, ran.rows, falling=True)
    return select(last, (*by, *sums))


def first_per_group(t: PaddedTable, by: Sequence[str], order: Sequence[Column]) -> PaddedTable:
    """The first row of each group, in the table's slots, by one sort and one scan."""
    ranked = t.engine.ordered(t.df, [~F.col("__real"), *(F.col(a) for a in by), *order, F.col("__pos")], t.rows)
    return _edge(t.with_df(ranked.withColumn("__pos", F.col("__rank"))), list(by), t.rows)


def _edge(t: PaddedTable, by: list[str], n: int, falling: bool = False) -> PaddedTable:
    """Of rows in the order of their groups only the first of each (``falling``: the last) stays real."""
    group = F.struct(*(F.col(a).alias(f"k{i}") for i, a in enumerate(by))) if by else F.struct(F.lit(1).alias("k0"))
    rank = F.lit(n - 1) - F.col("__pos") if falling else F.col("__pos")
    done = scan(t.engine, t.df.withColumn("__rank", rank).withColumn("__own", F.when(F.col("__real"), group)), n, before={"__past": F.col("__own")})
    keep = F.col("__real") & ~F.coalesce(F.col("__past") == F.col("__own"), F.lit(False))
    done = done.withColumn("__keep", keep)
    return t.with_df(done.withColumns(masked(t.attrs, F.col("__keep")) | {"__real": F.col("__keep")}))
