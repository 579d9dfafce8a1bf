"""Relational steps with outputs of public size.

In padded mode keys meet by Catalyst joins and aggregates; in hidden mode they meet by sorting tagged rows and scanning,
and helper rows of public number leave by a keyed permutation.
"""

from __future__ import annotations

from collections.abc import Sequence
from dataclasses import replace

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from obljoin.operators.padded import PaddedTable, empty_rows, masked
from obljoin.operators.scan import scan


def common(r: PaddedTable, s: PaddedTable, on: Sequence[str] | None = None) -> list[str]:
    return [a for a in r.attrs if a in s.attrs] if on is None else list(on)


def merged(r: PaddedTable, s: PaddedTable, on: list[str]) -> DataFrame:
    """Rows of both sides under one schema: __side (0: s, 1: r), __dead, __key, __at, and the columns of either as a struct."""

    def side(t: PaddedTable, number: int, offset: int) -> DataFrame:
        mine, other = ("__r", "__s") if number else ("__s", "__r")
        key = F.struct(*(F.col(a).alias(f"k{i}") for i, a in enumerate(on))) if on else F.struct(F.lit(1).alias("k0"))
        there = s if number else r
        nothing = F.lit(None).cast(there.df.select(F.struct(*there.columns()).alias("x")).schema["x"].dataType)
        return t.df.select(
            F.lit(number).alias("__side"), (~F.col("__real")).alias("__dead"), F.when(F.col("__real"), key).alias("__key"),
            (F.col("__pos") + offset).alias("__at"), F.struct(*t.columns()).alias(mine), nothing.alias(other),
        ).select("__side", "__dead", "__key", "__at", "__r", "__s")

    return side(r, 1, s.rows).unionByName(side(s, 0, 0))


def sort_keys(on: list[str]) -> list[Column]:
    return [F.col("__dead"), *(F.col(f"__key.k{i}") for i in range(max(1, len(on)))), F.col("__side")]


def meet(r: PaddedTable, s: PaddedTable, on: list[str]) -> tuple[DataFrame, int]:
    """Both sides in the order of the key, s before r."""
    n = r.rows + s.rows
    return r.engine.ordered(merged(r, s, on), sort_keys(on), n, "__at"), n


def reopened(r: PaddedTable, df: DataFrame, real: Column, extra: dict[str, Column] | None = None, counts: tuple[str, ...] | None = None, attrs: tuple[str, ...] | None = None) -> PaddedTable:
    """The r side of a scanned union, with new positions."""
    attrs = attrs or r.attrs
    counts = r.counts if counts is None else counts
    held = df.withColumn("__keep", real)
    names = {a: F.col(f"__r.{a}") for a in (*r.attrs, *r.counts)} | dict(extra or {})
    flat = held.select("__side", "__at", F.col("__keep").alias("__real"), *(names[a].alias(a) for a in (*attrs, *counts)))
    flat = flat.withColumns(masked(attrs, F.col("__real")))
    out = r.engine.opened(flat, "__side", 1)
    return replace(r, df=out.select(*attrs, "__real", "__pos", *counts), attrs=attrs, counts=counts)


def by_key(df: DataFrame, found: DataFrame, keys: Sequence[str], large: bool = False) -> DataFrame:
    """Left join of padded rows with at most one row per key. Dummies, which have no key, are dealt by position instead of all to one task.

    Those of a ``large`` table take no part in the exchange.
    """
    if large:
        live = df.where("__real").withColumn("__real", F.lit(True)).join(found, list(keys), "left")
        dead = df.where(~F.col("__real")).withColumn("__real", F.lit(False))
        return live.unionByName(dead.withColumns({f.name: F.lit(None).cast(f.dataType) for f in found.schema.fields if f.name not in keys}))
    part = F.when(F.col("__real"), F.lit(0)).otherwise(F.pmod("__pos", F.lit(4096)) + 1).cast("int")
    return df.withColumn("__part", part).join(found.withColumn("__part", F.lit(0)), [*keys, "__part"], "left").drop("__part")


def semijoin(r: PaddedTable, s: PaddedTable, on: Sequence[str] | None = None, anti: bool = False) -> PaddedTable:
    """Rows of r with a partner in s (``anti``: without). No shared attribute: whether s has any row."""
    keys = common(r, s, on)
    r.engine.step("antijoin" if anti else "semijoin", r.rows)
    if r.engine.hidden:
        ranked, n = meet(r, s, keys)
        done = scan(r.engine, ranked, n, fills={"__hit": F.when((F.col("__side") == 0) & ~F.col("__dead"), F.col("__key"))})
        hit = F.coalesce(F.col("__hit") == F.col("__key"), F.lit(False))
        return reopened(r, done, ~F.col("__dead") & (~hit if anti else hit))
    if not anti and _has_sieve(r, s, keys):
        return _sieved(r, [(s, keys)])
    if keys:
        found = s.df.where("__real").select(*keys).distinct().withColumn("__hit", F.lit(True))
        joined = by_key(r.df, found, keys, r.large)
    else:
        any_ = s.df.where("__real").agg(F.max("__real").alias("__hit"))  # one row
        joined = r.df.join(F.broadcast(any_))
    hit = F.coalesce(F.col("__hit"), F.lit(False))
    df = joined.withColumn("__keep", F.col("__real") & (~hit if anti else hit))
    return r.with_df(df.withColumns(masked(r.attrs, F.col("__keep")) | {"__real": F.col("__keep")}))


#: A large table of more slots than so many times those of its partner goes through a sieve; bits of a sieve for each slot of the
#: partner, and the most bits of one, as powers of two; words of a part of it.
SIEVED = 64
SIEVE_ROW, SIEVE_MOST, SIEVE_PART = 3, 26, 1 << 10


def _has_sieve(r: PaddedTable, s: PaddedTable, keys: Sequence[str]) -> bool:
    return bool(keys) and r.large and r.rows > SIEVED * s.rows


def semijoins(r: PaddedTable, partners: Sequence[PaddedTable]) -> PaddedTable:
    """Semi-joins with all partners. The sieves of a large table come first, those of the smallest partners before the others, and then the exact comparisons."""
    fits = [_has_sieve(r, s, common(r, s)) for s in partners]
    if sum(fits) > 1:
        sieved = sorted((s for s, fit in zip(partners, fits, strict=True) if fit), key=lambda s: s.rows)
        for _ in sieved:
            r.engine.step("semijoin", r.rows)
        r = _sieved(r, [(s, common(r, s)) for s in sieved])
        partners = [s for s, fit in zip(partners, fits, strict=True) if not fit]
    for s in partners:
        r = semijoin(r, s)
    return r


def _sieve(s: PaddedTable, found: DataFrame, keys: Sequence[str], name: str) -> tuple[DataFrame, Column]:
    """One row with the set of bits of the keys, and whether a row passes it."""
    bits = min(SIEVE_MOST, max(16, (max(s.rows, 1) - 1).bit_length() + SIEVE_ROW))
    h = F.xxhash64(*keys)
    places = [h.bitwiseAND(F.lit((1 << bits) - 1)), F.shiftrightunsigned(h, 64 - bits)]
    bit = F.expr("shiftleft(1L, CAST(__p & 63 AS INT))")
    words = found.select(F.explode(F.array(*places)).alias("__p")).select(F.shiftright("__p", 6).alias("__w"), bit.alias("__b"))
    every = s.engine.spark.range(1 << bits - 6).select(F.col("id").alias("__w"), F.lit(0).cast("long").alias("__b"))
    words = words.unionByName(every).groupBy("__w").agg(F.bit_or("__b").alias("__b"))
    listed = lambda by, value: F.transform(F.sort_array(F.collect_list(F.struct(by, value))), lambda x: x[value])
    part = F.expr(f"__w div {SIEVE_PART}").alias("__c")
    parts = words.select(part, "__w", "__b").groupBy("__c").agg(listed("__w", "__b").alias("__bits"))
    sieve = s.engine.barrier(parts.groupBy().agg(listed("__c", "__bits").alias(name)))

    def inside(place: Column) -> Column:
        word = F.shiftright(place, 6)
        held = F.get(F.get(F.col(name), F.shiftright(word, SIEVE_PART.bit_length() - 1).cast("int")), word.bitwiseAND(F.lit(SIEVE_PART - 1)).cast("int"))
        return F.getbit(held, place.bitwiseAND(F.lit(63)).cast("int")) == 1

    return sieve, inside(places[0]) & inside(places[1])


def _sieved(r: PaddedTable, partners: Sequence[tuple[PaddedTable, Sequence[str]]]) -> PaddedTable:
    """Semi-joins of a large table. Most rows without a partner fail a small set of bits, which is sent to all of them, so only the rest is exchanged and compared exactly."""
    live, dead = r.df.where("__real"), [r.df.where(~F.col("__real"))]
    exact = []
    for i, (s, keys) in enumerate(partners):
        found = s.df.where("__real").select(*keys).distinct()
        sieve, passes = _sieve(s, found, keys, f"__sieve{i}")
        both = live.join(F.broadcast(sieve))
        dead.append(both.where(~passes))
        live = both.where(passes).select(*r.columns())
        exact.append((found.withColumn(f"__hit{i}", F.lit(True)), keys))
    hit = F.lit(True)
    for i, (found, keys) in enumerate(exact):
        live, hit = live.join(found, list(keys), "left"), hit & F.coalesce(F.col(f"__hit{i}"), F.lit(False))
    out = live.withColumn("__keep", hit).withColumns({a: F.when(F.col("__keep"), F.col(a)) for a in r.attrs} | {"__real": F.col("__keep")}).select(*r.columns())
    for df in dead:
        out = out.unionByName(df.withColumns(masked(r.attrs, F.lit(False)) | {"__real": F.lit(False)}).select(*r.columns()))
    return r.with_df(out)


def antijoin(r: PaddedTable, s: PaddedTable, on: Sequence[str] | None = None) -> PaddedTable:
    return semijoin(r, s, on, anti=True)


def lookup(r: PaddedTable, s: PaddedTable, on: Sequence[str], columns: Sequence[str]) -> PaddedTable:
    """Fetches columns of the one row of s per key; rows without it stay, with nulls. The new columns become attributes."""
    on, columns = list(on), list(columns)
    attrs = (*r.attrs, *columns)
    r.engine.step("lookup", r.rows)
    if r.engine.hidden:
        ranked, n = meet(r, s, on)
        given = F.struct(F.col("__key").alias("key"), *(F.col(f"__s.{c}").alias(c) for c in columns))
        done = scan(r.engine, ranked, n, fills={"__got": F.when((F.col("__side") == 0) & ~F.col("__dead"), given)})
        hit = F.coalesce(F.col("__got.key") == F.col("__key"), F.lit(False))
        return reopened(r, done, ~F.col("__dead"), {c: F.when(hit, F.col(f"__got.{c}")) for c in columns}, attrs=attrs)
    joined = by_key(r.df, s.df.where("__real").select(*on, *columns), on, r.large)
    return replace(r, df=joined.select(*attrs, "__real", "__pos", *r.counts), attrs=attrs)


def project(r: PaddedTable, attrs: Sequence[str]) -> PaddedTable:
    """The different values of some attributes; as many rows as before."""
    attrs = tuple(attrs)
    if not attrs:
        raise ValueError("a projection needs an attribute")
    r.engine.step("project", r.rows)
    if r.engine.hidden:
        key = F.when(F.col("__real"), F.struct(*attrs))
        order = [~F.col("__real"), *(F.col(a) for a in attrs)]
        ranked = r.engine.ordered(r.df, order, r.rows)
        done = scan(r.engine, ranked.withColumn("__own", key), r.rows, before={"__past": F.col("__own")})
        new = F.col("__real") & ~F.coalesce(F.col("__past") == F.col("__own"), F.lit(False))
        df = done.withColumn("__keep", new).withColumn("__pos", F.col("__rank"))
    else:
        first = r.df.where("__real").groupBy(*attrs).agg(F.min("__pos").alias("__pos")).select("__pos", F.lit(True).alias("__first"))
        df = (by_key(r.df, first, ["__pos"], True) if r.large else r.df.join(first, "__pos", "left")).withColumn("__keep", F.coalesce("__first", F.lit(False)))
    df = df.withColumns(masked(attrs, F.col("__keep")) | {"__real": F.col("__keep")})
    return replace(r, df=df.select(*attrs, "__real", "__pos"), attrs=attrs, counts=())


def intersect(*tables: PaddedTable) -> PaddedTable:
    """Rows of all tables. The public size is that of the smallest."""
    first, *rest = sorted(tables, key=lambda t: t.rows)
    for t in rest:
        first = semijoin(first, t, first.attrs)
    return first


def augment(r: PaddedTable, partners: Sequence[tuple[str, PaddedTable, Sequence[str]]]) -> PaddedTable:
    """Adds ``__deg_<name>``: how many rows of each partner agree on the given attributes (none: all its rows)."""
    for name, s, on in partners:
        on, column = list(on), f"__deg_{name}"
        r.engine.step("augment", r.rows)
        if r.engine.hidden:
            done = counted(r, s, on)
            r = reopened(r, done, ~F.col("__dead"), {column: F.when(F.col("__dead"), F.lit(0)).otherwise(F.col("__n")).cast("long")}, counts=(*r.counts, column))
            continue
        live = s.df.where("__real")
        if on:
            joined = by_key(r.df, live.groupBy(*on).agg(F.count("*").alias("__n")), on, r.large)
        else:
            joined = r.df.join(F.broadcast(live.agg(F.count("*").alias("__n"))))  # one row
        n = F.when(F.col("__real"), F.coalesce("__n", F.lit(0))).otherwise(0).cast("long")
        r = replace(r, df=joined.withColumn(column, n).select(*r.columns(), column), counts=(*r.counts, column))
    return r


def counted(r: PaddedTable, s: PaddedTable, on: list[str]) -> DataFrame:
    """The sorted union with, for rows of r, ``__n`` partners that start at ``__start`` among s; for rows of s their number ``__start``."""
    ranked, n = meet(r, s, on)
    mine = (F.col("__side") == 0) & ~F.col("__dead")
    one = scan(r.engine, ranked, n, sums={"__c": F.when(mine, 1).otherwise(0).cast("long")}, before={"__past": F.when(mine, F.col("__key"))})
    first = mine & ~F.coalesce(F.col("__past") == F.col("__key"), F.lit(False))
    two = scan(r.engine, one, n, fills={"__run": F.when(first, F.struct(F.col("__key").alias("key"), (F.col("__c") - 1).alias("start")))})
    hit = F.coalesce(F.col("__run.key") == F.col("__key"), F.lit(False)) & ~F.col("__dead")
    number = F.when(F.col("__side") == 0, F.col("__c") - 1).otherwise(F.col("__run.start"))
    return two.withColumns({"__n": F.when(hit, F.col("__c") - F.col("__run.start")).otherwise(0), "__start": F.when(hit, number)})


def compact(r: PaddedTable, keep: int | None = None) -> PaddedTable:
    """Real rows first, in their order; only the first ``keep`` slots stay. Real rows beyond them raise an error at the client."""
    keep = r.rows if keep is None else keep
    r.engine.step("compact", keep)
    if r.engine.hidden:
        ranked = r.engine.ordered(r.df, [~F.col("__real"), F.col("__pos")], r.rows).withColumn("__pos", F.col("__rank"))
        if keep < r.rows:
            r.engine.needs("compact", keep, ranked.agg(F.sum(F.col("__real").cast("long")).alias("size")))
        out = replace(r, df=ranked.where(F.col("__rank") < keep).select(*r.columns()), rows=min(keep, r.rows))
    else:
        held = r.hold()
        used = held.df.where("__real").agg(F.count("*").alias("size"))
        if keep < r.rows:
            r.engine.needs("compact", keep, used)
        out = slotted(replace(r, rows=min(keep, r.rows)), numbered_real(held).withColumnRenamed("__number", "__slot").drop("__pos"), used)
    if keep > r.rows:
        out = replace(out, df=out.df.unionByName(empty_rows(out, r.rows, keep)), rows=keep)
    return out


#: Fixed value: slots in one bucket of a numbering, at most, so that real rows at the front of a large table are not one task.
BUCKET = 1 << 16


def numbered_real(t: PaddedTable, weight: str | None = None) -> DataFrame:
    """The real rows of a held padded table with their ``__number`` in the order of positions; dummies take no part in the exchange.

    ``weight``: a count column; the number is then the sum of it over the rows before.
    """
    size = min(BUCKET, max(1, -(-t.rows // t.engine.partitions)))
    live = t.df.where("__real").withColumn("__b", F.floor(F.col("__pos") / size))
    before = F.sum("__c").over(Window.orderBy("__b").rowsBetween(Window.unboundedPreceding, -1))  # a row per bucket
    carry = live.groupBy("__b").agg((F.sum(weight) if weight else F.count("*")).alias("__c")).select("__b", F.coalesce(before, F.lit(0)).alias("__before"))
    here = Window.partitionBy("__b").orderBy("__pos")
    inside = F.coalesce(F.sum(weight).over(here.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)) if weight else F.row_number().over(here) - 1
    return live.withColumn("__inside", inside).join(F.broadcast(carry), "__b").withColumn("__number", F.col("__before") + F.col("__inside")).drop("__b", "__inside", "__before")


def slotted(shape: PaddedTable, live: DataFrame, used: DataFrame) -> PaddedTable:
    """Real rows in the slots ``__slot`` from 0 on, of which ``used`` (one row, ``size``) says how many there are, and dummies up to ``shape.rows``."""
    kinds = {f.name: f.dataType for f in live.schema.fields}
    real = live.where(F.col("__slot") < shape.rows).select(*shape.attrs, F.lit(True).alias("__real"), F.col("__slot").cast("long").alias("__pos"), *shape.counts)
    free = shape.engine.spark.range(shape.rows).join(F.broadcast(used.select(F.coalesce("size", F.lit(0)).alias("__used")))).where(F.col("id") >= F.col("__used"))
    dummies = free.select(*(F.lit(None).cast(kinds[a]).alias(a) for a in shape.attrs), F.lit(False).alias("__real"), F.col("id").alias("__pos"), *(F.lit(0).cast("long").alias(c) for c in shape.counts))
    return shape.with_df(real.unionByName(dummies))


def encode(r: PaddedTable, attr: str) -> PaddedTable:
    """Replaces an attribute by its dense rank, which keeps its order and has a fixed width."""
    ranked = r.engine.ordered(r.df, [~F.col("__real"), F.col(attr)], r.rows)
    value = F.when(F.col("__real"), F.struct(F.col(attr).alias("v")))
    one = scan(r.engine, ranked.withColumn("__own", value), r.rows, before={"__past": F.col("__own")})
    new = F.col("__real") & ~F.coalesce(F.col("__past") == F.col("__own"), F.lit(False))
    two = scan(r.engine, one, r.rows, sums={"__c": new.cast("long")})
    df = two.withColumn(attr, F.when(F.col("__real"), F.col("__c") - 1)).withColumn("__pos", F.col("__rank"))
    return r.with_df(df)


def sort(r: PaddedTable, keys: Sequence[str], how: str = "shuffle") -> PaddedTable:
    """Positions in the order of some attributes, dummies last."""
    engine = replace(r.engine, sort=how)
    ranked = engine.ordered(r.df, [~F.col("__real"), *(F.col(k) for k in keys)], r.rows)
    return r.with_df(ranked.withColumn("__pos", F.col("__rank")))
