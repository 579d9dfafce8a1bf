"""Joins of two padded tables."""

from __future__ import annotations

from collections.abc import Callable, Sequence
from dataclasses import replace

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from obljoin.operators.padded import PaddedTable, is_large, masked, pad_to
from obljoin.operators.primitives import by_key, common, counted, numbered_real, slotted
from obljoin.operators.scan import scan


def _joined_attrs(r: PaddedTable, s: PaddedTable) -> tuple[str, ...]:
    return (*r.attrs, *(a for a in s.attrs if a not in r.attrs))


def nested_loop(r: PaddedTable, s: PaddedTable, predicate: Column | None = None, tiling: str = "flat", tile: int = 1024) -> PaddedTable:
    """One slot per pair of slots, real where both are and the shared attributes agree (and ``predicate`` holds).

    ``recursive`` halves the longer side until a tile has at most ``tile`` pairs; each tile is one group of the plan.
    """
    shared = common(r, s)
    attrs = _joined_attrs(r, s)
    rows = r.rows * s.rows
    r.engine.step("nested_loop", rows, each=True)
    right = s.df.select(*(F.col(a).alias(f"__s_{a}") for a in s.attrs), F.col("__real").alias("__s_real"), F.col("__pos").alias("__s_pos"))
    left = r.df.select(*r.attrs, "__real", "__pos")
    if tiling == "flat":
        pairs = left.crossJoin(right)
    else:
        height, width = max(r.rows, 1), max(s.rows, 1)
        while height * width > tile and max(height, width) > 1:
            height, width = (-(-height // 2), width) if height >= width else (height, -(-width // 2))
        down, across = -(-r.rows // height), -(-s.rows // width)
        left = left.withColumn("__down", F.floor(F.col("__pos") / height).cast("int"))
        right = right.withColumn("__across", F.floor(F.col("__s_pos") / width).cast("int"))
        if r.engine.hidden and not is_large(rows):
            pairs = _tiles_by_position(left, right, down, across)
        else:
            pairs = _tiles_of_blocks(left, right, down, across, max(r.engine.partitions, -(-rows // AT_ONCE)), r.engine.barrier if r.engine.hidden else lambda blocks: blocks)
    real = F.col("__real") & F.col("__s_real")
    for a in shared:
        real = real & F.coalesce(F.col(a) == F.col(f"__s_{a}"), F.lit(False))
    named = pairs.withColumns({a: F.col(f"__s_{a}") for a in s.attrs if a not in r.attrs})
    if predicate is not None:
        real = real & F.coalesce(predicate, F.lit(False))
    df = named.withColumn("__keep", real).withColumn("__at", F.col("__pos") * s.rows + F.col("__s_pos"))
    df = df.withColumns(masked(attrs, F.col("__keep")))
    return PaddedTable(df.select(*attrs, F.col("__keep").alias("__real"), F.col("__at").alias("__pos")), attrs, rows, r.engine)


def _tiles_by_position(left: DataFrame, right: DataFrame, down: int, across: int) -> DataFrame:
    """Every row once per tile of its side; the two sides of a tile meet by its public numbers."""
    spread = lambda n: F.explode(F.sequence(F.lit(0), F.lit(max(n, 1) - 1)))
    tiles = ["__down", "__across"]
    return left.withColumn("__across", spread(across)).join(right.withColumn("__down", spread(down)), tiles).drop(*tiles)


#: Fixed value: pairs that one task of a large loop opens, about, so that what it returns stays small.
AT_ONCE = 1 << 24


def _tiles_of_blocks(left: DataFrame, right: DataFrame, down: int, across: int, tasks: int, held: Callable[[DataFrame], DataFrame]) -> DataFrame:
    """A row per tile, made of a block of either side; its pairs are opened in place, so no row is copied across an exchange.

    Blocks are dealt by their public numbers, for as many tasks as there shall be, whichever side the session would broadcast. ``held`` may store the blocks.
    """

    def blocks(df: DataFrame, by: str, name: str, parts: int) -> DataFrame:
        made = held(df.groupBy(by).agg(F.collect_list(F.struct(*(c for c in df.columns if c != by))).alias(name)))
        return made.repartitionById(parts, F.pmod(by, F.lit(parts)).cast("int")).select(name)

    high = max(1, min(down, tasks))
    wide = max(1, min(across, -(-tasks // high)))
    mine, theirs = blocks(left, "__down", "__mine", high), blocks(right, "__across", "__theirs", wide)
    pairs = mine.crossJoin(theirs.hint("shuffle_replicate_nl")).select(F.explode("__mine").alias("__l"), "__theirs").select("__l", F.explode("__theirs").alias("__o"))
    return pairs.select(*(F.col(f"__l.{c}").alias(c) for c in left.columns if c != "__down"), *(F.col(f"__o.{c}").alias(c) for c in right.columns if c != "__across"))


def bounded_join(r: PaddedTable, s: PaddedTable, tau: int, on: Sequence[str] | None = None) -> PaddedTable:
    """The natural join in exactly ``tau`` slots; a larger result raises an error at the client after the run (in ``reveal``)."""
    keys = common(r, s, on)
    attrs = _joined_attrs(r, s)
    r.engine.step("bounded_join", tau)
    if r.engine.hidden:
        if is_large(tau) and tau >= r.rows * s.rows and set(keys) == set(common(r, s)):
            return _all_pairs(r, s, tau)
        return _expand_and_fetch(r, s, keys, attrs, tau)
    if not keys:
        return _product(r, s, attrs, tau)
    r, s = (t.hold() if t.large else t for t in (r, s))
    left, right = _in_key(r, keys), _in_key(s, keys)
    heads = by_key(left, _totals(s, keys, "__n"), keys, r.large).withColumn("__n", F.when(F.col("__real"), F.coalesce("__n", F.lit(0))).otherwise(0))
    if r.large:
        table = PaddedTable(heads, r.attrs, r.rows, r.engine, ("__at", "__n")).with_df(heads.withColumnRenamed("__number", "__at")).hold()
        used = table.df.where("__real").agg(F.sum("__n").alias("size"))
        placed = numbered_real(table, "__n").withColumn("__end", F.col("__number") + F.col("__n")).withColumn("__number", F.col("__at"))
    else:
        held = r.engine.barrier(heads.select(*r.attrs, "__real", F.col("__pos").alias("__rank"), "__number", "__n"))
        used = held.agg(F.sum("__n").alias("size"))
        placed = scan(r.engine, held, r.rows, sums={"__end": F.col("__n")})
    r.engine.needs("bounded_join", tau, used)
    blocks = lambda n: F.explode(F.sequence(F.lit(0).cast("long"), F.floor((F.col(n) - 1) / MEET)))
    block = F.floor(F.col("__number") / MEET)
    # at most MEET rows of either side meet in one place, however many share a key
    above = placed.where(F.col("__real") & (F.col("__n") > 0)).select(*r.attrs, block.alias("__down"), blocks("__n").alias("__across"), (F.col("__end") - F.col("__n")).alias("__from"))
    below = right.where("__real").join(_totals(r, keys, "__m"), keys).select(*s.attrs, block.alias("__across"), blocks("__m").alias("__down"), "__number")
    pairs = above.join(below, [*keys, "__down", "__across"]).withColumn("__slot", F.col("__from") + F.col("__number"))
    return slotted(PaddedTable(pairs, attrs, tau, r.engine), pairs, used)


#: Rows of one key that meet in one place of a padded join.
MEET = 4096


def _salted(t: PaddedTable) -> DataFrame:
    rows = t.df.where("__real") if t.large else t.df
    return rows.withColumn("__salt", F.pmod("__pos", F.lit(t.engine.partitions)).cast("int"))


def _totals(t: PaddedTable, keys: list[str], name: str) -> DataFrame:
    """How many real rows each key has."""
    return t.df.where("__real").groupBy(*keys).agg(F.count("*").alias(name))


def _in_key(t: PaddedTable, keys: list[str]) -> DataFrame:
    """Adds ``__number``, counting the rows of each key from 0. Keys are parted by position, so a hot one is no single task.

    Of a large table only the real rows are returned.
    """
    rows = _salted(t)
    inside = F.row_number().over(Window.partitionBy("__real", *keys, "__salt").orderBy("__pos")) - 1
    counts = rows.where("__real").groupBy(*keys, "__salt").agg(F.count("*").alias("__c"))  # a row per key and partition at most
    before = F.sum("__c").over(Window.partitionBy(*keys).orderBy("__salt").rowsBetween(Window.unboundedPreceding, -1))
    offsets = counts.select(*keys, "__salt", F.coalesce(before, F.lit(0).cast("long")).alias("__before"))
    return rows.withColumn("__inside", inside).join(offsets, [*keys, "__salt"], "left").withColumn("__number", F.coalesce("__before", F.lit(0)) + F.col("__inside")).drop("__salt", "__inside", "__before")


def _product(r: PaddedTable, s: PaddedTable, attrs: tuple[str, ...], tau: int) -> PaddedTable:
    """No shared attribute: slots find their rows by division, without comparing keys."""
    held = [t.hold() for t in (r, s)]
    sides = [numbered_real(t).select(*t.attrs, "__number") for t in held]
    sizes = [t.df.where("__real").agg(F.count("*").alias("__size")) for t in held]
    n, m = (F.coalesce(F.col(c), F.lit(0)) for c in ("__height", "__width"))
    both = sizes[0].toDF("__height").crossJoin(sizes[1].toDF("__width"))  # one row
    used = both.select((n * m).alias("size"))
    r.engine.needs("bounded_join", tau, used)
    slots = r.engine.spark.range(tau).select(F.col("id").alias("__slot")).join(F.broadcast(both))
    slots = slots.where(F.col("__slot") < n * m).select("__slot", F.expr("__slot div __width").alias("__a"), (F.col("__slot") % F.col("__width")).alias("__b"))
    pairs = slots.join(sides[0].withColumnRenamed("__number", "__a"), "__a").join(sides[1].withColumnRenamed("__number", "__b"), "__b")
    return slotted(PaddedTable(pairs, attrs, tau, r.engine), pairs, used)


def _all_pairs(r: PaddedTable, s: PaddedTable, tau: int) -> PaddedTable:
    """Too many slots to be stored and sorted, but one for every pair: pairs are looped over, by public position alone, and not stored.

    Either side is dealt anew by a keyed permutation first.
    """
    dealt = [replace(t, df=t.engine.numbered(t.engine.permuted(t.df).drop("__tag", "__pos"), "__pos")) for t in (r, s)]
    pairs = nested_loop(*dealt, tiling="recursive", tile=1 << 20)
    r.engine.audit(pairs.df)
    return pad_to(pairs, tau)


def _expand_and_fetch(r: PaddedTable, s: PaddedTable, keys: list[str], attrs: tuple[str, ...], tau: int) -> PaddedTable:
    """Counts partners, gives every row its interval of slots, fills rows down their slots, then fetches partners the same way."""
    engine = r.engine
    both = engine.barrier(counted(r, s, keys))
    heads = engine.barrier(engine.opened(both, "__side", 1).select(F.col("__r").alias("__head"), "__dead", "__n", "__start", F.col("__pos").alias("__rank")))
    live = F.when(F.col("__dead"), F.lit(0)).otherwise(F.col("__n"))
    placed = scan(engine, heads, r.rows, sums={"__end": live}).withColumn("__n", live)
    engine.needs("bounded_join", tau, heads.agg(F.sum(live).alias("size")))
    offset = F.col("__end") - F.col("__n")
    # a row without partners is parked behind all slots, where it can shadow none
    at = F.when(F.col("__n") > 0, offset).otherwise(F.lit(tau))
    row = F.struct(F.col("__head").alias("r"), offset.alias("from"), F.col("__end").alias("to"), F.col("__start").alias("start"))
    above = placed.select(at.alias("__p"), F.lit(0).alias("__side"), F.col("__rank").alias("__at"), row.alias("__row"))
    nothing = F.lit(None).cast(above.schema["__row"].dataType)
    slots = engine.spark.range(tau).select(F.col("id").alias("__p"), F.lit(1).alias("__side"), (F.col("id") + r.rows).alias("__at"), nothing.alias("__row"))
    n = r.rows + tau
    ranked = engine.ordered(above.unionByName(slots), [F.col("__p"), F.col("__side")], n, "__at")
    filled = scan(engine, ranked, n, fills={"__got": F.col("__row")})
    real = F.coalesce((F.col("__p") >= F.col("__got.from")) & (F.col("__p") < F.col("__got.to")), F.lit(False))
    target = F.when(real, F.col("__got.start") + F.col("__p") - F.col("__got.from")).otherwise(F.lit(s.rows))
    expanded = engine.opened(filled.select("__side", "__at", real.alias("__real"), target.alias("__target"), F.when(real, F.col("__got.r")).alias("__r")), "__side", 1)
    partners = engine.opened(both, "__side", 0).select(
        F.when(F.col("__dead"), F.lit(s.rows + 1)).otherwise(F.col("__start")).alias("__target"), F.lit(0).alias("__side"), F.col("__pos").alias("__at"), F.col("__s"), F.lit(False).alias("__real"),
        F.lit(None).cast(expanded.schema["__r"].dataType).alias("__r"),
    )
    # a partner that nothing in r meets has no number and is parked as well
    partners = partners.withColumn("__target", F.coalesce("__target", F.lit(s.rows + 1)).cast("long"))
    asking = expanded.select(F.col("__target").cast("long").alias("__target"), F.lit(1).alias("__side"), (F.col("__pos") + s.rows).alias("__at"), F.lit(None).cast(partners.schema["__s"].dataType).alias("__s"), "__real", "__r")
    n = s.rows + tau
    ranked = engine.ordered(partners.unionByName(asking), [F.col("__target"), F.col("__side")], n, "__at")
    fetched = scan(engine, ranked, n, fills={"__got": F.when(F.col("__side") == 0, F.col("__s"))})
    names = {a: F.col(f"__r.{a}") if a in r.attrs else F.col(f"__got.{a}") for a in attrs}
    flat = fetched.select("__side", "__at", "__real", *(F.when(F.col("__real"), c).alias(a) for a, c in names.items()))
    out = engine.opened(flat, "__side", 1)
    return PaddedTable(out.select(*attrs, "__real", "__pos"), attrs, tau, engine).hold()


