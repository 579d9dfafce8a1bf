"""Tables whose number of rows is public: real rows and dummies that look alike."""

from __future__ import annotations

from dataclasses import dataclass, field, replace

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from obljoin.operators.physical import Engine


#: In padded mode a table of more slots is stored in blocks, of so many slots, but so many blocks at most. A hidden join of more
#: slots is not stored if these have room for all pairs.
LARGE, BLOCK, MOST_BLOCKS = 1 << 24, 1 << 10, 1 << 20


def is_large(rows: int) -> bool:
    return rows > LARGE


@dataclass(frozen=True)
class PaddedTable:
    """``df`` has the attributes, ``__real``, ``__pos`` (a permutation of 0..rows-1) and count columns.

    Dummies have null attributes. Real rows differ in their attributes. Where a declared size proves too small, ``reveal`` raises.
    """

    df: DataFrame
    attrs: tuple[str, ...]
    rows: int
    engine: Engine
    counts: tuple[str, ...] = ()
    #: What ``hold`` wrote; a table whose ``df`` is still this one is not written again.
    stored: DataFrame | None = field(default=None, compare=False, repr=False)

    def columns(self) -> list[str]:
        return [*self.attrs, "__real", "__pos", *self.counts]

    def with_df(self, df: DataFrame, **changes) -> PaddedTable:
        out = replace(self, df=df, **changes)
        return replace(out, df=out.df.select(*out.columns()))

    def hold(self) -> PaddedTable:
        """Materialises the table, so that later steps do not compute it again."""
        if self.stored is self.df:
            return self
        done = self._in_blocks() if self.large else self.engine.barrier(self.df.select(*self.columns()))
        return replace(self, df=done, stored=done)

    def instead(self, mark: tuple[int, int], *kept: PaddedTable) -> PaddedTable:
        """In padded mode, materialises the table in place of the steps since the mark, which go, but for what the kept tables read."""
        if self.engine.hidden:
            return self
        held = self.hold()
        self.engine.release(mark, held.df, *(t.df for t in kept))
        return held

    @property
    def large(self) -> bool:
        """Whether the table is stored in blocks, and steps keep its dummies out of their exchanges."""
        return not self.engine.hidden and is_large(self.rows)

    def _in_blocks(self) -> DataFrame:
        """Stores one row per block of slots, whose number is public, with the block's real rows; its dummies are the slots that these leave.

        Slots are dealt to blocks in turn, so real rows at the front of a table spread over all of them.
        """
        n = min(MOST_BLOCKS, -(-self.rows // BLOCK))
        held = self.df.where("__real").select(F.pmod("__pos", F.lit(n)).alias("__block"), F.struct(*self.attrs, "__pos", *self.counts).alias("__row"))
        every = self.engine.spark.range(n).select(F.col("id").alias("__block"), F.lit(None).cast(held.schema["__row"].dataType).alias("__row"))
        blocks = self.engine.barrier(held.unionByName(every).groupBy("__block").agg(F.collect_list("__row").alias("__rows")))
        real = blocks.select(F.explode("__rows").alias("r")).select("r.*").withColumn("__real", F.lit(True))
        slots = F.array_except(F.sequence("__block", F.lit(self.rows - 1).cast("long"), F.lit(n).cast("long")), F.transform("__rows", lambda r: r["__pos"]))
        kinds = {f.name: f.dataType for f in real.schema.fields}
        dummies = blocks.select(F.explode(slots).alias("__pos")).select(
            "__pos", *(F.lit(None).cast(kinds[a]).alias(a) for a in self.attrs), *(F.lit(0).cast(kinds[c]).alias(c) for c in self.counts), F.lit(False).alias("__real")
        )
        return real.select(*self.columns()).unionByName(dummies)


def masked(attrs: tuple[str, ...] | list[str], real: Column) -> dict[str, Column]:
    """Attributes that are null unless the row is real."""
    return {a: F.when(real, F.col(a)) for a in attrs}


def load(engine: Engine, df: DataFrame, attrs: tuple[str, ...] | list[str], rows: int | None = None) -> PaddedTable:
    """A set of tuples as a padded table. ``rows`` is its public size; the default declares the number found.

    The owner's step: duplicates go by key, and only the padded table is written. A row with a null attribute cannot match and
    becomes a dummy. More rows than declared raise an error.
    """
    attrs = tuple(attrs)
    mark = engine.mark()
    complete = F.lit(True)
    for a in attrs:
        complete = complete & F.col(a).isNotNull()
    distinct = df.select(*attrs).distinct().withColumn("__real", complete)
    distinct = distinct.withColumns(masked(attrs, F.col("__real")))
    if rows is not None:
        found = distinct.count()
        if found > rows:
            raise ValueError(f"{found} rows do not fit in {rows}")
        kinds = {f.name: f.dataType for f in distinct.schema.fields}
        filler = engine.spark.range(rows - found).select(*(F.lit(None).cast(kinds[a]).alias(a) for a in attrs), F.lit(False).alias("__real"))
        distinct = distinct.unionByName(filler)
    held = engine.numbered(distinct, "__pos", audited=False)
    rows = held.count() if rows is None else rows
    engine.step("load", rows, each=True)
    held = engine.barrier(held)
    engine.release(mark, held)
    return PaddedTable(held, attrs, rows, engine, stored=held)


def empty_rows(table: PaddedTable, start: int, end: int) -> DataFrame:
    kinds = {f.name: f.dataType for f in table.df.schema.fields}
    return table.engine.spark.range(start, end).select(
        *(F.lit(None).cast(kinds[a]).alias(a) for a in table.attrs), F.lit(False).alias("__real"), F.col("id").alias("__pos"), *(F.lit(0).cast("long").alias(c) for c in table.counts)
    )


def pad_to(table: PaddedTable, rows: int) -> PaddedTable:
    """Adds dummies up to a public size."""
    if rows <= table.rows:
        return table
    return replace(table, df=table.df.select(*table.columns()).unionByName(empty_rows(table, table.rows, rows)), rows=rows)


def concat(*tables: PaddedTable) -> PaddedTable:
    """All rows of all tables; positions move by public offsets."""
    first = tables[0]
    if any(set(t.attrs) != set(first.attrs) for t in tables):
        raise ValueError("attributes differ")
    at, parts = 0, []
    for t in tables:
        parts.append(t.df.select(*first.attrs, "__real", (F.col("__pos") + at).alias("__pos")))
        at += t.rows
    df = parts[0]
    for p in parts[1:]:
        df = df.unionByName(p)
    first.engine.step("concat", at)
    return PaddedTable(df, first.attrs, at, first.engine)


def where(table: PaddedTable, condition: Column) -> PaddedTable:
    """Rows that fail become dummies; the size does not change. A null condition counts as false."""
    real = F.col("__real") & F.coalesce(condition, F.lit(False))
    df = table.df.withColumn("__keep", real)
    return table.with_df(df.withColumns(masked(table.attrs, F.col("__keep")) | {"__real": F.col("__keep")}))


def rename(table: PaddedTable, names: dict[str, str]) -> PaddedTable:
    return replace(table, df=table.df.withColumnsRenamed(names), attrs=tuple(names.get(a, a) for a in table.attrs))


def reveal(table: PaddedTable) -> DataFrame:
    """The real rows, for the trusted client only, who learns here whether a declared size was too small."""
    table.engine.settle()
    return table.df.where("__real").select(*table.attrs)


def deliver(table: PaddedTable, path: str, files: int | None = None) -> None:
    """Writes all rows, dummies too, to files of equally many rows."""
    n = files or table.engine.partitions
    size = max(1, -(-table.rows // n))
    table.df.repartitionById(n, F.floor(F.col("__pos") / size).cast("int")).write.parquet(path)


def real_count(table: PaddedTable) -> int:
    """Secret: how many rows are real. For tests and reports only."""
    return table.df.where("__real").count()
