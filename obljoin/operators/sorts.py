"""Sorting methods. Each adds ``__rank``; ties are broken by a keyed random tag."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from obljoin.operators.physical import Engine


def shuffle_sort(engine: Engine, df: DataFrame, keys: list[Column], n: int, position: str) -> DataFrame:
    """A keyed permutation, then one range exchange over a strict total order."""
    if engine.hidden:
        df = engine.barrier(engine.permuted(df, position))
    else:
        df = df.withColumn("__tag", engine.tag(F.col(position)))
    order = [*keys, F.col("__tag")]
    ranged = df.repartitionByRange(engine.partitions, *order).sortWithinPartitions(*order)
    return engine.numbered(ranged).drop("__tag")


def plain_sort(engine: Engine, df: DataFrame, keys: list[Column], n: int, position: str) -> DataFrame:
    """Catalyst's range sort: the exchange shows how keys are distributed."""
    order = [*keys, F.col(position)]
    return engine.numbered(df.repartitionByRange(engine.partitions, *order).sortWithinPartitions(*order))


def _filled(engine: Engine, df: DataFrame, keys: list[Column], total: int, n: int, position: str) -> DataFrame:
    """Keys as ``__k*``, and filler rows behind all others up to ``total``."""
    named = df.withColumns({f"__k{i}": k for i, k in enumerate(_values(keys))} | {"__filler": F.lit(False), "__slot": F.col(position)})
    filler = engine.spark.range(n, total).select(*(F.lit(None).cast(f.dataType).alias(f.name) if f.name not in ("__filler", "__slot") else (F.lit(True) if f.name == "__filler" else F.col("id")).alias(f.name) for f in named.schema.fields))
    return named.unionByName(filler)


def _values(keys: list[Column]) -> list[Column]:
    return [k if isinstance(k, Column) else F.col(k) for k in keys]


def _order(width: int) -> list[Column]:
    return [F.col("__filler"), *(F.col(f"__k{i}") for i in range(width)), F.col("__tag")]


def bitonic_sort(engine: Engine, df: DataFrame, keys: list[Column], n: int, position: str) -> DataFrame:
    """A bitonic network over blocks: a comparator merges two blocks and splits them at the middle."""
    blocks = 1
    while blocks * 2 <= max(2, engine.partitions):
        blocks *= 2
    size = max(1, -(-n // blocks))
    held = _filled(engine, df, keys, blocks * size, n, position).withColumn("__tag", engine.tag(F.col("__slot")))
    order = _order(len(keys))

    def place(rows: DataFrame, group: Column, first: Column, second: Column, groups: int) -> DataFrame:
        """Sorts each group; its lower half goes to block ``first``, the upper to ``second``."""
        rows = rows.withColumns({"__first": first, "__second": second}).withColumn("__group", group.cast("int")).repartitionById(groups, F.col("__group"))
        at = F.row_number().over(Window.partitionBy("__group").orderBy(*order)) - 1
        return rows.withColumn("__at", at).withColumn("__block", F.when(F.col("__at") < size, F.col("__first")).otherwise(F.col("__second")))

    block = F.col("__block")
    rows = held.withColumn("__block", F.floor(F.col("__slot") / size).cast("long"))
    rows = place(rows, block, block, block, blocks)
    span = 2
    while span <= blocks:
        step = span // 2
        while step:
            partner = block.bitwiseXOR(F.lit(step))
            low, high = F.least(block, partner), F.greatest(block, partner)
            rising = block.bitwiseAND(F.lit(span)) == 0
            # pairs are numbered 0 to blocks/2 - 1 by dropping the bit that tells the two apart
            pair = F.floor(low / (2 * step)) * step + low % step
            rows = place(rows, pair, F.when(rising, low).otherwise(high), F.when(rising, high).otherwise(low), max(1, blocks // 2))
            step //= 2
        rows = engine.barrier(rows)
        span *= 2
    rank = F.col("__block") * size + F.col("__at") % size
    # fillers are last, so this cut is at a public place
    return rows.withColumn("__rank", rank.cast("long")).where(F.col("__rank") < n).drop(*_helpers(len(keys)))


def _helpers(width: int) -> list[str]:
    return ["__filler", "__slot", "__tag", "__block", "__group", "__first", "__second", "__at", "__col", *(f"__k{i}" for i in range(width))]


def column_shape(n: int, columns: int) -> tuple[int, int]:
    """Rows and columns of a column sort: rows at least 2(columns-1)**2 and a multiple of both columns and 2."""
    while columns > 1 and -(-n // columns) < 2 * (columns - 1) ** 2:
        columns -= 1
    unit = 2 * columns
    return max(unit, -(-(-(-n // columns)) // unit) * unit), columns


def column_sort(engine: Engine, df: DataFrame, keys: list[Column], n: int, position: str) -> DataFrame:
    """Four sorts of columns with fixed permutations between them; all blocks are equally large."""
    height, width = column_shape(max(n, 1), engine.partitions)
    held = _filled(engine, df, keys, height * width, n, position).withColumn("__tag", engine.tag(F.col("__slot")))
    order = _order(len(keys))

    def columns(rows: DataFrame, column: Column, count: int, lead: int = 0) -> DataFrame:
        rows = rows.withColumn("__col", column.cast("int")).repartitionById(count, F.col("__col"))
        at = F.row_number().over(Window.partitionBy("__col").orderBy(*order)) - 1
        return rows.withColumn("__at", at + F.when(F.col("__col") == 0, lead).otherwise(0) if lead else at)

    down = F.col("__col") * height + F.col("__at")
    across = F.col("__at") * width + F.col("__col")
    rows = columns(held, F.floor(F.col("__slot") / height), width)
    rows = columns(rows, down % width, width)  # read down the columns, lay out along the rows
    rows = columns(engine.barrier(rows), F.floor(across / height), width)  # and back
    half = height // 2
    rows = columns(rows, F.floor((down + half) / height), width + 1, half)
    rows = rows.withColumn("__rank", (down - half).cast("long"))
    return engine.barrier(rows).where(F.col("__rank") < n).drop(*_helpers(len(keys)))


SORTS = {"shuffle": shuffle_sort, "plain": plain_sort, "bitonic": bitonic_sort, "columns": column_sort}
