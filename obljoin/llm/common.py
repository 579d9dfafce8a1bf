"""Helpers that several training-data operators share."""

from __future__ import annotations

import contextlib
import ctypes
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from obljoin.operators import physical
from obljoin.operators.physical import run_settings

#: A group with at least 1/HEAVY_PARTS of all rows is heavy; by counting, there are at most HEAVY_PARTS of them.
HEAVY_PARTS = 256

#: Maps A-Z to a-z and leaves every other byte; safe on UTF-8, whose multi-byte sequences hold no ASCII byte.
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32

#: True for the bytes that separate words: space and the five control blanks.
BLANK = np.zeros(256, dtype=bool)
BLANK[[32, 9, 10, 11, 12, 13]] = True


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


#: Rows in an Arrow batch of a materialised step; with the default of 10,000 a worker would hold tens of MB of text several times.
ARROW_ROWS = "2000"


def saved(df: DataFrame) -> DataFrame:
    """Writes ``df`` to the shared folder and reads it again: cuts the lineage and survives lost executors."""
    with run_settings(df.sparkSession, {"spark.sql.execution.arrow.maxRecordsPerBatch": ARROW_ROWS}):
        return physical.saved(df)


def attach(rows: DataFrame, groups: DataFrame, keys: list[str], size: str) -> DataFrame:
    """Inner join of ``rows`` with one row per key in ``groups``, safe for hot keys.

    ``groups[size]`` is the number of ``rows`` of each key. Keys that hold at least one part in
    HEAVY_PARTS of the rows are at most HEAVY_PARTS many, so these few are broadcast; the other
    keys are small and go through an ordinary shuffle join. Evaluates both inputs twice: pass saved ones.
    """
    total = groups.agg(F.sum(size)).first()[0] or 0
    is_heavy = F.col(size) * HEAVY_PARTS >= F.lit(total)
    heavy = F.broadcast(groups.where(is_heavy))
    rest = rows.join(F.broadcast(groups.where(is_heavy).select(*keys)), keys, "left_anti")
    light = groups.where(~is_heavy)
    return rows.join(heavy, keys).unionByName(rest.join(light, keys))


def content_key(text: str = "text") -> Column:
    return F.xxhash64(F.coalesce(F.col(text).cast("string"), F.lit("")))


def unused(columns: list[str], *names: str) -> list[str]:
    """The names, each with underscores behind it until no column is called so (in any case)."""
    taken, out = {c.lower() for c in columns}, []
    for name in names:
        while name.lower() in taken:
            name += "_"
        taken.add(name.lower())
        out.append(name)
    return out


def keep_rows(docs: DataFrame, judged: DataFrame, kept: Column, text: str = "text", doc_id: str = "doc_id") -> DataFrame:
    """The rows of ``docs`` that ``judged`` (a row each: doc_id, content, ...) marks as ``kept``, with all their columns.

    Rows are found again by id and content; of rows that agree in both, as many stay as are marked. Columns of ``docs`` may have any names.
    """
    key, id_, content, stay_, all_, n = unused(docs.columns, "_key", "_id", "_content", "_stay", "_all", "_n")
    stay = judged.groupBy(F.col("doc_id").alias(id_), F.col("content").alias(content)).agg(F.sum(kept.cast("long")).alias(stay_), F.count("*").alias(all_))
    stay = saved(stay.where(F.col(stay_) > 0))
    marked = docs.withColumn(key, content_key(text))
    joined = marked.join(stay, marked[doc_id].eqNullSafe(stay[id_]) & (marked[key] == stay[content]))
    whole = joined.where(F.col(stay_) == F.col(all_))
    if stay.where(F.col(stay_) < F.col(all_)).head(1):  # rows that repeat an id and a text
        order = Window.partitionBy(id_, content).orderBy(*[docs[c] for c, t in docs.dtypes if "map<" not in t and t != "variant"])
        part = joined.where(F.col(stay_) < F.col(all_)).withColumn(n, F.row_number().over(order)).where(F.col(n) <= F.col(stay_)).drop(n)
        whole = whole.unionByName(part)
    return whole.select(*(f"`{c}`" for c in docs.columns))


def key_bitmap(keys: DataFrame, code: Column, bits: int) -> np.ndarray:
    """A filter of 2**bits flags with that of every ``code`` set; its size does not depend on the data.

    May let other codes through, never misses one, so that an exact step after it stays exact.
    """
    at = F.pmod(code, F.lit(1 << bits)).cast("long")
    parts = (
        keys.select((at / F.lit(32768)).cast("long").alias("part"), (at % 32768).alias("at"))
        .groupBy("part")
        .agg(F.expr("bitmap_construct_agg(at)").alias("flags"))
        .collect()
    )  # at most 2**bits / 32768 rows of 4 KB
    flags = np.zeros(1 << bits, dtype=np.uint8)
    for part, found in parts:
        flags[part * 32768 : (part + 1) * 32768] = np.unpackbits(np.frombuffer(bytes(found), dtype=np.uint8), bitorder="little")
    return np.packbits(flags, bitorder="little")


def in_bitmap(bitmap: np.ndarray, code: np.ndarray) -> np.ndarray:
    at = code & np.int64(bitmap.size * 8 - 1)
    return (bitmap[at >> 3] >> (at & 7).astype(np.uint8)) & 1 == 1


def trim() -> None:
    """Gives memory that this process has freed back to the machine, where the C library can."""
    pa.default_memory_pool().release_unused()
    with contextlib.suppress(OSError, AttributeError):
        ctypes.CDLL(None).malloc_trim(0)


def trimmed(run: Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """The same function, returning freed memory between batches: workers are kept and used again by later stages."""

    def parted(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            yield batch
            del batch
            trim()

    def wrapped(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        yield from run(parted(batches))
        trim()

    return wrapped


def utf8(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """The bytes of a string column and the offsets of its rows; null counts as empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if column.null_count:
        column = pc.fill_null(column, "")
    wide = pa.types.is_large_string(column.type) or pa.types.is_large_binary(column.type)
    _, offsets, data = column.buffers()
    if not len(column):
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    at = np.frombuffer(offsets, dtype=np.int64 if wide else np.int32)[column.offset : column.offset + len(column) + 1].astype(np.int64)
    held = np.frombuffer(data, dtype=np.uint8) if data else np.zeros(0, np.uint8)
    return held[at[0] : at[-1]], at - at[0]


def blocks(offsets: np.ndarray, most: int, rows: int = 1 << 30) -> Iterator[tuple[int, int]]:
    """Row ranges of at most ``most`` bytes and ``rows`` rows each, or of one row that is longer."""
    n, first = len(offsets) - 1, 0
    while first < n:
        last = int(np.searchsorted(offsets, offsets[first] + most, side="right")) - 1
        last = min(max(last, first + 1), first + rows, n)
        yield first, last
        first = last


def numbers(column: pa.Array) -> np.ndarray:
    """An integer column as int64 (null: 0)."""
    return pc.fill_null(column.cast(pa.int64()), 0).to_numpy(zero_copy_only=False)
