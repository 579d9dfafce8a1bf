"""Streams in epochs of a public number of rows.

Each micro-batch is padded to a fixed size and joined with static relations; rows beyond the size wait in a queue of
files, padded to whole epochs, for the next epoch; late rows become dummies.
"""

from __future__ import annotations

from collections.abc import Callable, Sequence

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery
from pyspark.sql.types import BooleanType, StructType

from obljoin.operators.padded import PaddedTable, masked
from obljoin.operators.physical import Engine, saved, shared_dir


def padded_epoch(engine: Engine, batch: DataFrame, attrs: Sequence[str], rows: int, late: Column | None = None) -> tuple[PaddedTable, DataFrame]:
    """The first ``rows`` rows as a padded table, and what is left, in whole epochs of attributes and ``__real``.

    Only a whole number of epochs is written. A null attribute or a late row makes a dummy; a column ``__real`` of the batch counts.
    """
    real = F.col("__real") if "__real" in batch.columns else F.lit(True)
    if late is not None:
        real = real & ~F.coalesce(late, F.lit(False))
    for a in attrs:
        real = real & F.col(a).isNotNull()
    marked = batch.withColumn("__real", real).select(*attrs, "__real")
    marked = marked.withColumns(masked(attrs, F.col("__real")))
    found = marked.count()
    total = max(1, -(-found // rows)) * rows
    kinds = {f.name: f.dataType for f in marked.schema.fields}
    filler = engine.spark.range(total - found).select(*(F.lit(None).cast(kinds[a]).alias(a) for a in attrs), F.lit(False).alias("__real"))
    held = engine.numbered(marked.unionByName(filler), "__pos", audited=False)
    table = PaddedTable(held.where(F.col("__pos") < rows).select(*attrs, "__real", "__pos"), tuple(attrs), rows, engine)
    return table.hold(), held.where(F.col("__pos") >= rows).select(*attrs, "__real")


class PaddedEpochs:
    """A ``foreachBatch`` function that keeps the rows which did not fit, and passes every epoch as a padded table.

    What waits after an epoch is written under its number in the folder ``queue`` (by default in the session's shared folder). An epoch
    that is repeated, by this driver or by another one after a restart, reads the queue of the epoch before it again, so no row is lost or doubled.
    """

    def __init__(self, engine: Engine, attrs: Sequence[str], rows: int, each: Callable[[PaddedTable, int], None], late: Column | None = None, queue: str | None = None) -> None:
        self.engine, self.attrs, self.rows, self.each, self.late = engine, tuple(attrs), rows, each, late
        self.folder = queue or f"{shared_dir(engine.spark)}/epochs"
        self.schema: StructType | None = None
        self.last = -1

    def waiting(self, epoch: int) -> DataFrame | None:
        """The rows that wait after an epoch."""
        spark = self.engine.spark
        path = f"{self.folder}/{epoch}"
        target = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(f"{path}/_SUCCESS")
        if not target.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).exists(target):
            return None
        return (spark.read.schema(self.schema) if self.schema else spark.read).parquet(path).where("__real")

    def __call__(self, batch: DataFrame, epoch: int) -> None:
        batch = batch.select(*self.attrs).withColumn("__real", F.lit(True)) if self.late is None else batch.withColumn("__real", ~F.coalesce(self.late, F.lit(False))).select(*self.attrs, "__real")
        self.schema = StructType([*(batch.schema[a] for a in self.attrs)]).add("__real", BooleanType())
        before = self.waiting(epoch - 1)
        table, rest = padded_epoch(self.engine, batch if before is None else before.unionByName(batch), self.attrs, self.rows)
        rest.write.mode("overwrite").parquet(f"{self.folder}/{epoch}")
        self.last = epoch
        self.each(table, epoch)

    def drain(self, spark: SparkSession) -> None:
        """Passes what is still waiting, one epoch at a time; the queue of the last epoch is empty afterwards."""
        while (left := self.waiting(self.last)) is not None and left.head(1):
            table, rest = padded_epoch(self.engine, left, self.attrs, self.rows)
            saved(rest).write.mode("overwrite").parquet(f"{self.folder}/{self.last}")
            self.each(table, -1)


def run_epochs(stream: DataFrame, handler: PaddedEpochs, checkpoint: str) -> StreamingQuery:
    return stream.writeStream.foreachBatch(handler).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def windowed_counts(stream: DataFrame, time: str, keys: Sequence[str], length: str, slide: str | None = None, delay: str = "10 minutes") -> DataFrame:
    """Counts per tumbling or sliding window with a watermark."""
    at = F.window(time, length, slide) if slide else F.window(time, length)
    held = stream.withWatermark(time, delay) if stream.isStreaming else stream
    return held.groupBy(at.alias("w"), *keys).agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), *keys, "n")


def session_counts(stream: DataFrame, time: str, key: str, gap: str, delay: str = "10 minutes") -> DataFrame:
    """Rows per session: a gap of silence ends it."""
    held = stream.withWatermark(time, delay) if stream.isStreaming else stream
    return held.groupBy(F.session_window(time, gap).alias("w"), key).agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), key, "n")
