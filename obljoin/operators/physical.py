"""What may cross a node boundary: barriers, keyed permutations, range sorts, global ranks.

Hidden plans move rows only by public positions, by keyed pseudo-random numbers, or by range after a keyed permutation. Sizes
of all materialised tables are public.
"""

from __future__ import annotations

import secrets
import tempfile
import uuid
from collections.abc import Iterator
from contextlib import contextmanager
from dataclasses import dataclass, field
from functools import reduce
from itertools import count

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

#: Run-time settings that hidden plans need: no plan may adapt to data.
HIDDEN_SETTINGS = {
    "spark.sql.adaptive.enabled": "false",
    "spark.sql.cbo.enabled": "false",
    "spark.sql.autoBroadcastJoinThreshold": "-1",
}
#: A step that is written needs its shuffles no longer: their files go as soon as it is done, not when the driver collects garbage.
STEP_SETTINGS = {"spark.sql.classic.shuffleDependency.fileCleanup.enabled": "true"}
#: Slots that a step may work on one by one, and slots of a step in padded mode, which works on real rows alone and only numbers the rest.
MOST_WORKED, MOST_NUMBERED = 1 << 40, 1 << 62
LOCAL = (1 << 33) - 1  # bits of monotonically_increasing_id below the partition


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share; a temporary one only where the session names none and runs on this machine alone."""
    context = spark.sparkContext
    found = context._jsc.sc().getCheckpointDir()
    if found.isDefined():
        return found.get()
    configured = context.getConf().get("spark.checkpoint.dir")
    if not configured and context.master.partition("[")[0] != "local":
        raise ValueError("spark.checkpoint.dir must name a folder that the driver and all executors share")
    context.setCheckpointDir(configured or tempfile.mkdtemp(prefix="checkpoints-"))
    return context._jsc.sc().getCheckpointDir().get()


def saved(df: DataFrame) -> DataFrame:
    """Writes ``df`` to the shared folder and reads it again: cuts the lineage and survives lost executors.

    The files go when the session ends.
    """
    return _written(df)[1]


def _written(df: DataFrame) -> tuple[str, DataFrame]:
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/stage-{uuid.uuid4().hex}"
    with run_settings(spark, STEP_SETTINGS):
        df.write.parquet(path)
    target, system = _folder(spark, path)
    system.deleteOnExit(target)
    return path, spark.read.schema(df.schema).parquet(path)


def _folder(spark: SparkSession, path: str) -> tuple:
    target = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    return target, target.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())


@contextmanager
def run_settings(spark: SparkSession, settings: dict[str, str]) -> Iterator[None]:
    before = {k: spark.conf.get(k, None) for k in settings}
    try:
        for k, v in settings.items():
            spark.conf.set(k, v)
        yield
    finally:
        for k, v in before.items():
            spark.conf.unset(k) if v is None else spark.conf.set(k, v)


@dataclass
class Engine:
    """How padded tables are computed.

    ``padded``: materialised sizes are public, Catalyst may exchange rows by key. ``hidden``: every exchange is independent of the data, and
    each step's plan is audited before it is written. ``secret`` keys the permutations; it is drawn anew unless given.
    """

    spark: SparkSession
    mode: str = "padded"
    partitions: int | None = None
    secret: str = field(default_factory=lambda: secrets.token_hex(32), repr=False)
    sort: str = "shuffle"
    #: Refuse to run a step with more slots than this; the default goes by how the step works on them.
    most_rows: int | None = None
    steps: list[tuple[str, int]] = field(default_factory=list)
    #: (step, slots, one-row frame with the real size ``size``): secret, for the client's check after the run and for reports.
    sizes: list[tuple[str, int, DataFrame]] = field(default_factory=list, repr=False)
    _fresh: Iterator[int] = field(default_factory=count)
    #: Folders of the steps that are still on disk.
    _files: list[str] = field(default_factory=list, repr=False)

    def __post_init__(self) -> None:
        if self.mode not in ("padded", "hidden"):
            raise ValueError(f"no mode {self.mode}")
        if not self.secret:
            raise ValueError("an empty secret keys nothing")
        self.partitions = self.partitions or int(self.spark.conf.get("spark.sql.shuffle.partitions"))

    @property
    def hidden(self) -> bool:
        return self.mode == "hidden"

    def step(self, name: str, rows: int, each: bool = False) -> None:
        """Records a public size, and refuses one that is too large before anything runs. ``each``: in padded mode too, the step works on every slot."""
        most = self.most_rows
        if most is None:
            most = MOST_WORKED if self.hidden or each else MOST_NUMBERED
        if rows > most:
            raise ValueError(f"{name} would make {rows} slots, more than {most}")
        self.steps.append((name, rows))

    def needs(self, name: str, rows: int, size: DataFrame) -> None:
        """Notes the secret real size (one row, ``size``) of a step with so many slots; nothing runs until the client asks."""
        self.sizes.append((name, rows, size))

    def settle(self) -> None:
        """The client's check after the run: raises if a declared size proved too small."""
        found = self.real_sizes()
        self.sizes.clear()
        for name, rows, size in found:
            if size > rows:
                raise OverflowError(f"{name}: the result has more than {rows} rows")

    def real_sizes(self) -> list[tuple[str, int, int]]:
        """(step, slots, real rows) of the noted steps, by one job. Secret: for the client."""
        if not self.sizes:
            return []
        rows = {r.i: r["size"] for r in self._numbered_sizes(self.sizes).collect()}  # a row per step
        return [(name, slots, rows.get(i, 0)) for i, (name, slots, _) in enumerate(self.sizes)]

    @staticmethod
    def _numbered_sizes(sizes: list[tuple[str, int, DataFrame]]) -> DataFrame:
        one = lambda i, size: size.select(F.lit(i).alias("i"), F.coalesce("size", F.lit(0)).cast("long").alias("size"))
        return reduce(DataFrame.unionByName, (one(i, size) for i, (_, _, size) in enumerate(sizes)))

    def barrier(self, df: DataFrame, audited: bool = True) -> DataFrame:
        """Materialises a step. In hidden mode its plan must pass the audit first; only the owner's own loading is exempt."""
        with run_settings(self.spark, HIDDEN_SETTINGS if self.hidden else {}):
            if self.hidden and audited:
                self.audit(df)
            path, held = _written(df)
        self._files.append(path)
        return held

    def mark(self) -> tuple[int, int]:
        """Where the steps and noted sizes stand, for ``release``."""
        return len(self._files), len(self.sizes)

    def release(self, mark: tuple[int, int], *kept: DataFrame) -> None:
        """In padded mode, deletes what steps have written since the mark, but for what the kept frames read.

        Sizes noted since then are counted first. Other frames made since then can be read no longer.
        """
        if self.hidden:
            return
        at, noted = mark
        if fresh := self.sizes[noted:]:
            path, found = _written(self._numbered_sizes(fresh))
            self._files.append(path)
            self.sizes[noted:] = [(name, rows, found.where(F.col("i") == i).select("size")) for i, (name, rows, _) in enumerate(fresh)]
            kept = (*kept, found)
        used = {f.split("/")[-2] for df in kept for f in df.inputFiles()}
        done = [p for p in self._files[at:] if p.split("/")[-1] not in used]
        for path in done:
            target, system = _folder(self.spark, path)
            system.delete(target, True)
        self._files[at:] = [p for p in self._files[at:] if p not in done]

    def audit(self, df: DataFrame) -> None:
        """Raises unless the plan, under the settings of hidden plans, is independent of the data."""
        from obljoin.measures.audit import check  # the measures are built on this module

        with run_settings(self.spark, HIDDEN_SETTINGS):
            if found := check(df):
                raise RuntimeError("a hidden step depends on data: " + "; ".join(found))

    def tag(self, position: Column) -> Column:
        """A keyed pseudo-random number of a position: the same again if a task is repeated."""
        key = f"{self.secret}:{next(self._fresh)}:"
        return F.conv(F.substring(F.sha2(F.concat(F.lit(key), position.cast("string")), 256), 1, 15), 16, 10).cast("long")

    def numbered(self, df: DataFrame, rank: str = "__rank", audited: bool = True) -> DataFrame:
        """Adds the global rank in partition order, without an exchange of the rows."""
        held = self.barrier(df.withColumn("__id", F.monotonically_increasing_id()), audited)
        held = held.withColumn("__task", F.shiftright("__id", 33))
        # one row per partition
        sizes = held.groupBy("__task").agg(F.count("*").alias("__n"))
        before = F.sum("__n").over(Window.orderBy("__task").rowsBetween(Window.unboundedPreceding, -1))
        offsets = F.broadcast(sizes.select("__task", F.coalesce(before, F.lit(0)).alias("__offset")))
        ranked = held.join(offsets, "__task")
        return ranked.withColumn(rank, F.col("__offset") + F.col("__id").bitwiseAND(LOCAL)).drop("__task", "__offset", "__id")

    def permuted(self, df: DataFrame, position: str = "__pos") -> DataFrame:
        """Rows in a keyed random order."""
        tagged = df.withColumn("__tag", self.tag(F.col(position)))
        dealt = tagged.repartitionById(self.partitions, F.pmod("__tag", F.lit(self.partitions)).cast("int"))
        return dealt.sortWithinPartitions("__tag")

    def opened(self, df: DataFrame, side: str, value: int, position: str = "__at") -> DataFrame:
        """Drops helper rows whose number is public: one keyed permutation, then a plain filter. New ``__pos``."""
        if self.hidden:
            df = self.barrier(self.permuted(df, position)).drop("__tag")
        return self.numbered(df.where(F.col(side) == value), "__pos")

    def ordered(self, df: DataFrame, keys: list[Column], n: int, position: str = "__pos") -> DataFrame:
        """Adds ``__rank`` in the order of the keys (ties at random); by the engine's sorting method."""
        from obljoin.operators.sorts import SORTS  # the sorts are built on this module

        self.step("sort", n, each=True)
        return SORTS[self.sort](self, df, keys, n, position)
