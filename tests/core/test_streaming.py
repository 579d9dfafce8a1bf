from pyspark.sql import functions as F

from obljoin.operators.padded import load, reveal
from obljoin.operators.physical import Engine
from obljoin.operators.twoway import bounded_join
from obljoin.streaming.epochs import PaddedEpochs, run_epochs, windowed_counts


def test_epochs_have_one_size_and_lose_nothing(spark, tmp_path):
    rows = [(i, i % 4) for i in range(25)]
    spark.createDataFrame(rows, "id long, k long").repartition(3).write.parquet(str(tmp_path / "in"))
    engine = Engine(spark, "padded", 2)
    static = load(engine, spark.createDataFrame([(0, "a"), (1, "b"), (2, "c")], "k long, name string"), ["k", "name"])
    sizes, out = [], []

    def each(table, epoch):
        sizes.append(table.df.count())
        out.extend(tuple(r) for r in reveal(bounded_join(table, static, table.rows)).select("id", "name").collect())

    handler = PaddedEpochs(engine, ["id", "k"], 10, each, queue=str(tmp_path / "queue"))
    stream = spark.readStream.schema("id long, k long").option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in"))
    run_epochs(stream, handler, str(tmp_path / "checkpoint")).awaitTermination()
    handler.drain(spark)
    assert set(sizes) == {10}
    names = {0: "a", 1: "b", 2: "c"}
    assert sorted(out) == sorted((i, names[k]) for i, k in rows if k in names)


def test_a_restart_loses_and_doubles_nothing(spark, tmp_path):
    engine, seen = Engine(spark, "padded", 2), []
    each = lambda table, epoch: seen.append(sorted(r.id for r in reveal(table).collect()))
    batches = [spark.createDataFrame([(i, i) for i in range(a, b)], "id long, k long") for a, b in ((0, 9), (9, 16), (16, 17))]
    queue = str(tmp_path / "queue")
    first = PaddedEpochs(engine, ["id", "k"], 5, each, queue=queue)
    first(batches[0], 0)
    first(batches[1], 1)
    again = PaddedEpochs(engine, ["id", "k"], 5, each, queue=queue)  # a new driver repeats epoch 1
    again(batches[1], 1)
    again(batches[2], 2)
    again.drain(spark)
    assert seen[1] == seen.pop(2)
    assert sorted(sum(seen, [])) == list(range(17)) and all(len(s) <= 5 for s in seen)
    assert spark.read.parquet(f"{queue}/1").count() % 5 == 0


def test_watermarked_windows(spark, tmp_path):
    events = spark.range(120).select((F.timestamp_seconds(F.col("id") * 60)).alias("ts"), (F.col("id") % 2).alias("k"))
    events.write.parquet(str(tmp_path / "in"))
    stream = spark.readStream.schema(events.schema).parquet(str(tmp_path / "in"))
    query = windowed_counts(stream, "ts", ["k"], "30 minutes").writeStream.format("memory").queryName("counts").outputMode("complete").start()
    query.processAllAvailable()
    query.stop()
    assert sorted(r.n for r in spark.table("counts").collect()) == [15] * 8
