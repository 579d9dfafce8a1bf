"""Spark's own event log: hidden steps look alike on two inputs of one size, plain joins do not."""

import subprocess
import sys
from collections import defaultdict
from pathlib import Path

import pytest

from obljoin.measures.leakage import spark_profile

SCRIPT = """
import sys
sys.path.insert(0, {root!r})
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
mode, heavy, log = sys.argv[1], sys.argv[2] == "heavy", sys.argv[3]
spark = (SparkSession.builder.master("local[2]").config("spark.ui.enabled", "false").config("spark.sql.shuffle.partitions", "3")
         .config("spark.eventLog.enabled", "true").config("spark.eventLog.dir", "file://" + log).config("spark.eventLog.rolling.enabled", "false")
         .config("spark.eventLog.compress", "false").config("spark.sql.adaptive.enabled", "false").config("spark.sql.autoBroadcastJoinThreshold", "-1").getOrCreate())
spark.sparkContext.setLogLevel("ERROR")
n = 600 if mode in ("plain", "semijoin") else 20
ids = spark.range(0, n, 1, 3)
key = F.when(F.col("id") >= (0 if heavy else n), 1).otherwise(F.col("id")).cast("long")
rows = lambda *names: ids.select(key.alias(names[0]), F.col("id").alias(names[1]))
if mode == "plain":
    rows("k", "v").join(rows("k", "w"), "k").write.format("noop").mode("overwrite").save()
else:
    from obljoin.operators.padded import PaddedTable
    from obljoin.operators.physical import Engine
    from obljoin.operators.primitives import semijoin
    from obljoin.operators.triangle import triangle_choice, triangle_delay
    from obljoin.operators.twoway import bounded_join
    from obljoin.operators.wcoj import hidden_wcoj
    from obljoin.plans.hypergraph import parse_atoms
    engine = Engine(spark, "hidden", 3)
    table = lambda *names: PaddedTable(rows(*names).withColumn("__real", F.lit(True)).withColumn("__pos", F.col(names[1])), names, n, engine).hold()
    three = {{"R1": table("b", "c"), "R2": table("a", "c"), "R3": table("a", "b")}}
    run = {{
        "semijoin": lambda: semijoin(table("k", "v"), table("k", "w")),
        "bounded": lambda: bounded_join(table("k", "v"), table("k", "w"), n * n),
        "choice": lambda: triangle_choice(*three.values()),
        "delay": lambda: triangle_delay(*three.values()),
        "wcoj": lambda: hidden_wcoj(parse_atoms("R1(b, c), R2(a, c), R3(a, b)"), three),
    }}
    run[mode]().hold()
spark.stop()
"""


def profile(tmp_path, mode, kind):
    log = tmp_path / f"{mode}-{kind}"
    log.mkdir()
    root = str(Path(__file__).resolve().parents[2])
    subprocess.run([sys.executable, "-c", SCRIPT.format(root=root), mode, kind, str(log)], check=True, timeout=400, capture_output=True)
    stages = defaultdict(list)
    for stage, _, read, wrote, _ in spark_profile(str(log)):
        stages[stage].append((read, wrote))
    return stages


def totals(stages):
    return {k: (len(v), sum(x for x, _ in v), sum(y for _, y in v)) for k, v in stages.items()}


def test_hidden_step_looks_alike(tmp_path):
    even, heavy = profile(tmp_path, "semijoin", "even"), profile(tmp_path, "semijoin", "heavy")
    assert totals(even) == totals(heavy)
    # rows per task: equal blocks, or the random law of a permutation; never the one heavy key
    assert max(max(x for x, _ in v) for v in heavy.values()) <= 1.25 * max(max(x for x, _ in v) for v in even.values())


@pytest.mark.parametrize("method", ["bounded", "choice", "delay", "wcoj"])
def test_hidden_joins_look_alike(tmp_path, method):
    """Stages, tasks, and rows read and written by each stage are equal for different keys and for one key."""
    even, heavy = totals(profile(tmp_path, method, "even")), totals(profile(tmp_path, method, "heavy"))
    assert even == heavy and len(even) > 10


def test_plain_join_shows_the_heavy_key(tmp_path):
    even, heavy = profile(tmp_path, "plain", "even"), profile(tmp_path, "plain", "heavy")
    largest = lambda stages: max(x for v in stages.values() for x, _ in v)
    assert largest(heavy) > 1.5 * largest(even)
