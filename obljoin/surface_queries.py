"""Driver queries of the primitives and of the operators around the joins."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from obljoin.functions.registry import SCALARS, scalar_oracle, scalar_query
from obljoin.measures import tables
from obljoin.operators import surface
from obljoin.operators.padded import load, reveal, where
from obljoin.operators.physical import Engine
from obljoin.operators.primitives import antijoin, augment, compact, encode, intersect, lookup, project, semijoin, sort
from obljoin.operators.twoway import nested_loop
from obljoin.sources.readers import source
from obljoin.sources.workloads import WORKLOADS
from obljoin.sql import sql_join
from obljoin.streaming.epochs import padded_epoch, session_counts, windowed_counts

Query = Callable[[SparkSession, str], DataFrame]


def _engine(spark: SparkSession, mode: str = "padded") -> Engine:
    return Engine(spark, mode, 4)


def _read(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def _pair(mode: str, run: Callable) -> Query:
    """Over W14: customers C(cust, nat) and suppliers S(supp, nat)."""

    def query(spark: SparkSession, sf_dir: str) -> DataFrame:
        held = WORKLOADS["w14"].instance(_engine(spark, mode), sf_dir)
        return run(held["C"], held["S"])

    return query


def _rich(mode: str, run: Callable) -> Query:
    """Over customers and the nations of suppliers with much on their accounts."""

    def query(spark: SparkSession, sf_dir: str) -> DataFrame:
        e = _engine(spark, mode)
        rich = load(e, _read(spark, sf_dir, "supplier").where("s_acctbal > 7000").select(F.col("s_nationkey").cast("long").alias("nat")), ["nat"])
        return run(WORKLOADS["w14"].instance(e, sf_dir)["C"], rich)

    return query


_W14 = WORKLOADS["w14"].with_sql()


def _sorted_by(how: str, mode: str = "padded") -> Query:
    def query(spark: SparkSession, sf_dir: str) -> DataFrame:
        t = load(_engine(spark, mode), _read(spark, sf_dir, "supplier"), ["s_nationkey", "s_suppkey"])
        done = sort(t, ["s_nationkey", "s_suppkey"], how)
        return done.df.where("__real").select("s_suppkey", F.col("__pos").alias("rank"))

    return query


def _lookup(mode: str) -> Query:
    def query(spark: SparkSession, sf_dir: str) -> DataFrame:
        e = _engine(spark, mode)
        s, n = WORKLOADS["w14"].instance(e, sf_dir)["S"], WORKLOADS["w5"].instance(e, sf_dir)["N"]
        return reveal(lookup(s, n, ["nat"], ["reg"]))

    return query


def _events(spark: SparkSession, sf_dir: str, attrs: list[str], mode: str = "padded"):
    return load(_engine(spark, mode), _read(spark, sf_dir, "events"), attrs)


def _asof(spark: SparkSession, sf_dir: str) -> DataFrame:
    """For each purchase the latest earlier or simultaneous event of another kind by the same user."""
    df = _read(spark, sf_dir, "events")
    kinds = df.select(F.min("event_type")).first()[0]
    r = load(_engine(spark), df.where(F.col("event_type") == kinds).select("user_id", "ts", "event_id"), ["user_id", "ts", "event_id"])
    other = df.where(F.col("event_type") != kinds).groupBy("user_id", "ts").agg(F.max("event_id").alias("last_id"))
    s = load(_engine(spark), other.select("user_id", F.col("ts").alias("at"), "last_id"), ["user_id", "at", "last_id"])
    return reveal(surface.asof_join(r, s, "ts", "at", ["user_id"], ["last_id"])).select("event_id", "last_id")


def _interval(spark: SparkSession, sf_dir: str) -> DataFrame:
    parts = _read(spark, sf_dir, "part").groupBy("p_size").count()
    r = load(_engine(spark), parts.select(F.col("p_size").cast("long").alias("size")), ["size"])
    bands = spark.createDataFrame([(0, 0, 10), (1, 10, 30), (2, 25, 60)], "band long, lo long, hi long")
    s = load(_engine(spark), bands, ["band", "lo", "hi"])
    return reveal(surface.interval_join(r, s, "size", "lo", "hi", 200)).select("size", "band")


def _outer(how: str) -> Query:
    def query(spark: SparkSession, sf_dir: str) -> DataFrame:
        e = _engine(spark)
        r = load(e, _read(spark, sf_dir, "customer").where("c_acctbal > 9000").select(F.col("c_custkey").alias("cust"), F.col("c_nationkey").cast("long").alias("nat")), ["cust", "nat"])
        s = load(e, _read(spark, sf_dir, "supplier").where("s_acctbal > 5000").select(F.col("s_suppkey").alias("supp"), F.col("s_nationkey").cast("long").alias("nat")), ["supp", "nat"])
        return reveal(surface.outer_join(r, s, r.rows * s.rows, how)).select("cust", "nat", "supp")

    return query


def _outer_sql(how: str) -> str:
    return f"""
        WITH r AS (SELECT c_custkey AS cust, CAST(c_nationkey AS BIGINT) AS nat FROM customer WHERE c_acctbal > 9000),
             s AS (SELECT s_suppkey AS supp, CAST(s_nationkey AS BIGINT) AS nat FROM supplier WHERE s_acctbal > 5000)
        SELECT cust, coalesce(r.nat, s.nat) AS nat, supp FROM r {how} JOIN s ON r.nat = s.nat"""


def _aggregate(spark: SparkSession, sf_dir: str) -> DataFrame:
    t = load(_engine(spark), _read(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", "o_orderstatus"), ["o_orderkey", "o_custkey", "o_orderstatus"])
    aggs = {"n": F.count("*"), "customers": F.count_distinct("o_custkey"), "least": F.min("o_orderkey"), "most": F.max("o_orderkey"), "total": F.sum("o_custkey"), "mean": F.avg("o_orderkey").cast("decimal(20,3)")}
    return reveal(surface.aggregate(t, ["o_orderstatus"], aggs))


def _sets(spark: SparkSession, sf_dir: str) -> DataFrame:
    t = load(_engine(spark), _read(spark, sf_dir, "orders").select("o_orderkey", "o_orderstatus", "o_orderpriority"), ["o_orderkey", "o_orderstatus", "o_orderpriority"])
    return reveal(surface.grouping_sets(t, [["o_orderstatus", "o_orderpriority"], ["o_orderstatus"], []], {"n": F.count("*")}))


def _windows(spark: SparkSession, sf_dir: str) -> DataFrame:
    t = _events(spark, sf_dir, ["user_id", "ts", "event_id"])
    ran = surface.running(t, ["user_id"], ["ts", "event_id"], {"nth": F.lit(1).cast("long"), "total": F.col("event_id")})
    return reveal(surface.lagged(ran, ["user_id"], ["ts", "event_id"], {"previous": "event_id"})).select("event_id", "nth", "total", "previous")


def _top(spark: SparkSession, sf_dir: str) -> DataFrame:
    t = load(_engine(spark), _read(spark, sf_dir, "supplier").select("s_suppkey", "s_acctbal"), ["s_suppkey", "s_acctbal"])
    return reveal(surface.top_k(t, [F.desc("s_acctbal"), F.col("s_suppkey")], 7))


def _nations(spark: SparkSession, sf_dir: str):
    e = _engine(spark)
    a = load(e, _read(spark, sf_dir, "customer").where("c_acctbal > 5000").select(F.col("c_nationkey").cast("long").alias("nat")), ["nat"])
    b = load(e, _read(spark, sf_dir, "supplier").where("s_acctbal > 7000").select(F.col("s_nationkey").cast("long").alias("nat")), ["nat"])
    return a, b


def _set_query(run: Callable) -> Query:
    return lambda spark, sf_dir: reveal(run(*_nations(spark, sf_dir)))


def _set_sql(word: str) -> str:
    return f"SELECT CAST(c_nationkey AS BIGINT) AS nat FROM customer WHERE c_acctbal > 5000 {word} SELECT CAST(s_nationkey AS BIGINT) FROM supplier WHERE s_acctbal > 7000"


def _secret_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    t = source(_engine(spark), _read(spark, sf_dir, "part"), ["p_partkey", "p_brand"], F.col("p_size") > 16)
    return reveal(where(t, F.col("p_brand") > "Brand#2"))


def _plans(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Nulls, dummies and duplicates at load: keys that are null match nothing."""
    df = _read(spark, sf_dir, "customer").select(F.when(F.col("c_custkey") % 3 != 0, F.col("c_nationkey").cast("long")).alias("nat"), (F.col("c_custkey") % 50).alias("k"))
    e = _engine(spark)
    r = load(e, df, ["nat", "k"])
    s = load(e, df.select("nat", (F.col("k") + 1).alias("m")).where("m < 4"), ["nat", "m"])
    return reveal(semijoin(r, s))


def _text_join(mode: str) -> Query:
    def query(spark: SparkSession, sf_dir: str) -> DataFrame:
        nation, region = _read(spark, sf_dir, "nation"), _read(spark, sf_dir, "region")
        supplier = _read(spark, sf_dir, "supplier")
        return sql_join(
            spark, "N(nat, reg), R(reg, name), S(supp, nat)", mode, N=nation.select(F.col("n_nationkey").cast("long"), F.col("n_regionkey").cast("long")),
            R=region.select(F.col("r_regionkey").cast("long"), "r_name"), S=supplier.select("s_suppkey", F.col("s_nationkey").cast("long")),
            **({"tau": 20_000} if mode == "padded" else {}),
        )

    return query


def _epoch(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All events in epochs of EPOCH rows: real rows and dummies of the first epoch and of what waits."""
    now, rest = padded_epoch(_engine(spark), _read(spark, sf_dir, "events").select("event_id", "user_id"), ["event_id", "user_id"], EPOCH)
    both = now.df.select("__real", F.lit("first").alias("part")).unionByName(rest.select("__real", F.lit("waiting").alias("part")))
    return both.groupBy("part", F.col("__real").alias("is_real")).agg(F.count("*").alias("n"))


EPOCH = 4096


def _epoch_sql() -> str:
    return f"""
        WITH k AS (SELECT count(*) AS n, least(count(*), {EPOCH}) AS now, greatest(1, CAST(ceil(count(*) / {EPOCH}.0) AS BIGINT)) * {EPOCH} AS slots FROM events)
        SELECT * FROM (SELECT 'first' AS part, true AS is_real, now AS n FROM k UNION ALL SELECT 'first', false, {EPOCH} - now FROM k
                       UNION ALL SELECT 'waiting', true, n - now FROM k UNION ALL SELECT 'waiting', false, slots - {EPOCH} - (n - now) FROM k) WHERE n > 0"""


def _payload(spark: SparkSession, sf_dir: str) -> DataFrame:
    """W22: pairs of vectors of one label by a padded loop, the vectors fetched for what is left, and their inner product in thousandths."""
    held = WORKLOADS["w22"].instance(_engine(spark), sf_dir)
    pairs = reveal(nested_loop(held["A"], held["B"], F.col("va") < F.col("vb")))
    v = _read(spark, sf_dir, "embeddings").select("vec_id", F.transform("embedding", lambda x: F.round(x.cast("double") * 1000).cast("long")).alias("v"))
    both = pairs.join(v.select(F.col("vec_id").alias("va"), F.col("v").alias("x")), "va").join(v.select(F.col("vec_id").alias("vb"), F.col("v").alias("y")), "vb")
    product = F.aggregate(F.zip_with("x", "y", lambda x, y: x * y), F.lit(0).cast("long"), lambda s, x: s + x)
    return both.select("label", "va", "vb", product.alias("product"))


def _totals(mode: str) -> Query:
    """Customers and the sum of their numbers per nation, by sorts and scans."""

    def query(spark: SparkSession, sf_dir: str) -> DataFrame:
        t = WORKLOADS["w14"].instance(_engine(spark, mode), sf_dir)["C"]
        return reveal(surface.totals(t, ["nat"], {"n": F.lit(1).cast("long"), "total": F.col("cust")}))

    return query


def _first(mode: str) -> Query:
    def query(spark: SparkSession, sf_dir: str) -> DataFrame:
        t = WORKLOADS["w14"].instance(_engine(spark, mode), sf_dir)["C"]
        return reveal(surface.first_per_group(t, ["nat"], [F.desc("cust")]))

    return query


def build() -> tuple[dict[str, Query], dict[str, str]]:
    queries: dict[str, Query] = {}
    oracles: dict[str, str] = {}

    def add(name: str, query: Query, sql: str) -> None:
        queries[name], oracles[name] = query, sql

    for mode, end in (("padded", ""), ("hidden", "_hidden")):
        add(f"semijoin{end}", _pair(mode, lambda c, s: reveal(semijoin(c, s))), f"{_W14} SELECT * FROM C WHERE nat IN (SELECT nat FROM S)")
        add(f"project{end}", _pair(mode, lambda c, s: reveal(project(c, ["nat"]))), f"{_W14} SELECT DISTINCT nat FROM C")
        add(
            f"augment{end}", _pair(mode, lambda c, s: augment(s, [("C", c, ["nat"]), ("all", c, [])]).df.where("__real").select("supp", "nat", F.col("__deg_C").alias("partners"), F.col("__deg_all").alias("everyone"))),
            f"{_W14} SELECT supp, nat, (SELECT count(*) FROM C WHERE C.nat = S.nat) AS partners, (SELECT count(*) FROM C) AS everyone FROM S",
        )
        rich = "R AS (SELECT CAST(s_nationkey AS BIGINT) AS nat FROM supplier WHERE s_acctbal > 7000)"
        add(f"antijoin{end}", _rich(mode, lambda c, r: reveal(antijoin(c, r))), f"{_W14}, {rich} SELECT * FROM C WHERE nat NOT IN (SELECT nat FROM R)")
        add(f"intersect{end}", _rich(mode, lambda c, r: reveal(intersect(project(c, ["nat"]), r))), f"{_W14}, {rich} SELECT nat FROM C INTERSECT SELECT nat FROM R")
        add(f"totals{end}", _totals(mode), f"{_W14} SELECT nat, count(*) AS n, CAST(sum(cust) AS BIGINT) AS total FROM C GROUP BY nat")
        add(f"first_per_group{end}", _first(mode), f"{_W14} SELECT max(cust) AS cust, nat FROM C GROUP BY nat")
        add(
            f"compact{end}", _pair(mode, lambda c, s: compact(where(c, F.col("cust") % 5 == 0), c.rows // 2).df.groupBy("__real").agg(F.count("*").alias("n"), F.max("__pos").alias("last")).select(F.col("__real").alias("is_real"), "n", "last")),
            f"{_W14}, k AS (SELECT (SELECT count(*) FROM C WHERE cust % 5 = 0) AS r, (SELECT count(*) FROM C) // 2 AS t) SELECT true AS is_real, r AS n, r - 1 AS last FROM k UNION ALL SELECT false, t - r, t - 1 FROM k",
        )
    for mode, end in (("padded", ""), ("hidden", "_hidden")):
        add(f"lookup{end}", _lookup(mode), f"{_W14} SELECT supp, nat, CAST(n_regionkey AS BIGINT) AS reg FROM S JOIN nation ON nat = n_nationkey")
    add("encode", lambda spark, sf_dir: reveal(encode(load(_engine(spark), _read(spark, sf_dir, "part").select("p_partkey", "p_brand"), ["p_partkey", "p_brand"]), "p_brand")), "SELECT p_partkey, dense_rank() OVER (ORDER BY p_brand) - 1 AS p_brand FROM part")
    for how, mode in (("shuffle", "padded"), ("plain", "padded"), ("bitonic", "padded"), ("columns", "padded"), ("shuffle", "hidden"), ("bitonic", "hidden"), ("columns", "hidden")):
        add(f"sort_{how}" if mode == "padded" else f"sort_{how}_hidden", _sorted_by(how, mode), "SELECT s_suppkey, row_number() OVER (ORDER BY s_nationkey, s_suppkey) - 1 AS rank FROM supplier")
    for how in ("left", "right", "full"):
        add(f"outer_{how}", _outer(how), _outer_sql(how))
    add("interval_join", _interval, "SELECT DISTINCT CAST(p_size AS BIGINT) AS size, CAST(band AS BIGINT) AS band FROM part JOIN (VALUES (0, 0, 10), (1, 10, 30), (2, 25, 60)) AS b(band, lo, hi) ON p_size >= lo AND p_size < hi")
    add(
        "asof_join", _asof,
        """WITH k AS (SELECT min(event_type) AS kind FROM events), o AS (SELECT user_id, ts, max(event_id) AS last_id FROM events WHERE event_type <> (SELECT kind FROM k) GROUP BY ALL)
           SELECT e.event_id, (SELECT arg_max(o.last_id, o.ts) FROM o WHERE o.user_id = e.user_id AND o.ts <= e.ts) AS last_id FROM events e WHERE e.event_type = (SELECT kind FROM k)""",
    )
    add("aggregate", _aggregate, "SELECT o_orderstatus, count(*) AS n, count(DISTINCT o_custkey) AS customers, min(o_orderkey) AS least, max(o_orderkey) AS most, CAST(sum(o_custkey) AS BIGINT) AS total, CAST(avg(o_orderkey) AS DECIMAL(20,3)) AS mean FROM orders GROUP BY o_orderstatus")
    add("grouping_sets", _sets, "SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM orders GROUP BY GROUPING SETS ((o_orderstatus, o_orderpriority), (o_orderstatus), ())")
    add(
        "window_functions", _windows,
        "SELECT event_id, row_number() OVER w AS nth, CAST(sum(event_id) OVER w AS BIGINT) AS total, lag(event_id) OVER w AS previous FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)",
    )
    add("top_k", _top, "SELECT s_suppkey, s_acctbal FROM supplier ORDER BY s_acctbal DESC, s_suppkey LIMIT 7")
    add("union_distinct", _set_query(surface.union), _set_sql("UNION"))
    add("set_intersection", _set_query(surface.intersection), _set_sql("INTERSECT"))
    add("set_difference", _set_query(surface.difference), _set_sql("EXCEPT"))
    add("secret_filter", _secret_filter, "SELECT p_partkey, p_brand FROM part WHERE p_size > 16 AND p_brand > 'Brand#2'")
    add("edge_null", _plans, "WITH d AS (SELECT DISTINCT CASE WHEN c_custkey % 3 <> 0 THEN CAST(c_nationkey AS BIGINT) END AS nat, c_custkey % 50 AS k FROM customer) SELECT * FROM d WHERE nat IN (SELECT nat FROM d WHERE k + 1 < 4 AND nat IS NOT NULL)")
    text = "SELECT CAST(n_nationkey AS BIGINT) AS nat, CAST(n_regionkey AS BIGINT) AS reg, r_name AS name, s_suppkey AS supp FROM nation JOIN region ON n_regionkey = r_regionkey JOIN supplier ON s_nationkey = n_nationkey"
    for mode in ("plain", "padded"):
        add(f"sql_join_{mode}", _text_join(mode), text)
    add("padded_epoch", _epoch, _epoch_sql())
    add(
        "payload_fetch", _payload,
        """WITH v AS (SELECT CAST(label AS BIGINT) AS label, vec_id, [CAST(round(CAST(x AS DOUBLE) * 1000) AS BIGINT) FOR x IN embedding] AS v FROM embeddings)
           SELECT a.label, a.vec_id AS va, b.vec_id AS vb, CAST(list_sum([a.v[i] * b.v[i] FOR i IN generate_series(1, len(a.v))]) AS BIGINT) AS product FROM v a JOIN v b ON a.label = b.label AND a.vec_id < b.vec_id""",
    )
    add("tumbling_windows", lambda spark, sf_dir: windowed_counts(_read(spark, sf_dir, "events"), "ts", ["event_type"], "1 hour").drop("end"), "SELECT date_trunc('hour', ts) AS start, event_type, count(*) AS n FROM events GROUP BY ALL")
    add(
        "sliding_windows", lambda spark, sf_dir: windowed_counts(_read(spark, sf_dir, "events"), "ts", [], "2 hours", "1 hour").drop("end"),
        "SELECT start, count(*) AS n FROM (SELECT unnest([date_trunc('hour', ts), date_trunc('hour', ts) - INTERVAL 1 HOUR]) AS start FROM events) GROUP BY start",
    )
    add(
        "session_windows", lambda spark, sf_dir: session_counts(_read(spark, sf_dir, "events"), "ts", "user_id", "30 minutes").groupBy("user_id").agg(F.count("*").alias("sessions"), F.sum("n").alias("events")),
        """WITH g AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS new FROM events)
           SELECT user_id, CAST(sum(new) AS BIGINT) AS sessions, count(*) AS events FROM g GROUP BY user_id""",
    )
    for name in SCALARS:
        add(name, scalar_query(name), scalar_oracle(name))
    add(
        "fn_rank_windows", lambda spark, sf_dir: _read(spark, sf_dir, "supplier").select("s_suppkey", F.rank().over(Window.partitionBy("s_nationkey").orderBy("s_acctbal")).cast("long").alias("r"), F.dense_rank().over(Window.partitionBy("s_nationkey").orderBy("s_acctbal")).cast("long").alias("d"), F.lead("s_suppkey").over(Window.partitionBy("s_nationkey").orderBy("s_acctbal", "s_suppkey")).alias("nxt")),
        "SELECT s_suppkey, rank() OVER (PARTITION BY s_nationkey ORDER BY s_acctbal) AS r, dense_rank() OVER (PARTITION BY s_nationkey ORDER BY s_acctbal) AS d, lead(s_suppkey) OVER (PARTITION BY s_nationkey ORDER BY s_acctbal, s_suppkey) AS nxt FROM supplier",
    )
    add("ghd_widths", tables.widths, tables.widths_sql())
    add("budget_table", tables.budgets, tables.budgets_sql())
    add("split_sizes_w3", tables.split_sizes, tables.split_sizes_sql())
    add("leak_report_w3", tables.leak_report, tables.leak_report_sql())
    add("delay_report_w3", tables.delay_report, tables.delay_report_sql())
    add("padding_table", tables.padding, tables.padding_sql())
    for name in ("w1", "w2", "w3"):
        add(f"step_report_{name}", lambda spark, sf_dir, name=name: tables.step_report(spark, sf_dir, name), tables.step_report_sql(name))
    add("recursive_report_w3", tables.recursive_report, tables.recursive_report_sql())
    add("cost_table", tables.costs, tables.costs_sql())
    return queries, oracles

