"""Classes of join queries as relations over the given tables.

Each relation is a SELECT that Spark and DuckDB both read; ``{table}`` stands for a table. Every relation is a set, integers are BIGINT.
"""

from __future__ import annotations

from dataclasses import dataclass, field, replace

from pyspark.sql import DataFrame, SparkSession

from obljoin.operators.padded import PaddedTable, load
from obljoin.operators.physical import Engine
from obljoin.plans.hypergraph import JoinQuery


@dataclass(frozen=True)
class Workload:
    """``keys``: declared keys of some relations; ``finest``: attributes from most to fewest different values. Both as public as the schema."""

    relations: dict[str, tuple[tuple[str, ...], str]]
    keys: dict[str, tuple[str, ...]] = field(default_factory=dict)
    finest: tuple[str, ...] = ()

    @property
    def query(self) -> JoinQuery:
        return JoinQuery.of({n: a for n, (a, _) in self.relations.items()})

    def frames(self, spark: SparkSession, sf_dir: str) -> dict[str, DataFrame]:
        out = {}
        for name, (attrs, text) in self.relations.items():
            tables = {t: spark.read.parquet(f"{sf_dir}/{t}.parquet") for t in TABLES if "{" + t + "}" in text}
            out[name] = spark.sql(text, **tables).toDF(*attrs)
        return out

    def instance(self, engine: Engine, sf_dir: str) -> dict[str, PaddedTable]:
        return {n: load(engine, df, self.relations[n][0]) for n, df in self.frames(engine.spark, sf_dir).items()}

    def with_sql(self) -> str:
        """The relations as common table expressions of DuckDB."""
        names = {t: t for t in TABLES}
        return "WITH " + ", ".join(f"{n}({', '.join(a)}) AS ({text.format(**names)})" for n, (a, text) in self.relations.items())

    def sql(self, select: str | None = None) -> str:
        """The natural join in SQL."""
        first: dict[str, str] = {}
        equal = []
        for n, (attrs, _) in self.relations.items():
            for a in attrs:
                if a in first:
                    equal.append(f"{first[a]}.{a} = {n}.{a}")
                else:
                    first[a] = n
        columns = select or ", ".join(f"{n}.{a} AS {a}" for a, n in first.items())
        where = f" WHERE {' AND '.join(equal)}" if equal else ""
        return f"{self.with_sql()} SELECT DISTINCT {columns} FROM {', '.join(self.relations)}{where}"


TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")


def _w(**relations: str) -> Workload:
    """``R1="a b: SELECT ..."``."""
    out = {}
    for name, text in relations.items():
        attrs, _, body = text.partition(":")
        out[name] = (tuple(attrs.split()), body.strip())
    return Workload(out)


def _edges(names: str, kind: str = "TRUE", columns: str = "s, d") -> str:
    """From the user of every event to that of the next one; ``kind`` selects events by their value."""
    return (
        f"{names}: SELECT DISTINCT {columns} FROM (SELECT user_id AS s, lead(user_id) OVER (ORDER BY ts, event_id) AS d, value FROM {{events}}) AS moves"
        f" WHERE d IS NOT NULL AND s <> d AND {kind}"
    )


_R1 = "part supp: SELECT DISTINCT l_partkey, l_suppkey FROM {lineitem} WHERE l_quantity >= 46"
_R2 = "ord supp: SELECT DISTINCT l_orderkey, l_suppkey FROM {lineitem} WHERE l_quantity >= 46"
_R3 = "ord part: SELECT DISTINCT l_orderkey, l_partkey FROM {lineitem} WHERE l_quantity >= 46"
_NATION = "SELECT CAST(n_nationkey AS BIGINT), CAST(n_regionkey AS BIGINT) FROM {nation}"
_CUSTOMER = "SELECT c_custkey, CAST(c_nationkey AS BIGINT) FROM {customer}"
_SUPPLIER = "SELECT s_suppkey, CAST(s_nationkey AS BIGINT) FROM {supplier}"
_ORDERS = "SELECT o_orderkey, o_custkey FROM {orders}"
_GRADED = "{documents} AS d JOIN {labels} AS l ON d.doc_id = l.doc_id"
#: Events of small, large and very large value.
_SMALL, _LARGE, _LARGER = "value < 5", "value > 100", "value > 113"
_MONTH = "CAST(year(l_shipdate) * 12 + month(l_shipdate) AS BIGINT)"
_RETURNED = "FROM {lineitem} WHERE l_returnflag = 'R' AND l_quantity >= 40"

WORKLOADS: dict[str, Workload] = {
    "w1": _w(R1=_R1, R2=_R2, R3=_R3),
    "w2": _w(
        R1=_R1,
        R2="line supp: SELECT DISTINCT CAST(l_linenumber AS BIGINT), l_suppkey FROM {lineitem} WHERE l_quantity < 5",
        R3="line part: SELECT DISTINCT CAST(l_linenumber AS BIGINT), l_partkey FROM {lineitem} WHERE l_discount = 0.05",
    ),
    "w3": _w(R1=_edges("b c"), R2=_edges("a c"), R3=_edges("a b")),
    "w4": _w(
        R1="typ k: SELECT DISTINCT event_type, props FROM {events} WHERE value < 10",
        R2="usr k: SELECT DISTINCT user_id, props FROM {events} WHERE value BETWEEN 10 AND 60",
        R3="usr typ: SELECT DISTINCT user_id, event_type FROM {events} WHERE value > 200",
    ),
    "w4b": _w(
        R1=f"src q: SELECT DISTINCT source, CAST(quality * 2 + toxic AS BIGINT) FROM {_GRADED}",
        R2=f"lang q: SELECT DISTINCT lang, CAST(quality * 2 + toxic AS BIGINT) FROM {_GRADED} WHERE n_chars > 800",
        R3="lang src: SELECT DISTINCT lang, source FROM {documents} WHERE n_chars < 300",
    ),
    "w4c": _w(
        R1="turn len: SELECT DISTINCT turn, CAST(length(text) % 16 AS BIGINT) FROM {conversations} WHERE role = 'user'",
        R2="conv len: SELECT DISTINCT conv_id, CAST(length(text) % 16 AS BIGINT) FROM {conversations} WHERE role = 'assistant'",
        R3="conv turn: SELECT DISTINCT conv_id, turn FROM {conversations}",
    ),
    "w5": _w(N=f"nat reg: {_NATION}", C=f"cust nat: {_CUSTOMER}", O=f"ord cust: {_ORDERS}", L="ord line: SELECT DISTINCT l_orderkey, CAST(l_linenumber AS BIGINT) FROM {lineitem}"),
    "w6": _w(
        L="ord part supp: SELECT DISTINCT l_orderkey, l_partkey, l_suppkey FROM {lineitem}",
        O=f"ord cust: {_ORDERS}",
        P="part size: SELECT p_partkey, CAST(p_size AS BIGINT) FROM {part}",
        S=f"supp nat: {_SUPPLIER}",
    ),
    "w7": _w(O=f"ord cust: {_ORDERS}", C=f"cust nat: {_CUSTOMER}", S=f"supp nat: {_SUPPLIER}", L="ord supp: SELECT DISTINCT l_orderkey, l_suppkey FROM {lineitem}"),
    "w7u": _w(
        O=f"ord cust: {_ORDERS} WHERE o_orderpriority = '1-URGENT'", C=f"cust nat: {_CUSTOMER}", S=f"supp nat: {_SUPPLIER}", L="ord supp: SELECT DISTINCT l_orderkey, l_suppkey FROM {lineitem}"
    ),
    "w8": _w(
        O=f"ord cust: {_ORDERS} WHERE o_orderpriority = '1-URGENT'", C=f"cust cn: {_CUSTOMER}", N1=f"cn reg: {_NATION}", N2=f"sn reg: {_NATION}", S=f"supp sn: {_SUPPLIER}", L=_R2
    ),
    "w8b": _w(
        O=f"ord cust: {_ORDERS} WHERE o_orderpriority = '1-URGENT' AND o_orderstatus = 'F'",
        C=f"cust nat: {_CUSTOMER}",
        N=f"nat reg: {_NATION}",
        S="supp reg: SELECT s_suppkey, CAST(n_regionkey AS BIGINT) FROM {supplier} JOIN {nation} ON s_nationkey = n_nationkey WHERE s_acctbal > 5000",
        L="ord supp: SELECT DISTINCT l_orderkey, l_suppkey FROM {lineitem} WHERE l_quantity >= 40",
    ),
    "w9": _w(
        R4="part supp ord: SELECT DISTINCT l_partkey, l_suppkey, l_orderkey FROM {lineitem} WHERE l_quantity >= 48",
        R1="part brand: SELECT p_partkey, p_brand FROM {part}",
        R2=f"supp nat: {_SUPPLIER}",
        R3=f"ord cust: {_ORDERS}",
        R5="brand nat cust: SELECT DISTINCT p_brand, CAST(s_nationkey AS BIGINT), o_custkey FROM {lineitem} JOIN {part} ON l_partkey = p_partkey JOIN {orders} ON l_orderkey = o_orderkey"
        " JOIN {supplier} ON l_suppkey = s_suppkey WHERE l_quantity < 2 OR l_quantity = 50",
    ),
    "w10": _w(
        R1=f"b c d: SELECT DISTINCT CAST(l_linenumber AS BIGINT), {_MONTH}, CAST(l_quantity AS BIGINT) {_RETURNED}",
        R2=f"a c d: SELECT DISTINCT l_suppkey, {_MONTH}, CAST(l_quantity AS BIGINT) {_RETURNED}",
        R3=f"a b d: SELECT DISTINCT l_suppkey, CAST(l_linenumber AS BIGINT), CAST(l_quantity AS BIGINT) {_RETURNED}",
        R4=f"a b c: SELECT DISTINCT l_suppkey, CAST(l_linenumber AS BIGINT), {_MONTH} {_RETURNED}",
    ),
    "w11": _w(**{f"R{i}": _edges(f"{x} {y}", _LARGE, "least(s, d), greatest(s, d)") for i, (x, y) in enumerate(("ab", "ac", "ad", "bc", "bd", "cd"), 1)}),
    "w12": _w(R1=_R1, R2=_R2, R3=_R3, S=f"supp nat: {_SUPPLIER}", N=f"nat reg: {_NATION}"),
    "w13": _w(A1=_edges("h a", _SMALL), A2=_edges("a b", _SMALL), A3=_edges("h b", _SMALL), B1=_edges("h c", _LARGER), B2=_edges("c d", _LARGER), B3=_edges("h d", _LARGER)),
    "w14": _w(C=f"cust nat: {_CUSTOMER}", S=f"supp nat: {_SUPPLIER}"),
    "w15a": _w(R="a b: SELECT s_suppkey, s_suppkey AS other FROM {supplier}", S="b c: SELECT s_suppkey, s_suppkey AS other FROM {supplier}"),
    "w15b": _w(R="a b: SELECT s_suppkey, CAST(0 AS BIGINT) FROM {supplier}", S="b c: SELECT CAST(0 AS BIGINT), s_suppkey FROM {supplier}"),
    "w16": _w(**{f"R{i}": f"{x} {y}: SELECT CAST(x.n_nationkey AS BIGINT), CAST(y.n_nationkey AS BIGINT) FROM {{nation}} AS x CROSS JOIN {{nation}} AS y" for i, (x, y) in enumerate(("bc", "ac", "ab"), 1)}),
    "w17": _w(
        A="nat: SELECT DISTINCT CAST(c_nationkey AS BIGINT) FROM {customer} WHERE c_acctbal > 5000",
        B="nat: SELECT DISTINCT CAST(s_nationkey AS BIGINT) FROM {supplier}",
        C="nat: SELECT CAST(n_nationkey AS BIGINT) FROM {nation}",
    ),
    "w18": _w(A="reg: SELECT CAST(r_regionkey AS BIGINT) FROM {region}", B="nat: SELECT CAST(n_nationkey AS BIGINT) FROM {nation}"),
    "w19": _w(R1=_R1.replace(">= 46", "> 50"), R2=_R2, R3=_R3),
    "w20": _w(R1=_R1, R2=_R2, R3=_R3, U="part: SELECT p_partkey FROM {part} WHERE p_size < 10"),
    "w21": _w(
        A="host lang: SELECT DISTINCT regexp_extract(url, '^https?://([^/]+)', 1), regexp_extract(html, 'lang=\"([a-z]+)\"', 1) FROM {pages}", B="lang source: SELECT DISTINCT lang, source FROM {documents}"
    ),
    "w22": _w(A="label va: SELECT CAST(label AS BIGINT), vec_id FROM {embeddings}", B="label vb: SELECT CAST(label AS BIGINT), vec_id FROM {embeddings}"),
}

#: Primary keys of the given tables, by workload.
_KEYS = {
    "w5": {"N": ("nat",), "C": ("cust",), "O": ("ord",)},
    "w6": {"O": ("ord",), "P": ("part",), "S": ("supp",)},
    "w7": {"O": ("ord",), "C": ("cust",), "S": ("supp",)},
    "w7u": {"O": ("ord",), "C": ("cust",), "S": ("supp",)},
    "w8": {"O": ("ord",), "C": ("cust",), "N1": ("cn",), "N2": ("sn",), "S": ("supp",)},
    "w8b": {"O": ("ord",), "C": ("cust",), "N": ("nat",), "S": ("supp",)},
    "w9": {"R1": ("part",), "R2": ("supp",), "R3": ("ord",)},
    "w12": {"S": ("supp",), "N": ("nat",)},
    "w14": {"C": ("cust",), "S": ("supp",)},
}
#: There are more orders than parts, more parts than suppliers, and few lines of an order.
_FINEST = ("ord", "part", "supp", "line")
WORKLOADS = {name: replace(w, keys=_KEYS.get(name, {}), finest=_FINEST if name in ("w1", "w2", "w12", "w19", "w20") else ()) for name, w in WORKLOADS.items()}
