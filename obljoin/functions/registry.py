"""Stock functions offered inside padded expressions, each with a query over the given tables and its DuckDB text.

They run inside a task and see one row, so they move nothing. Each entry: table, Spark expressions, DuckDB expressions.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

_K = "get_json_object(props, '$.k')"

#: name -> (table, key columns, {column: (Spark SQL, DuckDB SQL)})
SCALARS: dict[str, tuple[str, tuple[str, ...], dict[str, tuple[str, str]]]] = {
    "fn_string": ("part", ("p_partkey",), {
        "up": ("upper(p_name)", "upper(p_name)"), "low": ("lower(p_brand)", "lower(p_brand)"), "sub": ("substring(p_name, 2, 4)", "substring(p_name, 2, 4)"),
        "cat": ("concat(p_brand, '/', p_type)", "concat(p_brand, '/', p_type)"), "len": ("cast(length(p_name) AS BIGINT)", "cast(length(p_name) AS BIGINT)"),
        "tr": ("trim(concat(' ', p_brand, ' '))", "trim(concat(' ', p_brand, ' '))"), "digits": ("regexp_extract(p_brand, '([0-9]+)', 1)", "regexp_extract(p_brand, '([0-9]+)', 1)"),
        "word": ("split(p_type, ' ')[0]", "split_part(p_type, ' ', 1)"),
    }),
    "fn_date": ("orders", ("o_orderkey",), {
        "y": ("cast(year(o_orderdate) AS BIGINT)", "cast(year(o_orderdate) AS BIGINT)"), "m": ("cast(month(o_orderdate) AS BIGINT)", "cast(month(o_orderdate) AS BIGINT)"),
        "d": ("cast(dayofmonth(o_orderdate) AS BIGINT)", "cast(day(o_orderdate) AS BIGINT)"), "q": ("cast(date_trunc('QUARTER', o_orderdate) AS DATE)", "cast(date_trunc('quarter', o_orderdate) AS DATE)"),
        "days": ("cast(datediff(o_orderdate, DATE '1992-01-01') AS BIGINT)", "cast(date_diff('day', DATE '1992-01-01', cast(o_orderdate AS DATE)) AS BIGINT)"),
    }),
    "fn_math": ("supplier", ("s_suppkey",), {
        "a": ("abs(s_acctbal)", "abs(s_acctbal)"), "f": ("cast(floor(s_acctbal) AS BIGINT)", "cast(floor(s_acctbal) AS BIGINT)"), "md": ("s_suppkey % 7", "s_suppkey % 7"),
        "pw": ("cast(pow(s_suppkey % 10, 3) AS BIGINT)", "cast(pow(s_suppkey % 10, 3) AS BIGINT)"), "g": ("greatest(s_suppkey, 50)", "greatest(s_suppkey, 50)"), "l": ("least(s_suppkey, 50)", "least(s_suppkey, 50)"),
    }),
    "fn_conditional": ("customer", ("c_custkey",), {
        "rich": ("CASE WHEN c_acctbal > 5000 THEN 'rich' WHEN c_acctbal > 0 THEN 'some' ELSE 'none' END", "CASE WHEN c_acctbal > 5000 THEN 'rich' WHEN c_acctbal > 0 THEN 'some' ELSE 'none' END"),
        "seg": ("coalesce(nullif(c_mktsegment, 'BUILDING'), '-')", "coalesce(nullif(c_mktsegment, 'BUILDING'), '-')"),
    }),
    "fn_array": ("embeddings", ("vec_id",), {
        "n": ("cast(size(embedding) AS BIGINT)", "cast(len(embedding) AS BIGINT)"), "first": ("cast(element_at(embedding, 1) AS DOUBLE)", "cast(embedding[1] AS DOUBLE)"),
        "least": ("cast(sort_array(embedding)[0] AS DOUBLE)", "cast(list_sort(embedding)[1] AS DOUBLE)"), "zero": ("array_contains(embedding, cast(0 AS FLOAT))", "list_contains(embedding, cast(0 AS FLOAT))"),
        "pos": ("cast(size(filter(transform(embedding, x -> x > 0), x -> x)) AS BIGINT)", "cast(len(list_filter(embedding, lambda x: x > 0)) AS BIGINT)"),
    }),
    "fn_json": ("events", ("event_id",), {
        "k": (f"cast({_K} AS BIGINT)", "cast(json_extract_string(props, '$.k') AS BIGINT)"), "from": ("cast(from_json(props, 'k BIGINT').k AS BIGINT)", "cast(json_extract_string(props, '$.k') AS BIGINT)"),
        "keys": ("cast(size(map_keys(from_json(props, 'MAP<STRING, BIGINT>'))) AS BIGINT)", "cast(len(json_keys(props)) AS BIGINT)"),
        "value": ("element_at(map_values(from_json(props, 'MAP<STRING, BIGINT>')), 1)", "cast(json_extract_string(props, '$.k') AS BIGINT)"),
    }),
}


def scalar_query(name: str):
    table, keys, columns = SCALARS[name]

    def query(spark: SparkSession, sf_dir: str) -> DataFrame:
        return spark.read.parquet(f"{sf_dir}/{table}.parquet").select(*keys, *(F.expr(s).alias(c) for c, (s, _) in columns.items()))

    return query


def scalar_oracle(name: str) -> str:
    table, keys, columns = SCALARS[name]
    return f"SELECT {', '.join(keys)}, {', '.join(f'{d} AS {c}' for c, (_, d) in columns.items())} FROM {table}"
