"""A text surface: natural joins written as lists of atoms over temporary views."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from obljoin.operators.baselines import catalyst
from obljoin.operators.decomposed import decomposed_join
from obljoin.operators.padded import load, reveal
from obljoin.operators.physical import Engine
from obljoin.operators.wcoj import hidden_wcoj
from obljoin.plans.hypergraph import parse_atoms


def sql_join(spark: SparkSession, text: str, mode: str = "padded", tau: int | str | None = None, view: str | None = None, **frames: DataFrame) -> DataFrame:
    """``sql_join(spark, "R(a, b), S(b, c)")``: each atom names a view (or a keyword argument) whose columns are taken in order.

    ``mode``: ``plain`` (a Catalyst join), ``padded`` or ``hidden``. ``tau`` asks for a decomposed join. ``view`` registers the result.
    """
    query = parse_atoms(text)
    held = {}
    for name, attrs in query.edges:
        df = frames[name] if name in frames else spark.table(name)
        if len(df.columns) != len(attrs):
            raise ValueError(f"{name} has {len(df.columns)} columns")
        held[name] = df.toDF(*attrs)
    if mode == "plain":
        out = catalyst(query, {n: df.distinct() for n, df in held.items()})
    else:
        engine = Engine(spark, mode)
        instance = {n: load(engine, df, query.relations[n]) for n, df in held.items()}
        out = reveal(hidden_wcoj(query, instance) if tau is None else decomposed_join(query, instance, tau)).select(*query.attributes)
    if view:
        out.createOrReplaceTempView(view)
    return out
