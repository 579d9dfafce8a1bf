"""The driver queries: one per method and workload, with the plain natural join as the oracle."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession

from obljoin.operators import baselines
from obljoin.operators.cover_join import cover_join
from obljoin.operators.decomposed import decomposed_join
from obljoin.operators.padded import PaddedTable, reveal
from obljoin.operators.physical import Engine
from obljoin.operators.triangle import triangle_choice, triangle_delay
from obljoin.operators.twoway import bounded_join, nested_loop
from obljoin.operators.wcoj import hidden_wcoj, sizes
from obljoin.plans.covers import tau as bound
from obljoin.sources.workloads import WORKLOADS, Workload

Query = Callable[[SparkSession, str], DataFrame]

def engine_for(spark: SparkSession, slots: int, mode: str) -> Engine:
    """As many partitions as the public number of slots needs, at most what the session has."""
    most = int(spark.conf.get("spark.sql.shuffle.partitions"))
    return Engine(spark, mode, max(2, min(most, -(-slots // 100_000))))


def _instance(work: Workload, spark: SparkSession, sf_dir: str, mode: str) -> tuple[dict[str, PaddedTable], int]:
    """The padded relations and the product bound, for which the engine is sized."""
    held = work.instance(engine_for(spark, 1, mode), sf_dir)
    limit = bound(work.query, sizes(held))
    engine = engine_for(spark, limit, mode)
    return {n: replace(t, engine=engine) for n, t in held.items()}, limit


def _ordered(df: DataFrame, work: Workload) -> DataFrame:
    return df.select(*work.query.attributes)


def method(name: str, mode: str, run: Callable[[Workload, dict[str, PaddedTable], int], PaddedTable]) -> Query:
    work = WORKLOADS[name]

    def query(spark: SparkSession, sf_dir: str) -> DataFrame:
        held, limit = _instance(work, spark, sf_dir, mode)
        return _ordered(reveal(run(work, held, limit)), work)

    return query


def plain(name: str, run: Callable[[Workload, dict[str, DataFrame]], DataFrame]) -> Query:
    work = WORKLOADS[name]
    return lambda spark, sf_dir: _ordered(run(work, work.frames(spark, sf_dir)), work)


def _triangle(how, **options):
    return lambda work, held, limit: how(*(held[n] for n in ("R1", "R2", "R3")), **options)


def _wcoj(**options):
    return lambda work, held, limit: hidden_wcoj(work.query, held, keys=work.keys, finest=work.finest, **options)


def _decomposed(tau):
    def run(work: Workload, held: dict[str, PaddedTable], limit: int) -> PaddedTable:
        return decomposed_join(work.query, held, tau(held) if callable(tau) else tau, keys=work.keys, finest=work.finest)

    return run


def _two(work: Workload, held: dict[str, PaddedTable], limit: int) -> PaddedTable:
    return bounded_join(*held.values(), limit)


def build() -> tuple[dict[str, Query], dict[str, str]]:
    queries: dict[str, Query] = {}
    oracles: dict[str, str] = {}

    def add(label: str, work: str, query: Query) -> None:
        queries[label] = query
        oracles[label] = WORKLOADS[work].sql()

    for w in ("w1", "w2", "w3", "w4", "w4b", "w4c", "w16", "w19"):
        add(f"tri_choice_{w}", w, method(w, "padded", _triangle(triangle_choice)))
        add(f"tri_delay_{w}", w, method(w, "padded", _triangle(triangle_delay)))
    for w in ("w4b", "w4c"):
        add(f"tri_choice_hidden_{w}", w, method(w, "hidden", _triangle(triangle_choice)))
        add(f"tri_delay_hidden_{w}", w, method(w, "hidden", _triangle(triangle_delay)))
    for w in ("w1", "w2", "w3", "w4b", "w7", "w7u", "w8b", "w10", "w11", "w16", "w17", "w18", "w19", "w20"):
        add(f"wcoj_single_{w}", w, method(w, "padded", _wcoj(j="single")))
    for w in ("w1", "w4b", "w7", "w7u", "w10", "w11"):
        add(f"wcoj_pair_{w}", w, method(w, "padded", _wcoj(j="pair")))
    for w in ("w1", "w4b", "w7", "w7u", "w10"):
        add(f"wcoj_fused_{w}", w, method(w, "padded", _wcoj(j="single", fuse=True)))
    add("wcoj_hidden_w4b", "w4b", method("w4b", "hidden", _wcoj(j="single")))
    add("wcoj_pair_hidden_w4b", "w4b", method("w4b", "hidden", _wcoj(j="pair")))
    add("wcoj_fused_hidden_w4b", "w4b", method("w4b", "hidden", _wcoj(j="single", fuse=True)))
    for w in ("w4", "w4b", "w7u", "w8", "w9", "w14", "w17", "w18"):
        add(f"cover_join_{w}", w, method(w, "padded", lambda work, held, limit: cover_join(work.query, held)))
    add("cover_join_all_w4b", "w4b", method("w4b", "padded", lambda work, held, limit: cover_join(work.query, held, "all")))
    add("cover_join_hidden_w4b", "w4b", method("w4b", "hidden", lambda work, held, limit: cover_join(work.query, held)))
    add("decomposed_hidden_w14", "w14", method("w14", "hidden", _decomposed(lambda held: held["C"].rows * 5)))
    add("decomposed_hidden_w4b", "w4b", method("w4b", "hidden", _decomposed(lambda held: held["R3"].rows * 5)))
    add("decomposed_w5", "w5", method("w5", "padded", _decomposed("keys")))
    add("decomposed_w6", "w6", method("w6", "padded", _decomposed("keys")))
    add("decomposed_w7", "w7", method("w7", "padded", _decomposed(lambda held: held["L"].rows)))
    add("decomposed_w8", "w8", method("w8", "padded", _decomposed("exact")))
    add("decomposed_w12", "w12", method("w12", "padded", _decomposed(lambda held: held["R1"].rows * 2)))
    add("decomposed_w13", "w13", method("w13", "padded", _decomposed("exact")))
    add("decomposed_w9", "w9", method("w9", "padded", _decomposed(lambda held: held["R4"].rows)))
    for w in ("w14", "w15a", "w15b", "w21"):
        add(f"bounded_join_{w}", w, method(w, "padded", _two))
    for w in ("w14", "w15a", "w15b"):
        add(f"bounded_join_hidden_{w}", w, method(w, "hidden", _two))
    for w in ("w14", "w18", "w22"):
        add(f"nested_loop_{w}", w, method(w, "padded", lambda work, held, limit: nested_loop(*held.values())))
        add(f"nested_loop_tiled_{w}", w, method(w, "padded", lambda work, held, limit: nested_loop(*held.values(), tiling="recursive", tile=1 << 16)))
    for w in ("w17", "w18"):
        add(f"nested_loop_hidden_{w}", w, method(w, "hidden", lambda work, held, limit: _loops(list(held.values()), "flat")))
        add(f"nested_loop_tiled_hidden_{w}", w, method(w, "hidden", lambda work, held, limit: _loops(list(held.values()), "recursive")))
    for w in ("w1", "w2", "w3", "w4"):
        add(f"plain_choice_{w}", w, plain(w, lambda work, f: baselines.triangle_choice_plain(f["R1"], f["R2"], f["R3"])))
        add(f"plain_delay_{w}", w, plain(w, lambda work, f: baselines.triangle_delay_plain(f["R1"], f["R2"], f["R3"])))
    for w in ("w1", "w7", "w8b", "w10", "w11"):
        add(f"plain_recursive_{w}", w, plain(w, lambda work, f: baselines.recursive_plain(work.query, f)))
    for w in ("w1", "w7", "w8", "w9", "w11", "w12", "w13"):
        add(f"plain_catalyst_{w}", w, plain(w, lambda work, f: baselines.catalyst(work.query, f, work.keys)))
    for w in ("w5", "w6"):
        add(f"plain_acyclic_{w}", w, plain(w, lambda work, f: baselines.acyclic_plain(work.query, f)))
    add("plain_sort_merge_w14", "w14", plain("w14", lambda work, f: baselines.sort_merge(f["C"], f["S"])))
    return queries, oracles


def _loops(tables: list[PaddedTable], tiling: str) -> PaddedTable:
    """Nested loops over all relations, one after the other."""
    out = tables[0]
    for t in tables[1:]:
        out = nested_loop(out, t, tiling=tiling, tile=256).hold()
    return out


CORE_QUERIES, CORE_ORACLES = build()
