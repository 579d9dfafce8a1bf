"""SimHash near-duplicates, linked through a segment-popcount embedding.

Fingerprints are cut into segments and mapped to the vector of bit counts per segment. The Manhattan distance of two
vectors never exceeds the Hamming distance of the fingerprints, and integer vectors at distance two or
less have a common neighbour at distance one. So every distinct fingerprint enters the grid cells
of its vector and of all neighbours, pairs are met in shared cells, and a pair is verified bit by bit.
A cell with more than CELL_MOST fingerprints emits no pairs: its fingerprints go through the embedding
with one-bit segments, where a cell can hold 65 fingerprints at most and all of them are truly linked, so
a star per cell is exact and linear.

Defined results: null or wordless text has fingerprint zero and is linked like any other; equal rows share
a fingerprint; a null ``doc_id`` keeps its row; an empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import repeat

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from xxhash import xxh64_intdigest

from obljoin.llm.common import BLANK, LOWER, attach, blocks, content_key, keep_rows, saved, trimmed, utf8
from obljoin.llm.components import connected_components

SEED = 42
MAX_BITS = 2
#: Bits per segment of the coarse embedding.
SEGMENT = 4
CELL_MOST = 16
BLOCK_BYTES = 512 << 10
HASHED_AT_ONCE = 50_000

_BITS = np.unpackbits(np.arange(256, dtype=np.uint8)[:, None], axis=1, bitorder="little").astype(np.int64)
_LANES = np.arange(8) * 256


def word_spans(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Texts with words parted by single spaces: bytes, word starts, word ends, and each text's first word (with the total last)."""
    blank = BLANK[data]
    opens = offsets[:-1][np.diff(offsets) > 0]
    behind = np.empty(len(data), bool)  # does a word of the same text end just before?
    behind[1:] = ~blank[:-1]
    behind[opens] = False
    keep = ~blank | behind
    place = np.concatenate([[0], np.cumsum(keep)])
    held = np.where(blank, np.uint8(32), data)[keep]
    starts = place[np.flatnonzero(~blank & ~behind)]
    last = np.empty(len(data), bool)
    last[:-1] = blank[1:]
    last[offsets[1:][np.diff(offsets) > 0] - 1] = True
    ends = place[np.flatnonzero(~blank & last) + 1]
    return held, starts, ends, np.searchsorted(starts, place[offsets])


def simhash_block(data: np.ndarray, offsets: np.ndarray, width: int) -> list[int]:
    """Unsigned fingerprints of whole lower-cased texts."""
    held, starts, ends, firsts = word_spans(data, offsets)
    raw, out = held.tobytes(), []
    for a, b in zip(firsts.tolist(), firsts.tolist()[1:], strict=False):
        span = min(width, b - a)
        n = b - a - span + 1 if span else 0
        counts = np.zeros(2048, np.int64)
        for i in range(0, n, HASHED_AT_ONCE):
            j = min(i + HASHED_AT_ONCE, n)
            pieces = [raw[x:y] for x, y in zip(starts[a + i : a + j].tolist(), ends[a + i + span - 1 : a + j + span - 1].tolist(), strict=True)]
            hashes = np.fromiter(map(xxh64_intdigest, pieces, repeat(SEED)), np.uint64, j - i)
            counts += np.bincount((hashes.view(np.uint8).reshape(-1, 8) + _LANES).ravel(), minlength=2048)
        ones = np.einsum("lv,vb->lb", counts.reshape(8, 256), _BITS).ravel()
        out.append(int.from_bytes(np.packbits(ones * 2 > n, bitorder="little").tobytes(), "little") if n else 0)
    return out


def fingerprints(docs: DataFrame, text: str = "text", doc_id: str = "doc_id", width: int = 3) -> DataFrame:
    """doc_id, content, fp long (the 64 bits, signed)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            data, offsets = utf8(batch.column(1))
            found = [f for a, b in blocks(offsets, BLOCK_BYTES) for f in simhash_block(LOWER[data[offsets[a] : offsets[b]]], offsets[a : b + 1] - offsets[a], width)]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(2), pa.array(np.array(found, np.uint64).view(np.int64))], names=["doc_id", "content", "fp"])

    chosen = docs.select(F.col(doc_id).cast("long").alias("doc_id"), F.col(text).cast("string").alias("text"), content_key(text).alias("content"))
    return chosen.mapInArrow(trimmed(run), "doc_id long, content long, fp long")


def cells(fp: Column, segment: int) -> Column:
    """The grid cells of a fingerprint: that of its vector of bit counts, and all at Manhattan distance one."""
    if segment == 1:
        return F.array(fp, *(fp.bitwiseXOR(F.lit(1 << k if k < 63 else -(1 << 63)).cast("long")) for k in range(64)))
    n, mask = 64 // segment, (1 << segment) - 1
    base = segment + 1
    counts = [F.bit_count(F.shiftrightunsigned(fp, k * segment).bitwiseAND(F.lit(mask).cast("long"))) for k in range(n)]
    home = sum((c * F.lit(base**k).cast("long") for k, c in enumerate(counts)), F.lit(0).cast("long"))
    near = [F.when(c < segment, home + F.lit(base**k).cast("long")) for k, c in enumerate(counts)]
    near += [F.when(c > 0, home - F.lit(base**k).cast("long")) for k, c in enumerate(counts)]
    return F.array_compact(F.array(home, *near))


def links(fps: DataFrame, max_bits: int = MAX_BITS, segment: int = SEGMENT, cell_most: int = CELL_MOST) -> DataFrame:
    """(a, b) links between distinct fingerprints ``fp`` that give all components at ``max_bits`` (0 to 2) differing bits."""
    if not 0 <= max_bits <= 2:
        raise ValueError("the grid meets pairs at two differing bits or fewer")
    met = fps.select("fp", F.explode(cells(F.col("fp"), segment)).alias("cell"))
    shared = saved(met.withColumn("n", F.count("*").over(Window.partitionBy("cell"))).where("n > 1"))
    few = shared.where(F.col("n") <= cell_most).groupBy("cell").agg(F.sort_array(F.collect_list("fp")).alias("fps"))
    pair = F.expr(
        f"flatten(transform(fps, (x, i) -> transform(filter(slice(fps, i + 2, size(fps)), y -> bit_count(x ^ y) <= {max_bits}), y -> struct(x as a, y as b))))"
    )
    exact = few.select(F.explode(pair).alias("pair")).select("pair.a", "pair.b").distinct()
    if max_bits < 2:  # a star would link fingerprints two bits apart
        crowd = shared.where(F.col("n") > cell_most).select("fp").distinct()
        near = crowd.select("fp", F.explode(cells(F.col("fp"), 1)).alias("other")) if max_bits else crowd.limit(0).select("fp", F.col("fp").alias("other"))
        found = near.join(crowd.select(F.col("fp").alias("other")), "other").select(F.col("fp").alias("a"), F.col("other").alias("b"))
        return exact.unionByName(found.where("a < b")).distinct()
    crowd = shared.where(F.col("n") > cell_most).select("fp").distinct()
    balls = crowd.select("fp", F.explode(cells(F.col("fp"), 1)).alias("cell")).groupBy("cell").agg(F.sort_array(F.collect_list("fp")).alias("fps"))
    stars = balls.where("size(fps) > 1").select(F.element_at("fps", 1).alias("a"), F.explode(F.expr("slice(fps, 2, 64)")).alias("b"))
    return exact.unionByName(stars).distinct()


def simhash_groups(docs: DataFrame, text: str = "text", doc_id: str = "doc_id", width: int = 3, max_bits: int = MAX_BITS) -> DataFrame:
    """One row per document: doc_id, content, fp, component_id (smallest doc_id reachable), keep (one row per component)."""
    found = saved(fingerprints(docs, text, doc_id, width).withColumn("row", F.monotonically_increasing_id()))
    distinct = saved(found.groupBy("fp").agg(F.count("*").alias("n_rows"), F.min(F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", "row")).alias("best")))
    roots = connected_components(links(distinct, max_bits))
    nodes = saved(distinct.join(roots, distinct.fp == roots.node).select("fp", "root", "best"))
    merged = saved(nodes.groupBy("root").agg(F.count("*").alias("n_nodes"), F.min("best").alias("first")))
    moved = attach(nodes, merged, ["root"], "n_nodes").select("fp", "first")
    groups = saved(distinct.join(moved, "fp", "left").select("fp", "n_rows", F.coalesce("first", "best").alias("first")))
    return attach(found, groups, ["fp"], "n_rows").select("doc_id", "content", "fp", F.col("first.doc_id").alias("component_id"), (F.col("first.row") == F.col("row")).alias("keep"))


def one_of_each(docs: DataFrame, text: str = "text", doc_id: str = "doc_id", width: int = 3, max_bits: int = MAX_BITS) -> DataFrame:
    """One row of each component (that of the smallest id), with all its columns."""
    return keep_rows(docs, saved(simhash_groups(docs, text, doc_id, width, max_bits)), F.col("keep"), text, doc_id)


def as_hex(fp: Column) -> Column:
    return F.lower(F.lpad(F.hex(fp), 16, "0"))
