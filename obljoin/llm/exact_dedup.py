"""Exact dedup by composable polynomial fingerprints.

A text is cut into chunks of CHUNK bytes, its first chunk being the short one. A chunk is a number in
base B modulo a prime; a block of texts is one exact matrix product with the powers of B. The hashes of
neighbouring pieces combine by shifting the left one by the right one's length, so a huge text needs no
sequential pass. Texts of equal fingerprint and length are then compared chunk by chunk; where a
chunk differs, the group is split by SHA-256.

Defined results: null text counts as empty; equal rows tie by an internal row number, so exactly one row
of a group stays; a null ``doc_id`` loses to any other; an empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from obljoin.llm.common import LOWER, attach, blocks, content_key, in_bitmap, keep_rows, key_bitmap, saved, trimmed, utf8

PRIME = 2**31 - 1
#: Bases of the four lanes; together 124 bits.
BASES = (1_103_515_245, 1_597_463_007, 742_938_285, 2_027_808_485)
CHUNK = 1024
BLOCK_BYTES = 4 << 20
COMPARE_BYTES = 64 << 10
FILTER_BITS = 24


def power_table(base: int, count: int, prime: int = PRIME) -> np.ndarray:
    out = np.ones(max(count, 1), dtype=np.int64)
    done = 1
    while done < len(out):  # doubling: each step multiplies all known powers by one more
        take = min(done, len(out) - done)
        out[done : done + take] = out[:take] * pow(base, done, prime) % prime
        done += take
    return out


def combine(left: int, right: int, right_length: int, base: int, prime: int = PRIME) -> int:
    """The hash of two neighbouring pieces from the hashes of each."""
    return (left * pow(base, right_length, prime) + right) % prime


def fingerprints(data: np.ndarray, offsets: np.ndarray, bases: tuple[int, ...] = BASES, prime: int = PRIME) -> np.ndarray:
    """One row of lane hashes per text."""
    lengths = np.diff(offsets)
    counts = -(-lengths // CHUNK)
    out = np.zeros((len(lengths), len(bases)), dtype=np.int64)
    weights = np.stack([power_table(b, CHUNK, prime)[::-1] for b in bases], axis=1).astype(np.float64)
    some = np.flatnonzero(counts)
    if not len(some):
        return out
    ends = np.cumsum(counts[some]) * CHUNK
    padded = np.zeros(int(ends[-1]), dtype=np.uint8)
    for end, row in zip(ends.tolist(), some.tolist(), strict=True):
        padded[end - int(lengths[row]) : end] = data[offsets[row] : offsets[row + 1]]
    rows = padded.reshape(-1, CHUNK)
    step = BLOCK_BYTES // CHUNK
    # exact: products below 2**39, sums of 1024 of them below 2**53
    hashes = np.concatenate([np.mod(rows[i : i + step].astype(np.float64) @ weights, prime) for i in range(0, len(rows), step)]).astype(np.int64)
    first = ends // CHUNK - counts[some]
    behind = np.repeat(ends // CHUNK, counts[some]) - 1 - np.arange(len(rows))
    for lane, base in enumerate(bases):
        shift = power_table(pow(base, CHUNK, prime), int(counts.max()), prime)
        out[some, lane] = np.add.reduceat(hashes[:, lane] * shift[behind] % prime, first) % prime
    return out


def _keys(lanes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    return lanes[:, 0] << 31 | lanes[:, 1], lanes[:, 2] << 31 | lanes[:, 3]


def digests(docs: DataFrame, text: str = "text", doc_id: str = "doc_id", prime: int = PRIME) -> DataFrame:
    """doc_id, content, hi, lo (fingerprint), n_bytes and text_sha256 of every normalised text."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            data, offsets = utf8(batch.column(1))
            data = LOWER[data]
            lanes = [fingerprints(data[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a], prime=prime) for a, b in blocks(offsets, BLOCK_BYTES)]
            hi, lo = _keys(np.concatenate(lanes)) if lanes else (np.zeros(0, np.int64),) * 2
            raw = data.tobytes()
            at = offsets.tolist()
            shas = [hashlib.sha256(raw[a:b]).hexdigest() for a, b in zip(at, at[1:], strict=False)]
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), batch.column(2), pa.array(hi), pa.array(lo), pa.array(np.diff(offsets)), pa.array(shas, pa.string())],
                names=["doc_id", "content", "hi", "lo", "n_bytes", "text_sha256"],
            )

    chosen = docs.select(F.col(doc_id).cast("long").alias("doc_id"), F.col(text).cast("string").alias("text"), content_key(text).alias("content"))
    return chosen.mapInArrow(trimmed(run), "doc_id long, content long, hi long, lo long, n_bytes long, text_sha256 string")


def differing(docs: DataFrame, groups: DataFrame, text: str = "text", prime: int = PRIME) -> DataFrame:
    """Keys of those groups whose members are not all alike, found chunk by chunk.

    Every map task folds equal chunks of a group before anything is shuffled, so a group of any size sends one
    chunk per task. Only texts that pass a filter of fixed size are cut at all.
    """
    spark = docs.sparkSession
    wanted = spark.sparkContext.broadcast(key_bitmap(groups.where("group_size > 1"), F.col("lo"), FILTER_BITS))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            data, offsets = utf8(batch.column(0))
            data = LOWER[data]
            for a, b in blocks(offsets, BLOCK_BYTES):
                part = offsets[a : b + 1]
                hi, lo = _keys(fingerprints(data[part[0] : part[-1]], part - part[0], prime=prime))
                rows = [
                    (int(hi[i]), int(lo[i]), int(part[i + 1] - part[i]), n, data[c : min(c + COMPARE_BYTES, part[i + 1])].tobytes())
                    for i in np.flatnonzero(in_bitmap(wanted.value, lo)).tolist()
                    for n, c in enumerate(range(int(part[i]), int(part[i + 1]), COMPARE_BYTES))
                ]
                if rows:
                    yield pa.RecordBatch.from_arrays(
                        [pa.array(x, t) for x, t in zip(zip(*rows, strict=True), (pa.int64(), pa.int64(), pa.int64(), pa.int32(), pa.binary()), strict=True)],
                        names=["hi", "lo", "n_bytes", "part", "piece"],
                    )

    cut = docs.select(F.col(text).cast("string").alias("text")).mapInArrow(trimmed(run), "hi long, lo long, n_bytes long, part int, piece binary")
    folded = cut.groupBy("hi", "lo", "n_bytes", "part").agg(F.min("piece").alias("least"), F.max("piece").alias("most"))
    return folded.where("least <> most").select("hi", "lo", "n_bytes").distinct()


def exact_dedup(docs: DataFrame, text: str = "text", doc_id: str = "doc_id", prime: int = PRIME) -> DataFrame:
    """One row per document: doc_id, keep_id, group_size, kept, text_sha256, n_bytes, content.

    ``prime`` may be made tiny in tests, to force fingerprints that collide.
    """
    found = saved(digests(docs, text, doc_id, prime).withColumn("row", F.monotonically_increasing_id()))
    keys = ["hi", "lo", "n_bytes"]
    groups = saved(found.groupBy(*keys).agg(F.count("*").alias("group_size")))
    unlike = saved(differing(docs, groups, text, prime))
    if unlike.head(1):  # different texts of one fingerprint: as good as never, but then they must part
        odd = unlike.withColumn("odd", F.lit(True))
        found = saved(found.join(odd, keys, "left").withColumn("split", F.when(F.col("odd"), F.col("text_sha256")).otherwise(F.lit(""))).drop("odd"))
    else:
        found = found.withColumn("split", F.lit(""))
    keys = [*keys, "split"]
    best = found.groupBy(*keys).agg(F.count("*").alias("group_size"), F.max(F.struct("doc_id", "row")).alias("best"))
    joined = attach(found, saved(best), keys, "group_size")
    return joined.select(
        "doc_id", F.col("best.doc_id").alias("keep_id"), "group_size", (F.col("row") == F.col("best.row")).alias("kept"), "text_sha256", "n_bytes", "content"
    )


def deduplicated(docs: DataFrame, text: str = "text", doc_id: str = "doc_id") -> DataFrame:
    """The rows that stay, with all their columns."""
    return keep_rows(docs, saved(exact_dedup(docs, text, doc_id)), F.col("kept"), text, doc_id)
