"""Nearest neighbours by inner product: inverted lists and an adaptive scan over dimensions.

One more component makes all vectors equally long, which turns the largest inner product into the
smallest distance. Vectors are rotated by a random orthogonal matrix and scanned in blocks of columns: after each
block the partial distance, scaled to all dimensions, is tested against the best so far, and a
candidate that is too far with high confidence is abandoned. Survivors are scored exactly, in double
precision, on the original vectors.

Lists come from k-means on a bounded sample; every row is in a list. The number of probed lists is tuned on that sample, whose
vectors in these lists also give each query its first limit; results come from the scan of the lists alone. A query that
finds too few there scans all lists without abandoning. Equal vectors are one class with its RESULTS + 1 smallest
ids, which is all that can ever be among the results. Large lists are dealt in blocks of vectors and of queries, so no
task holds a whole list.

Defined results: null vectors, zero vectors, those with null or non-finite components, of another length than
most, or with a null id take no part; ties of score fall to the smaller id; rows that repeat an id and a vector count
once, and of different vectors of one id only that with the least digest takes part; with fewer candidates than asked, all
are returned; an empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, replace

import numpy as np
import pyarrow as pa
from pyspark import Broadcast
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from obljoin.llm.common import attach, saved, trimmed

RESULTS = 20
#: The sample for lists, thresholds and tuning; a bound in rows.
SAMPLE = 16_000
LIST_ROWS = 2048
FEWEST_LISTS = 8
MOST_LISTS = 4096
BLOCK_ROWS = 4096
COLUMN_BLOCK = 16
#: Standard errors a partial distance must lie beyond the threshold; larger is safer and slower.
CONFIDENCE = 2.1
#: Recall that the sample must show for the number of probed lists.
TUNED_RECALL = 0.97


def usable(vector: Column) -> Column:
    fine = F.forall(vector, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf")))
    return vector.isNotNull() & F.coalesce(fine, F.lit(False)) & F.exists(vector, lambda x: x != 0)


@dataclass(frozen=True)
class Index:
    """Everything a task needs; its size is bounded by the sample and the number of lists."""

    longest: float  # squared norm of the longest vector
    rotation: np.ndarray
    centres: np.ndarray  # rotated
    sample: np.ndarray  # original
    sample_list: np.ndarray  # the list of each vector of the sample
    probes: int

    def lengthened(self, rows: np.ndarray) -> np.ndarray:
        rest = np.sqrt(np.maximum(self.longest - np.einsum("nd,nd->n", rows, rows), 0))
        return np.concatenate([rows, rest[:, None]], axis=1)

    def rotated(self, rows: np.ndarray, queries: bool = False) -> np.ndarray:
        wide = np.concatenate([rows, np.zeros((len(rows), 1))], axis=1) if queries else self.lengthened(rows)
        return (wide @ self.rotation).astype(np.float32)

    def to_centres(self, rotated: np.ndarray) -> np.ndarray:
        return np.einsum("nd,nd->n", self.centres, self.centres)[None] - 2 * rotated @ self.centres.T


def build(rows: np.ndarray, longest: float, total: int, seed: int = 5, rounds: int = 10) -> Index:
    rng = np.random.default_rng(seed)
    width = rows.shape[1] + 1
    rotation = np.linalg.qr(rng.normal(size=(width, width)))[0]
    index = Index(longest, rotation, np.zeros((0, width), np.float32), rows, np.zeros(0, np.int64), 1)
    points = index.rotated(rows)
    lists = int(np.clip(total // LIST_ROWS, FEWEST_LISTS, MOST_LISTS))
    lists = min(lists, len(rows))
    centres = points[rng.choice(len(points), lists, replace=False)].copy()
    for _ in range(rounds):
        nearest = replace(index, centres=centres).to_centres(points).argmin(axis=1)
        sums = np.zeros_like(centres)
        np.add.at(sums, nearest, points)
        count = np.bincount(nearest, minlength=lists)
        centres = np.where(count[:, None] > 0, sums / np.maximum(count, 1)[:, None], centres).astype(np.float32)
    index = replace(index, centres=centres)
    nearest = index.to_centres(points).argmin(axis=1)
    asked = rng.choice(len(rows), min(200, len(rows)), replace=False)
    products = rows[asked] @ rows.T
    products[np.arange(len(asked)), asked] = -np.inf
    k = min(RESULTS, len(rows) - 1)
    probes = lists
    if k and lists > 1:
        best = np.argpartition(-products, k - 1, axis=1)[:, :k]
        place = index.to_centres(index.rotated(rows[asked], True)).argsort(axis=1).argsort(axis=1)
        needed = np.sort(np.take_along_axis(place, nearest[best], axis=1).ravel())
        probes = int(needed[min(len(needed) - 1, int(np.ceil(TUNED_RECALL * len(needed))))]) + 1
    return replace(index, sample_list=nearest, probes=probes)


def _best(query: np.ndarray, product: np.ndarray, k: int) -> np.ndarray:
    """Which rows, sorted by query and falling product, are among the best k of their query, ties with the last one included."""
    if not len(query):
        return np.zeros(0, bool)
    at = np.arange(len(query))
    rank = at - np.searchsorted(query, query)
    return (rank < k) | (product >= product[np.minimum(at - rank + k - 1, len(query) - 1)])


def scan(index: Index, vectors: np.ndarray, queries: np.ndarray, limits: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, int]:
    """(query, vector, product) of the best k of each query, and how many components were read.

    ``limits`` holds a squared distance that k candidates of each query are known to reach.
    """
    points, asked = index.rotated(vectors), index.rotated(queries, True)
    width, limits = points.shape[1], limits.astype(np.float32).copy()
    edges = [*range(0, width, COLUMN_BLOCK), width]
    found_q, found_v, found_p, read = [], [], [], 0
    for a in range(0, len(queries), 256):
        some = asked[a : a + 256]
        kept_q, kept_v, kept_p = np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0)
        for b in range(0, len(points), 1024):
            part = points[b : b + 1024]
            lo, hi = edges[0], edges[1]
            near = np.einsum("nd,nd->n", some[:, :hi], some[:, :hi])[:, None] + np.einsum("nd,nd->n", part[:, :hi], part[:, :hi])[None] - 2 * some[:, :hi] @ part[:, :hi].T
            read += near.size * hi
            limit = limits[a : a + 256]
            bound = lambda d: (limit * (d / width) * (1 + CONFIDENCE / np.sqrt(d)) ** 2) if d < width else limit * (1 + 1e-4) + 1e-6  # noqa: B023, E731
            q, v = np.nonzero(near <= bound(hi)[:, None])
            far = near[q, v]
            for lo, hi in zip(edges[1:], edges[2:], strict=False):
                gap = some[q, lo:hi] - part[v, lo:hi]
                read += gap.size
                far = far + np.einsum("nd,nd->n", gap, gap)
                alive = far <= bound(hi)[q]
                q, v, far = q[alive], v[alive], far[alive]
            exact = np.einsum("nd,nd->n", queries[a + q], vectors[b + v])
            kept_q, kept_v, kept_p = np.concatenate([kept_q, q]), np.concatenate([kept_v, b + v]), np.concatenate([kept_p, exact])
            order = np.lexsort((-kept_p, kept_q))
            kept_q, kept_v, kept_p = kept_q[order], kept_v[order], kept_p[order]
            rank = np.arange(len(kept_q)) - np.searchsorted(kept_q, kept_q)
            last = np.flatnonzero(rank == k - 1)
            norms = np.einsum("nd,nd->n", queries[a + kept_q[last]], queries[a + kept_q[last]])
            limits[a + kept_q[last]] = np.minimum(limits[a + kept_q[last]], norms + index.longest - 2 * kept_p[last])
            if b + 1024 < len(points):
                best = _best(kept_q, kept_p, k)
                kept_q, kept_v, kept_p = kept_q[best], kept_v[best], kept_p[best]
        found_q.append(a + kept_q)
        found_v.append(kept_v)
        found_p.append(kept_p)
    q, v, p = (np.concatenate(x) if x else np.zeros(0) for x in (found_q, found_v, found_p))
    keep = _best(q, p, k)
    return q[keep].astype(np.int64), v[keep].astype(np.int64), p[keep], read


def _matrix(column: pa.Array) -> np.ndarray:
    column = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    return column.flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(len(column), -1)


def search(table: DataFrame, is_query: Column, vec_id: str = "vec_id", embedding: str = "embedding", k: int = RESULTS) -> DataFrame:
    """query_id, rank, vec_id, score: the k candidates of largest inner product for every row where ``is_query`` holds."""
    spark = table.sparkSession
    schema = "query_id long, rank int, vec_id long, score double"
    rows = table.select(F.col(vec_id).cast("long").alias("id"), F.col(embedding).cast("array<double>").alias("v"), F.coalesce(is_query, F.lit(False)).alias("asks")).where(F.col("id").isNotNull() & usable(F.col("v")))
    sizes = rows.groupBy(F.size("v").alias("n")).count().orderBy(F.desc("count"), "n").first()
    if sizes is None:
        return spark.createDataFrame([], schema)
    rows = saved(rows.where(F.size("v") == sizes.n).withColumn("class", F.sha2(F.concat_ws(",", F.col("v").cast("array<string>")), 256)))
    owners = rows.groupBy("id").agg(F.min(F.struct("class", ~F.col("asks"))).alias("one")).select("id", "one.class", (~F.col("one.col2")).alias("asks"))
    owners = saved(owners)
    few = Window.partitionBy("class", F.pmod(F.xxhash64("id"), F.lit(64))).orderBy("id")
    fewer = Window.partitionBy("class").orderBy("id")
    ids = owners.select("class", "id").withColumn("n", F.row_number().over(few)).where(F.col("n") <= k + 1)
    ids = ids.withColumn("n", F.row_number().over(fewer)).where(F.col("n") <= k + 1).groupBy("class").agg(F.sort_array(F.collect_list("id")).alias("ids"))
    asks = owners.groupBy("class").agg(F.sum(F.col("asks").cast("int")).alias("n_asks"))
    bodies = rows.groupBy("class").agg(F.first("v").alias("v"))
    classes = saved(bodies.join(ids, "class").join(asks, "class"))
    norm = F.aggregate("v", F.lit(0.0), lambda s, x: s + x * x)
    total, longest = classes.agg(F.count("*"), F.max(norm)).first()
    taken = classes.orderBy(F.xxhash64("class"), "class").limit(SAMPLE).select("v").toArrow()
    index = build(_matrix(taken["v"]), float(longest), total)
    held = spark.sparkContext.broadcast(index)

    def place(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            near = held.value.to_centres(held.value.rotated(_matrix(batch.column(1)))).argmin(axis=1) if len(batch) else np.zeros(0, np.int64)
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(near.astype(np.int32))], names=["class", "v", "list"])

    def probe(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        index = held.value
        for batch in batches:
            for a in range(0, len(batch), 512):
                part = batch.slice(a, 512)
                v = _matrix(part.column(1))
                lists = np.argsort(index.to_centres(index.rotated(v, True)), axis=1, kind="stable")[:, : index.probes].astype(np.int32)
                probed = np.zeros((len(v), len(index.centres)), bool)
                np.put_along_axis(probed, lists, True, axis=1)
                near = np.where(probed[:, index.sample_list], v @ index.sample.T, -np.inf)
                worst = np.partition(near, -(k + 1), axis=1)[:, -(k + 1)] if near.shape[1] > k else np.full(len(v), -np.inf)
                limit = np.einsum("nd,nd->n", v, v) + index.longest - 2 * worst  # infinite where the sample has too few
                yield pa.RecordBatch.from_arrays([part.column(0), part.column(1), pa.array(limit), pa.array(lists.tolist(), pa.list_(pa.int32()))], names=["class", "v", "reach", "lists"])

    placed = saved(classes.select("class", "v").mapInArrow(trimmed(place), "class string, v array<double>, list int"))
    asking = classes.where("n_asks > 0").select("class", "v")
    probed = saved(asking.mapInArrow(trimmed(probe), "class string, v array<double>, reach double, lists array<int>"))
    found = saved(_scanned(placed, probed, held, k))
    counts = found.groupBy("class").agg(F.count("*").alias("n_found"))
    short = saved(asking.join(counts, "class", "left").where(F.coalesce("n_found", F.lit(0)) < min(k + 1, total)).select("class", "v"))
    if short.head(1):
        everywhere = short.withColumns({"reach": F.lit(float("inf")), "lists": F.sequence(F.lit(0), F.lit(len(index.centres) - 1))})
        found = found.join(short.select("class"), "class", "left_anti").unionByName(_scanned(placed, everywhere, held, k))
    named = found.join(classes.select(F.col("class").alias("other"), "ids"), "other").withColumn("first", F.element_at("ids", 1))
    best = Window.partitionBy("class").orderBy(F.desc("score"), "first")
    top = named.withColumn("n", F.row_number().over(best)).where(F.col("n") <= k + 1).select("class", "score", F.explode("ids").alias("vec_id"))
    each = Window.partitionBy("class").orderBy(F.desc("score"), "vec_id")
    top = top.withColumn("n", F.row_number().over(each)).where(F.col("n") <= k + 1)
    packed = top.groupBy("class").agg(F.array_sort(F.collect_list(F.struct("n", "vec_id", "score"))).alias("found"))
    members = owners.where("asks").select("class", F.col("id").alias("query_id"))
    sized = members.groupBy("class").agg(F.count("*").alias("n_members")).join(packed, "class")
    answers = attach(members, saved(sized), ["class"], "n_members")
    own = F.filter("found", lambda x: x["vec_id"] != F.col("query_id"))
    out = answers.select("query_id", F.posexplode(F.slice(own, 1, k)).alias("at", "hit"))
    return out.select("query_id", (F.col("at") + 1).cast("int").alias("rank"), "hit.vec_id", "hit.score")


def _scanned(placed: DataFrame, probed: DataFrame, held: Broadcast, k: int) -> DataFrame:
    """class, other, score: what each query finds in its lists, k + 1 from each block of a list."""
    wide = probed.select("class", "v", "reach", F.explode("lists").alias("list"))
    shapes = placed.groupBy("list").agg(F.ceil(F.count("*") / BLOCK_ROWS).cast("int").alias("nv")).join(
        wide.groupBy("list").agg(F.ceil(F.count("*") / BLOCK_ROWS).cast("int").alias("nq")), "list"
    )
    shapes = F.broadcast(shapes)  # a row per list, MOST_LISTS at most
    deal = lambda n: F.pmod(F.xxhash64("class"), F.col(n)).cast("int")
    spread = lambda n: F.explode(F.sequence(F.lit(0), F.col(n) - 1))
    left = placed.join(shapes, "list").withColumn("bv", deal("nv")).withColumn("bq", spread("nq")).select("list", "bv", "bq", "class", "v")
    right = wide.join(shapes, "list").withColumn("bq", deal("nq")).withColumn("bv", spread("nv")).select("list", "bv", "bq", "class", "v", "reach")

    def meet(vectors: pa.Table, queries: pa.Table) -> pa.Table:
        names = {"class": pa.string(), "other": pa.string(), "score": pa.float64()}
        if not len(vectors) or not len(queries):
            return pa.table({n: pa.array([], t) for n, t in names.items()})
        q, v, p, _ = scan(held.value, _matrix(vectors["v"]), _matrix(queries["v"]), queries["reach"].to_numpy(), k + 1)
        return pa.table({"class": queries["class"].take(pa.array(q)), "other": vectors["class"].take(pa.array(v)), "score": pa.array(p)})

    keys = ["list", "bv", "bq"]
    return left.groupBy(*keys).cogroup(right.groupBy(*keys)).applyInArrow(meet, "class string, other string, score double")


def recall(found: DataFrame, exact: DataFrame) -> DataFrame:
    """The share of exact results that were found: one row with recall, n_exact."""
    hit = exact.join(found.select("query_id", "vec_id", F.lit(1).alias("hit")), ["query_id", "vec_id"], "left")
    return hit.agg(F.avg(F.coalesce("hit", F.lit(0))).alias("recall"), F.count("*").alias("n_exact"))
