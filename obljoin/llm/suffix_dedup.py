"""Removal of repeated byte strings with suffix arrays.

Every string of LENGTH bytes ("window") is judged by its anchor: the leftmost of its GRAM-byte pieces with the least
hash. The windows of one anchor lie side by side and form a context; equal windows have equal anchors at equal places, so
only contexts whose anchor occurs more than once in the corpus can hold a repeated window. Equal contexts are
collapsed to one with a multiplicity. The rest are dealt to shards by anchor; a shard gets a suffix array
by Larsson-Sadakane refinement (only groups that are still tied are sorted again, with doubled depth) and Kasai's
common prefixes, run side by side over all contexts. Runs with a common prefix of LENGTH are classes of
equal windows, and a class of multiplicity two or more is repeated. An anchor with very many different
contexts is split over several shards; the sorted digests of their different windows, repeated or not, are then
merged by binary search, two shards at a time.

Texts move only if they may hold something repeated, once per distinct text. Filters of fixed size spare traffic; joins
after them are exact.

Defined results: null counts as empty; texts under LENGTH bytes lose nothing; of equal texts all lose the same; a text of any
length is cut in pieces that overlap by LENGTH - 1, so each window is judged once; an empty table gives no rows; other
columns are ignored.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from functools import cache

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from obljoin.llm.common import attach, blocks, in_bitmap, key_bitmap, saved, trimmed, utf8

LENGTH = 200
GRAM = 64
BLOCK_BYTES = 512 << 10
#: Longer texts are judged in pieces of so many windows.
PIECE = 4 << 20
FILTER_BITS = 26
#: Different contexts of one anchor in a shard; more are split.
SHARD_CONTEXTS = 4096
SHARD_BYTES = 1 << 20

_BASES = (0x9E3779B97F4A7C15, 0xD1342543DE82EF95)


@cache
def _tables() -> tuple[np.ndarray, ...]:
    rng = np.random.default_rng(2024)
    return tuple(rng.integers(1, 1 << 63, 256, dtype=np.uint64) * np.uint64(2) + np.uint64(1) for _ in _BASES)


@cache
def _powers(lane: int, size: int) -> tuple[np.ndarray, np.ndarray]:
    out = []
    for base in (_BASES[lane], pow(_BASES[lane], -1, 1 << 64)):
        row = np.full(size, base, np.uint64)
        row[0] = 1
        out.append(np.multiply.accumulate(row))
    return out[0], out[1]


class Hashes:
    """Hashes of any substring of a block, from running sums modulo 2**64."""

    def __init__(self, data: np.ndarray, lanes: int = 2) -> None:
        size = 1 << max(12, int(len(data)).bit_length())
        self.sums, self.back = [], []
        for lane, values in enumerate(_tables()[:lanes]):
            up, down = _powers(lane, size)
            self.sums.append(np.concatenate([np.zeros(1, np.uint64), np.cumsum(values[data] * up[: len(data)], dtype=np.uint64)]))
            self.back.append(down)

    def of(self, lane: int, start: np.ndarray, end: np.ndarray) -> np.ndarray:
        return mixed((self.sums[lane][end] - self.sums[lane][start]) * self.back[lane][start])

    def grams(self, width: int) -> np.ndarray:
        n = max(len(self.sums[0]) - width, 0)
        return mixed((self.sums[0][width : width + n] - self.sums[0][:n]) * self.back[0][:n])


def mixed(value: np.ndarray) -> np.ndarray:
    value = value ^ (value >> np.uint64(31))
    value = value * np.uint64(0x7FB5D329728EA185)
    return value ^ (value >> np.uint64(29))


def sliding_least(keys: np.ndarray, width: int) -> np.ndarray:
    """The least of every ``width`` neighbours, from least values to either side of fixed cuts."""
    n = len(keys) - width + 1
    full = np.full(-(-len(keys) // width) * width, np.iinfo(np.uint64).max, np.uint64)
    full[: len(keys)] = keys
    rows = full.reshape(-1, width)
    right = np.minimum.accumulate(rows, axis=1).ravel()
    left = np.ascontiguousarray(np.minimum.accumulate(rows[:, ::-1], axis=1)[:, ::-1]).ravel()
    return np.minimum(left[:n], right[width - 1 : width - 1 + n])


def contexts(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, Hashes]:
    """For texts laid end to end: first and last window of each context, its anchor's hash, its text."""
    none = np.zeros(0, np.int64)
    hashes = Hashes(data)
    if len(data) < LENGTH:
        return none, none, none.astype(np.uint64), none, hashes
    grams = hashes.grams(GRAM)
    place = np.arange(len(grams), dtype=np.uint64)
    keys = (grams & ~np.uint64((1 << 24) - 1)) | place
    least = sliding_least(keys, LENGTH - GRAM + 1)
    lengths = np.maximum(np.diff(offsets) - LENGTH + 1, 0)
    windows = np.repeat(offsets[:-1] - (np.cumsum(lengths) - lengths), lengths) + np.arange(int(lengths.sum()))
    anchor = (least[windows] & np.uint64((1 << 24) - 1)).astype(np.int64)
    text = np.repeat(np.arange(len(lengths)), lengths)
    new = np.ones(len(windows), bool)
    new[1:] = (anchor[1:] != anchor[:-1]) | (text[1:] != text[:-1])
    first = np.flatnonzero(new)
    last = np.concatenate([first[1:], [len(windows)]]).astype(np.int64) - 1 if len(first) else first
    return windows[first], windows[last], grams[anchor[first]], text[first], hashes


def _pieces(data: np.ndarray, offsets: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]]:
    """Blocks for ``contexts``: bytes, offsets, the row of each text, and where in it the text begins."""
    for a, b in blocks(offsets, BLOCK_BYTES):
        size = int(offsets[b] - offsets[a])
        if b - a > 1 or size <= PIECE + LENGTH - 1:
            yield data[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a], np.arange(a, b), np.zeros(b - a, np.int64)
        else:
            for start in range(0, size - LENGTH + 1, PIECE):
                held = data[offsets[a] + start : min(offsets[a] + start + PIECE + LENGTH - 1, offsets[b])]
                yield held, np.array([0, len(held)]), np.array([a]), np.array([start])


def class_names(data: np.ndarray, offsets: np.ndarray) -> list[bytes]:
    """What texts are told apart by: the first half of their SHA-256."""
    raw, at = data.tobytes(), offsets.tolist()
    return [hashlib.sha256(raw[a:b]).digest()[:16] for a, b in zip(at, at[1:], strict=False)]


def _texts(docs: DataFrame, text: str) -> DataFrame:
    return docs.select(F.col(text).cast("string").alias("text"))


def document_classes(docs: DataFrame, text: str, doc_id: str) -> DataFrame:
    """doc_id, sha (SHA-256 of the text, hex), class (its first half), n_bytes."""
    body = F.coalesce(F.col(text).cast("string"), F.lit(""))
    rows = docs.select(F.col(doc_id).alias("doc_id"), F.sha2(body, 256).alias("sha"), F.octet_length(body).cast("long").alias("n_bytes"))
    return rows.withColumn("class", F.unhex(F.substring("sha", 1, 32)))


def anchor_counts(docs: DataFrame, text: str) -> DataFrame:
    """h, n: how often each anchor hash occurs, added up within a batch before anything is shuffled."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            data, offsets = utf8(batch.column(0))
            found = [contexts(part, at)[2] for part, at, _, _ in _pieces(data, offsets)]
            h, n = np.unique(np.concatenate(found) if found else np.zeros(0, np.uint64), return_counts=True)
            yield pa.RecordBatch.from_arrays([pa.array(h.view(np.int64)), pa.array(n)], names=["h", "n"])

    return _texts(docs, text).mapInArrow(trimmed(run), "h long, n long").groupBy("h").agg(F.sum("n").alias("n"))


_CONTEXT = "h long, c1 long, c2 long, size int"
_CONTEXT_KEYS = ["h", "c1", "c2", "size"]


def occurrences(docs: DataFrame, text: str, wanted: np.ndarray) -> DataFrame:
    """Contexts whose anchor passes the filter: their keys, class, start, and how many texts of the class."""
    held = docs.sparkSession.sparkContext.broadcast(wanted)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            data, offsets = utf8(batch.column(0))
            for part, at, rows, begin in _pieces(data, offsets):
                first, last, h, owner, hashes = contexts(part, at)
                some = np.flatnonzero(in_bitmap(held.value, h.view(np.int64)))
                if not len(some):
                    continue
                first, last, h, owner = first[some], last[some], h[some], owner[some]
                c1, c2 = (hashes.of(lane, first, last + LENGTH).view(np.int64) for lane in (0, 1))
                touched, back = np.unique(owner, return_inverse=True)
                raw = {int(t): hashlib.sha256(data[offsets[rows[t]] : offsets[rows[t] + 1]]).digest()[:16] for t in touched}
                names = pa.DictionaryArray.from_arrays(pa.array(back.astype(np.int32)), pa.array([raw[int(t)] for t in touched], pa.binary())).cast(pa.binary())
                start = first - at[owner] + begin[owner]
                columns = [pa.array(h.view(np.int64)), pa.array(c1), pa.array(c2), pa.array((last - first + 1).astype(np.int32)), names, pa.array(start)]
                yield pa.RecordBatch.from_arrays(columns, names=[*_CONTEXT_KEYS, "class", "start"])

    rows = _texts(docs, text).mapInArrow(trimmed(run), f"{_CONTEXT}, class binary, start long")
    return rows.groupBy(*_CONTEXT_KEYS, "class", "start").agg(F.count("*").alias("n_texts"))


def class_texts(docs: DataFrame, text: str, classes: DataFrame) -> DataFrame:
    """class, text: one row per wanted class; equal texts fold within each map task before the shuffle."""
    code = F.conv(F.substring(F.hex("class"), 1, 15), 16, 10).cast("long")
    held = docs.sparkSession.sparkContext.broadcast(key_bitmap(classes, code, FILTER_BITS))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            data, offsets = utf8(batch.column(0))
            names = class_names(data, offsets)
            chosen = np.flatnonzero(in_bitmap(held.value, np.array([int.from_bytes(x[:8], "big") >> 4 for x in names], np.int64)))
            last = dict(zip([names[i] for i in chosen], chosen.tolist(), strict=True))
            keep = pa.array(sorted(last.values()), pa.int64())
            yield pa.RecordBatch.from_arrays([pa.array([names[i] for i in keep.to_pylist()], pa.binary()), batch.column(0).take(keep)], names=["class", "text"])

    return _texts(docs, text).mapInArrow(trimmed(run), "class binary, text string").groupBy("class").agg(F.first("text").alias("text"))


def suffix_array(words: np.ndarray, left: np.ndarray) -> np.ndarray:
    """Positions in the order of their suffixes.

    ``words`` has the eight bytes at each position as one number, ``left`` how many bytes its string still has.
    The end of each string is a symbol of its own, below all bytes; later strings have lower ones.
    """
    n = len(words)
    own = np.arange(n)
    order = np.lexsort((np.where(left < 8, -1 - own, 0), words))
    short = left[order] < 8
    new = np.ones(n, bool)
    new[1:] = (words[order][1:] != words[order][:-1]) | short[1:] | short[:-1]
    rank = np.empty(n, np.int64)
    rank[order] = np.maximum.accumulate(np.where(new, own, 0))
    step = 8
    while len(tied := np.flatnonzero(~(new & np.concatenate([new[1:], [True]])))):
        at = order[tied]
        ends = left[at] <= step
        follower = np.where(ends, -1 - at, rank[np.minimum(at + step, n - 1)])
        leader = rank[at]
        by = np.argsort(leader * (2 * n + 2) + follower + n + 1, kind="stable")
        at, leader, follower = at[by], leader[by], follower[by]
        order[tied] = at
        parts = np.ones(len(tied), bool)
        parts[1:] = (leader[1:] != leader[:-1]) | (follower[1:] != follower[:-1])
        new[tied] = parts
        rank[at] = np.maximum.accumulate(np.where(parts, tied, 0))
        step *= 2
    return order


def common_prefixes(words: np.ndarray, left: np.ndarray, order: np.ndarray, starts: np.ndarray, sizes: np.ndarray, depth: int = LENGTH) -> np.ndarray:
    """Kasai's rule, capped at ``depth``: the common prefix of each suffix with the one before it in ``order``.

    A suffix keeps all but one byte of its left neighbour's common prefix, so only the rest is compared, eight
    bytes at a time; the strings (``starts``, ``sizes``) run side by side.
    """
    n = len(order)
    before = np.full(n, -1, np.int64)
    before[order[1:]] = order[:-1]
    found = np.zeros(n, np.int64)
    kept = np.zeros(len(starts), np.int64)
    longest_first = np.argsort(-sizes, kind="stable")
    starts, sizes = starts[longest_first], sizes[longest_first]
    for step in range(int(sizes.max(initial=0))):
        live = int(np.searchsorted(-sizes, -step, side="left"))
        at = starts[:live] + step
        other = before[at]
        most = np.where(other >= 0, np.minimum(np.minimum(left[at], left[np.maximum(other, 0)]), depth), 0)
        have = np.minimum(np.maximum(kept[:live] - 1, 0), most)
        open_ = np.flatnonzero(have < most)
        while len(open_):
            x = words[at[open_] + have[open_]] ^ words[other[open_] + have[open_]]
            same = np.full(len(open_), 8, np.int64)
            differs = x != 0
            # bytes in front of the first that differs; the exponent of a double names the highest bit
            high = np.frexp((x[differs] >> np.uint64(11)).astype(np.float64))[1]
            same[differs] = (53 - high) // 8
            low = differs.copy()
            low[differs] = high == 0
            same[low] = 6 + (x[low] < 256)
            have[open_] = np.minimum(have[open_] + same, most[open_])
            open_ = open_[(same == 8) & (have[open_] < most[open_])]
        kept[:live] = have
        found[at] = have
    return found[order]


def repeated_windows(texts: list[bytes], counts: np.ndarray) -> list[np.ndarray]:
    """For each string, which of its windows occur twice or more, counting each string ``counts`` times."""
    sizes = np.array([len(t) for t in texts], np.int64)
    data = np.frombuffer(b"".join(texts) + bytes(8), np.uint8)
    n = len(data) - 8
    ends = np.cumsum(sizes)
    starts = ends - sizes
    words = np.zeros(n, np.uint64)
    for k in range(8):
        words = words << np.uint64(8) | data[k : k + n]
    owner = np.repeat(np.arange(len(texts)), sizes)
    left = ends[owner] - np.arange(n)
    cut = np.flatnonzero(left < 8)
    words[cut] &= ~np.uint64(0) << (np.uint64(8) * (8 - left[cut]).astype(np.uint64))  # nothing of the next string
    order = suffix_array(words, left)
    prefix = common_prefixes(words, left, order, starts, sizes)
    run = np.cumsum(prefix < LENGTH)
    total = np.bincount(run, counts[owner[order]])
    twice = np.zeros(n, bool)
    twice[order] = (total[run] >= 2) & (left[order] >= LENGTH)
    return [twice[a : b - LENGTH + 1] for a, b in zip(starts.tolist(), ends.tolist(), strict=True)]


def _spans(flags: np.ndarray) -> tuple[list[int], list[int]]:
    edge = np.flatnonzero(np.diff(np.concatenate([[0], flags.astype(np.int8), [0]])))
    return edge[::2].tolist(), edge[1::2].tolist()


_JUDGED = f"{_CONTEXT}, begins array<int>, ends array<int>, block long, windows array<int>, digests array<binary>"


def judge(cut: DataFrame) -> DataFrame:
    """Suffix arrays over the contexts of each anchor: spans of repeated windows, and for split anchors a digest of every different window.

    ``block`` numbers what was judged together. ``windows`` has the place of each digest in its context if it is not yet known to be repeated, else -1.
    """

    def work(rows: list[tuple], block: int) -> pa.RecordBatch:
        flags = repeated_windows([r[5] for r in rows], np.array([r[4] for r in rows], np.float64))
        begins, ends, windows, digests, told = [], [], [], [], set()
        for row, flag in zip(rows, flags, strict=True):
            b, e = _spans(flag)
            begins.append(b)
            ends.append(e)
            places, marks = [], []
            for k, known in enumerate(flag.tolist() if row[6] else ()):
                mark = hashlib.md5(row[5][k : k + LENGTH]).digest()
                if not known or mark not in told:  # of a repeated window one digest is enough for the other shards to meet it
                    places.append(-1 if known else k)
                    marks.append(mark)
                    told.add(mark)
            windows.append(places)
            digests.append(marks)
        kinds = (pa.int64(), pa.int64(), pa.int64(), pa.int32())
        columns = [pa.array([r[i] for r in rows], t) for i, t in enumerate(kinds)]
        columns += [pa.array(begins, pa.list_(pa.int32())), pa.array(ends, pa.list_(pa.int32())), pa.array([block] * len(rows), pa.int64())]
        columns += [pa.array(windows, pa.list_(pa.int32())), pa.array(digests, pa.list_(pa.binary()))]
        return pa.RecordBatch.from_arrays(columns, names=[*_CONTEXT_KEYS, "begins", "ends", "block", "windows", "digests"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, size, now, block = [], 0, None, TaskContext.get().partitionId() << 32
        for batch in batches:  # sorted by anchor and shard; a block ends only between two of them
            for row in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                key = (row[0], row[7])
                if key != now and size >= SHARD_BYTES:
                    yield work(held, block)
                    held, size, block = [], 0, block + 1
                now = key
                held.append(row)
                size += len(row[5])
        if held:
            yield work(held, block)

    dealt = cut.repartition("h", "shard").sortWithinPartitions("h", "shard")
    return dealt.select(*_CONTEXT_KEYS, "n_rows", "body", "split", "shard").mapInArrow(trimmed(run), _JUDGED)


def met_in_two(runs: list[np.ndarray]) -> np.ndarray:
    """The values that two or more runs have. Each run is sorted without repeats; runs are merged two at a time by binary search."""
    shared = [np.zeros(0, "S16")]
    while len(runs) > 1:
        merged = []
        for a, b in zip(runs[::2], runs[1::2], strict=False):
            at = np.searchsorted(a, b)
            hit = a[np.minimum(at, len(a) - 1)] == b
            shared.append(b[hit])
            merged.append(np.insert(a, at[~hit], b[~hit]))
        runs = merged + runs[len(runs) & ~1 :]
    return np.unique(np.concatenate(shared))


def merge_shards(judged: DataFrame) -> DataFrame:
    """Windows of split anchors that only another shard shows to be repeated: context keys and window number.

    Digests are dealt by their first bytes; each block of shards then comes as one sorted run per cell.
    """
    each = judged.where("size(windows) > 0").select(*_CONTEXT_KEYS, "block", F.explode(F.arrays_zip("windows", "digests")).alias("w"))
    rows = each.select(*_CONTEXT_KEYS, "block", F.col("w.windows").alias("k"), F.col("w.digests").alias("digest"))
    rows = rows.withColumn("cell", F.conv(F.hex(F.substring("digest", 1, 2)), 16, 10).cast("int"))
    dealt = rows.repartition("cell").sortWithinPartitions("cell", "block", "digest").select(*_CONTEXT_KEYS, "k", "cell", "block", "digest")

    def work(held: pa.Table) -> pa.RecordBatch:
        marks = np.array(held["digest"].to_pylist(), "S16")
        block = held["block"].to_numpy()
        edge = [0, *(np.flatnonzero(np.diff(block)) + 1).tolist(), len(block)]
        shared = met_in_two([marks[a:b] for a, b in zip(edge, edge[1:], strict=False)])
        at = np.minimum(np.searchsorted(shared, marks), max(len(shared) - 1, 0))
        found = (shared[at] == marks) & (held["k"].to_numpy() >= 0) if len(shared) else np.zeros(len(marks), bool)
        out = held.select([*_CONTEXT_KEYS, "k"]).filter(pa.array(found)).combine_chunks()
        return pa.RecordBatch.from_arrays([c.combine_chunks() for c in out.columns], names=out.column_names)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[pa.RecordBatch] = []
        for batch in batches:  # sorted by cell
            cells = batch.column(5).to_numpy()
            edge = [0, *(np.flatnonzero(np.diff(cells)) + 1).tolist(), len(cells)]
            for a, b in zip(edge, edge[1:], strict=False):
                if held and a < b and held[-1].column(5)[0].as_py() != cells[a]:
                    yield work(pa.Table.from_batches(held))
                    held = []
                if a < b:
                    held.append(batch.slice(a, b - a))
        if held:
            yield work(pa.Table.from_batches(held))

    return dealt.mapInArrow(trimmed(run), f"{_CONTEXT}, k int")


def removal(docs: DataFrame, text: str = "text", doc_id: str = "doc_id") -> DataFrame:
    """class, begins, ends: the byte spans to remove from each distinct text that has any (sorted, apart from each other)."""
    counts = saved(anchor_counts(docs, text).where("n > 1"))
    wanted = key_bitmap(counts, F.col("h"), FILTER_BITS)
    found = saved(occurrences(docs, text, wanted))
    # one row per different context; the filter may have let anchors through that occur once
    alike = found.groupBy(*_CONTEXT_KEYS).agg(F.sum("n_texts").alias("n_rows"), F.count("*").alias("n_places"), F.min(F.struct("class", "start")).alias("place"))
    alike = saved(alike)
    anchors = alike.groupBy("h").agg(F.count("*").alias("n_contexts"), F.sum("n_rows").alias("n_anchor")).where("n_anchor > 1")
    kinds = saved(attach(alike, saved(anchors), ["h"], "n_contexts"))
    # a lone context that occurs twice is repeated as a whole; nothing is left to sort
    lone = kinds.where("n_contexts = 1").select(*_CONTEXT_KEYS, "n_places", F.array(F.lit(0)).alias("begins"), F.array(F.col("size")).alias("ends"))
    shards = F.ceil(F.col("n_contexts") / SHARD_CONTEXTS)
    sorted_ = kinds.where("n_contexts > 1").withColumn("shard", F.pmod("c1", shards).cast("int")).withColumn("split", shards > 1)
    places = sorted_.groupBy("place.class").agg(F.collect_list(F.struct(*_CONTEXT_KEYS, "n_rows", "split", "shard", F.col("place.start").alias("start"))).alias("cuts"))
    places = saved(places)  # lists no longer than a text
    bodies = class_texts(docs, text, places).join(places, "class").select("text", "cuts")

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names = [*_CONTEXT_KEYS, "n_rows", "split", "shard"]
        for batch in batches:
            data, offsets = utf8(batch.column(0))
            raw, lists = data.tobytes(), batch.column(1)
            flat, per = lists.flatten(), np.diff(np.concatenate([[0], np.cumsum(lists.value_lengths().fill_null(0).to_numpy(zero_copy_only=False))]))
            columns = {n: flat.field(i) for i, n in enumerate([*names, "start"])}
            begin = np.repeat(offsets[:-1], per) + columns["start"].to_numpy(zero_copy_only=False)
            end = begin + columns["size"].to_numpy(zero_copy_only=False) + LENGTH - 1
            body = pa.array([raw[a:b] for a, b in zip(begin.tolist(), end.tolist(), strict=True)], pa.binary())
            yield pa.RecordBatch.from_arrays([*(columns[n] for n in names), body], names=[*names, "body"])

    pieces = bodies.mapInArrow(trimmed(cut), f"{_CONTEXT}, n_rows long, split boolean, shard int, body binary")
    judged = saved(judge(pieces))
    met = merge_shards(judged).select(*_CONTEXT_KEYS, F.array("k").alias("begins"), F.array(F.col("k") + 1).alias("ends"))
    spans = judged.where("size(begins) > 0").select(*_CONTEXT_KEYS, "begins", "ends").unionByName(met)
    spans = spans.groupBy(*_CONTEXT_KEYS).agg(F.flatten(F.collect_list("begins")).alias("begins"), F.flatten(F.collect_list("ends")).alias("ends"))
    spans = spans.join(alike.select(*_CONTEXT_KEYS, "n_places"), _CONTEXT_KEYS).unionByName(lone)
    placed = attach(found.select(*_CONTEXT_KEYS, "class", "start"), saved(spans), _CONTEXT_KEYS, "n_places")
    moved = lambda column, by: F.transform(column, lambda x: x + F.col("start") + by)
    shifted = placed.select("class", moved("begins", 0).alias("begins"), moved("ends", LENGTH - 1).alias("ends"))
    return shifted.groupBy("class").agg(F.flatten(F.collect_list("begins")).alias("begins"), F.flatten(F.collect_list("ends")).alias("ends"))


def strip(docs: DataFrame, text: str = "text", doc_id: str = "doc_id", with_text: bool = False) -> DataFrame:
    """One row per document: doc_id, n_bytes, n_removed, n_spans, kept_sha256 (and ``kept`` bytes, if asked for)."""
    spans = saved(removal(docs, text, doc_id))
    bodies = class_texts(docs, text, spans).join(spans, "class")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            data, offsets = utf8(batch.column(1))
            removed, spans_, shas, kept = [], [], [], []
            for i in range(len(batch)):
                body = data[offsets[i] : offsets[i + 1]]
                edge = np.zeros(len(body) + 1, np.int64)
                np.add.at(edge, batch.column(2)[i].values.to_numpy(zero_copy_only=False), 1)
                np.add.at(edge, batch.column(3)[i].values.to_numpy(zero_copy_only=False), -1)
                gone = np.cumsum(edge[:-1]) > 0
                rest = body[~gone].tobytes()
                removed.append(int(gone.sum()))
                spans_.append(int(gone[:1].sum() + (gone[1:] & ~gone[:-1]).sum()))
                shas.append(hashlib.sha256(rest).hexdigest())
                kept.append(rest if with_text else None)
            columns = [batch.column(0), pa.array(removed, pa.int64()), pa.array(spans_, pa.int64()), pa.array(shas, pa.string()), pa.array(kept, pa.binary())]
            yield pa.RecordBatch.from_arrays(columns, names=["class", "n_removed", "n_spans", "kept_sha256", "kept"])

    done = bodies.select("class", "text", "begins", "ends").mapInArrow(trimmed(run), "class binary, n_removed long, n_spans long, kept_sha256 string, kept binary")
    rows = saved(document_classes(docs, text, doc_id))
    sizes = rows.groupBy("class").agg(F.count("*").alias("n_rows"))
    changed = saved(sizes.join(done, "class", "left"))
    out = attach(rows, changed, ["class"], "n_rows")
    none = F.lit(0).cast("long")
    columns = ["doc_id", "n_bytes", F.coalesce("n_removed", none).alias("n_removed"), F.coalesce("n_spans", none).alias("n_spans"), F.coalesce("kept_sha256", "sha").alias("kept_sha256")]
    return out.select(*columns, "kept") if with_text else out.select(*columns)
