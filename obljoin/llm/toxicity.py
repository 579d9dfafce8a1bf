"""Toxicity by a bag of subwords: embeddings of hashed character n-grams, averaged, into a linear softmax.

A word is the average of the vectors of its n-grams (3 to 6 bytes with its ends marked), a text the
average of its words and a few neutral ones, and a softmax over the text's vector gives the probability of label 1. Embeddings and
softmax are fitted together in numpy, so a misspelling that was never seen shares most vectors with the
word that was.

Training takes at most ``sample`` labelled rows (a documented bound), half of each label where there are so
many. Their whole texts are reduced on the executors to one weight per bucket, so the driver holds
at most ``sample`` times the number of buckets. One row in five is set aside to place the threshold at 0.5.
Averages are linear, so scoring needs one number per bucket and runs over arrays without a cache.

Defined results: null or wordless text gets the score of the bias alone; without labels every score is 0;
equal texts get equal scores; texts of any length are scored whole; an empty table gives no rows.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from obljoin.llm.common import LOWER, blocks, trim, trimmed, utf8

BUCKET_BITS = 16
WIDTH = 8
GRAMS = (3, 4, 5, 6)
SAMPLE = 6000
BLOCK_BYTES = 1 << 20
#: Averages over a text are small; this scale keeps the fitted values near one.
SCALE = 30.0
#: Every text is averaged with so many neutral words, so that a few odd words do not decide on a short one.
NEUTRAL_WORDS = 40

#: Bytes as words see them: ASCII letters in lower case, digits and UTF-8 bytes as they are, all else a blank.
_SEEN = LOWER.copy()
_SEEN[:128][~np.array([chr(c).isalnum() for c in range(128)])] = 32


def words(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Texts with a blank before each and after the last: bytes, word starts, word ends, each text's first word (total last)."""
    n = len(offsets) - 1
    held = np.full(len(data) + n + 1, 32, np.uint8)
    if len(data):
        held[np.arange(len(data)) + np.repeat(np.arange(1, n + 1), np.diff(offsets))] = _SEEN[data]
    inside = held != 32
    edge = np.flatnonzero(inside[1:] != inside[:-1]) + 1
    starts, ends = edge[::2], edge[1::2]
    return held, starts, ends, np.searchsorted(starts, offsets + np.arange(n + 1))


def grams(held: np.ndarray) -> Iterator[tuple[int, np.ndarray]]:
    """For each n: the bucket of the n-gram at every position."""
    wide = held.astype(np.uint32)
    for n in GRAMS:
        code = np.full(max(len(wide) - n + 1, 0), n, np.uint32)
        for k in range(n if len(code) else 0):
            code = code * np.uint32(0x01000193) + wide[k : len(wide) - n + 1 + k]
        code ^= code >> np.uint32(16)
        yield n, (code * np.uint32(0x9E3779B1)) >> np.uint32(32 - BUCKET_BITS)


def _range(starts: np.ndarray, ends: np.ndarray, n: int, size: int) -> tuple[np.ndarray, np.ndarray]:
    """Where the n-grams of each word lie, from the blank before it to the blank after."""
    first = np.minimum(starts - 1, size)
    return first, np.clip(ends - n + 2, first, size)


def bags(data: np.ndarray, offsets: np.ndarray) -> list[tuple[np.ndarray, np.ndarray]]:
    """Each text as the buckets that it has and their weights."""
    held, starts, ends, firsts = words(data, offsets)
    found, count = [], np.zeros(len(starts), np.int64)
    for n, code in grams(held):
        first, last = _range(starts, ends, n, len(code))
        found.append((first, last, code))
        count += last - first
    per_text = np.repeat(np.diff(firsts), np.diff(firsts))
    weight = 1.0 / (np.maximum(count, 1) * (per_text + NEUTRAL_WORDS))
    out = []
    for a, b in zip(firsts.tolist(), firsts.tolist()[1:], strict=False):
        total = np.zeros(1 << BUCKET_BITS)
        for first, last, code in found:
            size = (last - first)[a:b]
            at = np.repeat(first[a:b] - (np.cumsum(size) - size), size) + np.arange(int(size.sum()))
            total += np.bincount(code[at], np.repeat(weight[a:b], size), 1 << BUCKET_BITS)
        some = np.flatnonzero(total)
        out.append((some.astype(np.uint16), total[some].astype(np.float32)))
    return out


@dataclass(frozen=True)
class ToxicityModel:
    buckets: np.ndarray  # what a bucket adds to the difference of the two logits
    bias: float

    def logits(self, data: np.ndarray, offsets: np.ndarray) -> np.ndarray:
        held, starts, ends, firsts = words(data, offsets)
        total, count = np.zeros(len(starts)), np.zeros(len(starts), np.int64)
        for n, code in grams(held):
            running = np.concatenate([[0.0], np.cumsum(self.buckets[code], dtype=np.float64)])
            first, last = _range(starts, ends, n, len(code))
            total += running[last] - running[first]
            count += last - first
        running = np.concatenate([[0.0], np.cumsum(total / np.maximum(count, 1))])
        return self.bias + (running[firsts[1:]] - running[firsts[:-1]]) / (np.diff(firsts) + NEUTRAL_WORDS)


class _Fit:
    """Embeddings and softmax under one Adam."""

    def __init__(self, seed: int) -> None:
        rng = np.random.default_rng(seed)
        self.values = [rng.normal(0, 0.1, (1 << BUCKET_BITS, WIDTH)).astype(np.float32), rng.normal(0, 0.3, (WIDTH, 2)).astype(np.float32), np.zeros(2, np.float32)]
        self.first, self.second, self.steps = [np.zeros_like(v) for v in self.values], [np.zeros_like(v) for v in self.values], 0

    def step(self, code: np.ndarray, weight: np.ndarray, bounds: np.ndarray, label: np.ndarray, stress: np.ndarray, rate: float) -> None:
        mean = np.add.reduceat(self.values[0][code] * weight[:, None], bounds[:-1], axis=0)
        logits = mean @ self.values[1] + self.values[2]
        pull = np.exp(logits - logits.max(axis=1, keepdims=True))
        pull /= pull.sum(axis=1, keepdims=True)
        pull[np.arange(len(label)), label] -= 1
        pull *= (stress / len(label))[:, None]
        back = np.repeat(pull @ self.values[1].T, np.diff(bounds), axis=0) * weight[:, None]
        into = np.stack([np.bincount(code, back[:, k], 1 << BUCKET_BITS) for k in range(WIDTH)], axis=1).astype(np.float32)
        self.steps += 1
        for i, slope in enumerate((into, mean.T @ pull, pull.sum(axis=0))):
            self.first[i] += 0.1 * (slope - self.first[i])
            self.second[i] += 0.01 * (slope**2 - self.second[i])
            self.values[i] -= rate * (self.first[i] / (1 - 0.9**self.steps)) / (np.sqrt(self.second[i] / (1 - 0.99**self.steps)) + 1e-7)

    def model(self, known: np.ndarray) -> ToxicityModel:
        """Buckets that no training text has stay at zero, not at their random start."""
        across = self.values[1][:, 1] - self.values[1][:, 0]
        return ToxicityModel((self.values[0] @ across * known * SCALE).astype(np.float32), float(self.values[2][1] - self.values[2][0]))


def threshold(logits: np.ndarray, labels: np.ndarray) -> float:
    """The cut with the least sum of both labels' error shares, label 0 counting twice, in the middle of all such cuts."""
    cut = np.unique(logits)
    cut = np.concatenate([[cut[0] - 1], (cut[1:] + cut[:-1]) / 2, [cut[-1] + 1]])
    clean, toxic = np.sort(logits[labels == 0]), np.sort(logits[labels == 1])
    wrong = 2 * (len(clean) - np.searchsorted(clean, cut)) / max(len(clean), 1) + np.searchsorted(toxic, cut) / max(len(toxic), 1)
    best = cut[wrong <= wrong.min() + 1e-12]
    return float((best[0] + best[-1]) / 2)


def fit(texts: list[tuple[np.ndarray, np.ndarray]], labels: np.ndarray, seed: int = 11, batch: int = 64, epochs: int = 16, least_steps: int = 800, rate: float = 0.02) -> ToxicityModel:
    sizes = np.array([len(c) for c, _ in texts])
    bounds = np.concatenate([[0], np.cumsum(sizes)])
    code = np.concatenate([c for c, _ in texts])
    weight = np.concatenate([w for _, w in texts])
    rng = np.random.default_rng(seed)
    fitted, aside = _Fit(seed), np.arange(len(texts)) % 5 == 0
    if len(set(labels[aside].tolist())) < 2 or len(set(labels[~aside].tolist())) < 2:
        aside = np.zeros(len(texts), bool)
    learn = np.flatnonzero((sizes > 0) & ~aside)
    known = np.bincount(np.concatenate([np.zeros(0, np.uint16), *(code[bounds[i] : bounds[i + 1]] for i in learn)]), minlength=1 << BUCKET_BITS) > 0
    share = np.bincount(labels[learn], minlength=2) / max(len(learn), 1)
    stress = (0.5 / np.maximum(share, 0.02))[labels]  # either label weighs the same
    epochs = max(epochs, -(-least_steps * batch // max(len(learn), 1)))
    for epoch in range(epochs):
        order = rng.permutation(learn)
        for i in range(0, len(order), batch):
            some = order[i : i + batch]
            at = np.repeat(bounds[some] - (np.cumsum(sizes[some]) - sizes[some]), sizes[some]) + np.arange(int(sizes[some].sum()))
            fitted.step(code[at], weight[at] * SCALE, np.concatenate([[0], np.cumsum(sizes[some])]), labels[some], stress[some], rate * (1 - epoch / epochs))
    model = fitted.model(known)
    running = np.concatenate([[0.0], np.cumsum(model.buckets[code] * weight, dtype=np.float64)])
    logits = model.bias + running[bounds[1:]] - running[bounds[:-1]]
    judged = aside if aside.any() else np.ones(len(texts), bool)
    return ToxicityModel(model.buckets, model.bias - threshold(logits[judged], labels[judged]))


def train(docs: DataFrame, labels: DataFrame, learn: Column, text: str = "text", doc_id: str = "doc_id", label: str = "toxic", sample: int = SAMPLE) -> ToxicityModel | None:
    """Fits on at most ``sample`` labelled rows; a document with several labels counts as its highest."""
    mark = F.when(F.col(label) > 0, 1).otherwise(0)
    marks = labels.where(learn & F.col(label).isNotNull() & F.col(doc_id).isNotNull()).groupBy(F.col(doc_id).alias("doc_id")).agg(F.max(mark).alias("label"))
    some = marks.withColumn("order", F.xxhash64("doc_id"))
    half = [some.where(F.col("label") == k).orderBy("order", "doc_id").limit(sample // 2) for k in (0, 1)]
    wanted = F.broadcast(half[0].unionByName(half[1]))  # at most ``sample`` rows

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            data, offsets = utf8(batch.column(2))
            for a, b in blocks(offsets, BLOCK_BYTES):
                found = bags(data[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a])
                columns = [pa.array([x.tobytes() for x in side], pa.binary()) for side in zip(*found, strict=True)]
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(a, b - a), batch.column(1).slice(a, b - a), *columns], names=["order", "label", "code", "weight"])

    texts = docs.select(F.col(doc_id).alias("doc_id"), F.col(text).cast("string").alias("text"))
    rows = texts.join(wanted, "doc_id").select("order", "label", "text").mapInArrow(trimmed(run), "order long, label int, code binary, weight binary")
    got = [(r.order, r.label, np.frombuffer(bytes(r.code), np.uint16), np.frombuffer(bytes(r.weight), np.float32)) for r in rows.toLocalIterator()]
    if not got:
        return None
    got.sort(key=lambda r: (r[0], r[1], r[2].tobytes()))
    got = got[: 2 * sample]  # rows that repeat an id
    model = fit([(c, w) for _, _, c, w in got], np.array([r[1] for r in got], np.int64))
    del got
    trim()
    return model


def score(docs: DataFrame, model: ToxicityModel | None, text: str = "text", doc_id: str = "doc_id") -> DataFrame:
    """doc_id, score of every whole text."""
    held = docs.sparkSession.sparkContext.broadcast(model)  # one number per bucket

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model = held.value
        for batch in batches:
            data, offsets = utf8(batch.column(1))
            out = np.zeros(len(offsets) - 1)
            for a, b in blocks(offsets, BLOCK_BYTES) if model else ():
                logits = model.logits(data[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a])
                out[a:b] = 1 / (1 + np.exp(-np.clip(logits, -50, 50)))
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(out)], names=["doc_id", "score"])

    kind = docs.schema[doc_id].dataType.simpleString()
    return docs.select(F.col(doc_id).alias("doc_id"), F.col(text).cast("string").alias("text")).mapInArrow(trimmed(run), f"doc_id {kind}, score double")
