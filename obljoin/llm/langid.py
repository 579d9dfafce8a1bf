"""Language identification by error-correcting output codes.

Every language has a codeword of +1/-1 bits; one binary linear classifier over hashed byte n-grams
predicts each bit. Decoding sums a logistic loss per bit, weighted by how well that bit's classifier
does on rows it was not fitted on, and takes the nearest codeword; a small lead over the second is flagged.

The classifiers are fitted on at most ``sample`` labelled rows (a documented bound), taken evenly from
the languages by a hash; rows of any length are featurised whole, on the executors.

Defined results: null text or one without a letter is ``und`` with score 0 and flagged; without any
labelled row all texts are ``und``; with one language it is predicted with score 1; equal texts get
equal results; an empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from obljoin.llm.common import LOWER, blocks, trim, trimmed, utf8

DIMENSIONS = 4096
SAMPLE = 2400
BLOCK_BYTES = 1 << 20
#: Rows are dense, so a block of short texts is bounded by their number.
BLOCK_ROWS = 256
#: A lead (in probability) of the best codeword over the second below this is ambiguous.
LEAD = 0.2
UNKNOWN = "und"

#: Bytes as features see them: ASCII letters in lower case, every other ASCII byte a blank, the rest as they are.
_SEEN = LOWER.copy()
_SEEN[:128][~np.array([chr(c).isalpha() for c in range(128)])] = 32
_IS_LETTER = np.zeros(256, bool)
_IS_LETTER[[c for c in range(128) if chr(c).isalpha()]] = True


def features(data: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    """Square roots of hashed n-gram shares (n of 2 and 3), so each row has unit length; a row per text."""
    n = len(offsets) - 1
    lengths = np.diff(offsets)
    row = np.repeat(np.arange(n, dtype=np.int64) * DIMENSIONS, lengths)
    seen = _SEEN[data].astype(np.uint32)
    counts = np.zeros(n * DIMENSIONS, np.float32)
    for width in (2, 3):
        if len(seen) < width:
            continue
        code = np.full(len(seen) - width + 1, width, np.uint32)
        for k in range(width):
            code = code * np.uint32(0x9E3779B1) + seen[k : len(seen) - width + 1 + k]
        code ^= code >> np.uint32(15)
        code = (code * np.uint32(0x85EBCA6B)) >> np.uint32(32 - DIMENSIONS.bit_length() + 1)
        at = row[: len(code)] + code
        at = at[row[: len(code)] == row[width - 1 :]]  # no n-gram across two texts
        counts += np.bincount(at, minlength=n * DIMENSIONS).astype(np.float32)
    counts = counts.reshape(n, DIMENSIONS)
    return np.sqrt(counts / np.maximum(counts.sum(axis=1, keepdims=True), 1))


def have_letters(data: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    total = np.concatenate([[0], np.cumsum(_IS_LETTER[data])])
    found = total[offsets[1:]] > total[offsets[:-1]]
    for i in np.flatnonzero(~found).tolist():
        found[i] = any(c.isalpha() for c in data[offsets[i] : offsets[i + 1]].tobytes().decode("utf-8", "replace"))
    return found


def codewords(n: int, seed: int = 7) -> np.ndarray:
    """n rows of +1/-1: all splits up to seven languages, above that the best of some random codes."""
    if n <= 1:
        return np.ones((n, 0))
    if n <= 7:
        splits = range(1, 1 << (n - 1))
        return np.array([[1.0 if i == 0 or not s >> (i - 1) & 1 else -1.0 for s in splits] for i in range(n)])
    rng = np.random.default_rng(seed)
    length = math.ceil(10 * math.log2(n))
    tried = (rng.choice([-1.0, 1.0], (n, length)) for _ in range(50))

    def apart(code: np.ndarray) -> float:
        return -np.max(code @ code.T - 2 * length * np.eye(n))

    return max(tried, key=apart)


@dataclass(frozen=True)
class LanguageModel:
    languages: tuple[str, ...]
    code: np.ndarray  # languages x bits
    weights: np.ndarray  # dimensions x bits
    bias: np.ndarray
    trust: np.ndarray  # per bit

    def decode(self, rows: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Best language, its probability, its lead over the second."""
        if len(self.languages) == 1:
            return np.zeros(len(rows), np.int64), np.ones(len(rows)), np.ones(len(rows))
        margin = rows @ self.weights + self.bias
        loss = (np.logaddexp(0, -margin[:, None, :] * self.code[None]) * self.trust).sum(axis=2)
        share = np.exp(loss.min(axis=1, keepdims=True) - loss)
        share /= share.sum(axis=1, keepdims=True)
        ordered = np.sort(share, axis=1)
        return loss.argmin(axis=1), share.max(axis=1), ordered[:, -1] - ordered[:, -2]


def _logistic(rows: np.ndarray, signs: np.ndarray, steps: int = 250, rate: float = 0.3, shrink: float = 1e-5) -> tuple[np.ndarray, np.ndarray]:
    """All bits at once, by Adam on the full batch; each bit's two sides weigh the same."""
    weights, bias = np.zeros((rows.shape[1], signs.shape[1]), np.float32), np.zeros(signs.shape[1], np.float32)
    share = np.where(signs > 0, (signs > 0).mean(axis=0), (signs < 0).mean(axis=0))
    balance = (0.5 / np.maximum(share, 1e-6) / len(rows)).astype(np.float32)
    first, second = [0.0, 0.0], [0.0, 0.0]
    for t in range(1, steps + 1):
        pull = -signs * balance / (1 + np.exp(np.clip(signs * (rows @ weights + bias), -30, 30)))
        for i, (value, slope) in enumerate(((weights, rows.T @ pull + shrink * weights), (bias, pull.sum(axis=0)))):
            first[i] = 0.9 * first[i] + 0.1 * slope
            second[i] = 0.999 * second[i] + 0.001 * slope**2
            value -= (rate * (first[i] / (1 - 0.9**t)) / (np.sqrt(second[i] / (1 - 0.999**t)) + 1e-8)).astype(np.float32)
    return weights, bias


def fit(rows: np.ndarray, names: list[str]) -> LanguageModel | None:
    languages = tuple(sorted(set(names)))
    if not languages:
        return None
    code = codewords(len(languages))
    bits = code.shape[1]
    if not bits:
        return LanguageModel(languages, code, np.zeros((DIMENSIONS, 0), np.float32), np.zeros(0), np.zeros(0))
    signs = code[np.searchsorted(languages, names)].astype(np.float32)
    aside = np.arange(len(rows)) % 4 == 0
    trust = np.ones(bits)
    if aside.sum() and (~aside).sum():
        weights, bias = _logistic(rows[~aside], signs[~aside])
        wrong = ((rows[aside] @ weights + bias) * signs[aside] <= 0).mean(axis=0)
        trust = np.log((1 - (e := np.clip(wrong, 0.005, 0.45))) / e)
        trust /= trust.mean()
    weights, bias = _logistic(rows, signs)
    return LanguageModel(languages, code, weights, bias, trust)


def train(docs: DataFrame, learn: Column, text: str = "text", lang: str = "lang", doc_id: str = "doc_id", sample: int = SAMPLE) -> LanguageModel | None:
    """Fits on at most ``sample`` of the rows where ``learn`` holds and a language and a text are given."""
    labelled = docs.where(learn & F.col(lang).isNotNull() & F.col(text).isNotNull()).select(
        F.col(lang).cast("string").alias("lang"), F.col(text).cast("string").alias("text"), F.xxhash64(F.col(doc_id)).alias("order")
    )
    counts = labelled.groupBy("lang").count().orderBy(F.desc("count"), "lang").limit(sample).collect()  # one row per language
    if not counts:
        return None
    quota = max(1, sample // len(counts))
    top = F.create_map(*(x for name, n in counts for x in (F.lit(name), F.lit(min(1.0, 1.5 * quota / n)))))
    share = F.pmod(F.col("order"), F.lit(1 << 30)) / float(1 << 30)
    chosen = labelled.where(share < F.element_at(top, F.col("lang"))).orderBy("order", "lang", "text").limit(sample + sample // 2)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            data, offsets = utf8(batch.column(1))
            for a, b in blocks(offsets, BLOCK_BYTES, BLOCK_ROWS):
                rows = features(data[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a])
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(a, b - a), pa.array([r.tobytes() for r in rows], pa.binary())], names=["lang", "row"])

    got, names, rows = {}, [], []
    for name, row in chosen.select("lang", "text").repartition(4).mapInArrow(trimmed(run), "lang string, row binary").sort(F.xxhash64("row")).toLocalIterator():
        if got.get(name, 0) < quota:
            got[name] = got.get(name, 0) + 1
            names.append(name)
            rows.append(np.frombuffer(bytes(row), np.float32))
    model = fit(np.stack(rows), names) if rows else None
    del rows
    trim()
    return model


def identify(docs: DataFrame, model: LanguageModel | None, text: str = "text", doc_id: str = "doc_id", whole: bool = False) -> DataFrame:
    """doc_id (or, with ``whole``, all columns as a struct ``row``), lang_pred, score, ambiguous for every whole text."""
    held = docs.sparkSession.sparkContext.broadcast(model)  # bounded: languages x bits x dimensions
    body = F.col(text).cast("string")
    row = F.struct(*docs.columns) if whole else F.struct(F.col(doc_id).alias(doc_id), body.alias(text))
    at = docs.columns.index(text) if whole else 1

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model = held.value
        for batch in batches:
            rows = batch.column(0)
            data, offsets = utf8(rows.flatten()[at].cast(pa.string()))
            n = len(offsets) - 1
            names, scores, unsure = np.full(n, UNKNOWN, object), np.zeros(n), np.ones(n, bool)
            for a, b in blocks(offsets, BLOCK_BYTES, BLOCK_ROWS) if model else ():
                part, cut = data[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a]
                best, score, lead = model.decode(features(part, cut))
                some = have_letters(part, cut)
                names[a:b] = np.where(some, np.array(model.languages, object)[best], UNKNOWN)
                scores[a:b] = np.where(some, score, 0.0)
                unsure[a:b] = ~some | (lead < LEAD)
            kept = rows if whole else rows.flatten()[0]
            yield pa.RecordBatch.from_arrays([kept, pa.array(names, pa.string()), pa.array(scores), pa.array(unsure)], names=["row" if whole else "doc_id", "lang_pred", "score", "ambiguous"])

    given = docs.select(row.alias("row"))
    kind = f"row {given.schema['row'].dataType.simpleString()}" if whole else f"doc_id {docs.schema[doc_id].dataType.simpleString()}"
    return given.mapInArrow(trimmed(run), f"{kind}, lang_pred string, score double, ambiguous boolean")


def remainder(doc_id: str, of: int) -> Column:
    """crc32 of the id as text, modulo ``of``; a null id counts as -1."""
    return F.coalesce(F.crc32(F.col(doc_id).cast("string")) % of, F.lit(-1))
