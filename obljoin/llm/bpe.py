"""Byte-level BPE encoding and decoding without regular expressions.

Pre-tokenisation is a small automaton over classes of code points. The functions that its symbols
induce on its states form a finite monoid, so a block of text becomes an array of monoid elements and the
state before every character comes from an associative scan: products within columns, a scan of the
block products, and one pass that applies them. Slices between boundaries go through a bounded cache of
merged pairs; the offset of each id is kept, and decoding is a gather over the vocabulary.

Defined results: null text counts as empty and gives no ids; a text of any length is one row; an empty
table gives no rows; other columns than those named are dropped.
"""

from __future__ import annotations

import base64
import hashlib
import heapq
import sys
import unicodedata
from collections.abc import Iterator
from functools import cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from obljoin.llm.common import blocks, trimmed, utf8

BLOCK_BYTES = 512 << 10
COLUMNS = 64
CACHED_PIECES = 150_000
CACHED_LENGTH = 64
#: Pieces of more bytes are merged with a heap.
LONG_PIECE = 96

#: Symbols of the automaton. BLANKS: a blank before a blank or the end; LAST: any other blank before something
#: else than a blank; GAP: the same for the plain space; QUOTE1, QUOTE2: an apostrophe before a one-letter or two-letter ending.
LETTER, NUMBER, OTHER, BLANKS, LAST, GAP, QUOTE1, QUOTE2 = range(8)
#: States: at a text's start, in a run of each kind, after a gap, with one or two letters of an ending to come, after a closed piece.
START, IN_LETTERS, IN_NUMBERS, IN_OTHERS, IN_BLANKS, AFTER_GAP, ONE_LEFT, TWO_LEFT, CLOSED = range(9)
STATES = 9

#: Code points with the property White_Space.
WHITE_SPACE = (9, 10, 11, 12, 13, 32, 0x85, 0xA0, 0x1680, *range(0x2000, 0x200B), 0x2028, 0x2029, 0x202F, 0x205F, 0x3000)
#: Endings that are pieces of their own after an apostrophe.
ENDINGS1, ENDINGS2 = b"stmd", (b"re", b"ve", b"ll")


def _moves() -> tuple[np.ndarray, np.ndarray]:
    """next[symbol, state] and starts[symbol, state]."""
    to, starts = np.zeros((8, STATES), np.uint8), np.ones((8, STATES), bool)
    for symbol, run in ((LETTER, IN_LETTERS), (NUMBER, IN_NUMBERS), (OTHER, IN_OTHERS)):
        to[symbol] = run
        starts[symbol, [run, AFTER_GAP]] = False
    to[LETTER, [TWO_LEFT, ONE_LEFT]] = ONE_LEFT, CLOSED
    starts[LETTER, [TWO_LEFT, ONE_LEFT]] = False
    to[BLANKS], to[LAST], to[GAP] = IN_BLANKS, CLOSED, AFTER_GAP
    starts[BLANKS, IN_BLANKS] = False
    for symbol, left in ((QUOTE1, ONE_LEFT), (QUOTE2, TWO_LEFT)):
        to[symbol] = left
        to[symbol, [IN_OTHERS, AFTER_GAP]] = IN_OTHERS
        starts[symbol, [IN_OTHERS, AFTER_GAP]] = False
    return to, starts


@cache
def monoid() -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """products[a << 8 | b] (a first), effects[element, state], of_symbol, of_first (a symbol that opens a text), starts."""
    to, starts = _moves()
    symbols = [tuple(int(x) for x in row) for row in to]
    opened = [(row[START],) * STATES for row in symbols]
    known = {f: i for i, f in enumerate(dict.fromkeys([tuple(range(STATES)), *symbols, *opened]))}
    todo = list(known)
    while todo:
        f = todo.pop()
        for g in [*symbols, *opened]:
            h = tuple(g[x] for x in f)
            if h not in known:
                known[h] = len(known)
                todo.append(h)
    elements = list(known)
    assert len(elements) <= 256
    products = np.zeros(256 * 256, np.uint8)
    for a, f in enumerate(elements):
        for b, g in enumerate(elements):
            h = tuple(g[x] for x in f)
            if h in known:
                products[a << 8 | b] = known[h]
    effects = np.array(elements, np.uint8)
    return products, effects, np.array([known[f] for f in symbols], np.uint8), np.array([known[f] for f in opened], np.uint8), starts


def states_before(elements: np.ndarray) -> np.ndarray:
    """The state in front of every element, from an associative scan."""
    products, effects, *_ = monoid()
    n = len(elements)
    if n <= COLUMNS:
        out, state = np.zeros(n, np.uint8), START
        for i, e in enumerate(elements.tolist()):
            out[i], state = state, effects[e, state]
        return out
    height = -(-n // COLUMNS)
    grid = np.zeros(height * COLUMNS, np.uint8)  # element 0 is the identity
    grid[:n] = elements
    grid = np.ascontiguousarray(grid.reshape(height, COLUMNS).T)
    product = grid[0]
    for row in grid[1:]:
        product = products[product.astype(np.uint16) << 8 | row]
    state = states_before(product)
    out = np.empty((COLUMNS, height), np.uint8)
    flat = effects.ravel()
    for j in range(COLUMNS):
        out[j] = state
        state = flat[grid[j].astype(np.uint16) * STATES + state]
    return out.T.reshape(-1)[:n]


_SPACE, _WHITE = 8, 9  # before the look at the next character


@cache
def code_point_classes() -> np.ndarray:
    kinds = np.full(sys.maxunicode + 1, OTHER, np.uint8)
    for c in range(sys.maxunicode + 1):
        k = unicodedata.category(chr(c))[0]
        if k in "LN":
            kinds[c] = LETTER if k == "L" else NUMBER
    kinds[list(WHITE_SPACE)] = _WHITE
    kinds[32] = _SPACE
    return kinds


def boundaries(data: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    """Byte positions at which pieces start, for texts laid end to end."""
    *_, of_symbol, of_first, starts = monoid()
    kinds = code_point_classes()
    if not len(data):
        return np.zeros(0, np.int64)
    heads = np.flatnonzero((data & 0xC0) != 0x80)
    lead = data[heads].astype(np.int64)
    wide = np.flatnonzero(lead >= 0x80)
    points = lead.copy()
    if len(wide):
        padded = np.concatenate([data, np.zeros(3, np.uint8)]).astype(np.int64)
        at, first = heads[wide], lead[wide]
        tail = [padded[at + k] & 0x3F for k in (1, 2, 3)]
        two, three = (first & 0x1F) << 6 | tail[0], (first & 0x0F) << 12 | tail[0] << 6 | tail[1]
        four = (first & 0x07) << 18 | tail[0] << 12 | tail[1] << 6 | tail[2]
        points[wide] = np.where(first < 0xE0, two, np.where(first < 0xF0, three, np.minimum(four, sys.maxunicode)))
    symbol = kinds[points]
    opens = np.searchsorted(heads, offsets[:-1][np.diff(offsets) > 0])
    follows = np.empty(len(symbol), bool)  # is the next character of this text no blank?
    follows[:-1] = symbol[1:] < _SPACE
    follows[-1] = False
    follows[opens[1:] - 1] = False
    blank, space = symbol >= _SPACE, symbol == _SPACE
    symbol = np.where(blank, np.where(follows, np.where(space, GAP, LAST), BLANKS), symbol)
    quotes = np.flatnonzero(lead == 0x27)
    if len(quotes):
        at = heads[quotes]
        left = offsets[np.searchsorted(offsets, at, side="right")] - at - 1  # bytes of this text behind it
        padded = np.concatenate([data[:], np.zeros(2, np.uint8)])
        one, two = padded[at + 1], padded[at + 2]
        symbol[quotes[(left >= 1) & np.isin(one, np.frombuffer(ENDINGS1, np.uint8))]] = QUOTE1
        for a, b in ENDINGS2:
            symbol[quotes[(left >= 2) & (one == a) & (two == b)]] = QUOTE2
    elements = of_symbol[symbol]
    elements[opens] = of_first[symbol[opens]]
    before = states_before(elements)
    before[opens] = START
    return heads[starts[symbol, before]]


def load_ranks(path: str) -> dict[bytes, int]:
    with open(path, "rb") as lines:
        return {base64.b64decode(token): int(rank) for token, rank in map(bytes.split, lines)}


def merge(piece: bytes, ranks: dict[bytes, int]) -> list[int]:
    """Merges the neighbours of lowest rank, leftmost first, until none is known."""
    if piece in ranks:
        return [ranks[piece]]
    n = len(piece)
    if n > LONG_PIECE:
        return _merge_long(piece, ranks)
    none, get = 1 << 32, ranks.get
    cuts = list(range(n + 1))  # part i is piece[cuts[i]:cuts[i + 1]]
    pairs = [get(piece[i : i + 2], none) for i in range(n - 1)]  # of parts i and i + 1
    while pairs and (least := min(pairs)) < none:
        i = pairs.index(least)
        del cuts[i + 1], pairs[i]
        if i < len(pairs):
            pairs[i] = get(piece[cuts[i] : cuts[i + 2]], none)
        if i:
            pairs[i - 1] = get(piece[cuts[i - 1] : cuts[i + 1]], none)
    return [ranks[piece[x:y]] for x, y in zip(cuts, cuts[1:], strict=False)]


def _merge_long(piece: bytes, ranks: dict[bytes, int]) -> list[int]:
    """The same by a heap, which keeps long pieces at n log n."""
    n = len(piece)
    ends, previous, alive = list(range(1, n + 1)), list(range(-1, n - 1)), [True] * n  # of parts by their first byte; a part's follower starts at its end
    heap = [(r, i, i + 2) for i in range(n - 1) if (r := ranks.get(piece[i : i + 2])) is not None]
    heapq.heapify(heap)
    while heap:
        _, i, end = heapq.heappop(heap)
        if not alive[i] or ends[i] >= n:
            continue
        j = ends[i]
        if ends[j] != end:
            continue
        alive[j] = False
        ends[i] = end
        if end < n:
            previous[end] = i
            if (r := ranks.get(piece[i : ends[end]])) is not None:
                heapq.heappush(heap, (r, i, ends[end]))
        if (p := previous[i]) >= 0 and (r := ranks.get(piece[p:end])) is not None:
            heapq.heappush(heap, (r, p, end))
    return [ranks[piece[i : ends[i]]] for i in range(n) if alive[i]]


class Pieces(dict):
    """Little-endian ids of pieces seen lately, in two generations of bounded size: what is used again moves to the young one."""

    def __init__(self, ranks: dict[bytes, int]) -> None:
        super().__init__()
        self.ranks, self.old = ranks, {}

    def __missing__(self, piece: bytes) -> bytes:
        ids = self.old.get(piece)
        if ids is None:
            ids = np.array(merge(piece, self.ranks), "<u4").tobytes()
        if len(piece) <= CACHED_LENGTH:
            if len(self) >= CACHED_PIECES:
                self.old = dict(self)
                self.clear()
            self[piece] = ids
        return ids


def encode_texts(data: np.ndarray, offsets: np.ndarray, pieces: Pieces) -> Iterator[bytes]:
    """The ids of each text, as little-endian unsigned 32-bit integers."""
    for a, b in blocks(offsets, BLOCK_BYTES):
        part = offsets[a : b + 1] - offsets[a]
        held = data[offsets[a] : offsets[b]]
        starts = boundaries(held, part)
        cuts = np.searchsorted(starts, part).tolist()
        at, raw = [*starts.tolist(), len(held)], held.tobytes()
        for i, j in zip(cuts, cuts[1:], strict=False):
            yield b"".join([pieces[raw[x:y]] for x, y in zip(at[i:j], at[i + 1 : j + 1], strict=True)])


class Vocabulary:
    """Decoding by a gather: id -> bytes."""

    def __init__(self, ranks: dict[bytes, int]) -> None:
        self.tokens = [b""] * (max(ranks.values(), default=-1) + 1)
        for token, rank in ranks.items():
            self.tokens[rank] = token
        self.lengths = np.array([len(t) for t in self.tokens], np.int64)

    def decode(self, ids: bytes) -> bytes:
        return b"".join(map(self.tokens.__getitem__, np.frombuffer(ids, "<u4").tolist()))

    def offsets(self, ids: bytes) -> np.ndarray:
        """The byte at which each id starts."""
        lengths = self.lengths[np.frombuffer(ids, "<u4")]
        return np.cumsum(lengths) - lengths


def _mapped(docs: DataFrame, ranks_path: str, text: str, doc_id: str, schema: str, make) -> DataFrame:
    holder = docs.sparkSession.sparkContext.broadcast(load_ranks(ranks_path))  # bounded by the vocabulary

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        pieces, vocabulary = Pieces(holder.value), Vocabulary(holder.value)
        for batch in batches:
            data, offsets = utf8(batch.column(1))
            yield make(batch.column(0), encode_texts(data, offsets, pieces), vocabulary)

    chosen = docs.select(F.col(doc_id).alias("doc_id"), F.col(text).cast("string").alias("text"))
    kind = docs.schema[doc_id].dataType.simpleString()
    return chosen.mapInArrow(trimmed(run), f"doc_id {kind}, {schema}")


def encode(docs: DataFrame, ranks_path: str, text: str = "text", doc_id: str = "doc_id") -> DataFrame:
    """doc_id, ids array<long>, offsets array<long> (first byte of each id in the text's UTF-8)."""

    def make(keys: pa.Array, texts: Iterator[bytes], vocabulary: Vocabulary) -> pa.RecordBatch:
        held = list(texts)
        ids = pa.array([np.frombuffer(x, "<u4").astype(np.int64) for x in held], pa.list_(pa.int64()))
        at = pa.array([vocabulary.offsets(x) for x in held], pa.list_(pa.int64()))
        return pa.RecordBatch.from_arrays([keys, ids, at], names=["doc_id", "ids", "offsets"])

    return _mapped(docs, ranks_path, text, doc_id, "ids array<long>, offsets array<long>", make)


def decode(encoded: DataFrame, ranks_path: str, ids: str = "ids", doc_id: str = "doc_id") -> DataFrame:
    """doc_id, data binary: the bytes of each row's ids (null: none)."""
    holder = encoded.sparkSession.sparkContext.broadcast(load_ranks(ranks_path))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        vocabulary = Vocabulary(holder.value)
        for batch in batches:
            out = [vocabulary.decode(np.array(x or [], "<u4").tobytes()) for x in batch.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(out, pa.binary())], names=["doc_id", "data"])

    kind = encoded.schema[doc_id].dataType.simpleString()
    return encoded.select(F.col(doc_id).alias("doc_id"), F.col(ids).alias("ids")).mapInArrow(trimmed(run), f"doc_id {kind}, data binary")


def token_digests(docs: DataFrame, ranks_path: str, text: str = "text", doc_id: str = "doc_id") -> DataFrame:
    """doc_id, n_tokens, ids_sha256, decoded_sha256, n_bytes: encodes, then decodes the ids, without shipping them."""

    def make(keys: pa.Array, texts: Iterator[bytes], vocabulary: Vocabulary) -> pa.RecordBatch:
        n, ids_sha, text_sha, sizes = [], [], [], []
        for ids in texts:
            back = vocabulary.decode(ids)
            n.append(len(ids) // 4)
            ids_sha.append(hashlib.sha256(ids).hexdigest())
            text_sha.append(hashlib.sha256(back).hexdigest())
            sizes.append(len(back))
        columns = [keys, pa.array(n, pa.int64()), pa.array(ids_sha, pa.string()), pa.array(text_sha, pa.string()), pa.array(sizes, pa.int64())]
        return pa.RecordBatch.from_arrays(columns, names=["doc_id", "n_tokens", "ids_sha256", "decoded_sha256", "n_bytes"])

    return _mapped(docs, ranks_path, text, doc_id, "n_tokens long, ids_sha256 string, decoded_sha256 string, n_bytes long", make)
