"""Packing along a space-filling curve.

A document's token counts are hashed into a short vector, log-scaled, set to unit length and projected to few dimensions
by fixed random signs; the projections, cut into equal-probability steps, give a Hilbert key.  Documents are range-sorted
by that key and cut into sequences in curve order, so a sequence holds documents of like vocabulary.  Every range cuts its
own run: sequences are full but for the run's tail, which becomes sequences whose lengths are the powers of two that sum to
it.  So nothing is padded at all.

Defined results: a null or empty text is its end id alone; null ids are packed like others; equal keys are ordered by id
and size; rows that repeat an id are packed once each.  A sequence id names the range in its high bits and counts from 0
within it.  An empty table gives no pieces; extra columns are not read.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .shared import settle, small_batches
from .word_tokens import spans, word_tokens

BUCKETS = 256
#: Tokens of a range on average: 2,000 sequences of 2,048.
RANGE_TOKENS = 1 << 22


def hilbert_keys(cells: np.ndarray, bits: int) -> np.ndarray:
    """Positions on the Hilbert curve of points (rows) with integer coordinates of ``bits`` bits.

    Works on all points at once, one bit plane after the other: the low bits of the axes are inverted or exchanged as the
    planes above demand, then the Gray code is undone and the planes are interleaved.
    """
    x = cells.astype(np.int64).T.copy()
    dims = len(x)
    for plane in range(bits - 1, 0, -1):
        low = (1 << plane) - 1
        for d in range(dims):
            inverted = (x[d] >> plane & 1).astype(bool)
            swap = np.where(inverted, 0, (x[0] ^ x[d]) & low)
            x[0] ^= np.where(inverted, low, swap)
            x[d] ^= swap
    for d in range(1, dims):
        x[d] ^= x[d - 1]
    parity = np.zeros_like(x[0])
    for plane in range(bits - 1, 0, -1):
        parity ^= np.where(x[-1] >> plane & 1, (1 << plane) - 1, 0)
    x ^= parity
    key = np.zeros_like(x[0])
    for plane in range(bits - 1, -1, -1):
        for d in range(dims):
            key = key << 1 | (x[d] >> plane & 1)
    return key


class CurvePlacement:
    def __init__(self, vocab_size: int, dims: int = 4, bits: int = 10, seed: int = 11) -> None:
        rng = np.random.default_rng(seed)
        self.bucket_of = rng.integers(0, BUCKETS, vocab_size)
        self.signs = rng.choice([-1.0, 1.0], (BUCKETS, dims))
        self.bits = bits

    def vectors(self, ids: np.ndarray, ends: np.ndarray) -> np.ndarray:
        """A unit vector for each document; ``ends`` holds the position after each one's ids."""
        whose = np.repeat(np.arange(len(ends)), np.diff(ends, prepend=0))
        v = np.log1p(np.bincount(whose * BUCKETS + self.bucket_of[ids], minlength=len(ends) * BUCKETS).reshape(-1, BUCKETS))
        return v / np.maximum(np.linalg.norm(v, axis=1), 1e-300)[:, None]

    def keys(self, vectors: np.ndarray) -> np.ndarray:
        # Projections of unit vectors have unit variance; the logistic curve spreads them evenly over the cells.
        spread = 1 / (1 + np.exp(-1.7 * (vectors @ self.signs)))
        return hilbert_keys(np.minimum((spread * (1 << self.bits)).astype(np.int64), (1 << self.bits) - 1), self.bits)


def with_end(ids: np.ndarray, ends: np.ndarray, end_id: int) -> tuple[np.ndarray, np.ndarray]:
    """Every document's ids with the end id behind them."""
    return np.insert(ids, ends, end_id), ends + np.arange(1, len(ends) + 1)


def tokenised_with_keys(docs: DataFrame, vocab_path: str, *, end_id: int = 1, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """(doc_id, curve_key, n, ids): ids with the end id, in as few bytes each as the vocabulary allows."""
    source = docs.select(F.col(doc_id).alias("doc_id"), F.coalesce(F.col(text), F.lit("")).alias("text"))
    schema = T.StructType([source.schema["doc_id"], T.StructField("curve_key", T.LongType()), T.StructField("n", T.LongType()), T.StructField("ids", T.BinaryType())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        words = word_tokens(vocab_path)
        place, narrow = CurvePlacement(words.size), np.dtype(id_type(words.size))
        for batch in batches:
            for piece in spans(batch, 1):
                ids, ends = with_end(*words.encode(piece.column(1).to_pylist()), end_id)
                packed, borders = ids.astype(narrow), np.concatenate([[0], ends]).astype(np.int64) * narrow.itemsize
                raw = pa.Array.from_buffers(pa.large_binary(), len(ends), [None, pa.py_buffer(borders), pa.py_buffer(packed)]).cast(pa.binary())
                yield pa.RecordBatch.from_arrays([piece.column(0), pa.array(place.keys(place.vectors(ids, ends))), pa.array(np.diff(ends, prepend=0)), raw], names=schema.names)
            pa.default_memory_pool().release_unused()

    return small_batches(source).mapInArrow(run, schema)


def id_type(vocab_size: int) -> str:
    return "<u2" if vocab_size <= 1 << 16 else "<u4"


class _Cutter:
    """Cuts one run of documents into sequences; holds the pieces of the sequence that is not yet full."""

    def __init__(self, width: int, first_sequence: int) -> None:
        self.width, self.sequence, self.filled = width, first_sequence, 0
        self.waiting: list[tuple] = []
        self.done: list[tuple] = []

    def add(self, doc_id, ids: np.ndarray) -> None:
        at = 0
        while at < len(ids):
            take = min(self.width - self.filled, len(ids) - at)
            self.waiting.append((doc_id, at, ids[at : at + take], len(ids)))
            at, self.filled = at + take, self.filled + take
            if self.filled == self.width:
                self._seal(self.waiting)
                self.waiting, self.filled = [], 0

    def _seal(self, pieces: list[tuple]) -> None:
        offset = 0
        for doc_id, start, ids, whole in pieces:
            self.done.append((doc_id, start, len(ids), ids.astype("<u4").tobytes(), whole, self.sequence, offset))
            offset += len(ids)
        self.sequence += 1

    def finish(self) -> None:
        """The tail, as sequences of falling powers of two."""
        rest, pieces = self.filled, self.waiting
        while rest:
            room = 1 << (rest.bit_length() - 1)
            rest -= room
            now = []
            while room:
                doc_id, start, ids, whole = pieces[0]
                take = min(room, len(ids))
                now.append((doc_id, start, ids[:take], whole))
                room -= take
                pieces = [(doc_id, start + take, ids[take:], whole), *pieces[1:]] if take < len(ids) else pieces[1:]
            self._seal(now)


def curve_packed(docs: DataFrame, vocab_path: str, *, width: int = 2048, end_id: int = 1, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """Pieces (doc_id, start, length, ids, doc_tokens, sequence_id, offset); ids are little-endian unsigned 32-bit integers.

    The ids are written once, so that finding the ranges does not encode twice; then one range shuffle brings neighbours
    on the curve together.  A key that many documents share is split by id.
    """
    tokens = settle(tokenised_with_keys(docs, vocab_path, end_id=end_id, doc_id=doc_id, text=text))
    # Long documents lie near each other on the curve, so the number of ranges follows the tokens: a task's share is bounded at any size.
    total = tokens.agg(F.sum("n")).first()[0] or 0
    ranges = max(int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions")), math.ceil(total / RANGE_TOKENS))
    ordered = tokens.repartitionByRange(ranges, "curve_key", "doc_id", "n").sortWithinPartitions("curve_key", "doc_id", "n", "ids")
    schema = T.StructType([T.StructField("doc_id", tokens.schema["doc_id"].dataType), *(T.StructField(c, T.LongType()) for c in ("start", "length")), T.StructField("ids", T.BinaryType()), *(T.StructField(c, T.LongType()) for c in ("doc_tokens", "sequence_id", "offset"))])
    kind = pa.schema([("doc_id", pa.int64()), ("start", pa.int64()), ("length", pa.int64()), ("ids", pa.binary()), ("doc_tokens", pa.int64()), ("sequence_id", pa.int64()), ("offset", pa.int64())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cut, narrow, names = _Cutter(width, TaskContext.get().partitionId() << 40), None, None

        def out() -> Iterator[pa.RecordBatch]:
            if cut.done:
                columns = list(zip(*cut.done, strict=True))
                yield pa.RecordBatch.from_arrays([pa.array(columns[0], names), *(pa.array(c, f.type) for c, f in zip(columns[1:], list(kind)[1:], strict=True))], names=schema.names)
                cut.done = []

        for batch in batches:
            names = batch.schema.field(0).type
            for piece in spans(batch, 2):
                for who, n, raw in zip(piece.column(0).to_pylist(), piece.column(1).to_pylist(), piece.column(2).to_pylist(), strict=True):
                    narrow = "<u2" if len(raw) == 2 * n else "<u4"
                    cut.add(who, np.frombuffer(raw, dtype=narrow))
                yield from out()
            pa.default_memory_pool().release_unused()
        cut.finish()
        yield from out()

    return small_batches(ordered.select("doc_id", "n", "ids")).mapInArrow(run, schema)
