"""Byte-level BPE through a sentencepiece model that is written straight from a rank vocabulary.

Every byte b is shown to sentencepiece as the single character U+0100+b, so the model needs neither byte fallback nor
normalisation.  Piece number r is the byte string of rank r with score -r: sentencepiece joins the adjacent pair whose
union scores best, leftmost first, which is the lowest rank first rule of rank vocabularies.  Decoding is the inverse map.

Defined results: a null or empty text has no ids and decodes to no bytes; other columns of the input pass through
unchanged and repeated rows stay repeated; a column named like an output column is replaced by it.  Texts of any length
are encoded whole.

A worker makes its encoder once and keeps it for later tasks; batches have few rows on the way to it and few bytes of text
on the way back, so neither its memory nor the executor's for batches follows the number of tasks or rows.
"""

from __future__ import annotations

import base64
import functools
import struct
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import types as T

from .piece_cache import PieceCache
from .shared import small_batches
from .word_tokens import spans


def read_ranks(path: str) -> dict[bytes, int]:
    with open(path, "rb") as f:
        return {base64.b64decode(piece): int(rank) for piece, rank in map(bytes.split, f)}


def _varint(n: int) -> bytes:
    out = bytearray()
    n &= (1 << 64) - 1
    while n > 127:
        out.append(n & 127 | 128)
        n >>= 7
    out.append(n)
    return bytes(out)


def _field(number: int, value: bytes | int | float) -> bytes:
    """One protocol-buffer field: bytes, integers and 32-bit floats are all that the model needs."""
    if isinstance(value, bytes):
        return _varint(number << 3 | 2) + _varint(len(value)) + value
    if isinstance(value, float):
        return _varint(number << 3 | 5) + struct.pack("<f", value)
    return _varint(number << 3) + _varint(value)


_SHIFT = {b: chr(0x100 + b) for b in range(256)}


def show_bytes(raw: bytes) -> str:
    """Bytes as the characters U+0100..U+01FF."""
    return raw.decode("latin-1").translate(_SHIFT)


def hide_bytes(shown: str) -> bytes:
    return bytes(ord(c) - 0x100 for c in shown)


def sentencepiece_model(ranks: dict[bytes, int]) -> bytes:
    """A serialised sentencepiece BPE model whose piece ids are the ranks; the unknown piece, never met, comes last."""
    # Field numbers and enum members of the public sentencepiece model format.
    pieces, trainer, normalizer = 1, 2, 3
    piece_text, piece_score, piece_type = 1, 2, 3
    type_unknown, model_kind, kind_bpe, vocabulary, unk, bos, eos, pad = 2, 3, 2, 4, 40, 41, 42, 43
    rule_name, dummy_prefix, squeeze_spaces, escape_spaces = 1, 3, 4, 5

    ordered = sorted(ranks, key=ranks.__getitem__)
    if [ranks[p] for p in ordered] != list(range(len(ordered))):
        raise ValueError("ranks must be 0, 1, 2, ... without gaps")
    out = [_field(pieces, _field(piece_text, show_bytes(p).encode()) + _field(piece_score, float(-r))) for r, p in enumerate(ordered)]
    out.append(_field(pieces, _field(piece_text, b"<unk>") + _field(piece_score, 0.0) + _field(piece_type, type_unknown)))
    out.append(_field(trainer, _field(model_kind, kind_bpe) + _field(vocabulary, len(ordered) + 1) + _field(unk, len(ordered)) + b"".join(_field(n, -1) for n in (bos, eos, pad))))
    out.append(_field(normalizer, _field(rule_name, b"identity") + b"".join(_field(n, 0) for n in (dummy_prefix, squeeze_spaces, escape_spaces))))
    return b"".join(out)


class ByteBpe:
    """Encoder and decoder; ``pattern`` cuts a text into pre-tokens, which never merge with each other."""

    def __init__(self, vocab_path: str, pattern: str) -> None:
        import regex
        import sentencepiece

        self.ranks = read_ranks(vocab_path)
        self.model = sentencepiece.SentencePieceProcessor(model_proto=sentencepiece_model(self.ranks))
        self.split = regex.compile(pattern).findall
        self.bytes_of = [hide_bytes(self.model.id_to_piece(i)) for i in range(len(self.ranks))]
        self.memo = PieceCache(self._pieces(), 100_000)

    def _pieces(self) -> Callable[[str], bytes]:
        """Encodes one pre-token.  It does not hold the encoder, whose memo holds it, so an encoder goes with its last use."""
        ranks, model = self.ranks, self.model

        def encoded(piece: str) -> bytes:
            raw = piece.encode("utf-8")
            # A pre-token that is itself in the vocabulary is that one token, reachable by merges or not.
            ids = [ranks[raw]] if raw in ranks else model.encode(show_bytes(raw))
            return np.asarray(ids, dtype="<i4").tobytes()

        return encoded

    def encode(self, text: str) -> bytes:
        """The ids as little-endian 32-bit integers."""
        return b"".join(map(self.memo.__getitem__, self.split(text)))

    def decode(self, ids: bytes) -> bytes:
        return b"".join(map(self.bytes_of.__getitem__, np.frombuffer(ids, dtype="<i4").tolist()))


@functools.lru_cache(maxsize=1)
def worker_encoder(vocab_path: str, pattern: str) -> ByteBpe:
    """One encoder for each Python worker."""
    return ByteBpe(vocab_path, pattern)


def bpe_round_trip(docs: DataFrame, vocab_path: str, pattern: str, *, text: str = "text") -> DataFrame:
    """``docs`` without its text, with token_ids array<int> and decoded binary (the ids' bytes) for each row.  No shuffle."""
    carried = [c for c in docs.columns if c not in (text, "token_ids", "decoded")]
    source = docs.select(*carried, text)
    schema = T.StructType([source.schema[c] for c in carried] + [T.StructField("token_ids", T.ArrayType(T.IntegerType(), False)), T.StructField("decoded", T.BinaryType())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bpe = worker_encoder(vocab_path, pattern)
        for batch in batches:
            for part in spans(batch, len(carried)):
                ids = [bpe.encode(t) if t else b"" for t in part.column(len(carried)).to_pylist()]
                ends = np.concatenate([[0], np.cumsum([len(x) // 4 for x in ids])]).astype("i4")
                lists = pa.ListArray.from_arrays(pa.array(ends), pa.array(np.frombuffer(b"".join(ids), dtype="<i4")))
                yield pa.RecordBatch.from_arrays([*part.columns[:-1], lists, pa.array([bpe.decode(x) for x in ids], pa.binary())], names=[*carried, "token_ids", "decoded"])

    return small_batches(source).mapInArrow(run, schema)
