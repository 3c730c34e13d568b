"""Token ids as ORC: one ascending run of documents over all files.

The ids are an ORC list of integers, which the format stores by its integer run-length encodings; every file carries row
indexes of a stated stride and a Bloom filter on the document id, so a lookup by id skips files, stripes and row groups by
metadata alone, and stripes can be read in parallel.  Files are in id order: file k holds ids that are not above those of
file k+1.  Each row stores its offset within its file's partition; the offset over all files is that plus the sum of the
partitions before, a table with one row per file.

Defined results: a null or empty text is a document of the end id alone; null ids come first; rows that repeat an id lie
next to each other, ordered by text.  An empty table gives an empty folder of files.  Clashing extra columns are not read.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .packing import with_end
from .shared import small_batches
from .word_tokens import spans, word_tokens


def write_token_orc(docs: DataFrame, path: str, vocab_path: str, *, doc_id: str = "doc_id", text: str = "text", end_id: int = 2, row_stride: int = 1000, bloom_fpp: float = 0.01) -> None:
    """Encode every whole text, append ``end_id`` and write (doc_id, part, start_in_part, n_tokens, ids) in ascending id order.

    One shuffle, of the texts by id range (the ids of a text are longer than the text itself); encoding follows it.
    """
    ordered = docs.select(F.col(doc_id).alias("doc_id"), F.coalesce(F.col(text), F.lit("")).alias("text"))
    ordered = ordered.repartitionByRange("doc_id").sortWithinPartitions("doc_id", "text")
    schema = T.StructType([ordered.schema["doc_id"], T.StructField("part", T.IntegerType()), T.StructField("start_in_part", T.LongType()), T.StructField("n_tokens", T.LongType()), T.StructField("ids", T.ArrayType(T.IntegerType(), False))])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        words, part, at = word_tokens(vocab_path), TaskContext.get().partitionId(), 0
        for batch in batches:
            for piece in spans(batch, 1):
                ids, ends = with_end(*words.encode(piece.column(1).to_pylist()), end_id)
                starts = np.concatenate([[0], ends])
                lists = pa.ListArray.from_arrays(pa.array(starts.astype("i4")), pa.array(ids.view(np.int32)))
                yield pa.RecordBatch.from_arrays([piece.column(0), pa.array(np.full(len(ends), part, "i4")), pa.array(at + starts[:-1]), pa.array(np.diff(starts)), lists], names=schema.names)
                at += int(starts[-1])
            pa.default_memory_pool().release_unused()

    (small_batches(ordered).mapInArrow(run, schema).write.mode("error").option("compression", "zstd").option("orc.bloom.filter.columns", "doc_id")
     .option("orc.bloom.filter.fpp", str(bloom_fpp)).option("orc.row.index.stride", str(row_stride)).orc(path))


def read_token_orc(spark: SparkSession, path: str) -> DataFrame:
    """(doc_id, start, n_tokens, ids): ``start`` counts all ids before the document over all files."""
    rows = spark.read.orc(path)
    parts = rows.groupBy("part").agg(F.max(F.col("start_in_part") + F.col("n_tokens")).alias("total"))
    before = F.sum("total").over(Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1))
    # One row per written file, so its size follows the number of files and not the rows.
    starts = parts.select("part", F.coalesce(before, F.lit(0)).alias("before"))
    return rows.join(F.broadcast(starts), "part").select("doc_id", (F.col("before") + F.col("start_in_part")).alias("start"), "n_tokens", "ids")


def look_up(spark: SparkSession, path: str, doc_id: int) -> DataFrame:
    """The rows of one document; the filter reaches the ORC reader, which prunes by statistics and Bloom filter."""
    return spark.read.orc(path).where(F.col("doc_id") == F.lit(doc_id))


def id_checksums(tokens: DataFrame) -> DataFrame:
    """``tokens`` with ids replaced by ids_crc32, the unsigned crc32 of the little-endian 32-bit ids."""
    kept = [c for c in tokens.columns if c != "ids"]
    source = tokens.select(*kept, "ids")
    schema = T.StructType([source.schema[c] for c in kept] + [T.StructField("ids_crc32", T.LongType())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            lists = batch.column(len(kept))
            view, ends = memoryview(lists.values.to_numpy(zero_copy_only=False).astype("<i4", copy=False)).cast("B"), lists.offsets.to_numpy().astype("i8") * 4
            sums = [zlib.crc32(view[a:b]) for a, b in zip(ends[:-1], ends[1:], strict=True)]
            yield pa.RecordBatch.from_arrays([*batch.columns[:-1], pa.array(sums, pa.int64())], names=schema.names)

    return small_batches(source).mapInArrow(run, schema)
