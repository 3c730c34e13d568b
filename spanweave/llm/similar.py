"""One document of each group of similar ones: word shingles, Jaccard similarity of the shingle sets.

Documents that may be alike share a leaf.  The vantage-point tree of ``simhash`` gives a leaf for each component of
fingerprints that differ by a few bits.  Its radius cannot grow to where the similarity bound lies (at 0.8 fingerprints
differ by some 10 bits of 64, and a search that wide visits most leaves), so there is also a leaf for each band of
min-hashes: two sets of similarity s share a band of ``ROWS`` with probability s^ROWS, and one of ``BANDS`` almost surely
(0.998 at s = 0.8).

Links are pairs whose sets themselves reach the bound.  Leaves may hold any share of the rows, so their members are never
brought together: in each round a few members of a leaf, its leaders, are compared with all later ones that are not connected
with them yet, pair by pair, and components grow by the links found.  A pair is looked at in full only if the parities of
its sets' members over ``PARITIES`` buckets allow a link: each parity in which two sets differ is a member that only one of
them has, so the sets share at most half of what their sizes have beyond these.  That bound is exact, so it loses no link, and of a
group of edited copies little more than the links pass.  Only texts of sets that share a leaf are read again
for their shingles, kept as 32 bits each.  Leaders are new ones in each round, eight times as
many as before.  A leaf is done when it is connected or when all but one of its members have been leaders; so every pair of
a leaf has been compared or is connected.  Of documents that links connect the one with the smallest id stays.

Defined results: a null text counts as empty, and texts without words are alike; fewer words than a shingle make one
shingle; of rows with equal sets one stays; a null id stays only where all its group's are null.
"""

from __future__ import annotations

import functools
import itertools
import operator
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..operators.components import connected_components
from .shared import settle, small_batches
from .simhash import linked_fingerprints, majority_bits

SHINGLE, LEAST = 5, 0.8
BANDS, ROWS = 16, 5
#: Bits: of the tree's links; and beyond which sets of at least so many shingles are never alike (at 0.8 the mean is 10, the deviation 3).
RADIUS, FAR, ENOUGH = 2, 24, 100
#: Buckets of members' parities, a power of two and of whole 64-bit words; for sets of some thousand shingles they allow nearly all pairs.
PARITIES = 1024
FIRST_LEADERS, TIMES_LEADERS = 1, 8
_SEED = np.random.default_rng(21)
_TIMES, _PLUS = _SEED.integers(0, 1 << 63, (2, BANDS * ROWS, 1), dtype=np.uint64)
_TIMES |= np.uint64(1)


def shingle_hashes(text: str, shingle: int = SHINGLE) -> np.ndarray:
    """XXH64 of each word shingle in order, repeats included; words as in ``simhash``."""
    from xxhash import xxh64_intdigest

    words = text.encode().lower().split()
    if not words:
        return np.zeros(0, dtype=np.uint64)
    parts = [b" ".join(words)] if len(words) < shingle else map(b" ".join, zip(*(itertools.islice(words, k, None) for k in range(shingle)), strict=False))
    return np.array([xxh64_intdigest(p, 42) for p in parts], dtype=np.uint64)


def band_keys(members: np.ndarray) -> np.ndarray:
    """A signed 64-bit key for each band of a set's min-hashes; an empty set has keys of its own."""
    from xxhash import xxh64_intdigest

    least = np.full(BANDS * ROWS, (1 << 64) - 1, dtype=np.uint64)
    for at in range(0, len(members), 1024):
        mixed = members[None, at : at + 1024] * _TIMES + _PLUS
        mixed ^= mixed >> np.uint64(32)
        np.minimum(least, (mixed * np.uint64(0x9E3779B97F4A7C15)).min(axis=1), out=least)
    return np.array([xxh64_intdigest(b.tobytes(), k) for k, b in enumerate(least.reshape(BANDS, ROWS))], dtype=np.uint64).view(np.int64)


def parities(members: np.ndarray) -> np.ndarray:
    """Whether each bucket of the members' leading bits holds an odd number of them, as signed 64-bit words."""
    odd = np.bincount((members >> np.uint64(65 - PARITIES.bit_length())).astype(np.int64), minlength=PARITIES) & 1
    return np.packbits(odd.astype(bool), bitorder="little").view(np.int64)


def may_be_alike(a: str, b: str, least: float = LEAST) -> F.Column:
    """Whether sizes and parities of the sets named a and b allow a similarity of ``least``; true for all that have it."""
    n, m = F.col(f"{a}.n"), F.col(f"{b}.n")
    differ = functools.reduce(operator.add, (F.bit_count(F.col(f"{a}.odd")[k].bitwiseXOR(F.col(f"{b}.odd")[k])) for k in range(PARITIES // 64)))
    # Of sets that share c members n + m - 2c differ, and c >= least (n + m - c) makes that (1 - least) / (1 + least) of n + m at most; the last term is for rounding.
    return (F.least(n, m) >= least * F.greatest(n, m)) & ((1 + least) * differ <= (1 - least) * (n + m) + 1e-6)


def _sketches(docs: DataFrame) -> DataFrame:
    """(doc_id, text_hash, set_id, n, fp, bands, odd): the hash and size of the set, its fingerprint, its bands and its parities."""
    source = docs.select("doc_id", F.xxhash64(F.coalesce("text", F.lit(""))).alias("text_hash"), F.coalesce("text", F.lit("")).alias("text"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from xxhash import xxh64_intdigest

        for batch in batches:
            for at in range(0, batch.num_rows, 256):
                part = batch.slice(at, 256)
                ids, sizes, prints, bands, odd = [], [], [], [], []
                for t in part.column(2):
                    every = shingle_hashes(t.as_py())
                    own = np.unique(every)
                    ids.append(xxh64_intdigest(own.tobytes(), 7))
                    sizes.append(len(own))
                    prints.append(majority_bits(every))
                    bands.append(band_keys(own))
                    odd.append(parities(own))
                signed = lambda x: pa.array(np.array(x, dtype=np.uint64).view(np.int64))
                lists = [pa.ListArray.from_arrays(pa.array(np.arange(len(x) + 1, dtype=np.int32) * len(x[0])), pa.array(np.concatenate(x))) for x in (bands, odd)]
                yield pa.RecordBatch.from_arrays([part.column(0), part.column(1), signed(ids), pa.array(sizes, pa.int32()), signed(prints), *lists], names=["doc_id", "text_hash", "set_id", "n", "fp", "bands", "odd"])

    return small_batches(source).mapInArrow(run, f"doc_id {docs.schema['doc_id'].dataType.simpleString()}, text_hash bigint, set_id bigint, n int, fp bigint, bands array<bigint>, odd array<bigint>")


def alike(pairs: DataFrame, least: float = LEAST) -> DataFrame:
    """(src, dst) of the pairs (src, dst, a, b) whose sorted hash sets a and b have a Jaccard similarity of ``least`` or more; empty sets are alike."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            keep = []
            for a, b in zip(batch.column(2), batch.column(3), strict=True):
                x, y = np.frombuffer(a.as_py(), np.uint32), np.frombuffer(b.as_py(), np.uint32)
                at = np.searchsorted(y, x)
                both = int((y[np.minimum(at, len(y) - 1)] == x).sum()) if len(x) and len(y) else 0
                keep.append(both >= least * (len(x) + len(y) - both))
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1)], names=["src", "dst"]).filter(pa.array(keep, pa.bool_()))

    return small_batches(pairs.select("src", "dst", "a", "b")).mapInArrow(run, "src bigint, dst bigint")


def leaves_of(distinct: DataFrame) -> DataFrame:
    """(leaf, id, n, fp): the leaves that more than one set shares."""
    prints = settle(distinct.groupBy("fp").agg(F.count("*").alias("sets")))
    parts = connected_components(settle(linked_fingerprints(prints, RADIUS)))
    near = prints.join(parts.withColumnRenamed("vertex", "fp").hint("merge"), "fp", "left").where("component is not null or sets > 1")
    by_tree = distinct.join(near.select("fp", F.xxhash64(F.lit("tree"), F.coalesce("component", "fp")).alias("leaf")).hint("merge"), "fp")
    member = ("leaf", F.col("set_id").alias("id"), "n", "fp")
    every = by_tree.select(*member).unionByName(distinct.select(F.explode("bands").alias("leaf"), "set_id", "n", "fp").select(*member))
    shared = every.groupBy("leaf").agg(F.min("id").alias("low"), F.max("id").alias("high")).where("low < high").select("leaf")
    return every.join(shared.hint("merge"), "leaf", "left_semi")


def members_of(docs: DataFrame, wanted: DataFrame) -> DataFrame:
    """(id, members): the sorted 32-bit hashes of the sets of wanted(id, doc_id, text_hash), one text for each."""
    texts = docs.select("doc_id", F.xxhash64(F.coalesce("text", F.lit(""))).alias("text_hash"), F.coalesce("text", F.lit("")).alias("text"))
    w = wanted.select("id", F.col("doc_id").alias("wanted_id"), F.col("text_hash").alias("wanted_hash")).hint("merge")
    found = texts.join(w, texts["doc_id"].eqNullSafe(F.col("wanted_id")) & (texts["text_hash"] == F.col("wanted_hash"))).select("id", "text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            own = [np.unique((shingle_hashes(t.as_py()) & np.uint64(0xFFFFFFFF)).astype(np.uint32)).tobytes() for t in batch.column(1)]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(own, pa.binary())], names=["id", "members"])

    return small_batches(found).mapInArrow(run, "id bigint, members binary").dropDuplicates(["id"])


def similar_sets(distinct: DataFrame, docs: DataFrame) -> DataFrame:
    """(id, component) of the sets that share a leaf with others, components by links; ``distinct`` holds (set_id, n, fp, bands, odd, doc_id, text_hash), the last two of a text that has the set."""
    # ``place`` orders members by a hash that is the same in all leaves, so that leaves of the same texts have the same leaders.
    odd = distinct.select(F.col("set_id").alias("id"), "odd").hint("merge")
    members = settle(leaves_of(distinct).join(odd, "id").withColumn("place", F.xxhash64("id")).withColumn("component", F.col("id")))
    wanted = distinct.select(F.col("set_id").alias("id"), "doc_id", "text_hash").join(members.select("id").distinct().hint("merge"), "id", "left_semi")
    held = settle(members_of(docs, wanted))
    parts = settle(members.select("id").distinct().withColumn("component", F.col("id")))
    before, upto = 0, FIRST_LEADERS
    while not members.isEmpty():
        order = F.row_number().over(Window.partitionBy("leaf").orderBy("place", "id"))
        leaders = members.withColumn("rank", order).where(F.col("rank") <= upto).where(F.col("rank") > before)
        a, b = members.alias("a"), leaders.alias("b").hint("merge")
        later = (F.col("a.place") > F.col("b.place")) | ((F.col("a.place") == F.col("b.place")) & (F.col("a.id") > F.col("b.id")))
        apart = (F.bit_count(F.col("a.fp").bitwiseXOR(F.col("b.fp"))) > FAR) & (F.least("a.n", "b.n") >= ENOUGH)
        pairs = a.join(b, F.col("a.leaf") == F.col("b.leaf")).where((F.col("a.component") != F.col("b.component")) & later & may_be_alike("a", "b") & ~apart)
        pairs = pairs.select(F.least("a.id", "b.id").alias("src"), F.greatest("a.id", "b.id").alias("dst")).distinct()
        whole = pairs.join(held.select(F.col("id").alias("src"), F.col("members").alias("a")).hint("merge"), "src").join(held.select(F.col("id").alias("dst"), F.col("members").alias("b")).hint("merge"), "dst")
        # New links join components of the rounds before, so each round works on what is left to be connected.
        ends = [parts.select(F.col("id").alias(c), F.col("component").alias(f"of_{c}")) for c in ("src", "dst")]
        found = alike(whole).join(ends[0], "src").join(ends[1], "dst").where("of_src <> of_dst")
        found = settle(found.select(F.least("of_src", "of_dst").alias("src"), F.greatest("of_src", "of_dst").alias("dst")).distinct())
        if not found.isEmpty():
            names = connected_components(found).select(F.col("vertex").alias("component"), F.col("component").alias("joined"))
            parts = settle(parts.join(names, "component", "left").select("id", F.coalesce("joined", "component").alias("component")))
        labelled = members.drop("component").join(parts.hint("merge"), "id")
        before, upto = upto, upto * TIMES_LEADERS
        open_ = labelled.groupBy("leaf").agg(F.min("component").alias("low"), F.max("component").alias("high"), F.count("*").alias("members")).where(f"low < high and members > {before} + 1").select("leaf")
        members = settle(labelled.join(open_.hint("merge"), "leaf", "left_semi"))
    return parts


def keep_one(docs: DataFrame) -> DataFrame:
    """``docs`` with one row of each group of similar documents, that with the smallest id."""
    sketches = settle(_sketches(docs))
    row = F.struct(F.col("doc_id").isNull().alias("nameless"), "doc_id", "text_hash")
    distinct = settle(sketches.groupBy("set_id").agg(F.min(row).alias("row"), F.min("n").alias("n"), F.min("fp").alias("fp"), F.min("bands").alias("bands"), F.min("odd").alias("odd")))
    parts = similar_sets(distinct.select("set_id", "n", "fp", "bands", "odd", "row.doc_id", "row.text_hash"), docs)
    grouped = distinct.join(parts.withColumnRenamed("id", "set_id").hint("merge"), "set_id", "left")
    first = grouped.groupBy(F.coalesce("component", "set_id").alias("component")).agg(F.min("row").alias("row")).select(F.col("row.doc_id").alias("kept_id"), F.col("row.text_hash").alias("kept_hash"))
    hashed = docs.withColumn("_hash", F.xxhash64(F.coalesce("text", F.lit(""))))
    out = hashed.join(settle(first).hint("merge"), hashed["doc_id"].eqNullSafe(F.col("kept_id")) & (F.col("_hash") == F.col("kept_hash")), "left_semi")
    return out.dropDuplicates(["doc_id", "_hash"]).select(docs.columns)
