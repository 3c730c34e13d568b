"""One-permutation MinHash fingerprints, as column expressions only.

A text's shingles (``SHINGLE`` words, white space as separator, case kept) are hashed once.  The high bits of a hash name
its bin, and a bin keeps its smallest hash.  An empty bin borrows from a bin chosen by a hash of its own number and the
attempt, so the choice is uniform over the filled bins and the same for every text (optimal densification); after
``ATTEMPTS`` misses the filled bin with the smallest hash of the pair of bin numbers is taken, again a uniform choice.
Of every bin the low 8 bits are kept, eight bins to a 64-bit word.

Likeness counts equal codes and removes the share that agrees by chance: with b bits, (m/k - 2^-b) / (1 - 2^-b), cut to
0..1.

Defined results: a null text counts as empty; a text without words has the empty fingerprint, alike to an empty one (1)
and to no other (0); fewer words than a shingle make one shingle of all.  Rows that repeat a doc_id each give a row; the
document "next" to them is the next smaller distinct id, by its smallest text if that id repeats.  A null id comes last,
after the smallest.  The only document is its own next.  Extra columns are not read.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .native import let
from .shared import settle

SHINGLE, BIN_BITS, CODE_BITS, ATTEMPTS = 5, 7, 8, 8
BINS, CODES_PER_WORD = 1 << BIN_BITS, 64 // CODE_BITS


def shingle_hashes(text: Column, width: int = SHINGLE) -> Column:
    """Hashes of all word shingles, repeats included; words are hashed once and shingles chain their words' hashes."""
    words = F.filter(F.split(text, r"[\x20\x09-\x0D]+"), lambda w: w != "")

    def shingles(h: Column) -> Column:
        starts = F.sequence(F.lit(0), F.greatest(F.size(h) - width, F.lit(0)))
        return F.when(F.size(h) == 0, F.array().cast("array<bigint>")).otherwise(F.transform(starts, lambda i: F.xxhash64(*(F.get(h, i + k) for k in range(width)))))

    return let(F.transform(words, lambda w: F.xxhash64(w)), shingles)


def _bin(h: Column) -> Column:
    return F.shiftrightunsigned(h, 64 - BIN_BITS).cast("int")


def bin_minima(hashes: Column) -> Column:
    """The smallest hash of each filled bin: hashes of a bin are neighbours once sorted."""
    return let(F.sort_array(hashes), lambda s: F.filter(s, lambda h, i: (i == 0) | (_bin(h) != _bin(F.get(s, i - 1)))))


def densified(minima: Column) -> Column:
    """One hash for each of the bins, empty ones filled from others."""

    def fill(m: Column) -> Column:
        filled = F.map_from_arrays(F.transform(m, _bin), m)

        def with_bins(v: Column) -> Column:
            def value(i: Column) -> Column:
                tries = [F.get(v, F.pmod(F.xxhash64(i, F.lit(t)), F.lit(BINS)).cast("int")) for t in range(ATTEMPTS)]
                last = F.array_min(F.transform(m, lambda h: F.struct(F.xxhash64(_bin(h), i, F.lit(-1)).alias("order"), h.alias("h"))))["h"]
                return F.coalesce(F.get(v, i), *tries, last)

            return F.transform(F.sequence(F.lit(0), F.lit(BINS - 1)), value)

        return let(F.transform(F.sequence(F.lit(0), F.lit(BINS - 1)), lambda i: F.try_element_at(filled, i)), with_bins)

    return let(minima, fill)


def fingerprint(text: Column) -> Column:
    """array<bigint> of BINS / 8 words of packed codes; empty for a text without words."""

    def pack(v: Column) -> Column:
        code = lambda w, k: F.shiftleft(F.get(v, w * CODES_PER_WORD + k).bitwiseAND(F.lit((1 << CODE_BITS) - 1).cast("bigint")), 64 - CODE_BITS * (k + 1))

        def word(w: Column) -> Column:
            out = code(w, 0)
            for k in range(1, CODES_PER_WORD):
                out = out.bitwiseOR(code(w, k))
            return out

        return F.transform(F.sequence(F.lit(0), F.lit(BINS // CODES_PER_WORD - 1)), word)

    none = F.array().cast("array<bigint>")
    return let(bin_minima(shingle_hashes(text)), lambda m: F.when(F.size(m) == 0, none).otherwise(let(densified(m), pack)))


def likeness(a: Column, b: Column) -> Column:
    """Estimated resemblance of two fingerprints, 0 to 1."""

    def differing(x: Column, y: Column) -> Column:
        # Any set bit of a byte is folded into the byte's lowest bit.
        fold = lambda value, step: let(value, lambda f: f.bitwiseOR(F.shiftrightunsigned(f, step)))
        folded = fold(fold(fold(x.bitwiseXOR(y), 4), 2), 1)
        return F.bit_count(folded.bitwiseAND(F.lit(0x0101010101010101)))

    unequal = F.aggregate(F.zip_with(a, b, differing), F.lit(0), lambda s, n: s + n)
    chance = 2.0**-CODE_BITS
    estimate = ((BINS - unequal) / F.lit(float(BINS)) - F.lit(chance)) / F.lit(1 - chance)
    both_empty = (F.size(a) == 0) & (F.size(b) == 0)
    return F.when(both_empty, F.lit(1.0)).when((F.size(a) == 0) | (F.size(b) == 0), F.lit(0.0)).otherwise(F.greatest(F.lit(0.0), F.least(F.lit(1.0), estimate)))


def as_text(words: Column) -> Column:
    return F.array_join(F.transform(words, lambda w: F.lpad(F.hex(w), 16, "0")), "")


def fingerprints(docs: DataFrame, *, text: str = "text") -> DataFrame:
    """``docs`` with a column fingerprint (packed words).  No shuffle."""
    return docs.withColumn("fingerprint", fingerprint(F.coalesce(F.col(text), F.lit(""))))


def neighbour_ids(ids: DataFrame) -> tuple[DataFrame, bool]:
    """For (doc_id, n): each distinct id, its greatest n and the id that follows it in falling order, the first after the last.  Also whether an id repeats.

    Ids are range-partitioned; within a range the next row follows, and a range's last id is joined to the first of the next
    range by a table with one row per range.
    """
    distinct = ids.groupBy("doc_id").agg(F.max("n").alias("n"), F.count("*").alias("rows"))
    ranged = settle(distinct.repartitionByRange(F.desc_nulls_last("doc_id")).withColumn("range", F.spark_partition_id()))
    heads = ranged.groupBy("range").agg(F.max(F.struct(F.col("doc_id").isNotNull().alias("known"), F.col("doc_id"))).alias("head"))
    by_range = Window.orderBy("range")
    following = heads.select("range", F.lead("head").over(by_range).alias("after"), F.first("head").over(by_range).alias("first"))
    within = Window.partitionBy("range").orderBy(F.desc_nulls_last("doc_id"))
    near = ranged.withColumn("inside", F.lead(F.struct("doc_id")).over(within)).join(F.broadcast(following), "range")
    next_id = F.when(F.col("inside").isNotNull(), F.col("inside.doc_id")).when(F.col("after").isNotNull(), F.col("after.doc_id")).otherwise(F.col("first.doc_id"))
    return near.select(F.col("doc_id").alias("owner"), F.col("n").alias("owner_n"), next_id.alias("next_id")), bool(ranged.where("rows > 1").limit(1).count())


def edited_fingerprints(docs: DataFrame) -> DataFrame:
    """(doc_id, n_chars, edited, fingerprint, edited_fingerprint, near_edited, near_next) for (doc_id, text).

    The edited text keeps a text's first half and ends with as much of the next document.  Texts are shuffled once by id
    (both joins read that exchange), and only the needed beginning of a text travels to its neighbour.
    """
    source = docs.select("doc_id", F.coalesce(F.col("text"), F.lit("")).alias("text"))
    links, repeats = neighbour_ids(source.select("doc_id", F.char_length("text").alias("n")))
    rows = source.withColumn("fp", fingerprint(F.col("text")))
    lent = links.join(rows, links["next_id"].eqNullSafe(rows["doc_id"])).select("owner", F.substring(F.col("text"), F.lit(1), F.floor(F.col("owner_n") / 2).cast("int")).alias("lent"), F.col("fp").alias("next_fp"))
    if repeats:
        lent = lent.groupBy("owner").agg(F.min(F.struct("lent", "next_fp")).alias("x")).select("owner", "x.lent", "x.next_fp")
    both = rows.join(lent, rows["doc_id"].eqNullSafe(lent["owner"]))
    n = F.char_length("text")
    half = F.floor(n / 2).cast("int")
    edited = F.concat(F.substring(F.col("text"), F.lit(1), n - half), F.substring(F.col("lent"), F.lit(1), half))
    done = both.select("doc_id", n.cast("long").alias("n_chars"), edited.alias("edited"), "fp", "next_fp").withColumn("edited_fp", fingerprint(F.col("edited")))
    return done.select("doc_id", "n_chars", "edited", F.col("fp").alias("fingerprint"), F.col("edited_fp").alias("edited_fingerprint"), likeness(F.col("fp"), F.col("edited_fp")).alias("near_edited"), likeness(F.col("fp"), F.col("next_fp")).alias("near_next"))
