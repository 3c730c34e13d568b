"""SimHash near-duplicates found through a vantage-point tree.

Tree.  Every node has a vantage point, one of a bounded sample (``SAMPLE``) of the fingerprints that reach it, and the median
Hamming distance to it as its radius; those within the radius are inside, the others outside.  By the triangle inequality a
search of radius r needs the inside only for distances up to the node's radius + r, and the outside only for those above the
radius - r.  The tree is fitted on the driver and as deep as leaves of ``LEAF_MEAN`` fingerprints on average need.

Shards.  A leaf is a shard.  Every distinct fingerprint lives in its own leaf.  One that lives outside a node and whose ball
overlaps the inside is also sent there as a guest, and on to all leaves that its ball overlaps, so each pair meets exactly
once.  Within a leaf the tree goes on in memory, with vantage points and radii of the leaf's own members, down to a few
hundred members, which are compared bit by bit.  However many fingerprints a leaf has, it is split to that size.

A leaf reports a spanning forest of its links, never the pairs themselves, and components are found on those forests.

Defined results: a null text counts as empty; a text without words has fingerprint 0 and links like any other; fewer words
than a shingle make one shingle; repeated rows and ids each keep their row; a null id never names a component unless all
its members are null.  Extra columns are not read.
"""

from __future__ import annotations

import itertools
import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators.components import connected_components
from .shared import settle

#: Fingerprints that the tree is fitted on, members of a leaf on average, and those of a leaf's own leaves.
SAMPLE, LEAF_MEAN, INNER_LEAF = 1 << 16, 4096, 256


def simhash(text: str, shingle: int) -> int:
    """A bit is 1 if it is set in over half of the hashes (XXH64, seed 42) of the word shingles, repeats included."""
    from xxhash import xxh64_intdigest

    words = text.encode().lower().split()  # of bytes: lowers A-Z only, splits at \x20 and \x09-\x0d
    if not words:
        return 0
    parts = [b" ".join(words)] if len(words) < shingle else map(b" ".join, zip(*(itertools.islice(words, k, None) for k in range(shingle)), strict=False))
    return majority_bits(np.array([xxh64_intdigest(p, 42) for p in parts], dtype="<u8"))


def majority_bits(hashes: np.ndarray) -> int:
    """The bits that are set in over half of the hashes; none of no hashes."""
    ones = np.zeros(64, dtype=np.int64)
    for at in range(0, len(hashes), 4096):
        ones += np.unpackbits(hashes[at : at + 4096].view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    return int(np.packbits(ones * 2 > len(hashes), bitorder="little").view("<u8")[0])


def simhashes(docs: DataFrame, *, doc_id: str = "doc_id", text: str = "text", shingle: int = 3) -> DataFrame:
    """(doc_id, fp): the fingerprint as a signed 64-bit integer."""
    source = docs.select(F.col(doc_id).alias("doc_id"), F.coalesce(F.col(text), F.lit("")).alias("text"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found = np.array([simhash(t.as_py(), shingle) for t in batch.column(1)], dtype="<u8").view("<i8")
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(found)], names=["doc_id", "fp"])

    return source.mapInArrow(run, f"doc_id {docs.schema[doc_id].dataType.simpleString()}, fp bigint")


def vantage(members: np.ndarray) -> tuple[np.uint64, int]:
    """A vantage point among the members and its median distance: of a few, the one whose distances differ most."""
    some, best = members[:: max(1, len(members) // 512)][:512], None
    for point in some[:: max(1, len(some) // 5)][:5]:
        d = np.bitwise_count(some ^ point)
        if best is None or d.var() > best[0]:
            best = (d.var(), point, int(np.median(d)))
    return best[1], best[2]


class Tree:
    """A complete binary tree of vantage points and radii, in arrays as a heap: children of node n are 2n+1 (inside) and 2n+2 (outside)."""

    def __init__(self, sample: np.ndarray, depth: int) -> None:
        self.depth, nodes = depth, (1 << depth) - 1
        self.points, self.radii = np.zeros(nodes, dtype=np.uint64), np.full(nodes, 64, dtype=np.int16)
        reached = {0: sample}
        for n in range(nodes):
            members = reached.pop(n)
            if len(members):
                self.points[n], self.radii[n] = vantage(members)
            inside = np.bitwise_count(members ^ self.points[n]) <= self.radii[n]
            reached[2 * n + 1], reached[2 * n + 2] = members[inside], members[~inside]

    def placed(self, fps: np.ndarray, radius: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(leaf, guest, fingerprint): each fingerprint at home, and as a guest where links to other leaves' members are looked for."""
        node, guest, held = np.zeros(len(fps), dtype=np.int64), np.zeros(len(fps), dtype=bool), fps
        for _ in range(self.depth):
            inside, outside, visits = sides(np.bitwise_count(held ^ self.points[node]), self.radii[node], guest, radius)
            both = np.concatenate
            node = both([2 * node[inside] + 1, 2 * node[visits] + 1, 2 * node[outside] + 2])
            held, guest = both([held[inside], held[visits], held[outside]]), both([guest[inside], np.ones(int(visits.sum()), dtype=bool), guest[outside]])
        return node - len(self.radii), guest, held


def sides(distance: np.ndarray, node_radius: np.ndarray, guest: np.ndarray, radius: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Which fingerprints go on inside and outside as what they are, and which at home outside visit the inside."""
    d, r = distance.astype(np.int16), node_radius
    inside = (d <= r) | guest & (d <= r + radius)
    outside = np.where(guest, d > r - radius, d > r)
    return inside, outside, ~guest & (d > r) & (d <= r + radius)


def fitted(distinct: DataFrame) -> Tree:
    """The tree of the distinct fingerprints; a count and a bounded sample by hash reach the driver."""
    total = distinct.count()
    depth = min(max(0, math.ceil(math.log2(max(total, 1) / LEAF_MEAN))), SAMPLE.bit_length() - 6)
    sample = distinct.select("fp").orderBy(F.xxhash64("fp")).limit(SAMPLE if depth else 0).toPandas()["fp"].to_numpy(dtype=np.int64)
    return Tree(sample.view(np.uint64), depth)


def sent_to_leaves(distinct: DataFrame, tree: Tree, radius: int) -> DataFrame:
    """(leaf, guest, fp): each fingerprint once at home and once as a guest of each leaf that it has to be compared in."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            fps = batch.column(0).to_numpy(zero_copy_only=False).view(np.uint64)
            for at in range(0, len(fps), 2048):
                leaf, guest, held = tree.placed(fps[at : at + 2048], radius)
                yield pa.RecordBatch.from_arrays([pa.array(leaf), pa.array(guest), pa.array(held.view(np.int64))], names=["leaf", "guest", "fp"])

    return distinct.select("fp").mapInArrow(run, "leaf bigint, guest boolean, fp bigint")


class _Forest:
    def __init__(self, n: int) -> None:
        self.up = list(range(n))

    def root(self, x: int) -> int:
        while self.up[x] != x:
            self.up[x] = x = self.up[self.up[x]]
        return x

    def join(self, x: int, y: int) -> None:
        x, y = self.root(x), self.root(y)
        self.up[max(x, y)] = min(x, y)


def leaf_forest(homes: np.ndarray, guests: np.ndarray, radius: int) -> list[tuple[int, int]]:
    """Pairs of fingerprints that connect all those of a leaf which links of home members connect; guests are compared with home members only."""
    everyone = np.concatenate([homes, guests])
    forest = _Forest(len(everyone))
    parts = [(np.arange(len(homes)), np.arange(len(homes), len(everyone)))]
    while parts:
        home, guest = parts.pop()
        mine = everyone[home]
        point, middle = vantage(mine) if len(home) > INNER_LEAF else (np.uint64(0), 0)
        d = np.bitwise_count(mine ^ point)
        if len(home) > INNER_LEAF and (d > middle).any():
            inside, outside, visits = sides(d, np.int16(middle), np.zeros(len(home), dtype=bool), radius)
            g_in, g_out, _ = sides(np.bitwise_count(everyone[guest] ^ point), np.int16(middle), np.ones(len(guest), dtype=bool), radius)
            parts += [(home[inside], np.concatenate([guest[g_in], home[visits]])), (home[outside], guest[g_out])]
            continue
        queries, step = np.concatenate([home, guest]), max(1, (1 << 18) // max(1, len(home)))
        for at in range(0, len(queries) if len(home) else 0, step):
            some = queries[at : at + step]
            rows, columns = np.nonzero(np.bitwise_count(everyone[some][:, None] ^ mine[None, :]) <= radius)
            for q, h in zip(some[rows].tolist(), home[columns].tolist(), strict=True):
                if q != h:
                    forest.join(q, h)
    links = ((k, forest.root(k)) for k in range(len(everyone)))
    return [(everyone[k], everyone[r]) for k, r in links if k != r]


def linked_fingerprints(distinct: DataFrame, radius: int = 2) -> DataFrame:
    """(src, dst): links that connect exactly the fingerprints which are connected by steps of at most ``radius`` bits."""
    return linked_in_leaves(sent_to_leaves(distinct, fitted(distinct), radius), radius)


def linked_in_leaves(sent: DataFrame, radius: int) -> DataFrame:
    """(src, dst): links of at most ``radius`` bits between the members of each leaf of ``sent``, as spanning forests."""
    shards = sent.repartition("leaf").sortWithinPartitions("leaf", "guest")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def search(leaf: list[tuple[np.ndarray, np.ndarray]]) -> list[tuple[int, int]]:
            guest, fp = (np.concatenate(c) for c in zip(*leaf, strict=True))
            return leaf_forest(fp[~guest], fp[guest], radius) if not guest.all() else []

        held, now = [], None
        for batch in batches:
            if not batch.num_rows:
                continue
            leaf, guest = (batch.column(k).to_numpy(zero_copy_only=False) for k in (0, 1))
            fp, found = batch.column(2).to_numpy(zero_copy_only=False).view(np.uint64), []
            cuts = [0, *(np.flatnonzero(np.diff(leaf)) + 1).tolist(), len(leaf)]
            for a, b in itertools.pairwise(cuts):
                if held and leaf[a] != now:
                    found += search(held)
                    held = []
                now = leaf[a]
                held.append((guest[a:b], fp[a:b]))
            if found:
                yield _pairs(found)
        if held and (found := search(held)):
            yield _pairs(found)

    return shards.mapInArrow(run, "src bigint, dst bigint")


def _pairs(found: list[tuple[int, int]]) -> pa.RecordBatch:
    both = np.array(found, dtype=np.uint64).view(np.int64).reshape(-1, 2)
    return pa.RecordBatch.from_arrays([pa.array(both[:, 0]), pa.array(both[:, 1])], names=["src", "dst"])


def near_duplicates(docs: DataFrame, *, doc_id: str = "doc_id", text: str = "text", shingle: int = 3, radius: int = 2) -> DataFrame:
    """(doc_id, fp, component_id) for each row; component_id is the smallest id among the documents that links reach."""
    prints = settle(simhashes(docs, doc_id=doc_id, text=text, shingle=shingle))
    distinct = settle(prints.groupBy("fp").agg(F.min("doc_id").alias("least"), F.count("*").alias("rows")))
    parts = connected_components(settle(linked_fingerprints(distinct, radius)))
    placed = distinct.join(parts.withColumnRenamed("vertex", "fp"), "fp", "left").select("fp", "least", "rows", F.coalesce("component", "fp").alias("component"))
    names = placed.groupBy("component").agg(F.min("least").alias("component_id"))
    by_print = settle(placed.join(names, "component").select("fp", "rows", "component_id"))
    # A fingerprint of over a thousandth of all rows would fill a task; there are fewer than a thousand of them, so they are sent to the rows.
    total = distinct.agg(F.sum("rows")).first()[0] or 0
    frequent = F.broadcast(by_print.where(F.col("rows") * 1000 > total).select("fp", "component_id"))
    seldom = prints.join(frequent.select("fp"), "fp", "left_anti").join(by_print.select("fp", "component_id"), "fp")
    return prints.join(frequent, "fp").unionByName(seldom).select("doc_id", "fp", "component_id")


def fingerprint_text(fp: F.Column) -> F.Column:
    """16 lowercase hex digits."""
    return F.lower(F.lpad(F.hex(fp), 16, "0"))


def keep_one(docs: DataFrame, *, shingle: int = 3, radius: int = 2) -> DataFrame:
    """``docs`` with one document of each component, the one with the smallest id; of rows that repeat that id one stays.  All null ids of a component count as one id."""
    found = near_duplicates(docs, shingle=shingle, radius=radius)
    kept = settle(found.groupBy("component_id").agg(F.count(F.when(F.col("doc_id").eqNullSafe(F.col("component_id")), 1)).alias("rows")).select(F.col("component_id").alias("kept_id"), "rows"))
    # The ids grow with the documents, so they are never broadcast: the plan, and its share of disk, is the same at every size.
    out = docs.join(kept.select("kept_id").hint("merge"), docs["doc_id"].eqNullSafe(kept["kept_id"]), "left_semi")
    return out.dropDuplicates(["doc_id"]) if kept.where("rows > 1").limit(1).count() else out
