"""Baselines by joins: paths hop by hop, and solutions as tuples of paths."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .workspace import settle


def key(edges: Column, vertices: Column | None = None) -> Column:
    """Ascending edge ids joined by "-"; for no edges "v" and the first vertex."""
    joined = F.array_join(F.transform(F.array_sort(edges), lambda e: e.cast("string")), "-")
    return F.when(F.size(edges) > 0, joined).otherwise(F.lit("empty") if vertices is None else F.concat(F.lit("v"), F.array_min(vertices).cast("string")))


def paths(edges: DataFrame, sources: DataFrame, targets: DataFrame | None = None, *, directed: bool = False, inner_free_of: DataFrame | None = None, max_hops: int | None = None) -> DataFrame:
    """(s, t, vertices, edges) of simple paths from sources(s), the trivial ones too, one join a hop, each hop settled.

    ``targets(t)``: a path ends when it reaches one; without, every prefix is a path.  ``inner_free_of(v)``: vertices that no
    path may go on from.  ``max_hops``: more hops than that are an error, never a shorter answer.
    """
    arcs = edges.select("edge_id", "src", "dst")
    if not directed:
        arcs = arcs.unionByName(edges.select("edge_id", F.col("dst").alias("src"), F.col("src").alias("dst")))
    part = settle(sources.select("s", F.col("s").alias("t"), F.array("s").alias("vertices"), F.array().cast("array<bigint>").alias("edges")))
    rounds = []
    while not part.isEmpty():
        if max_hops is not None and len(rounds) > max_hops:
            raise ValueError(f"there are paths of over {max_hops} edges")
        rounds.append(part)
        front = part
        if targets is not None:
            front = front.join(F.broadcast(targets.select("t")), "t", "left_anti")
        if inner_free_of is not None:
            stop = inner_free_of.select(F.col("v").alias("t")).withColumn("stop", F.lit(True))
            front = front.join(F.broadcast(stop), "t", "left").where(F.col("stop").isNull() | (F.size("edges") == 0)).drop("stop")
        step = front.join(arcs, front["t"] == arcs["src"]).where(~F.array_contains(F.col("vertices"), F.col("dst")))
        part = settle(step.select("s", F.col("dst").alias("t"), F.array_append("vertices", F.col("dst")).alias("vertices"), F.array_append("edges", F.col("edge_id")).alias("edges")))
    out = rounds[0] if rounds else part
    for r in rounds[1:]:
        out = out.unionByName(r)
    return out.join(F.broadcast(targets.select("t")), "t", "left_semi").select("s", "t", "vertices", "edges") if targets is not None else out


def trees(edges: DataFrame, terminals: list[int], *, directed: bool = False, root: int | None = None) -> DataFrame:
    """(solution_key, n_edges): one path from the first terminal (or the root) to each other one; unions with one vertex more than edges are trees.

    Different tuples of paths give different trees, so nothing is repeated.
    """
    spark = edges.sparkSession
    start, *ends = (root, *terminals) if root is not None else terminals
    starts = spark.createDataFrame([(start,)], "s bigint")
    every = settle(paths(edges, starts, directed=directed))
    out = None
    for k, w in enumerate(ends):
        one = every.where(F.col("t") == w).select(F.col("vertices").alias("v"), F.col("edges").alias("e"))
        if out is None:
            out = one
            continue
        left = out.withColumnRenamed("v", "v0").withColumnRenamed("e", "e0")
        both = left.crossJoin(one)  # a product of two path sets: this is the baseline's cost
        out = both.select(F.array_union("v0", "v").alias("v"), F.array_union("e0", "e").alias("e")).where(F.size("v") == F.size("e") + 1)
    return out.select(key(F.col("e"), F.col("v")).alias("solution_key"), F.size("e").cast("bigint").alias("n_edges"))


def forests(edges: DataFrame, pairs: list[tuple[int, int]]) -> DataFrame:
    """(solution_key, n_edges): one path for each of two pairs; unions without a cycle.

    Two paths together have no cycle if what they share is one run: vertices are edges plus one, or plus two if apart.
    """
    (a, b), (c, d) = pairs
    spark = edges.sparkSession
    every = settle(paths(edges, spark.createDataFrame([(a,), (c,)], "s bigint")))
    p = every.where((F.col("s") == a) & (F.col("t") == b)).select(F.col("vertices").alias("v"), F.col("edges").alias("e"))
    q = every.where((F.col("s") == c) & (F.col("t") == d)).select(F.col("vertices").alias("w"), F.col("edges").alias("f"))
    both = p.crossJoin(q).select(F.array_union("v", "w").alias("v"), F.array_union("e", "f").alias("e"), F.arrays_overlap("v", "w").cast("int").alias("met"))
    return both.where(F.size("v") == F.size("e") + 2 - F.col("met")).select(key(F.col("e")).alias("solution_key"), F.size("e").cast("bigint").alias("n_edges"))


def _bit(k: int) -> int:
    return 1 << k


def _closure(start: Column, near: list[int], allowed: Column) -> Column:
    """Bits that are reached from ``start`` by neighbours within ``allowed``: as many rounds as there are bits."""
    masks = F.array(*[F.lit(m).cast("bigint") for m in near])
    none = F.lit(0).cast("bigint")

    def grow(reach: Column) -> Column:
        met = F.transform(masks, lambda m, k: F.when(F.call_function("shiftright", reach, k).bitwiseAND(F.lit(1)) == 1, m).otherwise(none))
        return F.aggregate(met, reach, lambda x, y: x.bitwiseOR(y)).bitwiseAND(allowed)

    return F.aggregate(F.sequence(F.lit(1), F.lit(len(near))), start, lambda reach, _: grow(reach))


def _small_graph(edges: DataFrame, most_vertices: int, most_edges: int) -> tuple[list[int], list[tuple[int, int, int]]]:
    """(vertices, edges) of a graph that an exhaustive search can take; an error beyond that."""
    rows = edges.select("edge_id", "src", "dst").limit(most_edges + 1).collect()
    vertices = sorted({v for r in rows for v in (r["src"], r["dst"])})
    if len(rows) > most_edges or len(vertices) > most_vertices:
        raise ValueError(f"at most {most_vertices} vertices and {most_edges} edges")
    return vertices, sorted((r["edge_id"], r["src"], r["dst"]) for r in rows)


def _named(mask: Column, names: list[int]) -> Column:
    ids = F.array(*[F.lit(n).cast("bigint") for n in names])
    return F.array_sort(F.filter(F.transform(ids, lambda n, k: F.when(F.call_function("shiftright", mask, k).bitwiseAND(F.lit(1)) == 1, n)), lambda n: n.isNotNull()))


def exhaustive_trees(edges: DataFrame, terminals: list[int]) -> DataFrame:
    """(solution_key, n_edges): minimal Steiner trees among all sets of at most 24 edges; a row a set, tested by bit operations."""
    vertices, rows = _small_graph(edges, 60, 24)
    if not set(terminals) <= set(vertices):
        return edges.sparkSession.createDataFrame([], "solution_key string, n_edges bigint")
    at = [sum(_bit(k) for k, (_, a, b) in enumerate(rows) if v in (a, b)) for v in vertices]
    every = edges.sparkSession.range(1, _bit(len(rows))).select(F.col("id").alias("mask"))
    degree = [F.bit_count(F.col("mask").bitwiseAND(F.lit(m))) for m in at]
    fine = F.lit(True)
    for v, d in zip(vertices, degree, strict=True):
        fine = fine & ((d > 0) if v in terminals else (d != 1))
    touched = sum(((d > 0).cast("int") for d in degree), F.lit(0))
    right = every.where(fine & (touched == F.bit_count("mask") + 1))
    # Connected: edges reach each other by common ends.
    near = [sum(_bit(j) for j, (_, c, d) in enumerate(rows) if {a, b} & {c, d}) for _, a, b in rows]
    first = F.col("mask").bitwiseAND(-F.col("mask"))
    whole = right.where(_closure(first, near, F.col("mask")) == F.col("mask"))
    key_of = F.array_join(F.transform(_named(F.col("mask"), [e for e, *_ in rows]), lambda e: e.cast("string")), "-")
    return whole.select(key_of.alias("solution_key"), F.bit_count("mask").cast("bigint").alias("n_edges"))


def exhaustive_induced(edges: DataFrame, terminals: list[int]) -> DataFrame:
    """(solution_key, n): minimal vertex sets that induce a connection of at most three terminals, among all sets of at most 24 vertices.

    A connected set is minimal if no other vertex of it can go alone, so each connected set is looked up without one vertex.
    """
    if len(set(terminals)) > 3:
        raise ValueError("at most three terminals")
    vertices, rows = _small_graph(edges, 24, 276)
    if not set(terminals) <= set(vertices):
        return edges.sparkSession.createDataFrame([], "solution_key string, n bigint")
    place = {v: k for k, v in enumerate(vertices)}
    near = [0] * len(vertices)
    for _, a, b in rows:
        near[place[a]] |= _bit(place[b])
        near[place[b]] |= _bit(place[a])
    wanted = sum(_bit(place[v]) for v in set(terminals))
    others = [k for k in range(len(vertices)) if not wanted >> k & 1]
    # Masks over the other vertices, spread to the places of all.
    spread = sum((F.call_function("shiftleft", F.call_function("shiftright", F.col("id"), F.lit(j)).bitwiseAND(F.lit(1)), F.lit(k)) for j, k in enumerate(others)), F.lit(0))
    every = edges.sparkSession.range(_bit(len(others))).select((spread + F.lit(wanted)).cast("bigint").alias("mask"))
    start = F.lit(_bit(place[terminals[0]])).cast("bigint")
    hits = settle(every.where(_closure(start, near, F.col("mask")) == F.col("mask")))
    less = hits.select("mask", F.explode(F.array(*[F.lit(_bit(k)).cast("bigint") for k in others])).alias("bit")).where(F.col("mask").bitwiseAND(F.col("bit")) > 0)
    spoilt = less.select("mask", F.col("mask").bitwiseXOR(F.col("bit")).alias("sub")).join(hits.select(F.col("mask").alias("sub")), "sub", "left_semi").select("mask").distinct()
    least = hits.join(spoilt, "mask", "left_anti")
    names = _named(F.col("mask"), vertices)
    return least.select(F.array_join(F.transform(names, lambda v: v.cast("string")), "-").alias("solution_key"), F.size(names).cast("bigint").alias("n"))


def recursive_paths_sql(view: str, source: str) -> str:
    """Spark SQL for simple paths by a recursive common table expression over a view of arcs: for small graphs, as every level is a stage."""
    return f"""
        WITH RECURSIVE p(t, vertices, edges) AS (
            SELECT CAST({source} AS BIGINT), array(CAST({source} AS BIGINT)), CAST(array() AS ARRAY<BIGINT>)
            UNION ALL
            SELECT a.dst, array_append(p.vertices, a.dst), array_append(p.edges, a.edge_id) FROM p JOIN {view} a ON p.t = a.src WHERE NOT array_contains(p.vertices, a.dst))
        SELECT t, vertices, edges FROM p"""


def hitting_masks(hyperedges: DataFrame, width: int) -> DataFrame:
    """(mask) of the minimal transversals among all 2^width sets: exhaustive, for elements below ``width`` (at most 24)."""
    if width > 24:
        raise ValueError("at most 24 elements")
    spark = hyperedges.sparkSession
    needs = settle(hyperedges.groupBy("hyperedge_id").agg(F.expr("bit_or(shiftleft(1L, cast(element as int)))").alias("need")).select("need").distinct())
    every = spark.range(1 << width).select(F.col("id").alias("mask"))
    missed = every.join(F.broadcast(needs), F.col("mask").bitwiseAND(F.col("need")) == 0, "left_semi")
    hits = settle(every.join(missed, "mask", "left_anti"))
    # Hitting is monotone, so a set is minimal if no set with one element less hits.
    less = hits.select("mask", F.explode(F.transform(F.sequence(F.lit(0), F.lit(width - 1)), lambda i: F.call_function("shiftleft", F.lit(1).cast("bigint"), i))).alias("bit"))
    smaller = less.where(F.col("mask").bitwiseAND(F.col("bit")) > 0).select("mask", F.col("mask").bitwiseXOR(F.col("bit")).alias("sub"))
    spoilt = smaller.join(hits.select(F.col("mask").alias("sub")), "sub", "left_semi").select("mask").distinct()
    return hits.join(spoilt, "mask", "left_anti")


def masked_key(mask: Column, width: int) -> Column:
    bits = F.filter(F.sequence(F.lit(0), F.lit(width - 1)), lambda i: F.call_function("shiftleft", F.lit(1).cast("bigint"), i).bitwiseAND(mask) > 0)
    return F.array_join(F.transform(bits, lambda i: i.cast("string")), "-")
