"""Tests and reductions of whole graphs as DataFrame plans.  Edges: (graph_id, edge_id, src, dst)."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..kernels.graph import Graph, two_connected_blocks
from ..kernels.graph import bridges as kernel_bridges
from ..plans.workspace import settle
from .components import connected_components


def oriented(edges: DataFrame) -> DataFrame:
    """Both directions of every edge, with its id."""
    return edges.select("edge_id", "src", "dst").unionByName(edges.select("edge_id", F.col("dst").alias("src"), F.col("src").alias("dst")))


def one_graph(edges: DataFrame) -> DataFrame:
    """``edges``, after an error if they are of several graphs: the operators here that name vertices alone would mix them."""
    if "graph_id" in edges.columns and len(edges.select("graph_id").distinct().limit(2).collect()) > 1:
        raise ValueError("edges of several graphs: give them one graph at a time")
    return edges


def degrees(edges: DataFrame) -> DataFrame:
    """(vertex, degree); edges must be of one graph."""
    return edges.select(F.explode(F.array("src", "dst")).alias("vertex")).groupBy("vertex").agg(F.count("*").alias("degree"))


def per_graph(edges: DataFrame, work, schema: str) -> DataFrame:
    """``work(graph_id, [(edge_id, src, dst)])`` for each graph, one row's nested edges at a time."""
    nested = edges.groupBy("graph_id").agg(F.sort_array(F.collect_list(F.struct("edge_id", "src", "dst"))).alias("edges"))
    names = [c.split()[0] for c in schema.split(", ")]

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in frames:
            for who, graph in zip(frame["graph_id"], frame["edges"], strict=True):
                yield pd.DataFrame(list(work(int(who), [(e["edge_id"], e["src"], e["dst"]) for e in graph])), columns=names)

    return nested.mapInPandas(run, schema)


def bridges(edges: DataFrame) -> DataFrame:
    """(graph_id, edge_id, src, dst) of the edges whose removal disconnects their ends.

    First each partition keeps two successive spanning forests of its edges, a certificate that has the same bridges; so
    what a graph's task holds is bounded by its vertices and the number of partitions, not by its edges.
    """

    def thin(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        kept: dict[int, list[dict[int, int]]] = {}

        def find(up: dict[int, int], v: int) -> int:
            while up.setdefault(v, v) != v:
                up[v] = v = up[up[v]]
            return v

        for frame in frames:
            keep = []
            for g, a, b in zip(frame["graph_id"], frame["src"], frame["dst"], strict=True):
                for up in kept.setdefault(g, [{}, {}]):
                    x, y = find(up, a), find(up, b)
                    if x != y:
                        up[x] = y
                        keep.append(True)
                        break
                else:
                    keep.append(False)
            yield frame[keep]

    certificate = edges.select("graph_id", "edge_id", "src", "dst").mapInPandas(thin, "graph_id bigint, edge_id bigint, src bigint, dst bigint")

    def work(who, graph):
        g = Graph(graph)
        found = kernel_bridges(g.n, g.ends)
        for k, (a, b) in enumerate(g.ends):
            if found[k]:
                yield who, g.edge_ids[k], g.names[a], g.names[b]

    return per_graph(certificate, work, "graph_id bigint, edge_id bigint, src bigint, dst bigint")


def blocks(edges: DataFrame) -> DataFrame:
    """(graph_id, block, edge_id): maximal parts without a cut vertex; a block is named by its smallest edge."""

    def work(who, graph):
        g = Graph(graph)
        for block in two_connected_blocks(g.n, g.ends):
            ids = g.named(block)
            yield from ((who, ids[0], e) for e in ids)

    return per_graph(edges, work, "graph_id bigint, block bigint, edge_id bigint")


def claws(edges: DataFrame) -> DataFrame:
    """(centre, a, b, c), a < b < c: three neighbours of a vertex of which no two are adjacent.

    Pairs of neighbours that are not adjacent come first, and only such pairs are extended.
    """
    near = oriented(one_graph(edges)).select(F.col("src").alias("centre"), F.col("dst").alias("v")).distinct()
    adjacent = near.select(F.col("centre").alias("x"), F.col("v").alias("y"))
    apart = near.select("centre", F.col("v").alias("a")).join(near.select("centre", F.col("v").alias("b")), "centre").where("a < b").join(adjacent, (F.col("a") == F.col("x")) & (F.col("b") == F.col("y")), "left_anti")
    two, ends = apart.alias("p"), apart.select("centre", "a", F.col("b").alias("c"))
    three = two.join(ends, ["centre", "a"]).where("b < c")
    return three.join(apart.select("centre", F.col("a").alias("b"), F.col("b").alias("c")), ["centre", "b", "c"], "left_semi").select("centre", "a", "b", "c")


def line_graph(edges: DataFrame, terminals: DataFrame | None = None) -> DataFrame:
    """Edges (src, dst) between different edges that share an end, and between a terminal's vertex (-1 - vertex) and its edges."""
    ends = oriented(one_graph(edges)).select("edge_id", F.col("src").alias("v"))
    pairs = ends.alias("p").join(ends.alias("q"), (F.col("p.v") == F.col("q.v")) & (F.col("p.edge_id") < F.col("q.edge_id"))).select(F.col("p.edge_id").alias("src"), F.col("q.edge_id").alias("dst"))
    if terminals is not None:
        w = terminals.select(F.col("vertex_id").alias("v")).distinct()
        pairs = pairs.union(ends.join(F.broadcast(w), "v").select((-1 - F.col("v")).alias("src"), F.col("edge_id").alias("dst")))
    return pairs.distinct()


def reachable(edges: DataFrame, roots: DataFrame) -> DataFrame:
    """(vertex): what directed paths from roots(vertex) lead to, roots included."""
    return distances(edges, roots, directed=True).select("vertex")


def distances(edges: DataFrame, roots: DataFrame, *, directed: bool = False) -> DataFrame:
    """(vertex, distance): fewest edges from a root to each vertex that paths lead to.  Rounds of a breadth-first search, each settled once and only added to."""
    arcs = one_graph(edges).select("src", "dst")
    if not directed:
        arcs = arcs.unionByName(edges.select(F.col("dst").alias("src"), F.col("src").alias("dst")))
    front = settle(roots.select("vertex").distinct().withColumn("distance", F.lit(0).cast("bigint")))
    seen, far = front, 0
    while not front.isEmpty():
        far += 1
        step = front.select("vertex").join(arcs, front["vertex"] == arcs["src"]).select(F.col("dst").alias("vertex")).distinct()
        front = settle(step.join(seen.select("vertex"), "vertex", "left_anti").withColumn("distance", F.lit(far).cast("bigint")))
        seen = seen.unionByName(front)
    return seen


def strip_leaves(edges: DataFrame, terminals: DataFrame) -> DataFrame:
    """Edges left after taking away, again and again, vertices of degree one that are no terminals: no minimal tree uses them."""
    w = terminals.select(F.col("vertex_id").alias("vertex")).distinct()
    edges = one_graph(edges)
    while True:
        leaves = degrees(edges).where("degree = 1").join(F.broadcast(w), "vertex", "left_anti")
        leaves = settle(leaves.select("vertex"))
        if leaves.isEmpty():
            return edges
        edges = settle(edges.join(leaves.withColumnRenamed("vertex", "src"), "src", "left_anti").join(leaves.withColumnRenamed("vertex", "dst"), "dst", "left_anti").select("graph_id", "edge_id", "src", "dst"))


def terminal_component(edges: DataFrame, terminals: DataFrame) -> DataFrame:
    """Edges of the component that holds all terminals; none if they lie in several or one is in no edge."""
    parts = connected_components(one_graph(edges))
    mine = terminals.select(F.col("vertex_id").alias("vertex")).distinct().join(parts, "vertex", "left")
    one = mine.agg(F.count_distinct("component").alias("parts"), F.count(F.when(F.col("component").isNull(), 1)).alias("lost"), F.min("component").alias("component")).where("parts = 1 and lost = 0")
    inside = parts.join(F.broadcast(one.select("component")), "component", "left_semi")
    return edges.join(inside.select(F.col("vertex").alias("src")), "src", "left_semi").select("graph_id", "edge_id", "src", "dst")


def admissible_components(edges: DataFrame, terminals: DataFrame) -> DataFrame:
    """(component, vertex): components of the graph without terminals that every terminal is next to."""
    w = terminals.select(F.col("vertex_id").alias("w")).distinct()
    both = oriented(one_graph(edges))
    free = both.join(F.broadcast(w), both["src"] == w["w"], "left_anti")
    inner = free.join(F.broadcast(w), free["dst"] == w["w"], "left_anti")
    alone = free.select("src", F.col("src").alias("dst"))
    parts = connected_components(inner.select("src", "dst").union(alone))
    touching = free.join(F.broadcast(w), free["dst"] == w["w"]).select("src", "w").join(parts, F.col("src") == F.col("vertex"))
    whole = touching.groupBy("component").agg(F.count_distinct("w").alias("n")).join(F.broadcast(w.agg(F.count("*").alias("n"))), "n")
    return parts.join(whole.select("component"), "component", "left_semi").select("component", "vertex")


def normalize_pairs(terminals: DataFrame) -> DataFrame:
    """(instance_id, a, b): each set's smallest member with each other one, every pair once."""
    first = F.min("vertex_id").over(Window.partitionBy("instance_id", "set_id"))
    return terminals.withColumn("a", first).where("a <> vertex_id").select("instance_id", "a", F.col("vertex_id").alias("b")).distinct()


def relevant_blocks(edges: DataFrame, terminals: DataFrame) -> DataFrame:
    """Edges of the blocks that lie between terminals; the others are in no minimal tree.

    Blocks and cut vertices form a tree; its leaves without a terminal of their own are stripped.
    """
    placed = settle(one_graph(edges).join(blocks(edges), ["graph_id", "edge_id"]))
    while True:
        ends = placed.select("block", F.explode(F.array("src", "dst")).alias("vertex")).distinct()
        shared = ends.groupBy("vertex").agg(F.count("*").alias("blocks"))
        own = ends.join(shared, "vertex").join(F.broadcast(terminals.select(F.col("vertex_id").alias("vertex"), F.lit(1).alias("t")).distinct()), "vertex", "left")
        # A block that meets the others in one vertex at most stays only for a terminal besides that vertex.
        counts = own.groupBy("block").agg(F.count(F.when(F.col("blocks") > 1, 1)).alias("cuts"), F.count(F.when((F.col("blocks") == 1) & F.col("t").isNotNull(), 1)).alias("inner"))
        idle = settle(counts.where("cuts <= 1 and inner = 0").select("block"))
        if idle.isEmpty():
            return placed.select("graph_id", "edge_id", "src", "dst")
        placed = settle(placed.join(idle, "block", "left_anti"))


def compress_chains(edges: DataFrame, terminals: DataFrame) -> DataFrame:
    """(graph_id, edge_id, src, dst, chain): runs through vertices of degree two that are no terminals become one edge.

    ``chain`` lists the original edge ids, in order; the new edge has the smallest of them.  Cycles through no other vertex vanish.
    """
    fixed = terminals.select(F.col("vertex_id").alias("vertex")).distinct()
    inner = degrees(one_graph(edges)).where("degree = 2").join(F.broadcast(fixed), "vertex", "left_anti").select("vertex", F.lit(1).alias("inner"))
    flagged = edges.join(inner.withColumnRenamed("vertex", "src").withColumnRenamed("inner", "si"), "src", "left").join(inner.withColumnRenamed("vertex", "dst").withColumnRenamed("inner", "di"), "dst", "left")
    # Edges meet at inner vertices: components of edges are the chains.
    meets = oriented(edges).join(inner, F.col("src") == F.col("vertex")).groupBy("src").agg(F.min("edge_id").alias("x"), F.max("edge_id").alias("y"))
    parts = connected_components(meets.select(F.col("x").alias("src"), F.col("y").alias("dst")))
    grouped = flagged.join(parts.select(F.col("vertex").alias("edge_id"), "component"), "edge_id", "left").withColumn("chain_id", F.coalesce("component", "edge_id"))
    rows = grouped.groupBy("graph_id", "chain_id").agg(F.flatten(F.collect_list(F.concat(F.when(F.col("si").isNull(), F.array("src")).otherwise(F.array().cast("array<bigint>")), F.when(F.col("di").isNull(), F.array("dst")).otherwise(F.array().cast("array<bigint>"))))).alias("outer"), F.sort_array(F.collect_list("edge_id")).alias("chain"))
    return rows.where(F.size("outer") == 2).where(F.get("outer", 0) != F.get("outer", 1)).select("graph_id", F.col("chain_id").alias("edge_id"), F.array_min("outer").alias("src"), F.array_max("outer").alias("dst"), "chain")
