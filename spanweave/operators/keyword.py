"""Keyword search: fragments of a data graph that connect all keywords."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.spread import ranked
from ..plans.workspace import settle
from . import enumerate as enum

#: Ids of keyword nodes count down from here, clear of tuple ids.
FIRST_KEYWORD = -1_000_000_000


def explain_fragments(solutions: DataFrame, vertices: DataFrame, edges: DataFrame) -> DataFrame:
    """(instance_id, solution_key, edge_id, src_label, dst_label): the edges of solutions(instance_id, solution_key, edges) in words, by vertices(vertex_id, label).

    An end without a label shows its id.
    """
    long = solutions.select("instance_id", "solution_key", F.explode("edges").alias("edge_id")).join(edges.select("edge_id", "src", "dst"), "edge_id")
    named = lambda c: vertices.select(F.col("vertex_id").alias(c), F.col("label").alias(f"{c}_label"))
    both = long.join(named("src"), "src", "left").join(named("dst"), "dst", "left")
    return both.select("instance_id", "solution_key", "edge_id", *[F.coalesce(f"{c}_label", F.col(c).cast("string")).alias(f"{c}_label") for c in ("src", "dst")])


def k_fragments(edges: DataFrame, holders: DataFrame, keywords: list[str], *, kind: str = "undirected", roots: DataFrame | None = None, limit: int | None = None) -> DataFrame:
    """Solutions that connect ``keywords`` over edges(edge_id, src, dst) and holders(keyword, vertex), which say what holds a keyword.

    ``undirected``: minimal trees; ``strong``: keyword nodes are leaves only; ``directed``: out-trees from each of roots(vertex),
    all vertices that anything leaves by default, instance_id being the root.  A keyword that nothing holds gives no fragment.
    Edges to keyword nodes have ids beyond the largest given one, by keyword and vertex.
    """
    spark = edges.sparkSession
    names = spark.createDataFrame([(w, FIRST_KEYWORD - k) for k, w in enumerate(keywords)], "keyword string, node bigint")
    base = edges.agg(F.coalesce(F.max("edge_id"), F.lit(-1)).alias("top")).first()["top"]
    held = holders.join(F.broadcast(names), "keyword").select("vertex", "node").distinct()
    extra = ranked(held, "number", F.desc("node"), F.col("vertex")).select((F.col("number") + 1 + base).cast("bigint").alias("edge_id"), F.col("vertex").alias("src"), F.col("node").alias("dst"))
    graph = settle(edges.select("edge_id", "src", "dst").unionByName(extra))
    nodes = names.select(F.col("node").alias("vertex_id"))
    if kind == "directed":
        starts = (roots.select("vertex") if roots is not None else graph.select(F.col("src").alias("vertex"))).distinct()
        jobs = starts.select(F.col("vertex").alias("instance_id"), F.lit(0).cast("bigint").alias("graph_id"), F.col("vertex").alias("root"))
        wanted = starts.select(F.col("vertex").alias("instance_id")).crossJoin(F.broadcast(nodes))  # a row a keyword on the right
        return enum.directed_steiner_trees(jobs, wanted, graph, limit=limit)
    jobs = spark.createDataFrame([(0, 0)], "instance_id bigint, graph_id bigint")
    wanted = nodes.withColumn("instance_id", F.lit(0).cast("bigint"))
    operator = {"undirected": enum.steiner_trees, "strong": enum.terminal_steiner_trees}[kind]
    return operator(jobs, wanted, graph, limit=limit)
