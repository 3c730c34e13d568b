"""Choice of a mode for a set of instances, and a report of why."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Edges that one task's kernel holds comfortably.
FLEET_EDGES = 5_000_000
#: Edges of graphs so small that splitting a search costs more than it gains.
SMALL_EDGES = 64


def explain_mode(instances: DataFrame, edges: DataFrame, *, fleet_edges: int = FLEET_EDGES, slots: int | None = None) -> DataFrame:
    """One row: instances, the largest graph's edges and (approximate) vertices, and the mode.

    ``fleet`` when there are as many instances as slots or graphs are small; ``shard`` for few instances whose graphs fit a
    task; ``relational`` when the largest graph does not.  Counts only; nothing else reaches the driver, and nothing does here.
    """
    slots = slots or instances.sparkSession.sparkContext.defaultParallelism
    per_graph = edges.groupBy("graph_id").agg(F.count("*").alias("edges"))
    vertices = edges.select("graph_id", F.explode(F.array("src", "dst")).alias("v")).groupBy("graph_id").agg(F.approx_count_distinct("v").alias("vertices"))
    sizes = per_graph.join(vertices, "graph_id").agg(F.max("edges").alias("largest_edges"), F.max("vertices").alias("largest_vertices"))
    n = instances.agg(F.count("*").alias("instances"))
    mode = F.when(F.col("largest_edges") > fleet_edges, "relational").when((F.col("instances") >= slots) | (F.col("largest_edges") <= SMALL_EDGES), "fleet").otherwise("shard")
    return n.crossJoin(sizes).withColumn("mode", mode)  # one row on each side


def choose_mode(instances: DataFrame, edges: DataFrame, **options) -> str:
    return explain_mode(instances, edges, **options).first()["mode"] or "fleet"
