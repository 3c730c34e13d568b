"""Connected components by hooking to the smallest neighbour and contracting, one settled table a round."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.workspace import settle


def connected_components(edges: DataFrame, a: str = "src", b: str = "dst") -> DataFrame:
    """(vertex, component): every end of an edge with the smallest vertex that it is connected to.

    Each round every vertex takes its smallest neighbour if that is smaller, two pointer jumps shorten the chains, and the
    edges are rewritten to the new representatives; rounds grow with the logarithm of the longest shortest path.  Only
    counts reach the driver.  Rows with a null end and self-loops connect nothing; a vertex with self-loops only is kept.
    """
    links = edges.select(F.col(a).alias("x"), F.col(b).alias("y")).where("x is not null and y is not null")
    places = settle(links.select(F.col("x").alias("vertex")).union(links.select("y")).distinct().withColumn("rep", F.col("vertex")))
    links = settle(links.where("x <> y").select(F.least("x", "y").alias("x"), F.greatest("x", "y").alias("y")).distinct())
    while not links.isEmpty():
        both = links.unionByName(links.select(F.col("y").alias("x"), F.col("x").alias("y")))
        parent = settle(both.groupBy("x").agg(F.min("y").alias("y")).select(F.col("x").alias("v"), F.least("x", "y").alias("p")))
        for _ in range(2):
            up = parent.select(F.col("v").alias("p"), F.col("p").alias("q"))
            parent = parent.join(up, "p", "left").select("v", F.coalesce("q", "p").alias("p"))
        parent = settle(parent)
        places = settle(places.join(parent.withColumnRenamed("v", "rep"), "rep", "left").select("vertex", F.coalesce("p", "rep").alias("rep")))
        moved = links.join(parent.select(F.col("v").alias("x"), F.col("p").alias("px")), "x").join(parent.select(F.col("v").alias("y"), F.col("p").alias("py")), "y")
        links = settle(moved.where("px <> py").select(F.least("px", "py").alias("x"), F.greatest("px", "py").alias("y")).distinct())
    return places.withColumnRenamed("rep", "component")
