"""Schemas of the tables that operators take and give, and checks at the boundary."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

EDGES = "graph_id bigint, edge_id bigint, src bigint, dst bigint"
INSTANCES = "instance_id bigint, graph_id bigint, root bigint"
TERMINALS = "instance_id bigint, set_id int, vertex_id bigint"
SOLUTIONS = "instance_id bigint, solution_key string, n_edges int, n_vertices int, edges array<bigint>, vertices array<bigint>, shard string, emit_seq bigint"
TRACE = "instance_id bigint, seq bigint, kind string, depth int, sibling int, work bigint, n_edges int"


def need(df: DataFrame, *columns: str) -> DataFrame:
    """``df`` cut to these columns, or a clear error."""
    if missing := [c for c in columns if c not in df.columns]:
        raise ValueError(f"missing columns {missing}; there are {df.columns}")
    return df.select(*columns)


def checked_edges(edges: DataFrame) -> DataFrame:
    """Edges as (graph_id, edge_id, src, dst) without self-loops; a null id raises an error in the query that meets it.  graph_id defaults to 0."""
    if "graph_id" not in edges.columns:
        edges = edges.withColumn("graph_id", F.lit(0).cast("bigint"))
    out = need(edges, "graph_id", "edge_id", "src", "dst")
    whole = [F.when(F.col(c).isNull(), F.raise_error(F.lit(f"null {c} in edges"))).otherwise(F.col(c)).cast("bigint").alias(c) for c in out.columns]
    return out.select(*whole).where("src <> dst")
