"""Small helpers that the operators share: reading tables, and the places for intermediate ones."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..plans.workspace import settle, workspace

__all__ = ["settle", "small_batches", "table", "whole", "workspace"]

#: Rows of an Arrow batch on its way to Python, so that a worker holds few texts at once.
BATCH_ROWS = 1000


def table(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    """The parquet table ``name`` under ``sf_dir``, with the named columns only."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def whole(column: str = "text") -> F.Column:
    """The text with null read as empty."""
    return F.coalesce(F.col(column), F.lit(""))


def small_batches(df: DataFrame) -> DataFrame:
    """``df``, after lowering the session's rows of an Arrow batch to ``BATCH_ROWS`` where they are more: Spark bounds a batch by rows, and texts have any length."""
    name = "spark.sql.execution.arrow.maxRecordsPerBatch"
    if not 0 < int(df.sparkSession.conf.get(name)) <= BATCH_ROWS:
        df.sparkSession.conf.set(name, str(BATCH_ROWS))
    return df
