"""Tables that cut lineage, in the shared folder that spark.checkpoint.dir names; they go when the application ends."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def workspace(spark: SparkSession) -> str:
    """A new folder below spark.checkpoint.dir, within one for this application that Hadoop deletes when the driver ends.

    Where the setting is missing, a local session (tests, benches) gets a folder of its own; on a cluster that is an error, as
    executors would not share it.
    """
    base = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not base:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("spark.checkpoint.dir must name a folder that driver and executors share")
        spark.sparkContext.setCheckpointDir(tempfile.mkdtemp(prefix="spanweave-"))
        base = spark.sparkContext.getCheckpointDir()
    mine = f"{base.rstrip('/')}/spanweave/{spark.sparkContext.applicationId}"
    if mine not in _MARKED:
        path = spark._jvm.org.apache.hadoop.fs.Path(mine)
        files = path.getFileSystem(spark._jsc.hadoopConfiguration())
        files.mkdirs(path)
        files.deleteOnExit(path)
        _MARKED.add(mine)
    return f"{mine}/{uuid.uuid4().hex}"


_MARKED: set[str] = set()


def settle(df: DataFrame) -> DataFrame:
    """``df`` written as parquet in the workspace and read back: later stages start from files that outlive executors."""
    path = workspace(df.sparkSession)
    df.write.mode("error").parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)
