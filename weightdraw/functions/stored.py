"""Lineage cut by writing: tables in the folder that the cluster shares."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_dir(spark: SparkSession) -> str:
    """A fresh path below ``spark.checkpoint.dir`` or the context's checkpoint folder.

    Where neither is set, a local master (tests) gets a temporary folder and a cluster the
    warehouse, which its machines share.
    """
    context = spark.sparkContext
    base = spark.conf.get("spark.checkpoint.dir", None) or context.getCheckpointDir()
    if not base and context.master.startswith("local"):
        context.setCheckpointDir(tempfile.mkdtemp(prefix="weightdraw-"))
        base = context.getCheckpointDir()
    base = base or spark.conf.get("spark.sql.warehouse.dir").rstrip("/") + "/_weightdraw"
    return f"{base.rstrip('/')}/{uuid.uuid4().hex}"


def materialise(df: DataFrame, partition_by: str | None = None) -> DataFrame:
    """Write to the shared folder and read back: computed once, and no executor's loss costs more."""
    spark = df.sparkSession
    path = shared_dir(spark)
    writer = df.write.option("compression", "zstd")
    if partition_by:
        writer = writer.partitionBy(partition_by)
    writer.parquet(path)
    return spark.read.schema(df.schema).parquet(path)
