"""Tables written once into the folder that all executors share."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_dir(spark: SparkSession) -> str:
    """``spark.checkpoint.dir``; a folder of this machine only where that is unset, as in tests."""
    where = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not where:
        spark.sparkContext.setCheckpointDir("file://" + tempfile.mkdtemp(prefix="gossamer-"))
        where = spark.sparkContext.getCheckpointDir()
    return where.rstrip("/")


def settled(df: DataFrame, name: str, by: str | None = None) -> DataFrame:
    """Written as Parquet and read back: cuts lineage and survives lost executors. ``by``: a folder for each of its values."""
    path = f"{shared_dir(df.sparkSession)}/{name}-{uuid.uuid4().hex}"
    (df.write.partitionBy(by) if by else df.write).parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)
