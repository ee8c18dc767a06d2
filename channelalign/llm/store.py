"""Folders that the driver and all executors share, and small tables written there to cut lineage."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession

from channelalign.sources.shared import shared_dir


def fresh_dir(spark: SparkSession, what: str) -> str:
    """A new, unused folder name below the shared one."""
    return f"{shared_dir(spark)}/{what}-{uuid.uuid4().hex}"


def written(frame: DataFrame, what: str) -> DataFrame:
    """The frame, written once as Parquet to the shared folder and read back: later steps neither recompute it nor depend on executors' disks."""
    spark = frame.sparkSession
    path = fresh_dir(spark, what)
    frame.write.parquet(path)
    return spark.read.schema(frame.schema).parquet(path)
