"""Folders for intermediate files that driver and executors share."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def scratch_path(spark: SparkSession) -> str:
    """A new path under spark.checkpoint.dir, read from the session; a local folder only where that is unset on a local master (tests)."""
    root = spark.conf.get("spark.checkpoint.dir", None)
    if not root and not spark.sparkContext.master.startswith("local"):
        raise ValueError("spark.checkpoint.dir must name a folder that driver and executors share")
    root = root or tempfile.mkdtemp(prefix="cleantrain")
    return f"{root.rstrip('/')}/{uuid.uuid4().hex}"


def scratch_table(df: DataFrame, row_group: int | None = None) -> DataFrame:
    """Writes the frame to such a path and reads it back, which cuts its lineage. row_group: bytes of a row group, for long rows."""
    spark = df.sparkSession
    path = scratch_path(spark)
    (df.write if row_group is None else df.write.option("parquet.block.size", row_group)).parquet(path)
    return spark.read.schema(df.schema).parquet(path)
