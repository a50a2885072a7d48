"""Reading and writing: pruned Parquet scans, dirty text files, bucketed matrices, ledgers with commit markers."""

from __future__ import annotations

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.pandas.types import to_arrow_schema

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")


def read_table(spark: SparkSession, sf_dir: str, name: str, columns: list[str] | None = None, where: str | Column | None = None) -> DataFrame:
    """Columns and filters reach the Parquet scan."""
    rows = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    rows = rows if where is None else rows.where(where)
    return rows if columns is None else rows.select(*columns)


def local_rows(spark: SparkSession, rows: list[dict], schema: T.StructType | str) -> DataFrame:
    """A few rows of the driver as a local relation: planned and collected without a task on an executor."""
    schema = T.DataType.fromDDL(schema) if isinstance(schema, str) else schema
    return spark.createDataFrame(pa.Table.from_pylist(rows, to_arrow_schema(schema)), schema)


def read_dirty_csv(spark: SparkSession, path: str, schema: str, header: bool = True) -> DataFrame:
    """Malformed lines are kept, with their text in _corrupt."""
    return spark.read.schema(f"{schema}, _corrupt string").option("mode", "PERMISSIVE").option("columnNameOfCorruptRecord", "_corrupt").option("header", header).csv(path)


def read_dirty_json(spark: SparkSession, path: str, schema: str) -> DataFrame:
    return spark.read.schema(f"{schema}, _corrupt string").option("mode", "PERMISSIVE").option("columnNameOfCorruptRecord", "_corrupt").json(path)


def write_matrix(rows: DataFrame, table: str, buckets: int = 16) -> None:
    """A table bucketed by row_id: later joins with ledger or truth of the same bucketing need no shuffle."""
    rows.write.mode("overwrite").bucketBy(buckets, "row_id").sortBy("row_id").saveAsTable(table)


class LedgerTable:
    """Append-only cleaned rows under a folder, one partition a run and iteration; an iteration counts once marked."""

    def __init__(self, spark: SparkSession, path: str):
        self.spark, self.path = spark, path

    def append(self, run_id: str, iteration: int, rows: DataFrame) -> None:
        """Overwrites the iteration's own folder, so a retried append is not counted twice; the marker comes last."""
        at = f"run_id={run_id}/iteration={iteration}"
        rows.drop("run_id", "iteration").write.mode("overwrite").parquet(f"{self.path}/rows/{at}")
        self.spark.range(1, numPartitions=1).write.mode("overwrite").parquet(f"{self.path}/marks/{at}")

    def read(self, run_id: str | None = None) -> DataFrame:
        rows = self.spark.read.option("basePath", f"{self.path}/rows").parquet(f"{self.path}/rows")
        marks = self.spark.read.option("basePath", f"{self.path}/marks").parquet(f"{self.path}/marks").select("run_id", "iteration").distinct()
        rows = rows.join(F.broadcast(marks), ["run_id", "iteration"], "left_semi")
        return rows if run_id is None else rows.where(F.col("run_id") == run_id)
