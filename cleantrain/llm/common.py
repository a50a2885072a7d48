"""Helpers shared by the operators: byte-level words, scratch tables and partition counts."""

from __future__ import annotations

import ctypes
import gc
import tempfile
import uuid

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

_FOLD = bytes(b if 48 <= b <= 57 or 97 <= b <= 122 or b >= 128 else b + 32 if 65 <= b <= 90 else 32 for b in range(256))


def words_of(text: str | None) -> list[bytes]:
    """Lower-cased (A-Z) runs of digits, letters and non-ASCII characters, as UTF-8 bytes; null has none.

    In UTF-8 every byte of a non-ASCII character is 0x80 or more, so one byte table does both the folding
    and the cutting, and bytes.split() the rest, without a regular expression.
    """
    return text.encode("utf-8", "surrogatepass").translate(_FOLD).split() if text else []


def scratch_dir(spark: SparkSession) -> str:
    """A new folder under the session's checkpoint folder, which driver and executors share.

    The session's own setting is used; only where none is set on a local master (tests) is a local one chosen.
    """
    sc = spark.sparkContext
    base = sc._jsc.sc().getCheckpointDir()
    if base.isDefined():
        root = base.get()
    else:
        root = spark.conf.get("spark.checkpoint.dir", None)
        if not root and not sc.master.startswith("local"):
            raise ValueError("spark.checkpoint.dir must name a folder that driver and executors share")
        sc.setCheckpointDir(root or tempfile.mkdtemp(prefix="checkpoints"))
        root = sc._jsc.sc().getCheckpointDir().get()
    return f"{root}/{uuid.uuid4().hex}"


def scratch_table(df: DataFrame) -> DataFrame:
    """Writes the frame as Parquet to the shared folder and reads it back: lineage is cut, lost executors cost nothing."""
    spark = df.sparkSession
    path = scratch_dir(spark)
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def shuffle_partitions(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions", "200"))


def release_memory() -> None:
    """Gives freed memory back to the system: a Python worker outlives its task and shares the executor's limit with the JVM."""
    gc.collect()
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)
    if trim is not None:
        trim(0)
