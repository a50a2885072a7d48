"""Joins that preparing and comparing data needs: as-of, interval, range, difference and write-back."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def as_of(left: DataFrame, right: DataFrame, key: str, time: str, value: str) -> DataFrame:
    """The last non-null value of `right` at or before each left row's time: a union and one window, no range join.

    Equal times count as before. Rows of a key meet in one task, sorted and streamed, not listed.
    """
    a = left.withColumn("_v", F.lit(None).cast(right.schema[value].dataType)).withColumn("_side", F.lit(1))
    b = right.select(*[F.col(c) if c in (key, time) else F.lit(None).cast(left.schema[c].dataType).alias(c) for c in left.columns], F.col(value).alias("_v"), F.lit(0).alias("_side"))
    w = Window.partitionBy(key).orderBy(time, "_side").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return a.unionByName(b).withColumn(f"{value}_before", F.last("_v", ignorenulls=True).over(w)).where("_side = 1").drop("_v", "_side")


def within(left: DataFrame, right: DataFrame, key: str, time: str, seconds: int) -> DataFrame:
    """Pairs of equal key whose times differ by at most so many seconds; time is cut into slots that are equi-joined."""
    slot = lambda c: F.floor(F.unix_seconds(F.col(c).cast("timestamp")) / seconds)
    b = right.select(*[F.col(c).alias(f"r_{c}") for c in right.columns]).withColumn("_s", F.explode(F.array(slot(f"r_{time}") - 1, slot(f"r_{time}"), slot(f"r_{time}") + 1)))
    near = F.abs(F.unix_micros(F.col(time).cast("timestamp")) - F.unix_micros(F.col(f"r_{time}").cast("timestamp"))) <= seconds * 1_000_000
    return left.withColumn("_t", slot(time)).join(b, (F.col(key) == F.col(f"r_{key}")) & (F.col("_t") == F.col("_s"))).where(near).drop("_s", "_t")


def in_ranges(rows: DataFrame, value: str, bounds: DataFrame) -> DataFrame:
    """Rows with the name of the range low <= value < high that holds them; bounds is a small table, checked by the planner."""
    return rows.join(bounds, (F.col(value) >= F.col("low")) & (F.col(value) < F.col("high")), "left")


def write_back(rows: DataFrame, repairs: DataFrame, key: str, column: str) -> DataFrame:
    """Repaired values where there are any; extra repairs are ignored."""
    return rows.join(repairs.select(F.col(key).alias("_k"), F.col(column).alias("_v")), F.col(key) == F.col("_k"), "left").withColumn(column, F.coalesce("_v", column)).drop("_k", "_v")


def cell_differences(dirty: DataFrame, clean: DataFrame, key: str, columns: list[str]) -> DataFrame:
    """column, changed: how many rows differ in each column, a row missing on one side counting for all."""
    b = clean.select(F.col(key).alias("_k"), *[F.col(c).alias(f"_{c}") for c in columns])
    both = dirty.join(b, F.col(key) == F.col("_k"), "full")
    return both.agg(F.array(*[F.struct(F.lit(c).alias("column"), F.count_if(~F.col(c).eqNullSafe(F.col(f"_{c}"))).alias("changed")) for c in columns]).alias("d")).select(F.inline("d"))


def duplicate_groups(rows: DataFrame, columns: list[str]) -> DataFrame:
    return rows.groupBy(*columns).agg(F.count(F.lit(1)).alias("n")).where("n > 1")


def null_profile(rows: DataFrame) -> DataFrame:
    """column, nulls, distinct (exact) in one row a column."""
    return rows.agg(F.array(*[F.struct(F.lit(c).alias("column"), F.count_if(F.col(c).isNull()).alias("nulls"), F.count_distinct(c).alias("distinct_values")) for c in rows.columns]).alias("d")).select(F.inline("d"))
