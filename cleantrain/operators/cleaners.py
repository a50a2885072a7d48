"""Cleaners: maps or filters of drawn rows, and of whole dirty parts at once. A removed row comes back with kept false."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


#: Ids up to which a lookup hands them to the scan of the truth, which then works out nothing for other rows.
ASKED_IDS = 10_000


class LookupCleaner:
    """Repairs from a table of truth: row_id, x_c, y_c, class_id, err_features. Only the drawn rows are joined."""

    def __init__(self, truth: DataFrame):
        self.truth = truth

    def clean(self, batch: DataFrame) -> DataFrame:
        """batch is bounded by the batch size, so it is the side to broadcast."""
        known = self.truth.select("row_id", "x_c", "y_c", *[c for c in ("class_id", "err_features") if c in self.truth.columns and c not in batch.columns])
        asked = [r.row_id for r in batch.select("row_id").limit(ASKED_IDS + 1).collect()]
        if len(asked) <= ASKED_IDS:
            known = known.where(F.col("row_id").isin(asked)) if asked else known.limit(0)
        return known.join(F.broadcast(batch.drop("x_c", "y_c")), "row_id").withColumn("kept", F.lit(True))


class FunctionCleaner:
    """A user's function on one row (a dict in, a dict or None out), called for drawn rows only; None removes the row.

    How often it was called is the number of ledger rows: an accumulator would count retried tasks twice.
    """

    def __init__(self, function: Callable[[dict], dict | None], schema: str):
        self.function, self.schema = function, schema

    def clean(self, batch: DataFrame) -> DataFrame:
        names = [x.split()[0] for x in self.schema.split(", ")]

        def run(parts: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            memo: dict = {}
            for part in parts:
                rows = []
                for row in part.to_dict("records"):
                    key = row.get("row_id")
                    if key not in memo:
                        memo[key] = self.function(row)
                    fixed = memo[key]
                    rows.append(((row if fixed is None else fixed) | {"kept": fixed is not None}))
                yield pd.DataFrame(rows, columns=[*names, "kept"])

        return batch.mapInPandas(run, self.schema + ", kept boolean")


def normalise_values(rows: DataFrame, column: str, mapping: DataFrame | None = None, suffixes: tuple[str, ...] = ("Inc.", "Inc", "Incorporated", "Ltd", "LLC", "Corp")) -> DataFrame:
    """Trims, drops company suffixes, then maps variants to their canonical value where a map (value, canonical) is given."""
    pattern = r"(?i)[,\s]+(" + "|".join(s.replace(".", r"\.") for s in suffixes) + r")\s*$"
    rows = rows.withColumn(column, F.trim(F.regexp_replace(F.trim(F.col(column)), pattern, "")))
    if mapping is None:
        return rows
    return rows.join(mapping.select(F.col("value").alias("_v"), F.col("canonical").alias("_c")), F.col(column) == F.col("_v"), "left").withColumn(column, F.coalesce("_c", column)).drop("_v", "_c")


def filter_outliers(rows: DataFrame, column: str, high: float) -> DataFrame:
    """kept false above the bound: the row is removed, but was visited."""
    return rows.withColumn("kept", F.coalesce(F.col(column) <= high, F.lit(False)))


def convert_units(rows: DataFrame, column: str, factors: dict[str, float], to: str) -> DataFrame:
    """Text like '1.2 miles' into the number of `to` units; a number without unit is taken as is, other text becomes null."""
    number = F.try_to_number(F.regexp_extract(column, r"^\s*([0-9]+(?:\.[0-9]+)?)", 1), F.lit("999999999.999999")).cast("double")
    unit = F.lower(F.regexp_extract(column, r"([A-Za-z]+)\s*$", 1))
    factor = F.when(unit == "", 1.0)
    for name, value in factors.items():
        factor = factor.when(unit == name, value)
    return rows.withColumn(f"{column}_{to}", number * factor)


def drop_wrong_attribute(rows: DataFrame, column: str, wrong) -> DataFrame:
    """Sets an attribute to null where it does not belong to the entity's type."""
    return rows.withColumn(column, F.when(~F.coalesce(wrong, F.lit(False)), F.col(column)))


def set_of_records(dirty: DataFrame, cleaned: DataFrame, column: str) -> DataFrame:
    """Find-and-replace of the value changes seen in a cleaned sample over the whole dirty part.

    cleaned: <column> and <column>_c. A value replaced in different ways takes its most frequent replacement, then the smallest.
    """
    seen = cleaned.where(F.col(column) != F.col(f"{column}_c")).groupBy(F.col(column).alias("_v"), F.col(f"{column}_c").alias("_c")).agg(F.count(F.lit(1)).alias("n"))
    mapping = seen.groupBy("_v").agg(F.min(F.struct((-F.col("n")).alias("m"), F.col("_c")))["_c"].alias("_c"))
    return dirty.join(F.broadcast(mapping), F.col(column) == F.col("_v"), "left").withColumn("replaced", F.col("_c").isNotNull()).withColumn(column, F.coalesce("_c", column)).drop("_v", "_c")


def promote(dirty: DataFrame, detector) -> DataFrame:
    """Rows of the dirty part that the detector finds clean after a set-of-records repair, marked promoted."""
    return detector.detect(dirty.drop("is_dirty", "err_cols", "err_features", "err_labels", "violated")).withColumn("promoted", ~F.col("is_dirty"))
