"""From records to (x, y): numeric, one-hot and text features with the lineage from columns to positions.

Scales and vocabularies are fitted once on the dirty rows and frozen, so that dirty and clean values share positions.
"""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

TOKEN = r"[^\p{L}\p{N}]+"


@dataclass
class Featurizer:
    """x = [1, standardised numeric columns, one-hot categories]; unknown categories and nulls are all zeros (the mean)."""

    numeric: list[str]
    categorical: list[str] = field(default_factory=list)
    max_levels: int = 50
    scale: dict[str, tuple[float, float]] = field(default_factory=dict)
    levels: dict[str, list[str]] = field(default_factory=dict)

    def fit(self, rows: DataFrame) -> Featurizer:
        if self.numeric:
            found = rows.agg(*[f(c).alias(f"{n}_{c}") for c in self.numeric for n, f in (("m", F.avg), ("s", F.stddev_pop))]).first()
            self.scale = {c: (found[f"m_{c}"] or 0.0, found[f"s_{c}"] or 1.0) for c in self.numeric}  # a constant column is only centred
        for c in self.categorical:
            top = rows.where(F.col(c).isNotNull()).groupBy(F.col(c).cast("string").alias("v")).agg(F.count(F.lit(1)).alias("n")).orderBy(F.desc("n"), "v").limit(self.max_levels).collect()
            self.levels[c] = sorted(r.v for r in top)[1:]  # the first level is the base
        return self

    @property
    def size(self) -> int:
        return 1 + len(self.numeric) + sum(len(v) for v in self.levels.values())

    def lineage(self) -> dict[str, list[int]]:
        """Column -> positions made of it."""
        out, at = {}, 1
        for c in self.numeric:
            out[c], at = [at], at + 1
        for c in self.categorical:
            out[c] = list(range(at, at + len(self.levels[c])))
            at += len(self.levels[c])
        return out

    def vector(self) -> Column:
        cells = [F.lit(1.0)]
        for c in self.numeric:
            m, s = self.scale[c]
            cells.append(F.coalesce((F.nanvl(F.col(c).cast("double"), F.lit(m)) - m) / (s or 1.0), F.lit(0.0)))
        cells += [F.coalesce((F.col(c).cast("string") == v).cast("double"), F.lit(0.0)) for c in self.categorical for v in self.levels[c]]
        return F.array(*cells)


def min_max(rows: DataFrame, column: str) -> DataFrame:
    """<column>_mm in [0, 1]; 0 for a constant column."""
    ends = rows.agg(F.min(column).alias("_lo"), F.max(column).alias("_hi"))
    return rows.crossJoin(F.broadcast(ends)).withColumn(f"{column}_mm", F.coalesce(F.try_divide(F.col(column) - F.col("_lo"), F.col("_hi") - F.col("_lo")), F.lit(0.0))).drop("_lo", "_hi")


def tokens(text: str | Column) -> Column:
    return F.filter(F.split(F.lower(text if isinstance(text, Column) else F.col(text)), TOKEN), lambda t: t != "")


def frozen_vocabulary(rows: DataFrame, text: str, size: int) -> list[str]:
    """The tokens of most rows, ties by token: at most `size` strings on the driver."""
    each = rows.select(F.explode(F.array_distinct(tokens(text))).alias("token"))
    return [r.token for r in each.groupBy("token").agg(F.count(F.lit(1)).alias("n")).orderBy(F.desc("n"), "token").limit(size).collect()]


def bag_of_words(text: str, vocabulary: list[str], other: bool = True) -> Column:
    """Counts over the frozen vocabulary, with one more position for tokens that only cleaning brings in."""
    t = tokens(text)
    at = F.transform(t, lambda w: F.coalesce(F.try_element_at(F.create_map(*[F.lit(v) for i, w2 in enumerate(vocabulary) for v in (w2, i)]), w), F.lit(len(vocabulary))))
    return F.transform(F.sequence(F.lit(0), F.lit(len(vocabulary) - (not other))), lambda i: F.size(F.filter(at, lambda a: a == i)).cast("double"))


def hashed_bag(text: str, size: int) -> Column:
    """Counts of tokens by md5 slot: no vocabulary, the same in every engine."""
    slot = F.transform(tokens(text), lambda w: (F.conv(F.substring(F.md5(w), 1, 8), 16, 10).cast("long") % size).cast("int"))
    return F.transform(F.sequence(F.lit(0), F.lit(size - 1)), lambda i: F.size(F.filter(slot, lambda a: a == i)).cast("double"))


def tf_idf(rows: DataFrame, key: str, text: str) -> DataFrame:
    """key, token, tf, df, tfidf in long form; counts combine before the shuffle."""
    each = rows.select(key, F.explode(tokens(text)).alias("token")).groupBy(key, "token").agg(F.count(F.lit(1)).alias("tf"))
    df = each.groupBy("token").agg(F.count(F.lit(1)).alias("df"))
    n = rows.agg(F.count(F.lit(1)).alias("_n"))
    return each.join(df, "token").crossJoin(F.broadcast(n)).select(key, "token", "tf", "df", (F.col("tf") * F.log(F.col("_n") / F.col("df"))).alias("tfidf"))


def surface(text: str) -> list[Column]:
    """Five length-free measures of a text: log size, and shares of punctuation, capitals, distinct words and digits."""
    c = F.col(text)
    n = F.greatest(F.length(c), F.lit(1)).cast("double")
    t = F.split(c, r"\s+")
    share = lambda pattern: (F.length(c) - F.length(F.regexp_replace(c, pattern, ""))) / n
    return [F.log1p(n), share(r"[!-/:-@\[-`{-~]"), share("[A-Z]"), F.size(F.array_distinct(t)) / F.size(t).cast("double"), share("[0-9]")]
