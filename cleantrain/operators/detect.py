"""Detectors: rules known up front, and detectors learned from cleaned rows. Each adds is_dirty and err_cols to a frame."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass
from functools import reduce
from itertools import combinations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.losses import Loss, hinge
from ..functions.vectors import dot
from ..sources.scratch import scratch_table


@dataclass(frozen=True)
class Rule:
    """columns: what a violation puts in doubt. A row rule has a predicate; other rules mark values or keys by a join."""

    name: str
    columns: tuple[str, ...]
    predicate: Callable[[], Column] | None = None
    mark: Callable[[DataFrame], DataFrame] | None = None  # adds a boolean column named like the rule

    @staticmethod
    def domain(column: str, values: list) -> Rule:
        """Null is outside every domain."""
        return Rule(f"domain_{column}", (column,), lambda: ~F.coalesce(F.col(column).isin(*values), F.lit(False)))

    @staticmethod
    def exclusive(a: str, b: str, at_most_one: bool = False) -> Rule:
        """Exactly one of two columns (or at most one) is set."""
        both = lambda: F.col(a).isNotNull() & F.col(b).isNotNull()
        return Rule(f"exclusive_{a}_{b}", (a, b), both if at_most_one else lambda: F.col(a).isNull() == F.col(b).isNull())

    @staticmethod
    def not_null(*columns: str) -> Rule:
        return Rule(f"not_null_{'_'.join(columns)}", columns, lambda: reduce(lambda p, q: p | q, [F.col(c).isNull() for c in columns]))

    @staticmethod
    def range(column: str, low: float | None = None, high: float | None = None) -> Rule:
        """Null and NaN are out of range."""
        v = lambda: F.nanvl(F.col(column).cast("double"), F.lit(None).cast("double"))
        return Rule(f"range_{column}", (column,), lambda: ~F.coalesce((F.lit(True) if low is None else v() >= low) & (F.lit(True) if high is None else v() <= high), F.lit(False)))

    @staticmethod
    def regex(column: str, pattern: str) -> Rule:
        return Rule(f"regex_{column}", (column,), lambda: ~F.coalesce(F.col(column).rlike(pattern), F.lit(False)))

    @staticmethod
    def functional(lhs: list[str], rhs: str) -> Rule:
        """Rows whose left side occurs with more than one right side. Counts combine before the shuffle."""
        name = f"fd_{'_'.join(lhs)}_{rhs}"

        def mark(rows: DataFrame) -> DataFrame:
            bad = rows.groupBy(*lhs).agg(F.min(rhs).alias("_lo"), F.max(rhs).alias("_hi")).where("_lo <> _hi").select(*[F.col(c).alias(f"_{c}") for c in lhs]).withColumn(name, F.lit(True))
            return rows.join(bad, [F.col(c).eqNullSafe(F.col(f"_{c}")) for c in lhs], "left").drop(*[f"_{c}" for c in lhs]).withColumn(name, F.coalesce(name, F.lit(False)))

        return Rule(name, (*lhs, rhs), mark=mark)

    @staticmethod
    def denial(name: str, key: list[str], columns: tuple[str, ...], pair: Callable[[str, str], str], row_id: str = "row_id") -> Rule:
        """No two rows of equal key may fulfil pair('a', 'b'), SQL over two aliases; an equi-join, then the test."""

        def mark(rows: DataFrame) -> DataFrame:
            a, b = rows.alias("a"), rows.alias("b")
            on = reduce(lambda p, q: p & q, [F.col(f"a.{k}") == F.col(f"b.{k}") for k in key]) & (F.col(f"a.{row_id}") != F.col(f"b.{row_id}"))
            bad = a.join(b, on & F.expr(pair("a", "b")), "left_semi").select(F.col(row_id).alias("_id")).withColumn(name, F.lit(True))
            return rows.join(bad.distinct(), F.col(row_id) == F.col("_id"), "left").drop("_id").withColumn(name, F.coalesce(name, F.lit(False)))

        return Rule(name, columns, mark=mark)

    @staticmethod
    def matching(column: str, threshold: float = 0.8, canonical: DataFrame | None = None, weights: str = "idf") -> Rule:
        """Values linked by similarity (weighted Jaccard) to a more frequent value are variants of it, and dirty.

        With a table of right values (its column `canonical`), those are never dirty, and only their variants are.
        """
        name = f"matching_{column}"

        def mark(rows: DataFrame) -> DataFrame:
            variants = variant_map(rows, column, threshold, weights, canonical).where("value <> canonical").select(F.col("value").alias("_v")).withColumn(name, F.lit(True))
            return rows.join(variants, F.col(column) == F.col("_v"), "left").drop("_v").withColumn(name, F.coalesce(name, F.lit(False)))

        return Rule(name, (column,), mark=mark)


def similar_values(rows: DataFrame, column: str, threshold: float = 0.8, weights: str = "idf") -> DataFrame:
    """a < b, similarity: pairs of distinct values whose token sets' weighted Jaccard similarity is above the threshold.

    Runs on distinct values. Tokens are ordered from rare to frequent and only a value's leading tokens are indexed:
    two values above the threshold must share one of those that hold more than (1 - threshold) of a value's weight.
    """
    values = rows.where(F.col(column).isNotNull()).select(F.col(column).alias("value")).distinct()
    tokens = values.select("value", F.explode(F.array_distinct(F.filter(F.split(F.lower("value"), r"[^\p{L}\p{N}]+"), lambda t: t != ""))).alias("token"))
    n = values.agg(F.count(F.lit(1)).alias("_n"))
    df = tokens.groupBy("token").agg(F.count(F.lit(1)).alias("df")).crossJoin(F.broadcast(n))
    df = df.select("token", "df", (F.log(1 + F.col("_n") / F.col("df")) if weights == "idf" else F.lit(1.0)).alias("w"))
    bags = tokens.join(df, "token").groupBy("value").agg(F.array_sort(F.collect_list(F.struct("df", "token", "w"))).alias("t"), F.sum("w").alias("size"))
    # The prefix: tokens before which less than (1 - threshold) of the weight has been seen.
    lead = F.aggregate("t", F.struct(F.lit(0.0).alias("sum"), F.array().cast("array<string>").alias("p")), lambda s, t: F.struct((s["sum"] + t["w"]).alias("sum"), F.when(s["sum"] <= (1 - threshold) * F.col("size") + 1e-9, F.concat(s["p"], F.array(t["token"]))).otherwise(s["p"]).alias("p")))["p"]
    bags = bags.withColumn("lead", lead).withColumn("bag", F.map_from_entries(F.transform("t", lambda t: F.struct(t["token"].alias("k"), t["w"].alias("v")))))
    left = bags.select(F.col("value").alias("a"), F.col("size").alias("sa"), F.col("bag").alias("ba"), F.explode("lead").alias("token"))
    right = bags.select(F.col("value").alias("b"), F.col("size").alias("sb"), F.col("bag").alias("bb"), F.explode("lead").alias("token"))
    pairs = left.join(right, "token").where((F.col("a") < F.col("b")) & (F.least("sa", "sb") > threshold * F.greatest("sa", "sb") - 1e-9)).drop("token").dropDuplicates(["a", "b"])
    # Tokens weigh the same in both values, so the union is the sizes less what is shared.
    shared = F.aggregate(F.map_keys("ba"), F.lit(0.0), lambda s, k: s + F.coalesce(F.try_element_at("bb", k), F.lit(0.0)))
    pairs = pairs.withColumn("_s", shared).withColumn("similarity", F.col("_s") / (F.col("sa") + F.col("sb") - F.col("_s")))
    return pairs.where(F.col("similarity") > threshold).select("a", "b", "similarity")


def connected(values: DataFrame, pairs: DataFrame) -> DataFrame:
    """value and component (its least value): each round takes the least label among neighbours, then that label's own.

    values: column value; pairs: a and b. Labels are written down after each round, so plans do not grow.
    """
    links = scratch_table(pairs.select("a", "b").union(pairs.select("b", "a")))
    labels = scratch_table(values.select("value", F.col("value").alias("component")))
    while True:
        seen = links.join(labels.select(F.col("value").alias("b"), "component"), "b").select(F.col("a").alias("value"), "component")
        least = seen.union(labels).groupBy("value").agg(F.min("component").alias("component"))
        jump = least.join(labels.select(F.col("value").alias("component"), F.col("component").alias("_next")), "component", "left")
        after = scratch_table(jump.select("value", F.least("component", F.coalesce("_next", "component")).alias("component")))
        if not after.join(labels, ["value", "component"], "left_anti").limit(1).count():
            return after
        labels = after


def variant_map(rows: DataFrame, column: str, threshold: float = 0.8, weights: str = "idf", canonical: DataFrame | None = None) -> DataFrame:
    """value and canonical: the most frequent value (then the smallest) of all those linked by similar pairs.

    Right values given in `canonical` come first and stand for themselves; a group without one keeps its values.
    """
    given = canonical.where("canonical is not null").select(F.col("canonical").alias("value")).distinct().withColumn("right", F.lit(True)) if canonical is not None else None
    counts = rows.where(F.col(column).isNotNull()).groupBy(F.col(column).alias("value")).agg(F.count(F.lit(1)).alias("n"))
    if given is not None:
        counts = counts.join(given, "value", "full").select("value", F.coalesce("n", F.lit(0)).alias("n"), F.coalesce("right", F.lit(False)).alias("right"))
    else:
        counts = counts.withColumn("right", F.lit(False))
    counts = scratch_table(counts)
    groups = connected(counts, similar_values(counts.select(F.col("value").alias(column)), column, threshold, weights)).join(counts, "value")
    first = groups.groupBy("component").agg(F.min(F.struct((~F.col("right")).alias("last"), (-F.col("n")).alias("m"), F.col("value"))).alias("f"))
    stays = F.col("right") | F.col("f.last") if given is not None else F.lit(False)
    out = groups.join(first, "component").select("value", F.when(stays, F.col("value")).otherwise(F.col("f.value")).alias("canonical"), "n")
    return out.where("n > 0").drop("n")


class ConstraintDetector:
    """A row is dirty if it violates a rule; its doubtful columns are the union over violated rules.

    lineage maps a column to the features made of it; label columns are named apart.
    """

    def __init__(self, rules: list[Rule], lineage: dict[str, list[int]] | None = None, labels: tuple[str, ...] = ()):
        self.rules, self.lineage, self.labels = rules, lineage or {}, labels

    def detect(self, rows: DataFrame) -> DataFrame:
        # Marks have names of their own: two rules may share one, or have a column's.
        marks, seen, labels = [f"__rule{k}" for k in range(len(self.rules))], {}, []
        for mark, rule in zip(marks, self.rules, strict=True):
            seen[rule.name] = seen.get(rule.name, 0) + 1
            labels.append(rule.name if seen[rule.name] == 1 else f"{rule.name}_{seen[rule.name]}")
            if rule.mark:
                held = f"__held_{rule.name}"
                own = rule.name in rows.columns
                rows = rule.mark(rows.withColumn(held, F.col(rule.name)) if own else rows).withColumnRenamed(rule.name, mark)
                rows = rows.withColumnRenamed(held, rule.name) if own else rows
            else:
                rows = rows.withColumn(mark, rule.predicate())
        named = F.array(*[F.when(F.col(m), F.lit(label)) for m, label in zip(marks, labels, strict=True)])
        columns = F.flatten(F.filter(F.array(*[F.when(F.col(m), F.array(*[F.lit(c) for c in r.columns])) for m, r in zip(marks, self.rules, strict=True)]), lambda a: a.isNotNull()))
        rows = rows.withColumn("violated", F.filter(named, lambda a: a.isNotNull())).withColumn("err_cols", F.array_sort(F.array_distinct(columns))).drop(*marks)
        features = [F.when(F.array_contains("err_cols", c), F.array(*[F.lit(i) for i in at])).otherwise(F.array().cast("array<int>")) for c, at in self.lineage.items() if c not in self.labels]
        rows = rows.withColumn("is_dirty", F.size("err_cols") > 0)
        return rows.withColumn("err_features", F.array_sort(F.array_distinct(F.flatten(F.array(*features)))) if features else F.array().cast("array<int>")).withColumn("err_labels", F.filter("err_cols", lambda c: c.isin(*self.labels)) if self.labels else F.array().cast("array<string>"))


def truth_detector(rows: DataFrame, truth: DataFrame) -> DataFrame:
    """Marks from a table of known errors: row_id, err_features, class_id."""
    known = truth.select(F.col("row_id").alias("_id"), F.col("err_features").alias("_f"), F.col("class_id").alias("_c"))
    out = rows.join(known, F.col("row_id") == F.col("_id"), "left")
    return out.withColumn("err_features", F.coalesce("_f", F.array().cast("array<int>"))).withColumn("class_id", F.coalesce("_c", F.lit(0))).withColumn("is_dirty", F.size("err_features") > 0).drop("_id", "_f", "_c")


class ClassifierDetector:
    """One-vs-all linear classifier of the class of error (0: clean), fitted to the cleaned rows after each batch.

    It knows nothing before the first batch: every row is a candidate then. Classes may appear at any time.
    """

    def __init__(self, loss: Loss | None = None, lam: float = 1e-3, steps: int = 200):
        self.loss, self.lam, self.steps = loss or hinge(), lam, steps
        self.classes: list[int] = []
        self.thetas = np.zeros((0, 0))

    def fit(self, x: np.ndarray, class_id: np.ndarray) -> ClassifierDetector:
        """On the driver: x holds at most the cleaned rows."""
        self.classes = sorted({int(c) for c in class_id})
        if len(self.classes) < 2:
            self.classes = []
            return self
        low = 0.0 if self.loss.name == "logistic" else -1.0
        thetas = []
        for c in self.classes:
            y = np.where(class_id == c, 1.0, low)
            w = np.where(class_id == c, 0.5 / max((class_id == c).mean(), 1e-9), 0.5 / max((class_id != c).mean(), 1e-9))
            theta, mean = np.zeros(x.shape[1]), np.zeros(x.shape[1])
            for t in range(1, self.steps + 1):
                g = (w * self.loss.np_slope(x @ theta, y)) @ x / len(y) + self.lam * theta
                theta = theta - g / np.sqrt(t)
                mean += (theta - mean) / t
            thetas.append(mean)
        self.thetas = np.stack(thetas)
        return self

    def class_column(self, x: str = "x") -> Column:
        """The class of the highest score as an expression inside the sampling scan; 1 while nothing is known."""
        if not self.classes:
            return F.lit(1)
        scores = F.array(*[dot(F.col(x), t) for t in self.thetas])
        return F.element_at(F.array(*[F.lit(c) for c in self.classes]), F.array_position(scores, F.array_max(scores)).cast("int"))

    def predict(self, x: np.ndarray) -> np.ndarray:
        return np.array(self.classes)[np.argmax(x @ self.thetas.T, axis=1)] if self.classes else np.ones(len(x), int)


def pattern_tableau(ledger: DataFrame, attributes: list[str], class_id: str = "class_id", min_support: int = 5, min_confidence: float = 0.8, max_length: int = 2) -> DataFrame:
    """Learned patterns: class_id, one column for each attribute, given, support, confidence.

    `given` names the attributes that a pattern fixes; of these null is a value, all others may be anything.
    Grouping sets over all subsets of at most max_length attributes, of the ledger only.
    """
    sets = [s for n in range(1, max_length + 1) for s in combinations(attributes, n)]
    rows = ledger.select(class_id, *[F.col(a).cast("string").alias(a) for a in attributes])
    grouped = rows.groupingSets([[F.col(a) for a in s] + [F.col(class_id)] for s in sets], *[F.col(a) for a in attributes], F.col(class_id)).agg(F.count(F.lit(1)).alias("support"), F.grouping_id().alias("_g"))
    whole = rows.groupingSets([[F.col(a) for a in s] for s in sets], *[F.col(a) for a in attributes]).agg(F.count(F.lit(1)).alias("_n"), F.grouping_id().alias("_h"))
    on = reduce(lambda p, q: p & q, [grouped[a].eqNullSafe(whole[a]) for a in attributes]) & (F.shiftright(grouped["_g"], 1) == whole["_h"])
    # A bit of the grouping id is set where an attribute is left out; the class is the lowest bit.
    free = [F.shiftright(grouped["_g"], len(attributes) - i).bitwiseAND(1) for i in range(len(attributes))]
    given = F.filter(F.array(*[F.when(f == 0, F.lit(a)) for f, a in zip(free, attributes, strict=True)]), lambda a: a.isNotNull())
    out = grouped.join(whole, on).select(class_id, *[grouped[a] for a in attributes], given.alias("given"), "support", (F.col("support") / F.col("_n")).alias("confidence"))
    return out.where((F.col("support") >= min_support) & (F.col("confidence") >= min_confidence) & (F.col(class_id) > 0))


def detect_by_patterns(rows: DataFrame, tableau: DataFrame, attributes: list[str], class_id: str = "class_id") -> DataFrame:
    """Adds class_id of the most confident fitting pattern (then best supported, then least class), 0 if none.

    One equi-join for each set of attributes that patterns fix; Spark broadcasts those tables that are small. A fixed
    null fits null alone. Rows are neither multiplied nor grouped.
    """
    sets = sorted(tuple(r.given) for r in tableau.select("given").distinct().collect())  # at most one for each set of attributes
    out, found = rows.drop("class_id"), []
    for k, given in enumerate(sets):
        rank = F.struct("confidence", "support", (-F.col(class_id)).alias("least"))
        best = tableau.where(F.col("given") == F.array(*[F.lit(a) for a in given])).groupBy(*[F.col(a).alias(f"_p{k}_{i}") for i, a in enumerate(given)]).agg(F.max(rank).alias(f"_best{k}"))
        on = reduce(lambda p, q: p & q, [F.col(f"_p{k}_{i}").eqNullSafe(F.col(a).cast("string")) for i, a in enumerate(given)])
        out = out.join(best, on, "left").drop(*[f"_p{k}_{i}" for i in range(len(given))])
        found.append(F.col(f"_best{k}"))
    if not found:
        return out.withColumn("class_id", F.lit(0))
    top = F.array_max(F.array(*found))
    return out.withColumn("class_id", F.coalesce(-top["least"], F.lit(0)).cast("int")).drop(*[f"_best{k}" for k in range(len(sets))])
