"""Corruption generators: they add x_d, is_dirty, err_features and class_id to clean rows (row_id, x), by hashes of row_id."""

from __future__ import annotations

from collections.abc import Callable
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.portable import uniform


def _finish(rows: DataFrame, flags: list[Column], values: list[Column], d: int, store: Callable[[DataFrame], DataFrame] | None = None) -> DataFrame:
    """class_id is the bit set of corrupted features (bit k for the k-th of them), 0 for a clean row.

    store: writes the rows with the bit set `_bits` and gives them back, so that later readers make no hashes for it.
    """
    if store is not None:
        at = [i for i, f in enumerate(flags) if f is not None]
        rows = store(rows.withColumn("_bits", sum((F.when(flags[i], F.lit(1 << k)).otherwise(F.lit(0)) for k, i in enumerate(at)), F.lit(0)).cast("long")))
        flags = [None if f is None else F.col("_bits").bitwiseAND(F.lit(1 << at.index(i)).cast("long")) != 0 for i, f in enumerate(flags)]
    x = F.array(*[F.when(flags[i], values[i]).otherwise(F.get("x", F.lit(i))) if flags[i] is not None else F.get("x", F.lit(i)) for i in range(d)])
    errs = F.filter(F.array(*[F.when(f, F.lit(i)) for i, f in enumerate(flags) if f is not None]), lambda v: v.isNotNull())
    bits = sum((F.when(f, F.lit(1 << k)).otherwise(F.lit(0)) for k, f in enumerate(f for f in flags if f is not None)), F.lit(0))
    # Of the flags themselves: a filter on the size of err_features is interpreted, row by row, for every reader of the dirty or the clean part.
    dirty = reduce(lambda p, q: p | q, [F.coalesce(f, F.lit(False)) for f in flags if f is not None], F.lit(False))
    return rows.withColumn("x_d", x).withColumn("err_features", errs).withColumn("class_id", bits.cast("int")).withColumn("is_dirty", dirty)


def random_magnitude(rows: DataFrame, d: int, rate: float = 0.05, factor: float = 3.0, seed: int = 1, first: int = 1, store: Callable[[DataFrame], DataFrame] | None = None) -> DataFrame:
    """A random feature of a random `rate` of rows becomes `factor` times the feature's largest value."""
    peaks = rows.agg(F.array(*[F.max(F.get("x", F.lit(i))) for i in range(d)]).alias("m")).first().m
    hit = uniform("row_id", seed, "hit") < rate
    which = (F.floor(uniform("row_id", seed, "feature") * (d - first)) + first).cast("int")
    flags = [None if i < first else hit & (which == i) for i in range(d)]
    return _finish(rows, flags, [F.lit(factor * float(m or 0.0)) for m in peaks], d, store)


#: Parts into which one pass of `exact_cuts` cuts each range.
PARTS = 4096


def exact_cuts(rows: DataFrame, values: dict[str, Column], wanted: dict[str, int], largest: bool) -> dict[str, tuple[float, int]]:
    """For each name the wanted-th largest (or smallest) of its values, and how many lie strictly beyond it.

    Exact at any size, without a sort: each pass counts values by parts of the range that still holds the rank, and
    narrows that range to the part's least and greatest value. The ends of a range are parts of their own, so every
    pass narrows it. Nulls and NaN are left out; a name with fewer values than wanted gets the outermost one.
    """
    each = rows.select(*[F.nanvl(v.cast("double"), F.lit(None).cast("double")).alias(k) for k, v in values.items()])
    ends = each.agg(*[f(k).alias(f"{n}_{k}") for k in values for n, f in (("lo", F.min), ("hi", F.max), ("n", F.count))]).first()
    open_ = {k: (ends[f"lo_{k}"], ends[f"hi_{k}"], 0) for k in values if ends[f"n_{k}"] and wanted[k] > 0}
    wanted = {k: min(wanted[k], ends[f"n_{k}"]) for k in open_}
    found: dict[str, tuple[float, int]] = {}
    while open_:
        found |= {k: (lo, beyond) for k, (lo, hi, beyond) in open_.items() if lo == hi}
        open_ = {k: r for k, r in open_.items() if k not in found}
        if not open_:
            break
        cells = []
        for k, (lo, hi, _) in open_.items():
            v, low, high = F.col(k), F.lit(float(lo)), F.lit(float(hi))
            part = F.floor((v / 2 - low / 2) / (high / 2 - low / 2) * PARTS)
            part = F.when(v == low, -1).when(v == high, PARTS + 1).otherwise(part).cast("int")
            cells.append(F.when(v.between(low, high), F.struct(F.lit(k).alias("name"), part.alias("part"), v.alias("v"))))
        counted = each.select(F.explode(F.array(*cells)).alias("c")).where("c is not null").groupBy("c.name", "c.part").agg(F.count(F.lit(1)).alias("n"), F.min("c.v").alias("lo"), F.max("c.v").alias("hi"))
        parts = sorted(counted.collect(), key=lambda r: r.lo, reverse=largest)  # at most PARTS + 2 rows a name
        for k in list(open_):
            beyond = open_[k][2]
            for r in (r for r in parts if r.name == k):
                if beyond + r.n >= wanted[k]:
                    open_[k] = (r.lo, r.hi, beyond)
                    break
                beyond += r.n
    return found


def systematic(rows: DataFrame, d: int, theta, rate: float = 0.05, features: int = 3, mix: float = 0.0, seed: int = 1, first: int = 1, store: Callable[[DataFrame], DataFrame] | None = None) -> DataFrame:
    """The highest values of the features with the largest |theta| become the feature's mean.

    Each feature takes rate / features of the rows; overlaps may happen. With probability `mix` a random row is taken
    instead of a top one. Of the rows at the cut-off, which may be many, those with the smallest uniform numbers are
    taken until the share is full. Cut-offs, for values and for these numbers, are exact ranks; no sort of the rows.
    """
    top = sorted(range(first, d), key=lambda i: (-abs(theta[i]), i))[:features]
    share = rate / len(top)
    value, tie = (lambda i: F.nanvl(F.get("x", F.lit(i)), F.lit(None).cast("double"))), (lambda i: uniform("row_id", seed, "tie", i))
    whole = rows.agg(F.count(F.lit(1)).alias("n"), F.array(*[F.avg(F.get("x", F.lit(i))) for i in top]).alias("m")).first()
    quota = int(share * (1 - mix) * whole.n)
    flags: list = [None] * d
    values = [F.lit(0.0)] * d
    cuts = exact_cuts(rows, {f"v{i}": value(i) for i in top}, {f"v{i}": quota for i in top}, largest=True) if quota else {}
    # Of the rows at the cut-off as many as the share still holds.
    left = {f"t{i}": quota - cuts[f"v{i}"][1] for i in top if f"v{i}" in cuts}
    at_cut = {f"t{i}": F.when(value(i) == cuts[f"v{i}"][0], tie(i)) for i in top if f"v{i}" in cuts}
    part = exact_cuts(rows, at_cut, left, largest=False) if at_cut else {}
    for k, i in enumerate(top):
        high = F.lit(False)
        if f"v{i}" in cuts:
            cut = F.lit(float(cuts[f"v{i}"][0]))
            high = (value(i) > cut) | ((value(i) == cut) & (tie(i) <= F.lit(part[f"t{i}"][0])))
        if mix:
            high = high | (uniform("row_id", seed, "mix", i) < share * mix)
        flags[i], values[i] = F.coalesce(high, F.lit(False)), F.lit(float(whole.m[k] or 0.0))
    # Without a mix hashes are made for rows at a cut-off only.
    return _finish(rows, flags, values, d, store if mix else None)


def block_removal(rows: DataFrame, side: int = 8, block: int = 3, rate: float = 0.05, seed: int = 1) -> DataFrame:
    """A block x block square at a random place of a random `rate` of images (arrays of side * side) becomes 0."""
    hit = uniform("row_id", seed, "hit") < rate
    top = F.floor(uniform("row_id", seed, "top") * (side - block + 1)).cast("int")
    left = F.floor(uniform("row_id", seed, "left") * (side - block + 1)).cast("int")

    def blank(v, i):
        r, c = F.floor(i / side), i % side
        return F.when((r >= top) & (r < top + block) & (c >= left) & (c < left + block), F.lit(0.0)).otherwise(v)

    return rows.withColumn("is_dirty", hit).withColumn("x_d", F.when(hit, F.transform("x", blank)).otherwise(F.col("x")))


def blur(rows: DataFrame, side: int = 8, window: int = 2, rate: float = 0.05, seed: int = 1) -> DataFrame:
    """Each cell becomes the mean of the window x window cells from it to the right and below, cut at the border."""
    hit = uniform("row_id", seed, "hit") < rate

    def smooth(i: int) -> Column:
        r, c = divmod(i, side)
        cells = [F.get("x", F.lit(a * side + b)) for a in range(r, min(side, r + window)) for b in range(c, min(side, c + window))]
        return sum(cells[1:], cells[0]) / len(cells)

    return rows.withColumn("is_dirty", hit).withColumn("x_d", F.when(hit, F.array(*[smooth(i) for i in range(side * side)])).otherwise(F.col("x")))


SUFFIXES = (" Inc.", " Incorporated", ", Inc", " LLC")


def name_variants(rows: DataFrame, column: str, rate: float = 0.18, seed: int = 1, key: str = "row_id") -> DataFrame:
    """Company suffixes on a random `rate` of names; the clean name stays in <column>_c."""
    hit = uniform(key, seed, "hit") < rate
    pick = F.get(F.array(*[F.lit(s) for s in SUFFIXES]), F.floor(uniform(key, seed, "suffix") * len(SUFFIXES)).cast("int"))
    return rows.withColumn(f"{column}_c", F.col(column)).withColumn("is_dirty", hit).withColumn(column, F.when(hit, F.concat(F.col(column), pick)).otherwise(F.col(column)))


def stale_groups(groups: DataFrame, at_most: int) -> DataFrame:
    """Groups of few members show their stale total: x_d, is_dirty from n, total and stale_total."""
    small = F.col("n") <= at_most
    return groups.withColumn("is_dirty", small & (F.col("total") != F.col("stale_total"))).withColumn("total_d", F.when(small, F.col("stale_total")).otherwise(F.col("total")))


def shifted_region(rows: DataFrame, feature: int, low: float, shift: float, d: int) -> DataFrame:
    """Moves one feature of the rows above `low`: the pooled slope may reverse when only some are moved back."""
    flags: list = [None] * d
    flags[feature] = F.get("x", F.lit(feature)) > low
    values = [F.lit(0.0)] * d
    values[feature] = F.get("x", F.lit(feature)) + shift
    return _finish(rows, flags, values, d)
