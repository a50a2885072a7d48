"""Exact top-k inner-product search by best-first search over M-tree pages.

Inner products become distances: with R the largest norm of a row, each row x gets the extra coordinate
sqrt(R^2 - |x|^2) and each query the extra coordinate 0, so that the squared distance is |q|^2 + R^2 - 2 q.x and the
nearest rows are those of the highest scores. The tree has regions (routing objects from a bounded sample), cells
of at most CELL_ROWS rows in a region, and leaf pages of at most LEAF_ROWS rows. Every leaf page stores its routing
object, covering radius and distance to the cell's routing object; every row stores its distance to the leaf's.
A query visits the leaf pages of a cell in order of their lower bound |d(q,cell) - d(leaf,cell)| - radius, drops a
page without computing a distance once that bound exceeds its k-th best distance, then once d(q,leaf) - radius does,
and inside a page drops rows by |d(q,leaf) - d(row,leaf)|. Bounds carry a slack, so rounding never drops a tie.

Groups of queries meet parts of the tree (at most PART_CELLS cells) by an equi-join on (part, group), always a shuffled
one: a broadcast of one side repeated for the other would pass through the driver. A row of it is one cell and one group,
both of bounded size, however large a region, a group of equal vectors or the query set is. Cells are repeated for each
group and groups for each part, so groups are large; a group's bounds are carried from cell to cell of a part. Only
per-query lists of at most k rows leave a part.

Edge cases: vectors that are null, empty, or hold null or non-finite components take no part; so do rows without a
vec_id. Vectors of different lengths are never compared. Fewer than k candidates give all of them. Rows that repeat
a query's vec_id are the query's own. Repeated identical query rows are asked once. A vector whose squared length reaches 2**63 takes no part: it
has no 64-bit score (two others' score is below, by Cauchy and Schwarz). An empty table gives no rows.
"""

from __future__ import annotations

import pickle
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import scratch_table

REGIONS, CELL_ROWS, LEAF_ROWS, QUERY_ROWS = 64, 4096, 128, 512
#: Queries of one group, cells of one part at most, and units below which parts are made smaller, so that all tasks have some.
GROUP_ROWS, PART_CELLS, MIN_UNITS = 16_384, 8, 48
SLACK = 1e-7


def quantised(table: DataFrame, scale: float = 64.0) -> DataFrame:
    """vec_id, dim and the packed vector floor(scale * x): int16 where that holds it, else float64."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            rows = []
            for key, vector in zip(batch["vec_id"], batch["embedding"], strict=True):
                if vector is None or not len(vector) or key is None or pd.isna(key):
                    continue
                x = np.array([np.nan if v is None else v for v in vector], dtype=np.float64)
                with np.errstate(over="ignore"):
                    x = np.floor(scale * x)
                    fits = float(x @ x) < 2.0**63  # false for NaN, too
                if fits:
                    rows.append((int(key), len(x), (x.astype("<i2") if np.abs(x).max() < 2**15 else x.astype("<f8")).tobytes()))
            yield pd.DataFrame(rows, columns=["vec_id", "dim", "packed"])

    return table.where("vec_id is not null").select("vec_id", F.col("embedding").cast("array<double>").alias("embedding")).mapInPandas(run, "vec_id long, dim int, packed binary")


def unpacked(packed, dim: int) -> np.ndarray:
    return np.stack([np.frombuffer(p, "<i2" if len(p) == 2 * dim else "<f8").astype(np.float64) for p in packed]) if len(packed) else np.zeros((0, dim))


def lifted(x: np.ndarray, bound: float) -> np.ndarray:
    """Rows with the coordinate that makes all norms equal to bound."""
    return np.hstack([x, np.sqrt(np.maximum(bound - (x * x).sum(1), 0.0))[:, None]])


def leaf_pages(points: np.ndarray, size: int = LEAF_ROWS) -> list[np.ndarray]:
    """Row numbers of each leaf: halves by the two routing objects that lie far apart, until a leaf fits."""
    out, stack = [], [np.arange(len(points))]
    while stack:
        rows = stack.pop()
        if len(rows) <= size:
            out.append(rows)
            continue
        part = points[rows]
        a = part[np.argmax(((part - part[0]) ** 2).sum(1))]
        b = part[np.argmax(((part - a) ** 2).sum(1))]
        order = np.argsort(((part - a) ** 2).sum(1) - ((part - b) ** 2).sum(1), kind="stable")
        stack += [rows[order[: len(rows) // 2]], rows[order[len(rows) // 2 :]]]
    return out


def none_found(n: int, k: int) -> tuple[np.ndarray, np.ndarray]:
    return np.full((n, k), -np.inf), np.full((n, k), np.iinfo(np.int64).max)


def compact(vectors: np.ndarray) -> np.ndarray:
    """int16 where that holds them, as in storage."""
    return vectors.astype(np.int16) if np.abs(vectors).max(initial=0) < 2**15 else vectors


class Cell:
    """One cell of the tree, as stored: rows in leaf order and a table of leaf pages."""

    def __init__(self, ids: np.ndarray, vectors: np.ndarray, bound: float):
        points = lifted(vectors, bound)
        self.center = points.mean(0)
        pages = leaf_pages(points)
        order = np.concatenate(pages)
        self.ids, self.vectors = ids[order], vectors[order]
        self.cuts = np.cumsum([0, *map(len, pages)])
        self.routing = np.stack([points[p].mean(0) for p in pages])
        self.to_routing = np.concatenate([np.sqrt(((points[p] - r) ** 2).sum(1)) for p, r in zip(pages, self.routing, strict=True)])
        self.radius = np.array([self.to_routing[a:b].max() for a, b in zip(self.cuts, self.cuts[1:], strict=False)])
        self.to_center = np.sqrt(((self.routing - self.center) ** 2).sum(1))

    def search(self, ids: np.ndarray, queries: np.ndarray, bound: float, k: int, before: tuple | None = None) -> tuple[np.ndarray, np.ndarray, dict]:
        """Scores and row ids of each query's k best, best first (missing: -inf), and counts of the work.

        before: scores and row ids that other cells gave; the result holds the best of both.
        """
        n, norms = len(queries), (queries * queries).sum(1)
        asked = np.hstack([queries, np.zeros((n, 1))])
        center = np.sqrt(((asked - self.center) ** 2).sum(1))
        lower = np.abs(center[:, None] - self.to_center[None, :]) - self.radius[None, :]
        order = np.argsort(lower, axis=1, kind="stable")
        best, who = none_found(n, k) if before is None else (before[0].copy(), before[1].copy())
        reach = self._reach(norms, bound, best)
        work = {"pages": 0, "bounded_pages": 0, "rows": 0}
        exact = len(queries[0]) * max(np.abs(self.vectors).max(initial=1), 1) * max(np.abs(queries).max(initial=1), 1) < 2**53 if n else True
        for step in range(len(self.radius)):
            page = order[:, step]
            live = np.flatnonzero(lower[np.arange(n), page] <= reach)
            work["bounded_pages"] += n - len(live)
            if not len(live):
                break  # bounds rise along each query's order
            by_page = live[np.argsort(page[live], kind="stable")]
            for group in np.split(by_page, np.flatnonzero(np.diff(page[by_page])) + 1):
                p = page[group[0]]
                away = np.sqrt(np.maximum(((asked[group] - self.routing[p]) ** 2).sum(1), 0))
                keep = away - self.radius[p] <= reach[group]
                group, away = group[keep], away[keep]
                if not len(group):
                    continue
                rows = slice(self.cuts[p], self.cuts[p + 1])
                near = np.abs(away[:, None] - self.to_routing[rows][None, :]) <= reach[group][:, None]
                used = np.flatnonzero(near.any(0))
                if not len(used):
                    continue
                work["pages"] += len(group)
                work["rows"] += len(group) * len(used)
                vectors, names = self.vectors[rows][used], self.ids[rows][used]
                if exact:
                    score = queries[group] @ vectors.T
                else:
                    score = np.array([[float(sum(int(a) * int(b) for a, b in zip(q, v, strict=True))) for v in vectors] for q in queries[group]])
                score[ids[group][:, None] == names[None, :]] = -np.inf
                better = (score >= best[group, -1][:, None]).any(1) & (score > -np.inf).any(1)
                group, score = group[better], score[better]
                if not len(group):
                    continue
                both = np.hstack([best[group], score])
                names = np.hstack([who[group], np.broadcast_to(names, score.shape)])
                top = np.lexsort((names, -both), axis=1)[:, :k]
                best[group], who[group] = np.take_along_axis(both, top, 1), np.take_along_axis(names, top, 1)
                reach[group] = self._reach(norms[group], bound, best[group])
        return best, who, work

    @staticmethod
    def _reach(norms: np.ndarray, bound: float, best: np.ndarray) -> np.ndarray:
        """The distance of each query's k-th best row, with slack; without bound while it has fewer."""
        far = norms + bound - 2 * best[:, -1]
        return np.where(np.isfinite(far), np.sqrt(np.maximum(far, 0)) * (1 + SLACK) + SLACK * np.sqrt(bound + 1), np.inf)


def top_k(table: DataFrame, k: int = 20, every: int = 20, scale: float = 64.0) -> DataFrame:
    """query_id, rank, vec_id, score: the k best rows for each row whose vec_id is divisible by `every`."""
    rows = scratch_table(quantised(table, scale))
    spark = table.sparkSession
    stats = rows.groupBy("dim").agg(F.count(F.lit(1)).alias("n")).orderBy("dim").collect()  # one row for each vector length
    parts = [_search(rows.where(F.col("dim") == r.dim), r.dim, r.n, k, every) for r in stats]
    if not parts:
        return spark.createDataFrame([], "query_id long, rank int, vec_id long, score long")
    found = parts[0]
    for p in parts[1:]:
        found = found.unionByName(p)
    return found


def _search(rows: DataFrame, dim: int, n: int, k: int, every: int) -> DataFrame:
    spark = rows.sparkSession
    # Routing objects: a sample bounded by REGIONS; it shapes the tree, every row is in it.
    sample = rows.orderBy(F.xxhash64("vec_id"), "packed").limit(min(REGIONS, max(1, n // (2 * CELL_ROWS)))).select("packed").collect()
    routing = unpacked([r.packed for r in sample], dim)

    def nearest(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            x = unpacked(list(batch["packed"]), dim)
            square = (x * x).sum(1)
            region = np.argmin((routing * routing).sum(1)[None, :] - 2 * x @ routing.T, axis=1) if len(x) else []
            yield batch.assign(region=region, square=square)[["vec_id", "packed", "region", "square"]]

    placed = scratch_table(rows.select("vec_id", "packed").mapInPandas(nearest, "vec_id long, packed binary, region int, square double"))
    sizes = placed.groupBy("region").agg(F.count(F.lit(1)).alias("n"), F.max("square").alias("square")).collect()
    bound = max(r.square for r in sizes)
    cells = {r.region: max(1, -(-r.n // (CELL_ROWS * 3 // 4))) for r in sizes}  # salted by a hash, so a quarter is left for unevenness
    starts, total = {}, 0
    for region in sorted(cells):
        starts[region], total = total, total + cells[region]
    pick = F.lit(0)
    for region, start in starts.items():
        pick = F.when(F.col("region") == region, start + F.pmod(F.xxhash64("vec_id", "packed"), F.lit(cells[region]))).otherwise(pick)
    asked = placed.where(F.pmod("vec_id", F.lit(every)) == 0)
    groups = max(1, -(-asked.count() // (GROUP_ROWS * 3 // 4)))  # dealt by a hash, too
    per = min(PART_CELLS, max(1, total * groups // MIN_UNITS))
    parts = -(-total // per)

    def pack(with_tree: bool):
        def run(part: pd.DataFrame) -> pd.DataFrame:
            part = part.drop_duplicates(["vec_id", "packed"]) if not with_tree else part
            ids, vectors = part["vec_id"].to_numpy(np.int64), unpacked(list(part["packed"]), dim)
            if with_tree:
                body = Cell(ids, vectors, bound)
                body.vectors = compact(body.vectors)
            else:
                body = (ids, compact(vectors))
            return pd.DataFrame({"at": [int(part["at"].iloc[0])], "body": [pickle.dumps(body)]})

        return run

    tree = placed.select("vec_id", "packed", pick.cast("long").alias("at")).groupBy("at").applyInPandas(pack(True), "at long, body binary")
    ask = asked.select("vec_id", "packed", F.pmod(F.xxhash64("vec_id"), F.lit(groups)).alias("at")).groupBy("at").applyInPandas(pack(False), "at long, body binary")
    tree, ask = scratch_table(tree), scratch_table(ask)
    # Every stated query meets every cell: each part and group is a key of its own, so they spread over all tasks.
    left = tree.select(F.floor(F.col("at") / per).alias("part"), F.col("body").alias("tree"), F.explode(F.sequence(F.lit(0).cast("long"), F.lit(groups - 1).cast("long"))).alias("group"))
    right = ask.select(F.col("at").alias("group"), F.col("body").alias("queries"), F.explode(F.sequence(F.lit(0).cast("long"), F.lit(parts - 1).cast("long"))).alias("part"))
    units = left.hint("merge").join(right, ["part", "group"]).select("part", "group", "tree", "queries")

    def search(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        at, ids, queries, best, who = None, None, None, None, None

        def found() -> Iterator[pd.DataFrame]:
            for s in range(0, len(ids) if at is not None else 0, QUERY_ROWS):
                row, column = np.nonzero(best[s : s + QUERY_ROWS] > -np.inf)
                yield pd.DataFrame({"query_id": ids[s + row], "vec_id": who[s + row, column], "score": best[s + row, column].astype(np.int64)})

        for batch in batches:
            for part, group, tree_bytes, query_bytes in zip(batch["part"], batch["group"], batch["tree"], batch["queries"], strict=True):
                if at != (part, group):  # units of one key follow each other
                    yield from found()
                    at, (ids, queries) = (part, group), pickle.loads(query_bytes)
                    best, who = none_found(len(ids), k)
                cell = pickle.loads(tree_bytes)
                cell.vectors = cell.vectors.astype(np.float64)
                for s in range(0, len(ids), QUERY_ROWS):
                    some = slice(s, s + QUERY_ROWS)
                    best[some], who[some], _ = cell.search(ids[some], queries[some].astype(np.float64), bound, k, (best[some], who[some]))
        yield from found()

    each = units.mapInPandas(search, "query_id long, vec_id long, score long")
    # Spark keeps the best k of each query before the shuffle, too.
    return each.selectExpr("query_id", "cast(row_number() over (partition by query_id order by score desc, vec_id) as int) as rank", "vec_id", "score").where(F.col("rank") <= k)


TOP_K_SQL = """
with v as (select distinct vec_id, list_transform(embedding, lambda x: floor(64 * x::double)::bigint) as q from embeddings
  where embedding is not null and len(list_filter(embedding, lambda x: x is null or not isfinite(x))) = 0 and len(embedding) > 0 and vec_id is not null),
pairs as (select a.vec_id as query_id, b.vec_id, list_sum(list_transform(list_zip(a.q, b.q), lambda z: z[1] * z[2]))::bigint as score
  from v a join v b on a.vec_id <> b.vec_id and len(a.q) = len(b.q) where a.vec_id % 20 = 0),
ranked as (select query_id, row_number() over (partition by query_id order by score desc, vec_id)::int as rank, vec_id, score from pairs)
select query_id, rank, vec_id, score from ranked where rank <= 20"""
