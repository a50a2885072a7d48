"""Near-duplicate documents by ProbMinHash signatures, banding and exact verification.

A document's five-word shingles weigh as often as they occur. Each shingle is a Poisson process of that rate, seeded
by its hash; each arrival goes to a random register, which keeps the earliest arrival's shingle. A shingle stops once
its next arrival is later than every register's. Two registers agree with the probability Jaccard similarity, which
doesn't change when a whole text is repeated, and equals the plain Jaccard similarity for texts without repeats.

Texts of equal words are one node. Nodes that agree on a band of registers are candidates. First the least node of
each bucket, its head, is compared with the others; this joins groups of near copies at the cost of the bucket's rows.
What is left are buckets whose nodes are of several classes. There whole signatures are compared, block by block of at
most BLOCK nodes; pairs whose agreement could mean the threshold (five standard deviations allowed) are verified on
the spot, the likeliest first, unless links found before already join them; a pair belongs to the first band in which
it agrees. Only links that join something leave a block, so their number is below the nodes', and no pair that could
join two classes is left out. A pair is a link if its exact probability Jaccard similarity reaches the threshold;
classes are the connected components of links.

Edge cases: a text of one to four words is one shingle of all its words; null and wordless texts are in a class of
their own; equal doc_ids with different texts are merged; rows are returned once for each input row.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import reduce

import numpy as np
import pandas as pd
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import release_memory, scratch_table, words_of

WORDS, SIMILARITY, BANDS, ROWS = 5, 0.8, 26, 5
_STEP = np.uint64(0x9E3779B97F4A7C15)
_BATCH_BYTES = 1_500_000
BLOCK = 1024


def mix(x: np.ndarray) -> np.ndarray:
    """The finaliser of splitmix64."""
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


class _WordHash(dict):
    def __missing__(self, word: bytes) -> int:
        if len(self) > 150_000:
            self.clear()
        value = self[word] = xxhash.xxh3_64_intdigest(word)
        return value


def shingles(documents: list[list[bytes]], hashes: dict, size: int = WORDS) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Document number, shingle hash and count, sorted by both, of all distinct shingles."""
    lengths = np.array([len(d) for d in documents], dtype=np.int64)
    if not lengths.sum():
        return np.zeros(0, np.int64), np.zeros(0, np.uint64), np.zeros(0)
    words = np.concatenate([np.fromiter(map(hashes.__getitem__, d), np.uint64, len(d)) for d in documents])
    ends = np.cumsum(lengths)
    owner = np.repeat(np.arange(len(documents)), lengths)
    left = ends[owner] - np.arange(len(words))  # words from here to the document's end
    factor = np.uint64(0x100000001B3)
    code = np.zeros(len(words), np.uint64)
    whole = lengths[owner] < size
    first = np.arange(len(words)) == (ends - lengths)[owner]
    padded = np.concatenate([words, np.zeros(size, np.uint64)])
    for k in range(size):
        code = np.where(left > k, code * factor + mix(padded[k : k + len(words)] + _STEP), code)
    take = (left >= size) | (whole & first)
    owner, code = owner[take], mix(code[take])
    order = np.lexsort((code, owner))
    owner, code = owner[order], code[order]
    new = np.ones(len(code), bool)
    new[1:] = (owner[1:] != owner[:-1]) | (code[1:] != code[:-1])
    at = np.flatnonzero(new)
    return owner[at], code[at], np.diff(np.append(at, len(code))).astype(np.float64)


def signatures(owner: np.ndarray, code: np.ndarray, weight: np.ndarray, n: int, registers: int) -> np.ndarray:
    """The shingle that arrived first in each register of each document; documents without shingles keep zeros."""
    first = np.full(n * registers, np.inf)
    who = np.zeros(n * registers, np.uint64)
    latest = np.full(n, np.inf)
    live, when, state = np.arange(len(code)), np.zeros(len(code)), mix(code + _STEP)
    while len(live):
        state = mix(state + _STEP)
        when = when - np.log(((state >> np.uint64(11)).astype(np.float64) + 1) * 2.0**-53) / weight[live]
        docs = owner[live]
        keep = when < latest[docs]
        live, when, state, docs = live[keep], when[keep], state[keep], docs[keep]
        place = docs * registers + (mix(state ^ np.uint64(0xA5A5A5A5A5A5A5A5)) % np.uint64(registers)).astype(np.int64)
        np.minimum.at(first, place, when)
        won = first[place] == when
        who[place[won]] = code[live[won]]
        open_docs = np.unique(docs)
        latest[open_docs] = first.reshape(n, registers)[open_docs].max(1)
        keep = when < latest[docs]
        live, when, state = live[keep], when[keep], state[keep]
    return who.reshape(n, registers)


def pack_shingles(code: np.ndarray, weight: np.ndarray) -> bytes:
    """32 bits of each shingle, and the counts where any is above one."""
    small = (code >> np.uint64(32)).astype("<u4")
    order = np.argsort(small, kind="stable")
    body = small[order].tobytes()
    return body if (weight == 1).all() else body + weight[order].astype("<u4").tobytes()


def unpack_shingles(body: bytes, n: int) -> tuple[np.ndarray, np.ndarray]:
    code = np.frombuffer(body, "<u4", n)
    return code, np.frombuffer(body, "<u4", n, 4 * n).astype(np.float64) if len(body) > 4 * n else np.ones(n)


def probability_jaccard(a: tuple[np.ndarray, np.ndarray], b: tuple[np.ndarray, np.ndarray]) -> float:
    """Sum over common elements i of 1 / sum_j max(a_j/a_i, b_j/b_i), by one sort of the weights' ratios."""
    (ca, wa), (cb, wb) = a, b
    if wa[0] == wb[0] == 1 and len(wa) == wa.sum() and len(wb) == wb.sum():  # plain sets
        both = np.concatenate([ca, cb])
        both.sort(kind="stable")
        shared = int((both[1:] == both[:-1]).sum())
        return shared / (len(ca) + len(cb) - shared)
    _, ia, ib = np.intersect1d(ca, cb, return_indices=True)
    if not len(ia):
        return 0.0
    x, y = wa[ia], wb[ib]
    order = np.argsort(x / y, kind="stable")
    x, y = x[order], y[order]
    # For element i, those of a higher ratio count by their weight in a, the others by theirs in b.
    above = np.concatenate([np.cumsum(x[::-1])[::-1], [0.0]])[:-1]
    below = np.concatenate([[0.0], np.cumsum(y)])[:-1]
    only_a, only_b = wa.sum() - x.sum(), wb.sum() - y.sum()
    return float((1.0 / ((above + only_a) / x + (below + only_b) / y)).sum())


def fingerprints(docs: DataFrame, size: int = WORDS, bands: int = BANDS, rows: int = ROWS) -> DataFrame:
    """doc_id, key (of the words), n (distinct shingles), bands, 16 bits of each register and packed shingles of every document with words."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hashes = _WordHash()
        for batch in batches:
            part, weight = [], 0
            for start in range(0, batch.num_rows, 64):  # texts become Python strings a few at a time
                rows = batch.slice(start, 64)
                for key, text in zip(rows.column(0).to_pylist(), rows.column(1).to_pylist(), strict=True):
                    if text and key is not None:
                        part.append((key, words_of(text)))
                        weight += len(text)
                    if weight > _BATCH_BYTES:
                        yield from rows_of(part, hashes)
                        part, weight = [], 0
            yield from rows_of(part, hashes)
        del hashes
        release_memory()

    def rows_of(part: list, hashes: dict) -> Iterator[pa.RecordBatch]:
        part = [(k, w) for k, w in part if w]
        if not part:
            return
        owner, code, weight = shingles([w for _, w in part], hashes, size)
        found = signatures(owner, code, weight, len(part), bands * rows).reshape(len(part), bands, rows)
        code_of_band = np.zeros((len(part), bands), np.uint64)
        for r in range(rows):
            code_of_band = mix(code_of_band + _STEP + found[:, :, r])
        cuts = np.searchsorted(owner, np.arange(len(part) + 1))
        columns = [
            pa.array([k for k, _ in part], pa.int64()),
            pa.array([xxhash.xxh3_128_digest(b" ".join(w)) for _, w in part], pa.binary()),
            pa.array(np.diff(cuts), pa.int32()),
            pa.ListArray.from_arrays(pa.array(np.arange(len(part) + 1) * bands, pa.int32()), pa.array(code_of_band.view(np.int64).ravel())),
            pa.array([x.tobytes() for x in (found.reshape(len(part), -1) >> np.uint64(48)).astype("<u2")], pa.binary()),
            pa.array([pack_shingles(code[a:b], weight[a:b]) for a, b in zip(cuts, cuts[1:], strict=False)], pa.binary()),
        ]
        yield pa.RecordBatch.from_arrays(columns, ["doc_id", "key", "n", "bands", "signature", "packed"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(run, "doc_id long, key binary, n int, bands array<long>, signature binary, packed binary")


def verified(pairs: DataFrame, nodes: DataFrame, similarity: float) -> DataFrame:
    """The pairs (a, b) of an exact similarity that reaches the threshold; nodes: id, n, packed."""
    body = nodes.select("id", "n", "packed")
    both = pairs.join(body.select(F.col("id").alias("b"), F.col("n").alias("nb"), F.col("packed").alias("pb")), "b").join(body.select(F.col("id").alias("a"), F.col("n").alias("na"), F.col("packed").alias("pa")), "a")

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            good = [probability_jaccard(unpack_shingles(r.pa, r.na), unpack_shingles(r.pb, r.nb)) >= similarity - 1e-9 for r in batch.itertuples(index=False)]
            yield batch.loc[good, ["a", "b"]]

    return both.mapInPandas(run, "a long, b long")


def components(links: DataFrame) -> DataFrame:
    """node and class (the least node) of every linked node, by alternating large and small stars.

    Each round joins a node's links with their minimum, never lists a node's links in one task, and is written down.
    """
    stars = scratch_table(links.where("a <> b").select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).distinct())
    while True:
        both = stars.select("u", "v").union(stars.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m"))
        large = both.where("v > u").join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v").distinct()
        least = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).union(least.select("u", F.col("m").alias("v"))).where("u <> v").distinct()
        following = scratch_table(small)
        # Done when every node has one link and no end of a link has a link itself.
        open_ends = following.join(following.select(F.col("u").alias("v")).distinct(), "v", "left_semi").limit(1).count()
        stars = following
        if not open_ends:
            return stars.select(F.col("u").alias("node"), F.col("v").alias("class"))


def joining_links(placed: DataFrame, nodes: DataFrame, similarity: float, bands: int, size: int) -> DataFrame:
    """Links (a, b) inside buckets that hold several classes, enough to join what belongs together."""
    registers = bands * size
    least = int(registers * similarity - 5 * (registers * similarity * (1 - similarity)) ** 0.5)
    open_buckets = placed.groupBy("band", "code").agg(F.min("class").alias("low"), F.max("class").alias("high"), F.ceil(F.count(F.lit(1)) / BLOCK).cast("int").alias("blocks")).where("low <> high").select("band", "code", "blocks")
    rows = placed.join(open_buckets, ["band", "code"]).join(nodes.select("id", "n", "signature", "packed"), "id")
    rows = rows.withColumn("block", F.pmod(F.xxhash64("id"), F.col("blocks")).cast("int"))
    # A unit is two blocks of a bucket, or one with itself, so a large bucket is spread over tasks.
    other = F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)).alias("other")
    units = rows.select("*", other).select("band", "code", F.least("block", "other").alias("i"), F.greatest("block", "other").alias("j"), "id", "class", "n", "signature", "packed", "block")

    def match(part: pd.DataFrame) -> pd.DataFrame:
        ids, classes = part["id"].to_numpy(), part["class"].to_numpy()
        marks = np.stack([np.frombuffer(x, "<u2") for x in part["signature"]])
        bodies, sizes = part["packed"].tolist(), part["n"].tolist()
        i, j, band = part["i"].iloc[0], part["j"].iloc[0], int(part["band"].iloc[0])
        left, right = np.flatnonzero(part["block"] == i), np.flatnonzero(part["block"] == j)
        root = {int(c): int(c) for c in classes}

        def find(c: int) -> int:
            while root[c] != c:
                root[c] = root[root[c]]
                c = root[c]
            return c

        out = []
        for start in range(0, len(left), 256):
            rows = left[start : start + 256]
            same = np.zeros((len(rows), len(right)), np.uint16)
            earlier = np.zeros((len(rows), len(right)), bool)
            for k in range(bands):
                agree = np.zeros((len(rows), len(right)), np.uint16)
                for r in range(k * size, (k + 1) * size):
                    agree += marks[rows, r][:, None] == marks[right, r][None, :]
                same += agree
                if k < band:
                    earlier |= agree == size
            a, b = np.nonzero((same >= least) & ~earlier & (classes[rows][:, None] != classes[right][None, :]))
            order = np.argsort(-same[a, b].astype(np.int32), kind="stable")
            for x, y in zip(rows[a[order]].tolist(), right[b[order]].tolist(), strict=True):
                if (i == j and x > y) or (p := find(int(classes[x]))) == (q := find(int(classes[y]))):
                    continue
                if probability_jaccard(unpack_shingles(bodies[x], sizes[x]), unpack_shingles(bodies[y], sizes[y])) >= similarity - 1e-9:
                    root[max(p, q)] = min(p, q)
                    out.append((ids[x], ids[y]))
        return pd.DataFrame(out, columns=["a", "b"]).astype("int64")

    return units.groupBy("band", "code", "i", "j").applyInPandas(match, "a long, b long")


def _with_class(rows: DataFrame, classes: DataFrame, node: str, name: str) -> DataFrame:
    return rows.join(classes.select(F.col("node").alias(node), F.col("class").alias(name)), node, "left").withColumn(name, F.coalesce(name, node))


def near_duplicates(docs: DataFrame, similarity: float = SIMILARITY, size: int = WORDS, bands: int = BANDS, rows: int = ROWS) -> DataFrame:
    """doc_id, class_id (the least doc_id of the class), text_id (the least doc_id of equal words) and class_size."""
    prints = scratch_table(fingerprints(docs, size, bands, rows))
    # One node for each text: the least doc_id of equal words. The minimum combines before the shuffle.
    texts = prints.groupBy("key").agg(F.min("doc_id").alias("id"))
    membership = scratch_table(prints.select("doc_id", "key").join(texts, "key").select("doc_id", F.col("id").alias("text_id")))
    nodes = prints.join(membership.select(F.col("doc_id").alias("_d"), F.col("text_id").alias("id")).where("_d = id").distinct(), F.col("doc_id") == F.col("_d"), "left_semi").withColumnRenamed("doc_id", "id")
    filed = nodes.select("id", F.posexplode("bands").alias("band", "code"))
    shared = filed.groupBy("band", "code").agg(F.count(F.lit(1)).alias("k")).where("k > 1").select("band", "code")
    buckets = scratch_table(filed.join(shared, ["band", "code"]))
    # doc_ids that repeat with different texts tie their texts together.
    links = [membership.groupBy("doc_id").agg(F.min("text_id").alias("a"), F.max("text_id").alias("b")).where("a <> b").select("a", "b")]
    heads = buckets.groupBy("band", "code").agg(F.min("id").alias("head"))
    first = buckets.join(heads, ["band", "code"]).where("id <> head").select(F.col("head").alias("a"), F.col("id").alias("b")).distinct()
    links.append(scratch_table(verified(first, nodes, similarity)))
    classes = components(reduce(DataFrame.union, links))
    found = scratch_table(joining_links(_with_class(buckets, classes, "id", "class"), nodes, similarity, bands, rows))
    if found.limit(1).count():
        links.append(found)
        classes = components(reduce(DataFrame.union, links))
    placed = _with_class(membership, classes, "text_id", "class_id").distinct()
    placed = placed.groupBy("doc_id").agg(F.min("class_id").alias("class_id"), F.min("text_id").alias("text_id"))
    sizes = placed.groupBy("class_id").agg(F.count(F.lit(1)).alias("class_size"))
    placed = placed.join(sizes, "class_id").select(F.col("doc_id").alias("_d"), "class_id", "text_id", "class_size")
    out = docs.select(F.col("doc_id")).join(placed, F.col("doc_id") == F.col("_d"), "left")
    return out.select("doc_id", F.coalesce("class_id", "doc_id").cast("long").alias("class_id"), F.coalesce("text_id", "doc_id").cast("long").alias("text_id"), F.coalesce("class_size", F.lit(1)).cast("long").alias("class_size"))


def keep_one(docs: DataFrame, similarity: float = SIMILARITY) -> DataFrame:
    """The documents whose doc_id is their class's least, so one of each class stays; others, nulls too, stay as they are."""
    copies = near_duplicates(docs.where("doc_id is not null"), similarity).where("doc_id <> class_id").select(F.col("doc_id").alias("__gone")).distinct()
    return docs.join(copies, F.col("doc_id") == F.col("__gone"), "left_anti")
