"""Line dedup by overlapping three-line windows, all in DataFrame functions.

Each three consecutive lines make a window, known by two 64-bit hashes of its trimmed lines. A window's first
occurrence, by (doc_id, line), stays; every later one covers its three lines, and covered lines go. A removed
line always has an equal line in an earlier occurrence, so no wording is lost from the corpus.

Edge cases: documents of fewer than three lines have no window and stay; windows of three blank lines don't count;
a null text stays null; a null doc_id takes no part. A document is a doc_id with its text: rows that repeat both count
as one, so their equal windows are one occurrence; rows that share a doc_id with other texts are documents of their
own, in the order of a hash of their texts. Extra columns are carried along.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

SIZE = 3


def _lines(text: Column) -> Column:
    return F.split(text, "\n", -1)


def line_windows(docs: DataFrame, size: int = SIZE) -> DataFrame:
    """doc_id, own (a hash of the text), start, h1, h2: the windows of every document."""
    lines = docs.where("doc_id is not null and text is not null").select("doc_id", F.xxhash64("text").alias("own"), F.transform(_lines(F.col("text")), lambda x: F.btrim(x, F.lit(" \t\r"))).alias("l"))
    # One hash a line, then one a window: each line's text is read once, not once a window.
    hashes = lines.select("doc_id", "own", F.transform("l", lambda x: F.struct(F.xxhash64(x).alias("a"), F.xxhash64(x, F.lit(size)).alias("b"), (x == "").alias("blank"))).alias("h"))
    each = hashes.where(F.size("h") >= size).select("doc_id", "own", "h", F.explode(F.sequence(F.lit(0), F.size("h") - size)).alias("start"))
    part = lambda k, field: F.col("h")[F.col("start") + k][field]
    some = ~F.lit(True)
    for k in range(size):
        some = some | ~part(k, "blank")
    return each.where(some).select("doc_id", "own", "start", F.xxhash64(*[part(k, "a") for k in range(size)]).alias("h1"), F.xxhash64(*[part(k, "b") for k in range(size)]).alias("h2"))


def covered_lines(docs: DataFrame, size: int = SIZE) -> DataFrame:
    """doc_id, own and the start lines of its later occurrences."""
    windows = line_windows(docs, size)
    # The minimum combines before the shuffle, so a window that a third of all documents hold costs a row for each task.
    first = windows.groupBy("h1", "h2").agg(F.min(F.struct("doc_id", "own", "start")).alias("first"), F.count(F.lit(1)).alias("n")).where("n > 1").select("h1", "h2", "first")
    later = windows.join(first, ["h1", "h2"]).where(F.struct("doc_id", "own", "start") > F.col("first"))
    return later.groupBy("doc_id", "own").agg(F.collect_set("start").alias("starts"))


def _marked(docs: DataFrame, size: int) -> DataFrame:
    covered = covered_lines(docs, size).withColumnsRenamed({"doc_id": "__doc", "own": "__own", "starts": "__starts"}).hint("shuffle_hash")
    out = docs.join(covered, (F.col("doc_id") == F.col("__doc")) & (F.xxhash64("text") == F.col("__own")), "left")
    lines = _lines(F.col("text"))
    # array_except hashes: merging covered positions stays linear in the lines of a document.
    gone = F.flatten(F.transform("__starts", lambda s: F.sequence(s, s + (size - 1))))
    kept = F.array_except(F.sequence(F.lit(0), F.size(lines) - 1), gone)
    return out.withColumn("__kept", F.when(F.col("__starts").isNotNull() & F.col("text").isNotNull(), kept)).withColumn("__lines", F.when(F.col("__kept").isNotNull(), lines))


def _joined() -> Column:
    return F.when(F.col("__kept").isNull(), F.col("text")).otherwise(F.array_join(F.transform("__kept", lambda i: F.get("__lines", i)), "\n"))


def dedup_report(docs: DataFrame, size: int = SIZE) -> DataFrame:
    """doc_id, n_lines, n_removed and the text that stays, for every row."""
    total = F.coalesce(F.size(_lines(F.col("text"))), F.lit(0))
    total = F.when(F.col("text").isNull(), 0).otherwise(total)
    removed = F.when(F.col("__kept").isNull(), 0).otherwise(F.size("__lines") - F.size("__kept"))
    return _marked(docs.select("doc_id", "text"), size).select("doc_id", total.cast("long").alias("n_lines"), removed.cast("long").alias("n_removed"), _joined().alias("text"))


def dedup_lines(docs: DataFrame, size: int = SIZE) -> DataFrame:
    """The documents with covered lines taken out; a document of which no line stays is dropped. n_chars follows."""
    out = _marked(docs, size).where("__kept is null or size(__kept) > 0").withColumn("text", _joined())
    if "n_chars" in docs.columns:
        out = out.withColumn("n_chars", F.when(F.col("__kept").isNull(), F.col("n_chars")).otherwise(F.length("text")).cast(docs.schema["n_chars"].dataType))
    return out.select(*docs.columns)


DEDUP_SQL = """
with line as (select doc_id, text, string_split(text, chr(10)) as l from documents),
trimmed as (select doc_id, list_transform(l, lambda x: trim(x, ' ' || chr(9) || chr(13))) as t from line where doc_id is not null and text is not null),
start as (select doc_id, t, unnest(range(0, len(t) - 2)) as s from trimmed where len(t) >= 3),
windows as (select distinct doc_id, s, t[s + 1] || chr(10) || t[s + 2] || chr(10) || t[s + 3] as w from start where t[s + 1] <> '' or t[s + 2] <> '' or t[s + 3] <> ''),
ranked as (select *, row_number() over (partition by w order by doc_id, s) as k from windows),
covered as (select distinct doc_id, unnest(range(s, s + 3)) as p from ranked where k > 1),
gone as (select doc_id, list(p) as g from covered group by doc_id)
select line.doc_id, coalesce(len(l), 0)::bigint as n_lines, coalesce(len(g), 0)::bigint as n_removed,
  case when g is null then text else array_to_string(list_transform(list_filter(range(0, len(l)), lambda i: not list_contains(g, i)), lambda i: l[i + 1]), chr(10)) end as text
from line left join gone on line.doc_id = gone.doc_id"""
