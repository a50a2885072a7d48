"""Language identification by fusing evidence in Bayes' rule.

The text's likelihood comes from letter trigrams, trained on a bounded sample of labelled rows. It is fused with what
the row declares (a markup or metadata language), with the address suffix, and with its host:

    P(l | all)  ~  P(text | l) * P(l) * P(l | declared)/P(l) * P(l | suffix)/P(l) * P(l | host)/P(l)

The last four are estimated from the whole table by grouped sums of text-only posteriors, each row's own share taken
out, and smoothed hierarchically: host towards its parent (registered domain), parent towards the whole table. Long
texts don't count without bound: n trigrams weigh n / (1 + n / EVIDENCE), since neighbouring trigrams depend on each
other. The class "und" is a text of evenly spread trigrams; it catches what is no language that was trained.

Edge cases: a text without letters, null or empty, is "und" and rejected; missing declared languages, suffixes or hosts
are no evidence; a table without any labelled row is all "und". Rows come back once for each input row.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import release_memory, scratch_table

LANGUAGES = ("de", "en", "es", "fr")
#: Labelled rows a language for training, in expectation; the rows with the smallest hashes are taken.
TRAINING_ROWS = 1000
SLOTS = 1 << 16
EVIDENCE = 40.0
SMOOTHING = 20.0
UNKNOWN_PRIOR = 0.01
#: Log-likelihood a trigram of "und": somewhat above even spread over all slots.
UNKNOWN_LOG = float(np.log(1.0 / SLOTS)) * 0.95
_CHUNK = 2_000_000


def trigram_slots(texts: list[str | None]) -> tuple[np.ndarray, np.ndarray]:
    """Slots of the letter trigrams of all texts on end, and how many each text has. Words are padded by one space."""
    parts, sizes = [], []
    for text in texts:
        codes = np.frombuffer((text or "").lower().encode("utf-32-le", "surrogatepass"), "<u4")
        letter = ((codes >= 97) & (codes <= 122)) | (codes >= 0xC0)
        before = np.zeros(len(codes), bool)
        before[1:] = letter[:-1]
        kept = np.where(letter, codes, np.uint32(32))[letter | before]  # one space for each run of others
        if not letter.any():
            sizes.append(0)
            continue
        kept = np.concatenate([np.array([32], np.uint32), kept, np.array([32], np.uint32)])
        h = (kept[:-2] * np.uint32(0x9E3779B1)) ^ (kept[1:-1] * np.uint32(0x85EBCA6B)) ^ (kept[2:] * np.uint32(0xC2B2AE35))
        h ^= h >> np.uint32(15)
        h *= np.uint32(0x2C1B3C6D)
        parts.append((h >> np.uint32(16)).astype(np.int64))
        sizes.append(len(parts[-1]))
    return np.concatenate(parts) if parts else np.zeros(0, np.int64), np.array(sizes, np.int64)


def train(labelled: DataFrame, languages: tuple[str, ...] = LANGUAGES, rows: int = TRAINING_ROWS) -> np.ndarray | None:
    """Log-probabilities, a row for each language, of the trigram slots; None without any labelled row.

    labelled: text, lang. The counting is distributed, and what reaches the driver is bounded by the model's size.
    """
    labelled = labelled.where(F.col("lang").isin(*languages))
    counts = {r.lang: r.n for r in labelled.groupBy("lang").agg(F.count(F.lit(1)).alias("n")).collect()}
    if not counts:
        return None
    share = F.lit(0.0)
    for lang, n in counts.items():
        share = F.when(F.col("lang") == lang, min(1.0, rows / n)).otherwise(share)
    sample = labelled.where((F.pmod(F.xxhash64("text", F.lit(7)), F.lit(1 << 30)) / (1 << 30)) < share)

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        table = np.zeros((len(languages), SLOTS), np.int64)
        for batch in batches:
            for k, lang in enumerate(languages):
                for text in batch["text"][batch["lang"] == lang]:
                    table[k] += np.bincount(trigram_slots([text])[0], minlength=SLOTS)
        k, slot = np.nonzero(table)
        yield pd.DataFrame({"k": k, "slot": slot, "n": table[k, slot]})

    model = np.full((len(languages), SLOTS), 0.1)
    for r in sample.select("text", "lang").mapInPandas(run, "k int, slot int, n long").groupBy("k", "slot").agg(F.sum("n").alias("n")).toPandas().itertuples():
        model[r.k, r.slot] += r.n
    return np.log(model / model.sum(1, keepdims=True)).astype(np.float32)


def text_scores(rows: DataFrame, model: np.ndarray | None, languages: tuple[str, ...] = LANGUAGES) -> DataFrame:
    """The rows with n_letters (trigrams), logs (weighed log-likelihoods, "und" last) and soft (text-only posterior) for text."""
    shared = rows.sparkSession.sparkContext.broadcast(model)  # languages x SLOTS floats: 1 MB
    others = [c for c in rows.columns if c != "text"]
    kind = ", ".join([*(f"{c} {rows.schema[c].dataType.simpleString()}" for c in others), "n_letters long, logs array<double>, soft array<double>"])

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            sizes = batch["text"].str.len().fillna(0).to_numpy()
            for _, part in batch.groupby((np.cumsum(sizes) // _CHUNK).astype(int), sort=False):
                slots, n = trigram_slots(list(part["text"]))
                at = np.concatenate([[0], np.cumsum(n)])[:-1]
                logs = np.zeros((len(part), len(languages) + 1))
                some = n > 0
                if shared.value is not None and some.any():
                    for k in range(len(languages)):
                        logs[some, k] = np.add.reduceat(shared.value[k][slots].astype(np.float64), at[some]) / n[some]
                else:
                    logs[:, :-1] = UNKNOWN_LOG - 1
                logs[:, -1] = UNKNOWN_LOG
                logs *= (n / (1 + n / EVIDENCE))[:, None]
                soft = logs + np.log(_priors(len(languages)))[None, :]
                soft = np.exp(soft - soft.max(1, keepdims=True))
                soft /= soft.sum(1, keepdims=True)
                yield part[others].assign(n_letters=n, logs=list(logs), soft=list(np.where(some[:, None], soft, 0.0)))
        release_memory()

    return rows.select(*others, "text").mapInPandas(run, kind)


def _priors(n: int) -> np.ndarray:
    return np.array([(1 - UNKNOWN_PRIOR) / n] * n + [UNKNOWN_PRIOR])


def _sums(n: int, name: str) -> Column:
    return F.array(*[F.sum(F.get("soft", F.lit(k))) for k in range(n)]).alias(name)


def _smoothed(sums: Column, own: Column, base: Column) -> Column:
    """(sums - own + s * base) / (their total + s): the row's own share is not its own evidence."""
    rest = F.zip_with(sums, own, lambda a, b: F.greatest(a - b, F.lit(0.0)))
    total = F.aggregate(rest, F.lit(0.0), lambda a, x: a + x)
    return F.zip_with(rest, base, lambda a, b: (a + SMOOTHING * b) / (total + SMOOTHING))


def identify(rows: DataFrame, model: np.ndarray | None, languages: tuple[str, ...] = LANGUAGES) -> DataFrame:
    """rows: any key columns with text, declared, suffix, host, parent. Adds language, probability, n_letters and rejected.

    Rejected is a row whose most probable class is "und".
    """
    keys = [c for c in rows.columns if c not in ("text", "declared", "suffix", "host", "parent")]
    scored = scratch_table(text_scores(rows, model, languages))
    n = len(languages) + 1
    whole = scored.agg(_sums(n, "s")).first()["s"]
    whole = np.array([x or 0.0 for x in whole])
    prior = (whole + SMOOTHING * _priors(n - 1)) / (whole.sum() + SMOOTHING)
    base = F.array(*[F.lit(float(p)) for p in prior])
    out = scored
    # One row a key on the small side; the sums combine before the shuffle, so a hot host costs a row for each task.
    by_host = scored.where("host is not null").groupBy("parent", "host").agg(_sums(n, "host_sums"))
    by_parent = by_host.where("parent is not null").groupBy("parent").agg(F.array(*[F.sum(F.get("host_sums", F.lit(k))) for k in range(n)]).alias("parent_sums"))
    grouped = {"host_sums": (by_host.groupBy("host").agg(F.array(*[F.sum(F.get("host_sums", F.lit(k))) for k in range(n)]).alias("host_sums")), "host"), "parent_sums": (by_parent, "parent")}
    for name in ("declared", "suffix"):
        grouped[f"{name}_sums"] = (scored.where(F.col(name).isNotNull()).groupBy(name).agg(_sums(n, f"{name}_sums")), name)
    for table, key in grouped.values():
        out = out.join(table, key, "left")
    zero = F.array(*[F.lit(0.0)] * n)
    smooth = lambda name, towards: _smoothed(F.coalesce(name, zero), F.when(F.col(name).isNotNull(), F.col("soft")).otherwise(zero), towards)
    out = out.withColumn("_parent", smooth("parent_sums", base))
    out = out.withColumn("_host", smooth("host_sums", F.col("_parent"))).withColumn("_declared", smooth("declared_sums", base)).withColumn("_suffix", smooth("suffix_sums", base))
    # P(l) enters once, in each of three ratios it is taken out again: host * declared * suffix / P(l)^2.
    logs = F.array(*[F.get("logs", F.lit(k)) + F.log(F.get("_host", F.lit(k))) + F.log(F.get("_declared", F.lit(k))) + F.log(F.get("_suffix", F.lit(k))) - 2 * F.log(F.get(base, F.lit(k))) for k in range(n)])
    out = out.withColumn("_logs", logs)
    top = F.array_max("_logs")
    total = F.aggregate("_logs", F.lit(0.0), lambda a, x: a + F.exp(x - top))
    name = F.element_at(F.array(*[F.lit(x) for x in (*languages, "und")]), F.array_position("_logs", top).cast("int"))
    name = F.when(F.col("n_letters") > 0, name).otherwise("und")
    return out.select(*keys, name.alias("language"), F.when(F.col("n_letters") > 0, 1 / total).otherwise(1.0).alias("probability"), "n_letters", (name == "und").alias("rejected"))


def document_evidence(docs: DataFrame, *keys: Column) -> DataFrame:
    """Documents declare `lang`; their host is the source, and they have no address. The doc_id is a string here: pandas reads numbers beside nulls as floats."""
    none = F.lit(None).cast("string")
    return docs.select(F.col("doc_id").cast("long").cast("string").alias("doc_id"), "text", F.lower("lang").alias("declared"), none.alias("suffix"), F.col("source").alias("host"), none.alias("parent"), *keys)


def page_evidence(pages: DataFrame) -> DataFrame:
    """Pages declare the lang of their html element; host, registered domain and suffix come from the url.

    The text is the page without markup, scripts and styles; whole, the boilerplate too.
    """
    host = F.nullif(F.lower(F.regexp_extract("url", r"(?s)^.*?://([^/?#:]*)", 1)), F.lit(""))
    page = F.col("html")
    for pattern, by in ((r"(?is)<(script|style)\b.*?</\1\s*>", " "), (r"(?s)<!--.*?-->", " "), (r"(?s)<[^>]*>", " "), (r"&[#A-Za-z0-9]+;", " ")):
        page = F.regexp_replace(page, pattern, by)
    declared = F.nullif(F.lower(F.regexp_extract("html", r"(?is)<html\b[^>]*?\blang\s*=\s*[\"']?([A-Za-z]{2,3})", 1)), F.lit(""))
    suffix = F.nullif(F.regexp_extract(host, r"\.([^.]+)$", 1), F.lit(""))
    return pages.select(F.col("page_id").cast("string").alias("page_id"), page.alias("text"), declared.alias("declared"), suffix.alias("suffix"), host.alias("host"), F.nullif(F.regexp_extract(host, r"([^.]+\.[^.]+)$", 1), F.lit("")).alias("parent"))


def identify_documents(docs: DataFrame, languages: tuple[str, ...] = LANGUAGES) -> DataFrame:
    """doc_id, language, probability, n_letters, rejected for every row; the model is trained on the table's own labels."""
    out = identify(document_evidence(docs), train(docs.select("text", "lang"), languages), languages)
    return out.withColumn("doc_id", F.col("doc_id").cast("long"))


def keep_identified(docs: DataFrame, languages: tuple[str, ...] = LANGUAGES) -> DataFrame:
    """Documents that are not rejected, row by row where rows share a doc_id; rows without a doc_id are not judged and stay."""
    own, judged = F.xxhash64("text", "lang", "source"), docs.where("doc_id is not null")
    rows = document_evidence(judged, own.alias("own"))
    found = identify(rows, train(judged.select("text", "lang"), languages), languages)
    gone = scratch_table(found.where("rejected").select(F.col("doc_id").cast("long").alias("__gone"), F.col("own").alias("__own")).distinct())
    return docs.join(gone, (F.col("doc_id") == F.col("__gone")) & (own == F.col("__own")), "left_anti")
