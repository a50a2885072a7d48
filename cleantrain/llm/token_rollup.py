"""Token counts as delta-maintained rollups.

A rollup is a folder. Each batch of changes writes signed document rows (a ledger: +1 for what is counted now, -1 for
what was counted before) and their signed sums by source, language and tokenizer version; a marker written last
commits it. Totals are the sums over committed batches, so they never need the documents again. A batch that was
committed is skipped when it comes again; one that broke off is written anew, since nothing reads it without a marker.

Edge cases: a null or empty text has no tokens; null sources and languages are groups of their own; rows that repeat a
doc_id in a batch are all counted, and all withdrawn when a later batch names the doc_id; a null doc_id is counted and
can't be revised; a delete or revision of an unknown doc_id withdraws nothing; groups without documents don't show.
"""

from __future__ import annotations

import base64
import hashlib
from collections.abc import Callable, Iterator
from pathlib import Path

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import words_of

TOKENIZER_FILE = "/opt/tokenizers/byte_bpe_50k.tiktoken"
#: Fixed value: the pattern that cuts texts before the byte-pair merges of this vocabulary.
PATTERN = r"'(?:[sdmt]|ll|ve|re)| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"
LEDGER = "doc_id long, source string, lang string, tokenizer string, sign int, n_tokens long, n_bytes long"
KEYS = ("source", "lang", "tokenizer")
SCHEMAS = {"ledger": f"{LEDGER}, bucket int, batch string", "totals": "source string, lang string, tokenizer string, n_docs long, n_tokens long, n_bytes long, batch string"}
BUCKETS = 16
_ENCODINGS: dict = {}


def _encoding(raw: bytes):
    import tiktoken

    name = hashlib.sha256(raw).hexdigest()
    if name not in _ENCODINGS:
        ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, raw.splitlines())}
        _ENCODINGS[name] = tiktoken.Encoding(name, pat_str=PATTERN, mergeable_ranks=ranks, special_tokens={})
    return _ENCODINGS[name]


def byte_pair_counter(raw: bytes) -> Callable[[str], int]:
    encode = _encoding(raw).encode_ordinary
    return lambda text: len(encode(text))


def count_tokens(docs: DataFrame, tokenizer_file: str = TOKENIZER_FILE) -> DataFrame:
    """A ledger row of sign +1 for each document row and tokenizer version: the byte-pair vocabulary, and plain words."""
    raw = docs.sparkSession.sparkContext.broadcast(Path(tokenizer_file).read_bytes())  # one vocabulary file, below 1 MB
    version = f"{Path(tokenizer_file).stem}@{hashlib.sha256(raw.value).hexdigest()[:8]}"

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        count = byte_pair_counter(raw.value)
        for batch in batches:
            texts = [t or "" for t in batch["text"]]
            shared = {"doc_id": batch["doc_id"], "source": batch["source"], "lang": batch["lang"], "sign": 1, "n_bytes": [len(t.encode("utf-8", "surrogatepass")) for t in texts]}
            for name, counts in ((version, [count(t) for t in texts]), ("words@1", [len(words_of(t)) for t in texts])):
                yield pd.DataFrame(shared | {"tokenizer": name, "n_tokens": counts}, columns=[x.split()[0] for x in LEDGER.split(", ")])

    # Ids go through pandas as strings: beside nulls it would read them as floats.
    rows = docs.select(F.col("doc_id").cast("long").cast("string").alias("doc_id"), "source", "lang", "text").mapInPandas(run, LEDGER.replace("doc_id long", "doc_id string"))
    return rows.withColumn("doc_id", F.col("doc_id").cast("long"))


class TokenRollup:
    """A rollup under `path`, a folder that driver and executors share."""

    def __init__(self, spark: SparkSession, path: str, tokenizer_file: str = TOKENIZER_FILE):
        self.spark, self.path, self.tokenizer_file = spark, path, tokenizer_file

    def _exists(self, path: str) -> bool:
        place = self.spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
        return place.getFileSystem(self.spark.sparkContext._jsc.hadoopConfiguration()).exists(place)

    def committed(self, batch: str) -> bool:
        return self._exists(f"{self.path}/commits/batch={batch}/_SUCCESS")

    def _read(self, kind: str) -> DataFrame | None:
        """Rows of committed batches only."""
        if not self._exists(f"{self.path}/commits") or not self._exists(f"{self.path}/{kind}"):
            return None
        # With the schemas given, batch names stay strings and a folder without rows can be read.
        rows = self.spark.read.schema(SCHEMAS[kind]).option("basePath", f"{self.path}/{kind}").parquet(f"{self.path}/{kind}")
        marks = self.spark.read.schema("id long, batch string").parquet(f"{self.path}/commits").select("batch")
        return rows.join(marks, "batch", "left_semi")

    def commit(self, batch: str, upserts: DataFrame | None = None, deletes: DataFrame | None = None) -> bool:
        """Inserts or revises the documents of `upserts` and withdraws the doc_ids of `deletes`; False if done before."""
        if self.committed(batch):
            return False
        parts, ledger = [], self._read("ledger")
        if upserts is not None:
            parts.append(count_tokens(upserts, self.tokenizer_file))
        if ledger is not None:
            ids = [d.select(F.col("doc_id").cast("long").alias("doc_id")) for d in (upserts, deletes) if d is not None]
            named = (ids[0] if len(ids) == 1 else ids[0].union(ids[1])).where("doc_id is not null").distinct().withColumn("bucket", self._bucket())
            counted = ledger.join(named, ["bucket", "doc_id"], "left_semi").groupBy("doc_id", *KEYS, "n_tokens", "n_bytes").agg(F.sum("sign").alias("live")).where("live > 0")
            parts.append(counted.select("doc_id", *KEYS, F.explode(F.array_repeat(F.lit(-1), F.col("live").cast("int"))).alias("sign"), "n_tokens", "n_bytes"))
        if parts:
            signed = parts[0] if len(parts) == 1 else parts[0].unionByName(parts[1])
            # Buckets by doc_id let a later small batch read only the parts that can hold its documents.
            signed.withColumn("bucket", self._bucket()).repartition(F.col("bucket"), F.pmod(F.xxhash64("doc_id", F.lit(1)), F.lit(8))).write.mode("overwrite").partitionBy("bucket").parquet(f"{self.path}/ledger/batch={batch}")
            written = self.spark.read.schema(f"{LEDGER}, bucket int").parquet(f"{self.path}/ledger/batch={batch}")
            written.groupBy(*KEYS).agg(F.sum("sign").alias("n_docs"), F.sum(F.col("sign") * F.col("n_tokens")).alias("n_tokens"), F.sum(F.col("sign") * F.col("n_bytes")).alias("n_bytes")).coalesce(1).write.mode("overwrite").parquet(f"{self.path}/totals/batch={batch}")
        self.spark.range(1, numPartitions=1).write.mode("overwrite").parquet(f"{self.path}/commits/batch={batch}")
        return True

    @staticmethod
    def _bucket():
        return F.coalesce(F.pmod(F.xxhash64("doc_id"), F.lit(BUCKETS)), F.lit(0)).cast("int")

    def totals(self) -> DataFrame:
        """source, lang, tokenizer, n_docs, n_tokens, n_bytes over all committed batches."""
        rows = self._read("totals")
        if rows is None:
            return self.spark.createDataFrame([], "source string, lang string, tokenizer string, n_docs long, n_tokens long, n_bytes long")
        return rows.groupBy(*KEYS).agg(*[F.sum(c).alias(c) for c in ("n_docs", "n_tokens", "n_bytes")]).where("n_docs > 0")
