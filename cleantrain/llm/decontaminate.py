"""Benchmark decontamination with a generalised suffix automaton of the test items.

The automaton holds every word substring of every item. Training words are streamed through it, keeping the
longest suffix of what was read that is also a substring of an item. A window is `window` consecutive item
words, or the whole item where it is shorter; every word of an occurring window is hit. Maximal hit runs are
the contaminated spans. Documents are never shuffled: one pass, one row out for each row in.

Edge cases: a null or wordless document has no words and no hits; a null or wordless item has no window; items
with equal text are all reported; a null item_id takes no part; repeated document rows each get their own row.
"""

from __future__ import annotations

import hashlib
import math
import re
from array import array
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import release_memory, scratch_table, words_of

#: Item words in one automaton (measured: about 150 bytes a word in the driver while it is built and in each Python
#: worker, so 0.3 GB at most); more items go to further automata in turn.
AUTOMATON_WORDS = 2_000_000
SPAN_SCHEMA = "doc_id long, n_words long, starts array<long>, ends array<long>, items array<string>"
_RUN = re.compile(rb"[0-9A-Za-z\x80-\xff]+")


class SuffixAutomaton:
    """Online construction over word ids; several items share it by restarting at the root.

    Most states have one way out and at most one window, so both lie in flat arrays of 32-bit numbers; only states
    with several ways out, or several windows, have a dictionary entry. Pickled and copied as it is.
    """

    def __init__(self, items: list[tuple[str, list[bytes]]], window: int):
        self.window, self.vocabulary = window, {}
        self.via, self.to, self.branch = array("i", [-1]), array("i", [0]), {}  # the only word out of a state and where it leads; or a dictionary
        self.link, self.length = array("i", [-1]), array("i", [0])
        self.names, last_states, sizes, numbers = [name for name, _ in items], array("i"), array("i"), array("i")
        for number, (_, item) in enumerate(items):
            state = 0
            for k, word in enumerate(item, 1):
                state = self._extend(state, self.vocabulary.setdefault(word, len(self.vocabulary)))
                if k >= window or k == len(item):
                    last_states.append(state)
                    sizes.append(min(window, k))
                    numbers.append(number)
        self.shortest = min(sizes, default=0)
        # Each window lives in the state whose length range holds the window's length.
        self.size, self.item, self.more = array("i", bytes(4 * len(self.link))), array("i", bytes(4 * len(self.link))), {}
        for state, size, number in zip(last_states, sizes, numbers, strict=True):
            while self.length[self.link[state]] >= size:
                state = self.link[state]
            if not self.size[state]:
                self.size[state], self.item[state] = size, number
            elif (self.size[state], self.item[state]) != (size, number):
                self.more.setdefault(state, {}).setdefault(size, set()).add(number)
        # The nearest shorter state with a window, found from short to long.
        self.up = array("i", bytes(4 * len(self.link)))
        for state in np.argsort(np.frombuffer(self.length, np.int32), kind="stable")[1:].tolist():
            above = self.link[state]
            self.up[state] = above if self.size[above] else self.up[above]

    def _get(self, state: int, word: int) -> int | None:
        if (moves := self.branch.get(state)) is not None:
            return moves.get(word)
        return self.to[state] if self.via[state] == word else None

    def _put(self, state: int, word: int, target: int) -> None:
        if (moves := self.branch.get(state)) is not None:
            moves[word] = target
        elif self.via[state] in (-1, word):
            self.via[state], self.to[state] = word, target
        else:
            self.branch[state] = {self.via[state]: self.to[state], word: target}

    def _add(self, length: int, link: int) -> int:
        for column, value in ((self.via, -1), (self.to, 0), (self.link, link), (self.length, length)):
            column.append(value)
        return len(self.length) - 1

    def _split(self, parent: int, word: int, target: int) -> int:
        """A copy of target for the strings that end after parent; shorter contexts now lead to it."""
        clone = self._add(self.length[parent] + 1, self.link[target])
        self.via[clone], self.to[clone] = self.via[target], self.to[target]
        if target in self.branch:
            self.branch[clone] = dict(self.branch[target])
        self.link[target] = clone
        while parent >= 0 and self._get(parent, word) == target:
            self._put(parent, word, clone)
            parent = self.link[parent]
        return clone

    def _extend(self, last: int, word: int) -> int:
        target = self._get(last, word)
        if target is not None:
            return target if self.length[target] == self.length[last] + 1 else self._split(last, word, target)
        fresh, state = self._add(self.length[last] + 1, 0), last
        while state >= 0 and (target := self._get(state, word)) is None:
            self._put(state, word, fresh)
            state = self.link[state]
        if state >= 0:
            self.link[fresh] = target if self.length[target] == self.length[state] + 1 else self._split(state, word, target)
        return fresh

    def _ending(self, state: int, size: int, items: set[int]) -> int:
        """Adds the items of the windows of at most `size` words that end here; the longest such window's size, or 0."""
        longest = 0
        at = state if self.size[state] else self.up[state]
        while at:
            if (need := self.size[at]) <= size:
                items.add(self.item[at])
                longest = max(longest, need)
            for need, numbers in self.more.get(at, {}).items():
                if need <= size:
                    items |= numbers
                    longest = max(longest, need)
            at = self.up[at]
        return longest

    def scan(self, words: list[bytes]) -> tuple[list[int], list[int], set[int]]:
        """Merged hit spans [start, end) and the numbers of the items whose windows occur."""
        branch, via, to, link, length, shortest = self.branch, self.via, self.to, self.link, self.length, self.shortest
        starts, ends, items = [], [], set()
        state = size = 0
        if not shortest:
            return starts, ends, items
        for at, word in enumerate(map(self.vocabulary.get, words)):
            if word is None:
                state = size = 0
                continue
            while True:
                moves = branch.get(state)
                target = moves.get(word) if moves is not None else to[state] if via[state] == word else None
                if target is not None or not state:
                    break
                state = link[state]
                size = length[state]
            if target is None:
                continue
            state, size = target, size + 1
            if size >= shortest:
                longest = self._ending(state, size, items)
                if longest:
                    start = at + 1 - longest
                    while starts and start <= ends[-1]:
                        start = min(start, starts.pop())
                        ends.pop()
                    starts.append(start)
                    ends.append(at + 1)
        return starts, ends, items


def _blocks(benchmark: DataFrame, window: int) -> Iterator[SuffixAutomaton]:
    """Automata over parts of the items, each within AUTOMATON_WORDS; nearly always one."""
    items = benchmark.select(F.col("item_id").cast("string").alias("item_id"), "text").where("item_id is not null and text is not null").distinct()
    # A word takes two bytes with its separator, so half the bytes bound the words.
    total = items.agg(F.sum(F.octet_length("text") / 2 + 1)).first()[0] or 0
    parts = max(1, math.ceil(total / AUTOMATON_WORDS))
    for part in range(parts):
        rows = items.where(F.pmod(F.xxhash64("item_id", "text"), F.lit(parts)) == part).collect()
        yield SuffixAutomaton([(r.item_id, words_of(r.text)) for r in sorted(rows)], window)


def _merge(starts: list[int], ends: list[int]) -> tuple[list[int], list[int]]:
    out: list[list[int]] = []
    for start, end in sorted(zip(starts, ends, strict=True)):
        if out and start <= out[-1][1]:
            out[-1][1] = max(out[-1][1], end)
        else:
            out.append([start, end])
    return [x[0] for x in out], [x[1] for x in out]


def _apply(docs: DataFrame, benchmark: DataFrame, window: int, finish, schema: str) -> DataFrame:
    """Streams (doc_id, text) through each automaton; finish(doc_id, text, words, starts, ends, names) makes the row."""
    sc = docs.sparkSession.sparkContext
    automata = [sc.broadcast(a) for a in _blocks(benchmark, window)]
    # Ids go through pandas as strings: beside nulls it would read them as floats.
    docs, schema = docs.withColumn("doc_id", F.col("doc_id").cast("long").cast("string")), schema.replace("doc_id long", "doc_id string")
    fields = f"doc_id string, text string, {SPAN_SCHEMA.split(', ', 2)[2]}"

    def scanner(shared, last: bool, first: bool):
        def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            automaton = shared.value
            for batch in batches:
                rows = []
                for row in batch.itertuples(index=False):
                    words = words_of(row.text)
                    starts, ends, found = automaton.scan(words)
                    names = {automaton.names[i] for i in found}
                    if not first:
                        starts, ends = _merge([*starts, *row.starts], [*ends, *row.ends])
                        names |= set(row.items)
                    rows.append(finish(row.doc_id, row.text, words, starts, ends, names) if last else (row.doc_id, row.text, starts, ends, sorted(names)))
                yield pd.DataFrame(rows, columns=[x.split()[0] for x in (schema if last else fields).split(", ")])

        return run

    frame = docs
    for k, shared in enumerate(automata):
        last = k == len(automata) - 1
        frame = frame.mapInPandas(scanner(shared, last, k == 0), schema if last else fields)
        if not last:
            frame = scratch_table(frame)  # one automaton at a time in an executor's memory
    return frame.withColumn("doc_id", F.col("doc_id").cast("long"))


def scan_documents(docs: DataFrame, benchmark: DataFrame, window: int = 10) -> DataFrame:
    """One row per document: its words, merged hit spans as word positions [start, end), and the items found."""
    return _apply(docs.select("doc_id", "text"), benchmark, window, lambda key, text, words, starts, ends, names: (key, len(words), starts, ends, sorted(names)), SPAN_SCHEMA)


def contamination_report(docs: DataFrame, benchmark: DataFrame, window: int = 10) -> DataFrame:
    """n_words, n_hit, n_items, items_sha256 and contaminated for every document row."""

    def row(key, text, words, starts, ends, names):
        hit = sum(ends) - sum(starts)
        return key, len(words), hit, len(names), hashlib.sha256(",".join(sorted(names)).encode()).hexdigest(), hit > 0

    return _apply(docs.select("doc_id", "text"), benchmark, window, row, "doc_id long, n_words long, n_hit long, n_items long, items_sha256 string, contaminated boolean")


def remove_spans(text: str, starts: list[int], ends: list[int]) -> str:
    """The text without the words of the spans and what stands between them; each cut leaves one space."""
    raw = text.encode("utf-8", "surrogatepass")
    where = [m.span() for m in _RUN.finditer(raw)]
    kept, at = [], 0
    for start, end in zip(starts, ends, strict=True):
        kept.append(raw[at : where[start][0]])
        at = where[end - 1][1]
    kept.append(raw[at:])
    return b" ".join(x.strip(b" ") for x in kept if x.strip(b" ")).decode("utf-8", "surrogatepass")


def decontaminate(docs: DataFrame, benchmark: DataFrame, window: int = 10, max_coverage: float = 0.5) -> DataFrame:
    """Documents without contaminated spans.

    Spans are cut out of the text (n_chars, where there is one, follows); a document whose hit words exceed
    `max_coverage` of its words is dropped. Clean documents, nulls included, stay byte for byte. All columns of
    the input are kept, extra ones too.
    """
    sc, place = docs.sparkSession.sparkContext, docs.columns.index("text")
    spans = [pa.field("__starts", pa.list_(pa.int64())), pa.field("__ends", pa.list_(pa.int64()))]
    automata = [sc.broadcast(a) for a in _blocks(benchmark, window)]

    def cutter(shared, first: bool, last: bool):
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            automaton = shared.value
            for batch in (whole.slice(start, 128) for whole in batches for start in range(0, whole.num_rows, 128)):  # the words of a few texts at a time
                texts = batch.column(place).to_pylist()
                words = [words_of(t) for t in texts]
                found = [automaton.scan(w)[:2] for w in words]
                if not first:
                    before = zip(batch.column(batch.num_columns - 2).to_pylist(), batch.column(batch.num_columns - 1).to_pylist(), strict=True)
                    found = [_merge([*s, *a], [*e, *b]) for (s, e), (a, b) in zip(found, before, strict=True)]
                if not last:
                    arrays = batch.columns[: len(batch.columns) - 2 * (not first)] + [pa.array([s for s, _ in found], spans[0].type), pa.array([e for _, e in found], spans[1].type)]
                    yield pa.RecordBatch.from_arrays(arrays, schema=pa.schema([batch.schema.field(i) for i in range(len(arrays) - 2)] + spans))
                    continue
                texts = [remove_spans(t, s, e) if s else t for t, (s, e) in zip(texts, found, strict=True)]
                arrays = batch.columns[: len(batch.columns) - 2 * (not first)]
                arrays[place] = pa.array(texts, pa.string())
                keep = pa.array([not w or sum(e) - sum(s) <= max_coverage * len(w) for w, (s, e) in zip(words, found, strict=True)])
                fields = [batch.schema.field(i) if i != place else pa.field("text", pa.string()) for i in range(len(arrays))]
                yield pa.RecordBatch.from_arrays(arrays, schema=pa.schema(fields)).filter(keep)
            release_memory()

        return run

    out, between = docs, T.StructType([*docs.schema.fields, *(T.StructField(f.name, T.ArrayType(T.LongType())) for f in spans)])
    for k, shared in enumerate(automata):
        last = k == len(automata) - 1
        out = out.mapInArrow(cutter(shared, k == 0, last), docs.schema if last else between)
        if not last:
            out = scratch_table(out)
    if "n_chars" in docs.columns:
        out = out.withColumn("n_chars", F.when(F.col("text").isNull(), F.col("n_chars")).otherwise(F.length("text")).cast(docs.schema["n_chars"].dataType))
    return out
