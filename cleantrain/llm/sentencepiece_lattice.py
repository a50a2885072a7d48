"""SentencePiece encoding and decoding over a relational lattice.

A text becomes a string in which the space is U+2581, with one in front. It is cut into units at places that no piece
of the model spans (such places are found in the piece table itself), so units can be encoded apart, and each distinct
unit is encoded once: its substrings of at most the longest piece's length are exploded and meet the piece table in an
equi-join; the edges are grouped by unit and folded with Spark's aggregate().

The dictionary of units comes back to the texts by two ways that give the same ids. The HOT_UNITS most frequent units
of the whole corpus, a table of bounded size, are broadcast. All others go by an equi-join: each row of texts sends
its distinct other units, which meet the lattice's result in one exchange by unit and return to the row in another. A
unit left out of the broadcast table holds at most about one HOT_UNITS-th of all places, so no join key is hot. Texts are
shuffled once, some of them in a row, as the compressed ids of their frequent units with places for the others; no group is larger than one row's own units.

The fold follows the model's kind. For unigram models it is Viterbi's: edges come by their end, and the best path to
every position is kept. The scores of byte-pair models are merge ranks, of which no sum means anything, so a best path
is not what such a model encodes to; there the fold goes over the edges by rank and keeps the piece boundaries as bits:
an edge that spans just two pieces joins them. One pass is enough for pieces made of better-ranked parts; of others, which
here are runs of spaces, the fold takes the best edge again and again.

Edge cases: null and empty texts have no ids and decode to the empty text; U+2581 itself decodes to a space, as in
the reference library; ties go to the edge that starts first. Every input row gets a row, whatever its doc_id, which
may be null or repeated. Models that normalise characters, drop spaces or add no space in front raise ValueError.
"""

from __future__ import annotations

import re
import sys
import unicodedata
from array import array
from collections import Counter
from collections.abc import Iterator
from functools import lru_cache
from itertools import accumulate, chain

import numpy as np
import pandas as pd
import pyarrow as pa
import zstandard
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import release_memory, scratch_table

MODEL_FILE = "/opt/tokenizers/piece_bpe_32k.model"
SPACE = "▁"
BYTE_PAIR = 2
#: Units in the broadcast table, and the longest of them; the rest are joined by shuffle.
HOT_UNITS, HOT_CHARS = 3 << 18, 64
#: Pieces in the broadcast table; a larger one is joined by shuffle.
BROADCAST_PIECES = 500_000
#: Longer units are cut wherever two neighbours occur in no piece.
CUT_CHARS = 48
#: Distinct words that a task counts at a time, words that it keeps encoded, and characters of texts in one row.
_FLUSH, _KEPT, _ROW_CHARS = 250_000, 150_000, 1 << 19
#: Bits of the boundary set in one number, and so the longest piece that the one-pass fold takes.
_BITS = 32


class PieceTable:
    """Pieces with ids and scores, the byte pieces, and the pattern that cuts units; merges: a byte-pair model."""

    def __init__(self, pieces: list[tuple[str, int, float]], byte_ids: dict[int, int], unknown: int, merges: bool):
        self.pieces, self.bytes, self.unknown, self.merges = pieces, byte_ids, unknown, merges
        self.longest = max(len(p) for p, _, _ in pieces)
        self.fallback = min(s for _, _, s in pieces) - 10.0
        self.find = {p: (i, s) for p, i, s in pieces}
        self.fine = not any(_kind(a) != _kind(b) and _kind(a) != "S" for p, _, _ in pieces for a, b in zip(p, p[1:], strict=False))
        if any(a != SPACE and b == SPACE for p, _, _ in pieces for a, b in zip(p, p[1:], strict=False)):
            raise ValueError("a piece spans the start of a word")
        if merges and self.longest > _BITS:
            raise ValueError(f"byte-pair pieces of more than {_BITS} characters")
        self.pairs = {a + b for p, _, _ in pieces for a, b in zip(p, p[1:], strict=False)}
        self.pooled, self.run = self._unsteady() if merges else (None, 0)
        self.text_of = [b""] * (1 + max([unknown, *byte_ids.values(), *(i for _, i, _ in pieces)]))
        for p, i, _ in pieces:
            self.text_of[i] = p.replace(SPACE, " ").encode()
        for b, i in byte_ids.items():
            self.text_of[i] = bytes([b])
        self.text_of[unknown] = b"" if byte_ids else "\ufffd".encode()

    @staticmethod
    def of_model(model: bytes) -> PieceTable:
        """Reads a model file, which names its kind."""
        import sentencepiece

        _check_settings(model)
        reader = sentencepiece.SentencePieceProcessor(model_proto=model)
        n = reader.get_piece_size()
        normal = [i for i in range(n) if not (reader.is_byte(i) or reader.is_control(i) or reader.is_unknown(i) or reader.is_unused(i))]
        scores = [reader.get_score(i) for i in normal]
        byte_ids = {int(reader.id_to_piece(i)[1:-1], 16): i for i in range(n) if reader.is_byte(i)}
        return PieceTable([(reader.id_to_piece(i), i, float(s)) for i, s in zip(normal, scores, strict=True)], byte_ids, reader.unk_id(), _model_kind(model) == BYTE_PAIR)

    def _unsteady(self) -> tuple[float | None, int]:
        """The best score of a piece that has no two better-ranked parts, below which merges needn't come in the order of ranks.

        And, if all such pieces are runs of U+2581, the length of the longest where it surely fills the start of a longer
        run, so that a run may be cut behind it: the leftmost pair goes first, and nothing joins a longest piece.
        """
        part = lambda p, s: len(p) == 1 or p in self.find and self.find[p][1] > s
        odd = [(p, s) for p, _, s in self.pieces if len(p) > 1 and not any(part(p[:k], s) and part(p[k:], s) for k in range(1, len(p)))]
        if not odd:
            return None, 0
        pooled, runs = max(s for _, s in odd), {len(p): s for p, _, s in self.pieces if p == SPACE * len(p) and len(p) > 1}
        if any(p != SPACE * len(p) for p, _ in odd) or len(set(runs.values())) > 1:
            return pooled, 0
        most, row = max(runs), [1] * max(runs)
        while (at := next((i for i in range(len(row) - 1) if row[i] + row[i + 1] in runs), None)) is not None:
            row[at : at + 2] = [row[at] + row[at + 1]]
        return pooled, most if row == [most] else 0

    def words(self, text: str) -> list[str]:
        """Parts that hold whole units: cut at single spaces; a text with runs of spaces is one part."""
        return text.split(" ") if "  " not in text and text[0] != " " and text[-1] != " " else [text]

    def units(self, text: str | None) -> list[str]:
        if not text:
            return []
        if self.fine and len(text) < CUT_CHARS:
            if text.isalpha():
                return [SPACE + text]
            if text[-1] in ",.;:!?" and text[:-1].isalpha():
                return [SPACE + text[:-1], text[-1]]
            if ".\n" in text:
                left, end, right = text.partition(".\n")
                if left.isalpha() and right.isalpha():
                    return [SPACE + left, end, right]
        found = _pattern(self.fine).findall(SPACE + text.replace(" ", SPACE))
        return found if len(text) <= CUT_CHARS else [u for x in found for u in (self._cut(x) if len(x) > CUT_CHARS else [x])]

    def _cut(self, unit: str) -> list[str]:
        at = [0]
        if self.run:
            spaces = len(unit) - len(unit.lstrip(SPACE))
            at += range(self.run, spaces - CUT_CHARS, self.run)
        at += [*(i for i in range(at[-1] + 1, len(unit)) if unit[i - 1 : i + 1] not in self.pairs), len(unit)]
        return [unit[a:b] for a, b in zip(at, at[1:], strict=False)]

    def lone(self, char: str) -> list[int]:
        """The id of a character that stands alone, else its byte pieces or the unknown id."""
        if (found := self.find.get(char)) is not None:
            return [found[0]]
        return [self.bytes.get(b, self.unknown) for b in char.encode("utf-8", "surrogatepass")] if self.bytes else [self.unknown]

    def finished(self, ids: np.ndarray, ends: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Characters that stand alone, written -1 - code point, as their ids; ends of parts move along."""
        if not (ids < 0).any():
            return ids, ends
        chars, place = np.unique(-1 - ids[ids < 0], return_inverse=True)
        parts = [np.array(self.lone(chr(c)), np.int32) for c in chars]
        longs = np.array([len(x) for x in parts])
        marked = ids.copy()
        marked[ids < 0] = -1 - place
        return _expand(marked, ends, np.cumsum(longs) - longs, longs, np.concatenate(parts))

    def decode(self, ids) -> str:
        raw = b"".join(map(self.text_of.__getitem__, ids))
        return (raw[1:] if raw[:1] == b" " else raw).decode("utf-8", "replace")


def _fields(message: bytes) -> Iterator[tuple[int, int | bytes]]:
    """Field numbers and values of a protocol buffer message."""
    at = 0

    def varint() -> int:
        nonlocal at
        value = shift = 0
        while True:
            byte = message[at]
            at += 1
            value |= (byte & 127) << shift
            shift += 7
            if byte < 128:
                return value

    while at < len(message):
        key = varint()
        if key & 7 == 0:
            yield key >> 3, varint()
        else:
            size = {1: 8, 5: 4}.get(key & 7) or varint()
            yield key >> 3, message[at : at + size]
            at += size


def _check_settings(model: bytes) -> None:
    """Fields 2 to 5 of the normaliser's settings, which are field 3 of the model: character map, space in front, drop spaces, write spaces as U+2581."""
    rules = next((dict(_fields(v)) for k, v in _fields(model) if k == 3), {})
    suffix = next((dict(_fields(v)).get(24, 0) for k, v in _fields(model) if k == 2), 0)
    if rules.get(2) or not rules.get(3, 1) or rules.get(4, 1) or not rules.get(5, 1) or suffix:
        raise ValueError("only models are read that leave characters and spaces as they are and put a space in front")


def _model_kind(model: bytes) -> int:
    """Field 3 of the trainer's settings, which are field 2 of the model: 1 (also if absent) unigram, 2 byte-pair."""
    for number, value in _fields(model):
        if number == 2:
            return next((v for k, v in _fields(value) if k == 3), 1)
    return 1


def _kind(c: str) -> str:
    return "S" if c == SPACE else "L" if (k := unicodedata.category(c))[0] in "LM" else "D" if k == "Nd" else "O"


@lru_cache(maxsize=2)
def _pattern(fine: bool) -> re.Pattern:
    """Spaces with one run of letters, of digits or of others; without `fine`, with everything up to the next space."""
    if not fine:
        return re.compile(f"{SPACE}*[^{SPACE}]+|{SPACE}+")
    ranges: dict[str, list[list[int]]] = {"L": [], "D": []}
    for code in range(sys.maxunicode + 1):
        if (kind := _kind(chr(code))) in ranges:
            if ranges[kind] and ranges[kind][-1][1] == code - 1:
                ranges[kind][-1][1] = code
            else:
                ranges[kind].append([code, code])
    letters, digits = ("".join(f"\\U{a:08x}-\\U{b:08x}" for a, b in ranges[k]) for k in "LD")
    return re.compile(f"{SPACE}*(?:[{letters}]+|[{digits}]+|[^{letters}{digits}{SPACE}]+)|{SPACE}+")


_TABLES: dict[int, PieceTable] = {}


def piece_table(model: bytes) -> PieceTable:
    """One table a process and model."""
    if (key := hash(model)) not in _TABLES:
        _TABLES[key] = PieceTable.of_model(model)
    return _TABLES[key]


def _read_model(spark: SparkSession, model_file: str) -> bytes:
    with open(model_file, "rb") as f:
        return f.read()


def frequent_units(docs: DataFrame, shared) -> DataFrame:
    """unit: at most HOT_UNITS of the most frequent units of all texts, of 2 to HOT_CHARS characters.

    Tasks count words, and let out the units that occur twice among _FLUSH distinct words; the sums are cut where
    a histogram of their logarithms says that the bound is kept. Which units are in it changes no result.
    """
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table, words, units = piece_table(shared.value), Counter(), Counter()

        def flush() -> pa.RecordBatch:
            for word, n in words.items():
                for u in table.units(word):
                    units[u] += n
            kept = [(u, n) for u, n in units.items() if n > 1 and 1 < len(u) <= HOT_CHARS]
            words.clear()
            units.clear()
            return pa.RecordBatch.from_arrays([pa.array([u for u, _ in kept], pa.string()), pa.array([n for _, n in kept], pa.int64())], ["unit", "n"])

        for batch in batches:
            for start in range(0, batch.num_rows, 256):
                for text in batch.column(0).slice(start, 256).to_pylist():
                    if text:
                        parts = table.words(text)
                        if len(parts) > 1:
                            words.update(parts)
                        else:
                            units.update(table.units(text))
                if len(words) + len(units) > _FLUSH:
                    yield flush()
        yield flush()
        release_memory()

    counts = scratch_table(docs.select("text").mapInArrow(run, "unit string, n long").groupBy("unit").agg(F.floor(F.log2(F.sum("n")) * 8).alias("size")))
    room, least = HOT_UNITS, None
    for r in sorted(counts.groupBy("size").count().collect(), reverse=True):
        room -= r["count"]
        if room < 0:
            break
        least = r["size"]
    return counts.where(F.col("size") >= least if least is not None else F.lit(False)).select("unit")


def unit_dictionary(units: DataFrame, table: PieceTable) -> DataFrame:
    """unit and ids (lone characters as -1 - code point) of distinct units of two characters or more.

    A byte-pair fold needs no edges of one character, so units on which no longer piece lies have no row.
    """
    spark = units.sparkSession
    order = {s: k for k, s in enumerate(sorted({s for _, _, s in table.pieces}, reverse=True))}
    pieces = spark.createDataFrame(pd.DataFrame([(p, i, s, order[s]) for p, i, s in table.pieces], columns=["piece", "id", "score", "rank"]), "piece string, id int, score double, rank int")
    if len(table.pieces) <= BROADCAST_PIECES:
        pieces = F.broadcast(pieces)
    size, start, long = F.length("unit"), F.col("start"), F.col("long")
    cut = lambda spans: spans.select("unit", "start", "long", F.col("unit").substr(start + 1, long).alias("piece"))
    if table.merges:
        # Only lengths of pieces that begin with the substring's first two characters are exploded.
        longs: dict[str, set[int]] = {}
        for p, _, _ in table.pieces:
            if len(p) > 1:
                longs.setdefault(p[:2], set()).add(len(p))
        heads = spark.createDataFrame([(h, sorted(x)) for h, x in longs.items()], "head string, longs array<int>")
        heads = F.broadcast(heads) if len(longs) <= BROADCAST_PIECES else heads
        starts = units.select("unit", F.explode(F.sequence(F.lit(0), size - 2)).alias("start")).select("unit", "start", F.col("unit").substr(start + 1, F.lit(2)).alias("head"))
        spans = starts.join(heads, "head").select("unit", "start", F.explode("longs").alias("long")).where(start + long <= size)
        edges = cut(spans).join(pieces, "piece").select("unit", F.struct("rank", "start", "long", "id", _Bits.ends_at(start, long).alias("ends"), _Bits.inside(start, long).alias("inner")).alias("edge"))
        edges = edges.groupBy("unit").agg(F.sort_array(F.collect_list("edge")).alias("edges"))
        return edges.select("unit", _merge_fold(F.col("edges"), order.get(table.pooled)).alias("ids"))
    starts = units.select("unit", F.explode(F.sequence(F.lit(0), size - 1)).alias("start"))
    spans = cut(starts.select("unit", "start", F.explode(F.sequence(F.lit(1), F.least(F.lit(table.longest), size - start))).alias("long")))
    edges = spans.join(pieces, "piece", "left").where("id is not null or long = 1")
    edge = F.struct((F.col("start") + F.col("long")).alias("end"), "start", F.coalesce("id", -1 - F.ascii("piece")).alias("id"), F.coalesce("score", F.lit(table.fallback)).alias("score"))
    return edges.groupBy("unit").agg(F.sort_array(F.collect_list(edge)).alias("edges")).select("unit", _viterbi_fold(F.col("edges")).alias("ids"))


def _viterbi_fold(edges: Column) -> Column:
    """The ids of the best path over edges that come by end, then by start."""

    def relax(best, e):
        """Paths by end position; a path's end is either the last one known or the next."""
        path = F.struct((F.get(best, e["start"])["score"] + e["score"]).alias("score"), F.concat(F.get(best, e["start"])["ids"], F.array(e["id"])).alias("ids"))
        last = F.element_at(best, -1)
        return F.when(F.size(best) == e["end"], F.concat(best, F.array(path))).when(F.get(best, e["start"])["score"] + e["score"] > last["score"], F.concat(F.slice(best, F.lit(1), e["end"]), F.array(path))).otherwise(best)

    none = F.array(F.struct(F.lit(0.0).alias("score"), F.array().cast("array<int>").alias("ids")))
    return F.element_at(F.aggregate(edges, none, relax), -1)["ids"]


def _let(value: Column, body) -> Column:
    """body(value) with value computed once: Spark's expressions have no local names, but lambdas have arguments."""
    return F.get(F.transform(F.array(value), body), F.lit(0))


def _merge_fold(edges: Column, pooled: int | None) -> Column:
    """The ids of a unit under byte-pair merges, from its lattice's edges of two or more characters, best first.

    The state is the set of piece boundaries as bits. Edges ranked before `pooled` are passed once; from there on, the
    first of the others that spans two pieces is applied until none does.
    """
    size = F.length("unit")
    return F.when(size < 63, _folded(edges, pooled, _Bits())).otherwise(_folded(edges, pooled, _ManyBits()))


def _shift(name: str, x, by) -> Column:
    """F.shiftleft() and the like take no column as distance."""
    return F.call_function(name, x, by)


def _one() -> Column:
    return F.lit(1).cast("long")


def _from(place) -> Column:
    """All bits from a place on; no sums here, which might overflow."""
    return _shift("shiftleft", F.lit(-1).cast("long"), place)


class _Bits:
    """Boundaries 0 to 62 in one number; edges know the bits of their ends, and those in between."""

    @staticmethod
    def ends_at(start, long):
        return _shift("shiftleft", _one(), start).bitwiseOR(_shift("shiftleft", _one(), start + long))

    @staticmethod
    def inside(start, long):
        return _from(start + 1).bitwiseAND(F.bitwise_not(_from(start + long)))

    def full(self, size):
        return F.bitwise_not(_from(size + 1))

    def spans_two(self, b, e):
        return (b.bitwiseAND(e["ends"]) == e["ends"]) & (F.bit_count(b.bitwiseAND(e["inner"])) == 1)

    def joined(self, b, e):
        """The boundaries after an edge that spans two pieces, else as they are."""
        return F.when(self.spans_two(b, e), b.bitwiseAND(F.bitwise_not(e["inner"]))).otherwise(b)

    def whole(self, b, e):
        return b.bitwiseAND(e["ends"].bitwiseOR(e["inner"])) == e["ends"]

    def lone(self, b, size):
        """Where characters stand alone."""
        both = b.bitwiseAND(F.shiftright(b, 1))
        return F.when(both == 0, F.array().cast("array<int>")).otherwise(_let(both, lambda x: F.filter(F.sequence(F.lit(0), size - 1), lambda s: _shift("shiftright", x, s).bitwiseAND(_one()) != 0)))


class _ManyBits(_Bits):
    """Any number of boundaries, _BITS in a number, with a zero behind: an edge touches two neighbours of the array."""

    word, off = staticmethod(lambda s: F.shiftright(s, 5)), staticmethod(lambda s: s.bitwiseAND(F.lit(_BITS - 1)))

    def full(self, size):
        return F.transform(F.sequence(F.lit(0), self.word(size) + 1), lambda k: _shift("shiftleft", _one(), F.greatest(F.lit(0), F.least(F.lit(_BITS), size + 1 - k * _BITS))) - 1)

    def window(self, b, s):
        """The boundaries from position s on."""
        return _shift("shiftrightunsigned", F.get(b, self.word(s)).bitwiseOR(F.shiftleft(F.get(b, self.word(s) + 1), _BITS)), self.off(s))

    def gap(self, b, e):
        """The boundaries inside an edge whose ends are both boundaries, else 0."""
        ends, inner = self.ends_at(F.lit(0), e["long"]), self.inside(F.lit(0), e["long"])
        return _let(self.window(b, e["start"]), lambda w: F.when(w.bitwiseAND(ends) == ends, w.bitwiseAND(inner)).otherwise(F.lit(0).cast("long")))

    def spans_two(self, b, e):
        return F.bit_count(self.gap(b, e)) == 1

    def joined(self, b, e):
        def without(gone):
            k, moved = self.word(e["start"]), _shift("shiftleft", gone, self.off(e["start"]))
            low, high = F.get(b, k).bitwiseAND(F.bitwise_not(moved.bitwiseAND(F.lit(2**32 - 1)))), F.get(b, k + 1).bitwiseAND(F.bitwise_not(F.shiftrightunsigned(moved, _BITS)))
            return F.concat(F.slice(b, F.lit(1), k), F.array(low, high), F.slice(b, k + 3, F.size(b)))

        return _let(self.gap(b, e), lambda g: F.when(F.bit_count(g) == 1, without(g)).otherwise(b))

    def whole(self, b, e):
        ends = self.ends_at(F.lit(0), e["long"])
        return self.window(b, e["start"]).bitwiseAND(ends.bitwiseOR(self.inside(F.lit(0), e["long"]))) == ends

    def lone(self, b, size):
        here = lambda s: _shift("shiftright", F.get(b, self.word(s)), self.off(s)).bitwiseAND(_one()) != 0
        return F.filter(F.sequence(F.lit(0), size - 1), lambda s: here(s) & here(s + 1))


def _folded(edges: Column, pooled: int | None, bits: _Bits) -> Column:
    size = F.length("unit")
    bounds = F.aggregate(edges if pooled is None else F.filter(edges, lambda e: e["rank"] < pooled), bits.full(size), bits.joined)
    if pooled is not None:
        rest = F.filter(edges, lambda e: e["rank"] >= pooled)
        step = lambda b, _: F.coalesce(_let(F.get(F.filter(rest, lambda e: bits.spans_two(b, e)), F.lit(0)), lambda e: F.when(e.isNotNull(), bits.joined(b, e))), b)
        bounds = F.when(F.element_at(edges, -1)["rank"] < pooled, bounds).otherwise(F.aggregate(F.sequence(F.lit(1), size), bounds, step))

    def pieces(b):
        whole = F.transform(F.filter(edges, lambda e: bits.whole(b, e)), lambda e: F.struct(e["start"].alias("start"), e["id"].alias("id")))
        return F.concat(whole, F.transform(bits.lone(b, size), lambda s: F.struct(s.alias("start"), (-1 - F.ascii(F.col("unit").substr(s + 1, F.lit(1)))).alias("id"))))

    return F.transform(F.sort_array(_let(bounds, pieces)), lambda p: p["id"])


def _expand(ids: np.ndarray, ends: np.ndarray, starts: np.ndarray, longs: np.ndarray, values: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Every entry -1 - k replaced by values[starts[k] : starts[k] + longs[k]]; ends of parts move along."""
    k = -1 - ids[ids < 0]
    sizes = np.ones(len(ids), np.int64)
    sizes[ids < 0] = longs[k]
    out, own = np.repeat(ids, sizes), longs[k]
    out[np.repeat(ids < 0, sizes)] = values[np.repeat(starts[k] - np.cumsum(own) + own, own) + np.arange(own.sum())]
    return out, np.concatenate([[0], np.cumsum(sizes)])[ends]


class _Coder:
    """Groups of texts to ids, given the ids of frequent units; any other unit becomes -1 - its place among the others."""

    def __init__(self, table: PieceTable, hot: tuple[list[str], bytes, array]):
        units, ids, ends = hot
        self.table, self.young, self.old = table, {}, {}
        self.hot = {u: ids[a:b] for u, a, b in zip(units, chain([0], ends), ends, strict=False)}

    def encoded(self, texts: list[str]) -> tuple[list[bytes], list[str]]:
        if len(self.young) > _KEPT:
            self.young, self.old = {}, self.young
        young, old, hot, found, own = self.young, self.old, self.hot, {}, {}
        lists = [self.table.words(t) if t else [] for t in texts]
        for word in dict.fromkeys(chain.from_iterable(lists)):
            ids = young.get(word)
            if ids is None and (ids := old.get(word)) is not None:
                young[word] = ids
            if ids is None:
                parts, rare = [], False
                for u in self.table.units(word):
                    part = hot.get(u)
                    if part is None and len(u) == 1:
                        part = hot[u] = np.array(self.table.lone(u), np.int32).tobytes()
                    elif part is None:
                        rare = True
                        if (part := found.get(u)) is None:
                            part = found[u] = (-1 - len(found)).to_bytes(4, sys.byteorder, signed=True)
                    parts.append(part)
                ids = b"".join(parts)
                if not rare and len(word) <= HOT_CHARS:
                    young[word] = ids
            own[word] = ids
        return [b"".join(map(own.__getitem__, words)) for words in lists], list(found)


def _spread(opener: zstandard.ZstdDecompressor, sizes: list[int], packed: bytes) -> list[str]:
    whole, ends = opener.decompress(packed), list(accumulate(sizes))
    return [whole[a:b].decode("utf-8", "surrogatepass") for a, b in zip([0, *ends], ends, strict=False)]


def encode(docs: DataFrame, model_file: str = MODEL_FILE, decoded: bool = False) -> DataFrame:
    """doc_id, n_tokens and ids of every document row; with `decoded`, also the text that the ids decode to."""
    spark = docs.sparkSession
    model = _read_model(spark, model_file)
    table, shared = piece_table(model), spark.sparkContext.broadcast(model)  # the model file, about 0.5 MB
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    listed = unit_dictionary(frequent_units(rows, shared), table).toArrow()
    ids = listed.column("ids").combine_chunks()
    ids = ids if isinstance(ids, pa.ListArray) else pa.concat_arrays(ids.chunks)
    flat, ends = table.finished(ids.flatten().to_numpy().astype(np.int32), np.cumsum(ids.value_lengths().to_numpy()))
    hot = spark.sparkContext.broadcast((listed.column("unit").to_pylist(), flat.tobytes(), array("l", 4 * ends)))  # at most HOT_UNITS units

    def code(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Texts in rows of about _ROW_CHARS bytes, with the units that are not in the broadcast table."""
        coder, packer, names, texts, held = _Coder(piece_table(shared.value), hot.value), zstandard.ZstdCompressor(level=6), [], [], 0

        def flush() -> pa.RecordBatch:
            coded, rare = coder.encoded(texts)
            whole = np.frombuffer(b"".join(coded), np.int32)
            small = len(rare) < 1 << 15 and not (whole >= 1 << 15).any()
            packed = packer.compress((whole.astype(np.int16) if small else whole).tobytes())
            columns = [pa.array([names], pa.list_(pa.int64())), pa.array([[len(x) // 4 for x in coded]], pa.list_(pa.int32())), pa.array([small]), pa.array([packed], pa.binary())]
            rare = [u.encode("utf-8", "surrogatepass") for u in rare]
            columns += [pa.array([[len(u) for u in rare]], pa.list_(pa.int32())), pa.array([packer.compress(b"".join(rare))], pa.binary())]
            return pa.RecordBatch.from_arrays(columns, ["doc_id", "size", "small", "coded", "long", "rare"])

        for batch in batches:
            for start in range(0, batch.num_rows, 64):
                part = batch.slice(start, 64)
                for i, text in zip(part.column(0).to_pylist(), part.column(1).to_pylist(), strict=True):
                    names.append(i)
                    texts.append(text)
                    held += len(text or "") + 8
                    if held > _ROW_CHARS:
                        yield flush()
                        names, texts, held = [], [], 0
        if names:
            yield flush()
        del coder
        release_memory()

    def others(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        opener = zstandard.ZstdDecompressor()
        for batch in batches:
            for row, long, rare in zip(*(batch.column(c).to_pylist() for c in ("row", "long", "rare")), strict=True):
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(long), row, np.int64)), pa.array(np.arange(len(long), dtype=np.int32)), pa.array(_spread(opener, long, rare), pa.string())], ["row", "place", "unit"])

    def finish(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own, opener = piece_table(shared.value), zstandard.ZstdDecompressor()
        for batch in batches:
            for at in range(batch.num_rows):
                doc_ids, size, small, packed, long, rare = (c[at].as_py() for c in batch.columns[:6])
                whole = np.frombuffer(opener.decompress(packed), np.int16 if small else np.int32).astype(np.int32)
                starts, longs, values = np.zeros(len(long), np.int64), np.zeros(len(long), np.int64), np.zeros(0, np.int32)
                if (places := batch.column(6)[at].values) is not None and len(places):
                    found, places = batch.column(7)[at].values, places.to_numpy()
                    longs[places] = found.value_lengths().to_numpy()
                    values = found.flatten().to_numpy()
                    starts[places] = np.cumsum(longs[places]) - longs[places]
                if (bare := np.flatnonzero(longs == 0)).size:  # units on which no longer piece lies
                    rare = _spread(opener, long, rare)
                    chars = [-1 - np.array([ord(c) for c in rare[k]], np.int32) for k in bare]
                    longs[bare] = [len(x) for x in chars]
                    starts[bare] = len(values) + np.cumsum(longs[bare]) - longs[bare]
                    values = np.concatenate([values, *chars])
                flat, ends = own.finished(*_expand(whole, np.cumsum(size), starts, longs, values))
                ends = np.concatenate([[0], ends]).astype(np.int32)
                columns = [pa.array(doc_ids, pa.int64()), pa.array(np.diff(ends), pa.int64()), pa.ListArray.from_arrays(pa.array(ends), pa.array(flat))]
                if decoded:
                    columns.append(pa.array([own.decode(x.tolist()) for x in np.split(flat, ends[1:-1])], pa.string()))
                yield pa.RecordBatch.from_arrays(columns, results)
        release_memory()

    results = ["doc_id", "n_tokens", "ids", "decoded"][: 3 + decoded]
    # All columns go through both sides of the join below, rare ones and filters too, so that both share one exchange.
    coded = rows.mapInArrow(code, "doc_id array<long>, size array<int>, small boolean, coded binary, long array<int>, rare binary")
    coded = coded.select(F.monotonically_increasing_id().alias("row"), "doc_id", "size", "small", "coded", "long", "rare").repartition("row")
    other = coded.mapInArrow(others, "row long, place int, unit string").where("unit is not null and row is not null").repartition("unit")
    lone = other.groupBy("unit").agg(F.max(F.struct("row", "place")).alias("last")).where("last is not null").select("unit")
    found = other.join(unit_dictionary(lone, table), "unit").select("row", "place", "ids").repartition("row")
    found = found.groupBy("row").agg(F.collect_list(F.struct("place", "ids")).alias("found"))
    whole = coded.join(found, "row", "left").select("doc_id", "size", "small", "coded", "long", "rare", F.col("found.place").alias("place"), F.col("found.ids").alias("ids"))
    return whole.mapInArrow(finish, "doc_id long, n_tokens long, ids array<int>" + ", decoded string" * decoded)


def decode(rows: DataFrame, model_file: str = MODEL_FILE) -> DataFrame:
    """The rows with the text of their ids in the column `decoded`."""
    shared = rows.sparkSession.sparkContext.broadcast(_read_model(rows.sparkSession, model_file))
    at = rows.columns.index("ids")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = piece_table(shared.value)
        for batch in batches:
            for start in range(0, batch.num_rows, 256):
                part = batch.slice(start, 256)
                texts = ["" if x is None else table.decode(x) for x in part.column(at).to_pylist()]
                yield pa.RecordBatch.from_arrays([*part.columns, pa.array(texts, pa.string())], [*part.schema.names, "decoded"])

    return rows.mapInArrow(run, T.StructType([*rows.schema.fields, T.StructField("decoded", T.StringType())]))
