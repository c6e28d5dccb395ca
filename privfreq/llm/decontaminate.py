"""Benchmark decontamination: rare n-gram seeds pick passages, Smith-Waterman alignment of words scores them.

Seeds are pairs of an item's words, next to each other or with one word between, whose chance by the corpus's own word
shares is small; they meet the same pairs of a document at either distance, so that replaced, added and left out words
leave seeds. Each document is read once against all seeds of a block of items. Hits of one item on neighbouring diagonals
name a passage if they are surprising enough together, and it is aligned with the item (match +2, mismatch and gap -1).
The score is the alignment's share of a perfect one, so edited and paraphrased copies score by what is left of the item.
"""

from __future__ import annotations

import unicodedata
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common

MATCH, MISMATCH, GAP = 2, 1, 1
#: Largest chance of a rare seed at any place; an item keeps this many of its rarest seeds in any case.
RARE, AT_LEAST = 1e-5, 12
#: Distances between the words of a seed, and the fewest words of an item.
REACH, SHORTEST = (1, 2), 3
#: Surprise (-log10 of the chances) that the hits of a passage must have together, and its share of all that the item has.
SURPRISE, SHARE = 18.0, 0.1
#: Score from which a passage counts as the item's copy.
LEAK = 0.5
#: Items held by a broadcast at a time; more are matched in further blocks.
BLOCK = 20_000
_CUT = bytes(c if chr(c).isalnum() else 32 for c in range(256))

RESULT = "doc_id long, item_id long, score double, first_word int, last_word int, matched int"
NAMES = [c.split()[0] for c in RESULT.split(", ")]


class _Cut(dict):
    """Letters, digits and the marks on them stay; everything else is a space."""

    def __missing__(self, c: int) -> int:
        value = self[c] = c if chr(c).isalnum() or unicodedata.category(chr(c))[0] == "M" else 32
        return value


_CUT_WIDE = _Cut()


def spoken(text: bytes) -> list[bytes]:
    """Case-folded words of letters and digits of any script, in composed form (NFC)."""
    if text.isascii():
        return text.lower().translate(_CUT).split()
    folded = unicodedata.normalize("NFC", text.decode(errors="replace")).casefold()
    return unicodedata.normalize("NFC", folded).translate(_CUT_WIDE).encode().split()


#: Scores and matched words travel in one number: the score's unit, above any number of matches.
_UNIT = 1 << 32


def _sweep(item: np.ndarray, passage: np.ndarray, local: bool) -> tuple[int, int, int]:
    """The best value of score * _UNIT + matches and where it ends (words of the item, of the passage); one row is kept.

    local: it may begin anywhere; otherwise at the beginning of both.
    """
    width = len(passage)
    slope = GAP * _UNIT * np.arange(width + 1)
    row = np.zeros(width + 1, np.int64) if local else -slope
    best = (0, 0, 0)
    for i, word in enumerate(item.tolist(), 1):
        new = np.empty_like(row)
        new[0] = 0 if local else -GAP * _UNIT * i
        new[1:] = np.maximum(row[:-1] + np.where(passage == word, MATCH * _UNIT + 1, -MISMATCH * _UNIT), row[1:] - GAP * _UNIT)
        row = np.maximum.accumulate(new + slope) - slope
        if local:
            row[row < _UNIT] = 0
        j = int(row.argmax())
        if row[j] > best[0]:
            best = int(row[j]), i, j
    return best


def reachable(item: np.ndarray, passage: np.ndarray) -> int:
    """A score that no alignment exceeds: that of all words which both have, each as often as the one that has it less often."""
    both = np.concatenate([item, passage])
    words, of = np.unique(both, return_inverse=True)
    return MATCH * int(np.minimum(np.bincount(of[: len(item)], minlength=len(words)), np.bincount(of[len(item) :], minlength=len(words))).sum())


def align(item: np.ndarray, passage: np.ndarray, least: int = 1) -> tuple[int, int, int, int]:
    """Best local alignment: score, first and last place in the passage, words matched. Memory grows with the passage alone.

    A score under `least` comes without its place.
    """
    value, i, j = (0, 0, 0) if reachable(item, passage) < least else _sweep(item, passage, True)
    if value // _UNIT < least:
        return value // _UNIT, 0, -1, 0
    _, _, back = _sweep(item[:i][::-1], passage[:j][::-1], False)
    return value // _UNIT, j - back, j - 1, value % _UNIT


class SeedIndex:
    """Seeds of a block of items: sorted keys, and for each the items and places that hold it."""

    def __init__(self, items: list[tuple[int, list[bytes]]], chance: dict[bytes, float]):
        self.ids = {w: i for i, w in enumerate(sorted({w for _, ws in items for w in ws}), 1)}
        self.base = len(self.ids) + 1
        self.items = [(name, np.array([self.ids[w] for w in ws], np.int64)) for name, ws in items]
        share = np.array([1.0] + [max(chance.get(w, 0.0), 1e-9) for w in self.ids])
        parts: list[tuple] = [(np.empty(0, np.int64),) * 3 + (np.empty(0),)]
        self.need = np.full(len(self.items), np.inf)
        self.sizes = np.array([len(x) for _, x in self.items], np.int64)
        for n, (_, a) in enumerate(self.items):
            if len(a) < SHORTEST:
                continue
            key = np.concatenate([a[:-d] * self.base + a[d:] for d in REACH])
            at = np.concatenate([np.arange(len(a) - d) for d in REACH])
            rare = -np.log10(np.concatenate([share[a[:-d]] * share[a[d:]] for d in REACH]))
            use = (rare >= -np.log10(RARE)) | (rare >= -np.sort(-rare)[: min(AT_LEAST, len(rare))][-1])
            parts.append((key[use], np.full(int(use.sum()), n), at[use], rare[use]))
            self.need[n] = min(SURPRISE, SHARE * rare[use].sum())
        key, of, at, rare = (np.concatenate(x) for x in zip(*parts, strict=True))
        order = np.argsort(key, kind="stable")
        self.key, self.of, self.at, self.rare = key[order], of[order], at[order], rare[order]

    def passages(self, a: np.ndarray) -> list[tuple[int, int, int]]:
        """(item number, from, to): stretches of the document around hits of one item that are surprising together."""
        if not len(self.key):
            return []
        entries, places = [], []
        for d in REACH:
            full = np.flatnonzero((a[:-d] > 0) & (a[d:] > 0))
            key = a[full] * self.base + a[full + d]
            low = np.searchsorted(self.key, key)
            hit = np.flatnonzero(self.key[np.minimum(low, len(self.key) - 1)] == key)
            many = np.searchsorted(self.key, key[hit], "right") - low[hit]
            entries.append(np.repeat(low[hit] - (np.cumsum(many) - many), many) + np.arange(int(many.sum())))
            places.append(np.repeat(full[hit], many))
        entry, place = np.concatenate(entries), np.concatenate(places)
        if not len(entry):
            return []
        item, diagonal = self.of[entry], place - self.at[entry]
        order = np.lexsort((diagonal, item))
        entry, item, diagonal = entry[order], item[order], diagonal[order]
        size = self.sizes[item]
        # a stretch ends where the item changes or the next hit lies too many diagonals on
        new = np.concatenate([[True], (item[1:] != item[:-1]) | (diagonal[1:] - diagonal[:-1] > size[1:] // 2 + 2)])
        stretch = np.cumsum(new) - 1
        # a seed counts once in a stretch, however often it is hit
        once = np.unique(stretch * len(self.key) + entry)
        surprise = np.bincount(once // len(self.key), self.rare[once % len(self.key)])
        first, last = np.flatnonzero(new), np.append(np.flatnonzero(new)[1:] - 1, len(new) - 1)
        good = surprise >= self.need[item[first]] * (1 - 1e-9)
        slack = size[first] // 2 + 2
        low, high = np.maximum(0, diagonal[first] - slack), np.minimum(len(a), diagonal[last] + size[first] + slack)
        return list(zip(item[first][good].tolist(), low[good].tolist(), high[good].tolist(), strict=True))


def word_shares(docs: DataFrame, vocabulary: set[bytes]) -> dict[bytes, float]:
    """The share that each of these words has among all words of all documents."""
    known = common.broadcast_of(docs.sparkSession, vocabulary)

    def run(batches):
        from collections import Counter

        counts: Counter = Counter()
        total = 0
        for batch in batches:
            for text in common.raw(batch.column(0)):
                words = spoken(text)
                total += len(words)
                counts.update(filter(known.value.__contains__, words))
        yield pa.RecordBatch.from_arrays([pa.array([b"", *counts], pa.binary()), pa.array([total, *counts.values()], pa.int64())], ["word", "n"])

    rows = common.mapped(common.texts(docs).select("text"), run, "word binary, n long").groupBy("word").agg(F.sum("n").alias("n")).collect()
    counts = {bytes(r["word"]): r["n"] for r in rows}
    total = max(1, counts.pop(b"", 0))
    return {w: n / total for w, n in counts.items()}


def leaks(docs: DataFrame, benchmark: DataFrame, at_least: float = LEAK) -> DataFrame:
    """One row for each document and item with a passage of score >= at_least: the best one (columns of RESULT).

    first_word and last_word count the document's words of letters and digits from 0. Items of fewer than three words, and
    null or empty texts, match nothing. Rows without doc_id or item_id are passed over as items, kept as documents. An
    empty table on either side gives no rows.
    """
    spark = docs.sparkSession
    items = benchmark.select(F.col("item_id").cast("long").alias("item_id"), F.col("text").cast("string").alias("text")).where("item_id is not null and text is not null")
    blocks = max(1, -(-items.count() // BLOCK))
    parts = []
    for b in range(blocks):
        rows = items.where(F.pmod(F.xxhash64("item_id"), F.lit(blocks)) == b).collect()
        listed = sorted((r["item_id"], spoken(r["text"].encode())) for r in rows)
        shares = word_shares(docs, {w for _, ws in listed for w in ws})
        index = common.broadcast_of(spark, SeedIndex(listed, shares))

        def run(batches, index=index):
            held = index.value
            get = held.ids.get
            for batch in batches:
                columns: list[list] = [[] for _ in NAMES]
                for doc, text in zip(batch.column(0).to_pylist(), common.raw(batch.column(1)), strict=True):
                    a = np.array([get(w, 0) for w in spoken(text)], np.int64)
                    best: dict[int, tuple] = {}
                    for n, lo, hi in held.passages(a):
                        name, item = held.items[n]
                        score, first, last, matched = align(item, a[lo:hi], int(np.ceil(at_least * MATCH * len(item) - 1e-9)))
                        row = (doc, name, score / (MATCH * len(item)), lo + first, lo + last, matched)
                        if row[2] >= at_least and (name not in best or row[2] > best[name][2]):
                            best[name] = row
                    for row in best.values():
                        for column, value in zip(columns, row, strict=True):
                            column.append(value)
                kinds = (pa.int64(), pa.int64(), pa.float64(), pa.int32(), pa.int32(), pa.int32())
                yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(columns, kinds, strict=True)], NAMES)

        parts.append(common.mapped(common.texts(docs), run, RESULT))
    return reduce(DataFrame.unionByName, parts)


def op5_benchmark_leaks(spark: SparkSession, sf_dir: str) -> DataFrame:
    return leaks(common.read(spark, sf_dir, "documents"), common.read(spark, sf_dir, "benchmark"))
