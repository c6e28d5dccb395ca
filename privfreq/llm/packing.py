"""Best-fit packing of token sequences, by supersteps over sorted documents and gaps.

Lengths are whole numbers up to the capacity, so sorting documents by length leaves at most `capacity` classes of
equal documents, and sorting open sequences by gap at most as many classes of equal gaps. A superstep takes the longest
class that is left, sweeps for the successor gap (the smallest that holds it), gives the gap's sequences out by rank
(so no two documents want the same place), moves those sequences to their new gap class, and goes on with what is left
of the class. What a sweep reads is therefore bounded by capacity squared, whatever the corpus; the documents themselves
are ranked and placed in distributed passes: two shuffles of (length, crc) rows in all, none of texts or tokens.
"""

from __future__ import annotations

import re
import zlib
from bisect import bisect_left, insort
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import common

CAPACITY, END_ID = 4096, 1
LETTERS = "a-zß-öø-ÿāăąćĉċčďđēĕėęěĝğġģĥħĩīĭįıĳĵķĸĺļľŀłńņňŋōŏőœŕŗřśŝşšţťŧũūŭůűųŵŷźżž"
PIECES = "doc_id long, piece int, start long, length long, ids_crc32 long"
PLACED = f"{PIECES}, sequence_id long, offset long"


class Encoder:
    """The ids of a whole text, equal to the tokenizer's own.

    Texts of plain Latin letters are taken word by word, each new word being encoded once: the vocabulary's splitter
    never looks across white space, and NFC and lower-casing change such letters one by one. The new words of a text are
    encoded together; every piece of the splitter ends in the only id of it that is marked as an end. Any other text goes
    through the tokenizer whole.
    """

    limit = 400_000

    def __init__(self, path: str):
        from tokenizers import Tokenizer, normalizers, pre_tokenizers

        self.tokenizer = Tokenizer.from_file(path)
        self.pieces = Tokenizer.from_file(path)  # for words that are normal and cut already
        self.pieces.normalizer = normalizers.Sequence([])
        self.pieces.pre_tokenizer = pre_tokenizers.Sequence([pre_tokenizers.WhitespaceSplit(), pre_tokenizers.ByteLevel(add_prefix_space=False, use_regex=False)])
        vocabulary = self.tokenizer.get_vocab(with_added_tokens=False)
        self.ends = np.zeros(max(vocabulary.values()) + 1, bool)
        self.ends[[i for word, i in vocabulary.items() if word.endswith("</w>")]] = True
        self.words: dict[str, bytes] = {}
        # printable ASCII, tab and line ends, and the Latin letters that have one lower-case letter each
        self.plain = re.compile(rf"[\t\n\r\x20-\x7e\xc0-\xd6\xd8-\xdf{LETTERS}Ā-įı-ňŊ-ž]*").fullmatch
        self.split = re.compile(rf"[{LETTERS}]+|[0-9]|'s|'t|'re|'ve|'m|'ll|'d|[^\s{LETTERS}0-9]+").findall

    def whole(self, text: str) -> np.ndarray:
        return np.array(self.tokenizer.encode(text, add_special_tokens=False).ids, "<u4")

    def learn(self, new: list[str]) -> None:
        pieces = [self.split(word) for word in new]
        joined = " ".join(" ".join(p) for p in pieces)
        ids = np.array(self.pieces.encode_batch_fast([joined], add_special_tokens=False)[0].ids, "<u4")
        last = np.flatnonzero(self.ends[ids])[np.cumsum([len(p) for p in pieces]) - 1] + 1
        data, at = ids.tobytes(), 0
        for word, end in zip(new, (4 * last).tolist(), strict=True):
            self.words[word] = data[at:end]
            at = end

    def ids(self, text: str) -> bytes:
        if not self.plain(text) or "<|" in text:
            return self.whole(text).tobytes()
        tokens = text.lower().split()
        if new := set(tokens).difference(self.words):
            if len(self.words) + len(new) > self.limit:
                self.words.clear()
                new = set(tokens)
            self.learn(list(new))
        return b"".join(map(self.words.__getitem__, tokens))


def cut(ids: bytes, capacity: int) -> Iterator[tuple[int, int, int, int]]:
    """(piece, start, length, crc32) of a document's ids; only what is longer than the capacity is cut."""
    step = 4 * capacity
    for piece, at in enumerate(range(0, len(ids), step)):
        part = ids[at : at + step]
        yield piece, at // 4, len(part) // 4, zlib.crc32(part)


def tokenized_pieces(docs: DataFrame, tokenizer_path: str, capacity: int = CAPACITY, end_id: int = END_ID) -> DataFrame:
    """One row for each piece of each document; an empty text is the end id alone."""
    last = np.array([end_id], "<u4").tobytes()

    def run(batches):
        encoder = common.process_cache(f"encoder {tokenizer_path}", lambda: Encoder(tokenizer_path))
        for batch in batches:
            columns = ([], [], [], [], [])
            for doc, text in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                for row in cut(encoder.ids(text.as_py()) + last, capacity):
                    for column, value in zip(columns, (doc, *row), strict=True):
                        column.append(value)
            kinds = (pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64())
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(columns, kinds, strict=True)], PIECE_NAMES)

    return common.mapped(common.texts(docs), run, PIECES)


PIECE_NAMES = ["doc_id", "piece", "start", "length", "ids_crc32"]


def plan_best_fit(counts: dict[int, int], capacity: int = CAPACITY) -> tuple[np.ndarray, int]:
    """Runs (length, first rank, documents, first sequence, documents a sequence, offset), and the number of sequences."""
    runs: list[tuple[int, ...]] = []
    waiting: dict[int, list[tuple[int, int]]] = {}  # gap -> runs of sequences that have it
    gaps: list[int] = []
    opened = 0

    def keep(gap: int, first: int, n: int) -> None:
        if gap and n:
            if gap not in waiting:
                waiting[gap] = []
                insort(gaps, gap)
            waiting[gap].append((first, n))

    for length in sorted(counts, reverse=True):
        left, rank = counts[length], 0
        while left:
            at = bisect_left(gaps, length)
            if at < len(gaps):
                gap = gaps[at]
                first, n = waiting[gap].pop()
                if not waiting[gap]:
                    del waiting[gap]
                    gaps.pop(at)
            else:
                gap, first, n = capacity, opened, -(-left // (capacity // length))
                opened += n
            each = gap // length
            full, rest = divmod(min(left, n * each), each)
            if full:
                runs.append((length, rank, full * each, first, each, capacity - gap))
                keep(gap - each * length, first, full)
            if rest:
                runs.append((length, rank + full * each, rest, first + full, rest, capacity - gap))
                keep(gap - rest * length, first + full, 1)
            keep(gap, first + full + bool(rest), n - full - bool(rest))
            rank += full * each + rest
            left -= full * each + rest
    return np.array(runs, np.int64).reshape(-1, 6), opened


def pack(pieces: DataFrame, capacity: int = CAPACITY) -> DataFrame:
    """Sequence and offset of each piece (columns of PIECES, read twice: hand in a written table).

    Lengths lie in 1..capacity. Equal rows are separate pieces. An empty table gives an empty result. A length that a
    third of all rows share is ranked in salted parts, so no task gathers it.
    """
    spark = pieces.sparkSession
    salts = 8 * common.partitions(spark)
    salted = pieces.withColumn("salt", F.pmod(F.xxhash64("doc_id", "piece", "ids_crc32"), F.lit(salts)).cast("int"))
    sizes = common.materialize(salted.groupBy("salt", "length").count(), "pack-sizes")
    counts = {r["length"]: r["n"] for r in sizes.groupBy("length").agg(F.sum("count").alias("n")).collect()}
    if bad := [n for n in counts if not 0 < n <= capacity]:
        raise ValueError(f"pieces of lengths outside 1..{capacity}: {bad[:5]}")
    runs, _ = plan_best_fit(counts, capacity)
    order = np.lexsort((runs[:, 1], runs[:, 0])) if len(runs) else np.empty(0, np.int64)
    plan = common.broadcast_of(spark, runs[order])
    before = Window.partitionBy("length").orderBy("salt").rowsBetween(Window.unboundedPreceding, -1)
    starts = sizes.select("salt", "length", F.coalesce(F.sum("count").over(before), F.lit(0)).alias("before"))
    within = Window.partitionBy("salt", "length").orderBy("doc_id", "piece", "ids_crc32")
    ranked = salted.withColumn("rank", F.row_number().over(within) - 1).join(starts, ["salt", "length"])

    def place(batches):
        table = plan.value
        key = (table[:, 0] << 44) + table[:, 1]
        for batch in batches:
            length, rank = (batch.column(i).to_numpy(zero_copy_only=False) for i in (3, 5))
            run = table[np.searchsorted(key, (length << 44) + rank, "right") - 1]
            bins, slots = np.divmod(rank - run[:, 1], run[:, 4])
            yield pa.RecordBatch.from_arrays([*batch.columns[:5], pa.array(run[:, 3] + bins), pa.array(run[:, 5] + slots * length)], [*PIECE_NAMES, "sequence_id", "offset"])

    return common.mapped(ranked.select(*PIECE_NAMES, (F.col("rank") + F.col("before")).cast("long").alias("rank")), place, PLACED)


def vocabulary_path(name: str = "word_bpe_49k.json") -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def pack_documents(docs: DataFrame, tokenizer_path: str | None = None, capacity: int = CAPACITY, end_id: int = END_ID) -> DataFrame:
    """Pack whole documents: doc_id, piece, start, length, ids_crc32, sequence_id, offset.

    Null text: empty (the end id alone). Null doc_id: kept, as null. Repeated rows: packed each. Empty table: no rows.
    """
    pieces = tokenized_pieces(docs, tokenizer_path or vocabulary_path(), capacity, end_id)
    return pack(common.materialize(pieces, "pack-pieces"), capacity)


def op2_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack_documents(common.read(spark, sf_dir, "documents"))
