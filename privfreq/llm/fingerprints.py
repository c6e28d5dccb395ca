"""Bottom-k sketches of word-shingle hashes: mergeable fingerprints of documents and of their parts.

A fingerprint holds the k smallest distinct 64-bit hashes of a text's five-word shingles (all of them where there are
fewer). The fingerprint of a union is the k smallest of the joined ones, so parts can be sketched apart and merged in
any order. Likeness is the share of the union's k smallest hashes that both sides hold.
"""

from __future__ import annotations

import base64
import hashlib
from itertools import chain

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common

K, WIDTH = 128, 5


def sketch(text: bytes, keyed: common.Keyed, k: int = K, width: int = WIDTH) -> np.ndarray:
    """The k smallest shingle hashes, sorted; empty for a text without words."""
    return common.shingles(common.words(text), width, keyed)[:k]


def merge(a: np.ndarray, b: np.ndarray, k: int = K) -> np.ndarray:
    return np.union1d(a, b)[:k]


def resemblance(a: np.ndarray, b: np.ndarray, k: int = K) -> float:
    """Estimated Jaccard similarity; exact where the union has at most k hashes. Two empty ones are alike."""
    union = merge(a, b, k)
    if not len(union):
        return 1.0
    top = union[-1]
    return len(np.intersect1d(a[a <= top], b[b <= top], assume_unique=True)) / len(union)


def distinct(a: np.ndarray, k: int = K) -> float:
    """Estimated number of distinct shingles: (k-1) over the k-th smallest hash as a share of the range."""
    return float(len(a)) if len(a) < k else (k - 1) / ((int(a[-1]) + 1) / 2.0**64)


def containment(a: np.ndarray, b: np.ndarray, k: int = K) -> float:
    """Estimated share of a's shingles that b has: hashes below both sketches' reach are a sample of a."""
    if not len(a):
        return 1.0
    reach = min(x[-1] if len(x) == k else np.uint64(common.MASK) for x in (a, b))
    own = a[a <= reach]
    return len(np.intersect1d(own, b, assume_unique=True)) / max(1, len(own))


def to_text(a: np.ndarray) -> str:
    return base64.b64encode(a.astype(">u8").tobytes()).decode()


def from_text(s: str) -> np.ndarray:
    return np.frombuffer(base64.b64decode(s), ">u8").astype(np.uint64)


def fingerprints(docs: DataFrame, k: int = K, width: int = WIDTH) -> DataFrame:
    """doc_id, fingerprint of each row, null texts as empty ones."""

    def run(batches):
        keyed = common.Keyed()
        for batch in batches:
            made = [to_text(sketch(x, keyed, k, width)) for x in common.raw(batch.column(1))]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(made, pa.string())], ["doc_id", "fingerprint"])

    return common.mapped(common.texts(docs), run, "doc_id long, fingerprint string")


def merged(prints: DataFrame, group: str, k: int = K) -> DataFrame:
    """One fingerprint for each value of `group`: partial merges in every input part, then one for each group of parts.

    A group may hold any share of the rows: parts are merged before the shuffle, so a group gets a sketch for each task.
    """
    kind = prints.schema[group].dataType.simpleString()
    schema = f"`{group}` {kind}, fingerprint string"

    def partial(batches):
        held: dict = {}
        for batch in batches:
            for key, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                held[key] = merge(held[key], from_text(text), k) if key in held else from_text(text)
            if len(held) > 50_000:
                yield rows(held)
                held = {}
        yield rows(held)

    def rows(held):
        return pa.RecordBatch.from_arrays([pa.array(list(held), pa_kind), pa.array([to_text(v) for v in held.values()], pa.string())], [group, "fingerprint"])

    from pyspark.sql.pandas.types import to_arrow_type

    pa_kind = to_arrow_type(prints.schema[group].dataType)
    def whole(batches):
        key, held, out = None, None, {}
        for batch in batches:
            for k_, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                if held is not None and k_ == key:
                    held = merge(held, from_text(text), k)
                    continue
                if held is not None:
                    out[key] = held
                key, held = k_, from_text(text)
            if len(out) > 10_000:
                yield rows(out)
                out = {}
        yield rows(out if held is None else out | {key: held})

    once = common.mapped(prints.select(group, "fingerprint"), partial, schema)
    return common.mapped(once.repartition(group).sortWithinPartitions(group), whole, schema)


def edit(text: str, following: str) -> str:
    """The last floor(n/2) code points replaced by the first as many (or all) of the following text."""
    half = len(text) // 2
    return text[: len(text) - half] + following[:half]


RESULT = "doc_id long, n_chars long, edited_sha256 string, fingerprint string, edited_fingerprint string, near_edited double, near_next double, held_by_edited double, n_distinct double"


def with_next(docs: DataFrame) -> DataFrame:
    """Rows dealt into ranges of doc_id and sorted in them (columns bucket, ghost, doc_id, text).

    Each range ends with a ghost: the first row of the range that follows, so that every row has its successor beside it
    and each text moves once. Range bounds are quantiles of the ids, as many as 8 for each shuffle partition.
    """
    spark = docs.sparkSession
    n = common.partitions(spark)
    buckets = 8 * n
    first = -(2**63)  # null ids come first
    rows = common.texts(docs).withColumn("at", F.coalesce("doc_id", F.lit(first)))
    ids = docs.select(F.coalesce(F.col("doc_id").cast("long"), F.lit(first)).alias("at"))
    cuts = ids.agg(F.percentile_approx("at", [i / buckets for i in range(1, buckets)], 20 * buckets).alias("q")).first()["q"] or []
    cuts = common.broadcast_of(spark, np.unique(np.array(cuts, np.int64)))

    @F.pandas_udf("int")
    def bucket_of(at: pd.Series) -> pd.Series:
        return pd.Series(np.searchsorted(cuts.value, at.to_numpy(), "right").astype(np.int32))

    heads = sorted((r["at"], r["bucket"]) for r in ids.groupBy(bucket_of("at").alias("bucket")).agg(F.min("at").alias("at")).collect())
    before = {at: heads[i - 1][1] for i, (at, _) in enumerate(heads)}  # the first of all follows the last
    table = common.broadcast_of(spark, before)

    def deal(batches):
        bounds, ghost_of = cuts.value, table.value
        for batch in batches:
            at = batch.column(2).to_numpy(zero_copy_only=False)
            bucket = np.searchsorted(bounds, at, "right").astype(np.int32)
            ghosts = [i for i, a in enumerate(at.tolist()) if a in ghost_of]
            where = pa.array(np.concatenate([np.arange(len(at)), np.array(ghosts, np.int64)]))
            out = pa.RecordBatch.from_arrays(batch.columns[:3], ["doc_id", "text", "at"]).take(where)
            to = np.concatenate([bucket, np.array([ghost_of[int(at[i])] for i in ghosts], np.int32)])
            # the head of all, as the last range's ghost, sorts behind it; others do so by their ids
            yield pa.RecordBatch.from_arrays([pa.array(to), pa.array(np.arange(len(to)) >= len(at)), *out.columns], ["bucket", "ghost", "doc_id", "text", "at"])

    dealt = common.mapped(rows, deal, "bucket int, ghost boolean, doc_id long, text string, at long").repartition(n, "bucket")
    return dealt.sortWithinPartitions("bucket", "ghost", "at", F.xxhash64("text")).select("bucket", "ghost", "doc_id", "text")


def edited_likeness(docs: DataFrame, k: int = K, width: int = WIDTH) -> DataFrame:
    """For each document its fingerprint, that of its edited text, and the likeness to that and to the next document.

    held_by_edited: the estimated share of its shingles that the edited text has; n_distinct: how many it has, estimated.

    Next: ascending doc_id (null first, equal ids by their texts' hash), after the last the first. Null and empty texts
    have the empty fingerprint, alike to each other only. An empty table gives no rows.
    """

    def run(batches):
        keyed = common.Keyed()
        columns: tuple[list, ...] = tuple([] for _ in NAMES)

        def rows(batches):
            for batch in batches:
                for row in zip(*(batch.column(i).to_pylist() for i in range(4)), strict=True):
                    yield row

        def flush():
            kinds = (pa.int64(), pa.int64(), *[pa.string()] * 3, *[pa.float64()] * 4)
            out = pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(columns, kinds, strict=True)], NAMES)
            for c in columns:
                c.clear()
            return out

        held = None
        for bucket, ghost, doc, text in chain(rows(batches), [(None, True, None, "")]):
            if held is None and ghost:
                continue
            own = sketch(text.encode(), keyed, k, width)
            if held is not None:
                of, held_text, held_own = held
                new = edit(held_text, text)
                changed = sketch(new.encode(), keyed, k, width)
                row = (of, len(held_text), hashlib.sha256(new.encode()).hexdigest(), to_text(held_own), to_text(changed), resemblance(held_own, changed, k), resemblance(held_own, own, k), containment(held_own, changed, k), distinct(held_own, k))
                for column, value in zip(columns, row, strict=True):
                    column.append(value)
                if len(columns[0]) >= 500:
                    yield flush()
            held = None if ghost else (doc, text, own)
        yield flush()

    return common.mapped(with_next(docs), run, RESULT)


NAMES = [c.split()[0] for c in RESULT.split(", ")]


def op10_bottom_k_fingerprints(spark: SparkSession, sf_dir: str) -> DataFrame:
    return edited_likeness(common.read(spark, sf_dir, "documents"))
