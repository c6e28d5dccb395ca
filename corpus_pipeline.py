"""The corpus pipeline: quality, line dedup, near-duplicates, decontamination, packing.

Every stage takes (spark, docs, sf_dir), works on all that the one before kept, and returns the columns of documents;
the last returns the packed pieces. A stage's rows are written as Parquet and read again as the next one's docs.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from privfreq.llm import common, decontaminate, lines, near, packing, quality

COLUMNS = ("doc_id", "text", "lang", "source", "n_chars")


#: Ids of documents to drop that a broadcast may hold; more of them are joined by shuffle.
BROADCAST_IDS = 2_000_000


def _keyed(docs: DataFrame) -> DataFrame:
    return docs.select(*COLUMNS)


def _without(docs: DataFrame, ids: DataFrame) -> DataFrame:
    """The documents whose doc_id is not listed; rows without one stay."""
    ids = common.materialize(ids.where("doc_id is not null").select("doc_id").distinct(), "dropped")
    side = F.broadcast(ids) if ids.count() <= BROADCAST_IDS else ids
    return _keyed(docs).join(side, "doc_id", "left_anti").select(*COLUMNS)


def quality_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the ranking puts below its cut go. Rows without doc_id, which no label can name, stay."""
    scored = quality.score(docs, common.read(spark, sf_dir, "labels"))
    return _without(docs, scored.where(F.col("score") < quality.BAR))


def line_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Later occurrences of repeated three-line windows go; a document of which nothing is left goes."""
    out = lines.without_repeats(_keyed(docs))
    some = (F.col("lines_removed") == 0) | (F.trim(F.regexp_replace("text", r"\s+", " ")) != "")
    changed = F.when(F.col("lines_removed") > 0, F.length("text").cast("long")).otherwise(F.col("n_chars"))
    return out.where(some).withColumn("n_chars", changed).select(*COLUMNS)


def near_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of near-duplicates (five-word shingles, similarity of 0.8) the document of the smallest id stays."""
    return _without(docs, near.near_duplicates(docs).where("not kept"))


def benchmark_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents with a passage that aligns with a test item go."""
    return _without(docs, decontaminate.leaks(docs, common.read(spark, sf_dir, "benchmark")))


def packing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return packing.pack_documents(docs)


STAGES = [
    ("quality classifier", quality_stage),
    ("line dedup", line_stage),
    ("near-duplicates", near_stage),
    ("benchmark decontamination", benchmark_stage),
    ("best-fit packing", packing_stage),
]
#: Learnt scores, signatures, alignments and tokens are not SQL; tests compare with brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = common.read(spark, sf_dir, "documents")
    for name, stage in STAGES:
        before = docs
        with common.temporary() as made:  # a stage's own tables go as soon as its rows are written
            docs = common.materialize(stage(spark, before, sf_dir), name.replace(" ", "-"))
            made.remove(docs)
        common.discard(before)
    return docs
