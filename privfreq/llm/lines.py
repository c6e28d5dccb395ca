"""Line dedup by overlapping three-line windows: later occurrences of a repeated window lose the lines it covers."""

from __future__ import annotations

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common

WINDOW = 3
#: Documents with covered lines that a broadcast may hold (with four times as many windows); more are joined by shuffle.
BROADCAST_ROWS = 500_000
#: Windows that a task holds before it gives them out.
MOST_WINDOWS = 50_000


def solid_lines(text: str) -> tuple[list[str], list[int]]:
    """All lines, and the places of those that have more than spaces."""
    lines = text.split("\n")
    return lines, [i for i, x in enumerate(lines) if x.strip(" ")]


def repeated_windows(rows: DataFrame, window: int = WINDOW) -> DataFrame:
    """d, k, first: where windows begin (number of the solid line) that occurred earlier in the corpus (rows: d, k, text).

    A window's identity is 128 bits of a hash of its lines. Counting combines before its shuffle, and the join back to the
    occurrences is one that Spark splits, so a window that a third of all rows hold goes to no single task. Windows are cut
    with one line's hash at a time, so long texts cost as much a line as short ones.
    """

    def cut(batches):
        import xxhash

        def rows(held):
            first = np.concatenate([np.arange(len(h) // 16, dtype=np.int32) for _, _, h in held]) if held else np.empty(0, np.int32)
            sizes = [len(h) // 16 for _, _, h in held]
            hashes = np.frombuffer(b"".join(h for _, _, h in held), ">i8").astype(np.int64).reshape(-1, 2)
            d, k = (np.repeat(np.array([x[i] for x in held], np.int64), sizes) for i in (0, 1))
            return pa.RecordBatch.from_arrays([*map(pa.array, (d, k, first, hashes[:, 0], hashes[:, 1]))], ["d", "k", "first", "h1", "h2"])

        held, n = [], 0
        for batch in batches:
            ids, keys, column = batch.column(0).to_pylist(), batch.column(1).to_pylist(), batch.column(2)
            for i in range(len(batch)):
                lines, solid = solid_lines(column[i].as_py())
                digests = [xxhash.xxh3_128_digest(lines[i].strip(" ").encode()) for i in solid]
                windows = [xxhash.xxh3_128_digest(b"".join(digests[j : j + window])) for j in range(len(solid) - window + 1)]
                if windows:
                    held.append((ids[i], keys[i], b"".join(windows)))
                    n += len(windows)
                if n > MOST_WINDOWS:
                    yield rows(held)
                    held, n = [], 0
        yield rows(held)

    seen = common.materialize(common.mapped(rows.select("d", "k", "text"), cut, "d long, k long, first int, h1 long, h2 long"), "windows")
    where = F.struct("d", "k", "first")
    origin = seen.groupBy("h1", "h2").agg(F.min(where).alias("origin"), F.max(where).alias("last")).where("origin <> last").select("h1", "h2", "origin")
    origin = common.materialize(origin, "repeated")
    return seen.join(origin, ["h1", "h2"]).where(where != F.col("origin")).select("d", "k", "first")


def without_repeats(docs: DataFrame, window: int = WINDOW) -> DataFrame:
    """All columns of docs, text without covered lines, and n_lines, lines_removed.

    Lines end at newlines and are compared without outer spaces; blank lines are passed over and stay. Of a repeated
    window the occurrence of the smallest (doc_id, place) stays whole, others lose all lines they cover, overlaps merged.
    Texts of fewer than three such lines are unchanged; null texts stay null. Rows of equal doc_id and text are one
    occurrence. Columns of docs named like the new ones are replaced.
    """
    smallest = F.lit(-(2**63))
    text = F.coalesce("text", F.lit(""))
    keyed = docs.withColumns({"_d": F.coalesce(F.col("doc_id").cast("long"), smallest), "_k": F.xxhash64(text)})
    rows = keyed.select(F.col("_d").alias("d"), F.col("_k").alias("k"), text.alias("text"))
    cover = repeated_windows(rows, window).groupBy("d", "k").agg(F.collect_set("first").alias("_first"))
    cover = common.materialize(cover.withColumnsRenamed({"d": "_d", "k": "_k"}), "covered")
    size = cover.agg(F.count("*").alias("rows"), F.coalesce(F.sum(F.size("_first")), F.lit(0)).alias("places")).first()
    small = size["rows"] <= BROADCAST_ROWS and size["places"] <= 4 * BROADCAST_ROWS
    joined = keyed.join(F.broadcast(cover) if small else cover, ["_d", "_k"], "left")

    @F.pandas_udf("text string, lines_removed int")
    def rewrite(texts: pd.Series, firsts: pd.Series) -> pd.DataFrame:
        common.claim(__name__)
        out = []
        for text, first in zip(texts, firsts, strict=True):
            if text is None or first is None:
                out.append((None, 0))
            else:
                lines, solid = solid_lines(text)
                gone = {solid[f + i] for f in first for i in range(window)}
                out.append(("\n".join(x for i, x in enumerate(lines) if i not in gone), len(gone)))
        return pd.DataFrame(out, columns=["text", "lines_removed"])

    # only the texts that lose lines go to Python and back
    covered = F.col("_first").isNotNull() & F.col("text").isNotNull()
    # not deterministic by name only: else a filter on the new columns repeats the call below itself, in a worker of its own
    done = joined.withColumn("_new", rewrite.asNondeterministic()(F.when(covered, F.col("text")), "_first"))
    done = done.withColumns(
        {
            "n_lines": F.coalesce(F.length("text") - F.length(F.replace("text", F.lit("\n"), F.lit(""))) + 1, F.lit(1)).cast("int"),
            "lines_removed": F.col("_new.lines_removed"),
            "text": F.when(covered, F.col("_new.text")).otherwise(F.col("text")),
        }
    )
    return done.drop("_d", "_k", "_first", "_new")


def op8_three_line_windows(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = without_repeats(common.read(spark, sf_dir, "documents"))
    return out.select("doc_id", "n_lines", "lines_removed", F.length("text").cast("long").alias("kept_chars"), F.md5("text").alias("kept_md5"))


OP8_SQL = """
WITH lines AS (
  SELECT doc_id, unnest(generate_series(0, len(w) - 1)) AS place, unnest(w) AS line FROM (SELECT doc_id, string_split(coalesce(text, ''), chr(10)) AS w FROM documents)
), solid AS (
  SELECT doc_id, place, row_number() OVER (PARTITION BY doc_id ORDER BY place) AS n, trim(line) AS line FROM lines WHERE trim(line) <> ''
), windows AS (
  SELECT a.doc_id, a.n, a.line AS l1, b.line AS l2, c.line AS l3
  FROM solid a JOIN solid b ON a.doc_id = b.doc_id AND b.n = a.n + 1 JOIN solid c ON a.doc_id = c.doc_id AND c.n = a.n + 2
), ranked AS (
  SELECT *, row_number() OVER (PARTITION BY l1, l2, l3 ORDER BY doc_id, n) AS r FROM windows
), covered AS (
  SELECT DISTINCT doc_id, n + d AS n FROM ranked, (VALUES (0), (1), (2)) v(d) WHERE r > 1
), marked AS (
  SELECT l.doc_id, l.place, l.line, c.n IS NOT NULL AS gone
  FROM lines l LEFT JOIN solid s ON l.doc_id = s.doc_id AND l.place = s.place LEFT JOIN covered c ON s.doc_id = c.doc_id AND s.n = c.n
), kept AS (
  SELECT doc_id, CAST(count(*) AS INTEGER) AS n_lines, CAST(sum(CASE WHEN gone THEN 1 ELSE 0 END) AS INTEGER) AS lines_removed,
    coalesce(string_agg(line, chr(10) ORDER BY place) FILTER (WHERE NOT gone), '') AS text
  FROM marked GROUP BY doc_id
)
SELECT doc_id, n_lines, lines_removed, length(text) AS kept_chars, md5(text) AS kept_md5 FROM kept
"""
