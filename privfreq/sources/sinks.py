"""States and results at rest."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def materialize(df: DataFrame, name: str) -> DataFrame:
    """Write df in the folder that spark.checkpoint.dir names and read it back: one run, whoever reads it and is lost.

    In local mode, where no folder is named, a temporary one serves.
    """
    spark = df.sparkSession
    folder = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not folder:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("spark.checkpoint.dir must name a folder that driver and executors share")
        folder = f"file://{tempfile.mkdtemp(prefix='privfreq-')}"
        spark.sparkContext.setCheckpointDir(folder)
    path = f"{folder.rstrip('/')}/{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def save_state(state: DataFrame, path: str, run_id: str, phase: int) -> None:
    """Partitions by run and phase, so that a query reads its own files only."""
    marked = state.withColumns({"run_id": F.lit(run_id), "phase": F.lit(phase)})
    marked.write.mode("append").partitionBy("run_id", "phase").parquet(path)


def load_state(spark: SparkSession, path: str, run_id: str, phase: int) -> DataFrame:
    return spark.read.parquet(path).where((F.col("run_id") == run_id) & (F.col("phase") == phase)).drop("run_id", "phase")


def save_table(df: DataFrame, name: str, key: str, buckets: int = 64) -> None:
    """A bucketed table: later joins by key need no shuffle of it."""
    df.write.mode("overwrite").bucketBy(buckets, key).sortBy(key).saveAsTable(name)


def pack_bits(bits: DataFrame, m: int) -> DataFrame:
    """rid, j, bits BINARY of a report's m bits (from rid, j, b, plus), first bit first."""
    text = F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("b", F.col("plus").cast("int").cast("string").alias("v")))), lambda x: x["v"]), "")
    size = -(-m // 8)
    byte = lambda i: F.lpad(F.conv(F.substr("t", i * 8 + 1, F.lit(8)), 2, 16), 2, "0")
    rows = bits.groupBy("rid", "j").agg(F.rpad(text, size * 8, "0").alias("t"))
    return rows.select("rid", "j", F.unhex(F.array_join(F.transform(F.sequence(F.lit(0), F.lit(size - 1)), byte), "")).alias("bits"))


def unpack_bits(packed: DataFrame, m: int) -> DataFrame:
    """rid, j, b, plus of packed reports."""
    digits = F.conv(F.substr(F.hex("bits"), F.floor(F.col("b") / 8).cast("int") * 2 + 1, F.lit(2)), 16, 10).cast("int")
    rows = packed.select("rid", "j", "bits", F.explode(F.sequence(F.lit(0), F.lit(m - 1))).alias("b"))
    return rows.select("rid", "j", "b", (F.floor(digits / F.pow(F.lit(2), 7 - F.col("b") % 8)) % 2 == 1).alias("plus"))


def sink(df: DataFrame, kind: str = "noop") -> None:
    """noop: run everything, keep nothing (for timing)."""
    df.write.format(kind).mode("overwrite").save()
