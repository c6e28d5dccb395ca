"""Relational steps around the methods: versions of models in force, segments, windows over counts, differences."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def attach_version(events: DataFrame, versions: DataFrame) -> DataFrame:
    """event_id, version: the version with valid_from <= ts < valid_to. Versions are a published list, broadcast."""
    on = (F.col("ts") >= F.col("valid_from")) & (F.col("ts") < F.col("valid_to"))
    return events.join(F.broadcast(versions), on).select("event_id", "version")


def asof_version(events: DataFrame, versions: DataFrame) -> DataFrame:
    """event_id, version: the last version at or before the event; none before the first.

    The list gets the end of each validity from its successor and is joined by interval, so events are not sorted.
    """
    ends = versions.select("version", "valid_from", F.lead("valid_from").over(Window.orderBy("valid_from")).alias("valid_to"))
    on = (F.col("ts") >= F.col("valid_from")) & (F.col("valid_to").isNull() | (F.col("ts") < F.col("valid_to")))
    return events.join(F.broadcast(ends), on, "left").select("event_id", "version")


def binned_range_join(values: DataFrame, ranges: DataFrame, value: str, width: float) -> DataFrame:
    """values joined with ranges (lo, hi, label) where lo <= value < hi, by an equal join on coarse bins."""
    bins = ranges.withColumn("_bin", F.explode(F.sequence(F.floor(F.col("lo") / width), F.floor(F.col("hi") / width))))
    return values.withColumn("_bin", F.floor(F.col(value) / width)).join(bins, "_bin").where((F.col(value) >= F.col("lo")) & (F.col(value) < F.col("hi"))).drop("_bin")


def unseen_items(phased: DataFrame) -> DataFrame:
    """item: seen in phase 2 only."""
    items = lambda n: phased.where(F.col("phase") == n).select("item").distinct()
    return items(2).join(items(1), "item", "left_anti")


def restrict_candidates(clients: DataFrame, candidates: DataFrame) -> DataFrame:
    return clients.join(F.broadcast(candidates.select("item")), "item", "left_semi")


def domain_diff(a: DataFrame, b: DataFrame) -> DataFrame:
    """side, n: items of one domain only, and of both."""
    x, y = a.select("item").distinct(), b.select("item").distinct()
    count = lambda df, side: df.agg(F.count("*").alias("n")).select(F.lit(side).alias("side"), "n")
    return count(x.exceptAll(y), "left").unionByName(count(y.exceptAll(x), "right")).unionByName(count(x.intersect(y), "both"))


def domain_stats(clients: DataFrame, approx: bool = False) -> DataFrame:
    """n, d, f_max: records, distinct items, the largest frequency."""
    if approx:
        return clients.agg(F.count("*").alias("n"), F.approx_count_distinct("item").alias("d"))
    return clients.groupBy("item").agg(F.count("*").alias("f")).agg(F.sum("f").alias("n"), F.count("*").alias("d"), F.max("f").alias("f_max"))


def rank_items(truth: DataFrame, n: int) -> DataFrame:
    """item, f and its ranks among the n largest (ties by item)."""
    top = truth.orderBy(F.desc("f"), "item").limit(n)
    w = Window.orderBy(F.desc("f"))
    whole = Window.orderBy(F.desc("f"), "item")
    return top.select("item", "f", F.rank().over(w).alias("rank"), F.dense_rank().over(w).alias("dense_rank"), F.row_number().over(whole).alias("row_number"), F.ntile(4).over(whole).alias("quarter"), F.round(F.percent_rank().over(w), 6).alias("percent_rank"), F.round(F.cume_dist().over(w), 6).alias("cume_dist"))


def top_by_group(counts: DataFrame, group: str, n: int) -> DataFrame:
    w = Window.partitionBy(group).orderBy(F.desc("f"), "item")
    return counts.withColumn("rn", F.row_number().over(w)).where(F.col("rn") <= n)


def moving_count(counts: DataFrame, days: int = 7) -> DataFrame:
    """item, day, f, moving: the item's count over the last days (counts: item, day as a number, f)."""
    w = Window.partitionBy("item").orderBy("day").rangeBetween(-(days - 1), 0)
    return counts.select("item", "day", "f", F.sum("f").over(w).alias("moving"))


def segment_clients(orders: DataFrame, customer: DataFrame, nation: DataFrame, region: DataFrame) -> DataFrame:
    """segment, region, item (order priority), rid of every order, through its customer's dimensions."""
    dims = customer.join(F.broadcast(nation), F.col("c_nationkey") == F.col("n_nationkey")).join(F.broadcast(region), F.col("n_regionkey") == F.col("r_regionkey"))
    joined = orders.join(dims, F.col("o_custkey") == F.col("c_custkey"))
    return joined.select(F.col("o_orderkey").cast("string").alias("rid"), F.col("c_mktsegment").alias("segment"), F.col("r_name").alias("region"), F.col("o_orderpriority").alias("item"))
