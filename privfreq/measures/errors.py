"""Accuracy measures over the whole domain."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def score(truth: DataFrame, estimates: DataFrame) -> DataFrame:
    """item, f, f_hat, e2 (and path, if there is one); items that were not estimated count as 0."""
    extra = [c for c in ("path",) if c in estimates.columns]
    joined = truth.join(estimates, "item", "left").withColumn("f_hat", F.coalesce("f_hat", F.lit(0.0)))
    return joined.select("item", "f", "f_hat", F.pow(F.col("f_hat") - F.col("f"), 2).alias("e2"), *extra)


def mse(truth: DataFrame, estimates: DataFrame) -> DataFrame:
    return score(truth, estimates).agg(F.avg("e2").alias("mse"), F.sum("e2").alias("sse"), F.count("*").alias("n_items"))


def sse_by_path(truth: DataFrame, estimates: DataFrame) -> DataFrame:
    return score(truth, estimates).groupBy("path").agg(F.sum("e2").alias("sse"), F.avg("e2").alias("mse"), F.count("*").alias("n_items"))


def sse_curve(truth: DataFrame, estimates: DataFrame, steps: int = 100) -> DataFrame:
    """f, n_items, sse (and step): the running sum of squared errors over items in falling true frequency, at even steps.

    Ranks and sums are made in a bounded number of classes: frequencies first, so the one-partition running sum is over
    distinct frequencies (at most a root of twice the number of clients).
    """
    by_f = score(truth, estimates).groupBy("f").agg(F.count("*").alias("n"), F.sum("e2").alias("s"))
    down = Window.orderBy(F.desc("f")).rowsBetween(Window.unboundedPreceding, Window.currentRow)
    sums = by_f.select("f", F.sum("n").over(down).alias("n_items"), F.sum("s").over(down).alias("sse"))
    if steps is None:
        return sums
    # the last frequency within each of the even steps of the domain
    of = F.ceil(F.col("n_items") * steps / F.max("n_items").over(Window.partitionBy()))
    return sums.withColumn("step", of.cast("int")).groupBy("step").agg(F.max_by(F.struct("f", "n_items", "sse"), "n_items").alias("x")).select("step", "x.*").orderBy("step")


def error_quantiles(scored: DataFrame, levels=(0.5, 0.9, 0.99)) -> DataFrame:
    return scored.agg(*[F.percentile("e2", q).alias(f"q{round(q * 100)}") for q in levels])


def method_errors(truth: DataFrame, estimates: dict[str, DataFrame]) -> DataFrame:
    """method, mse, sse, n_items; with the answer 0 for everything beside the methods."""
    rows = [mse(truth, e).select(F.lit(name).alias("method"), "mse", "sse", "n_items") for name, e in estimates.items()]
    zero = truth.agg(F.avg(F.pow("f", F.lit(2.0))).alias("mse"), F.sum(F.pow("f", F.lit(2.0))).alias("sse"), F.count("*").alias("n_items"))
    return reduce(DataFrame.unionByName, [*rows, zero.select(F.lit("all_zero").alias("method"), "mse", "sse", "n_items")])


def error_report(errors: DataFrame, *by: str, kind: str = "rollup") -> DataFrame:
    """Mean squared errors at every level of `by` (rollup), for every combination (cube) or for each column alone (sets)."""
    columns = [F.col(c) for c in by]
    grouped = {"rollup": errors.rollup, "cube": errors.cube, "sets": lambda *c: errors.groupingSets([[x] for x in c], *c)}[kind](*columns)
    return grouped.agg(F.sum("e2").alias("sse"), F.avg("e2").alias("mse"), F.count("*").alias("n_items"))


def pivot_methods(errors: DataFrame, row: str, methods: list[str]) -> DataFrame:
    return errors.groupBy(row).pivot("method", methods).agg(F.first("mse"))


def unpivot_errors(table: DataFrame, row: str) -> DataFrame:
    return table.unpivot([row], [c for c in table.columns if c != row], "method", "mse")


def diff_estimates(a: DataFrame, b: DataFrame) -> DataFrame:
    """item, side: items that only one of two estimates has, by a full join."""
    joined = a.select("item", F.lit(1).alias("_a")).join(b.select("item", F.lit(1).alias("_b")), "item", "full")
    return joined.where("_a is null or _b is null").select("item", F.when(F.col("_a").isNull(), "right").otherwise("left").alias("side"))
