"""Closed forms: variances of the estimates, the privacy ratio, sizes."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..params import Params


def _moments(truth: DataFrame) -> DataFrame:
    return truth.agg(F.sum("f").alias("n"), F.sum(F.col("f") * F.col("f")).alias("f2"), F.count("*").alias("d"))


def _factor(p: Params) -> float:
    return (p.m / (p.m - 1)) ** 2


def one_hot_variance(f: Column, n: Column, f2: Column, p: Params) -> Column:
    """Of the one-hot estimate of an item of frequency f, exactly."""
    m, k = p.m, p.k
    noise = n * F.lit((p.c**2 - 1) / 4)
    return F.lit(_factor(p)) * (noise + (n - f) / m * F.lit(1 - 1 / m - 1 / k + 1 / (k * m)) + F.lit(1 / (k * m) - 1 / (k * m * m)) * (f2 - f * f))


def light_bound(f: Column, n: Column, light_f2: Column, theta: float, p: Params) -> Column:
    """Upper bound for a light item of the split path; n: phase-2 reports, light_f2: sum of squares of light frequencies."""
    return F.lit(_factor(p)) * (n * F.lit((p.c**2 - 1) / 4) + (n * F.lit(1 - theta) - f) / p.m + light_f2 / (p.k * p.m))


def hadamard_variance(n: Column, f2: Column, p: Params) -> Column:
    """Noise of one sign, and the collisions that the one-hot rows have."""
    return F.lit(_factor(p)) * (n * F.lit(p.hadamard_c**2) + f2 / (p.k * p.m))


def local_hash_variance(n: Column, f2: Column, p: Params) -> Column:
    q = 1 / p.g
    return n * F.lit(q * (1 - q) / (p.keep - q) ** 2) + f2 * F.lit(q * (1 - q) / p.k_pool)


def theory_variance(truth: DataFrame, p: Params, method: str) -> DataFrame:
    """One row: the mean variance over the domain (truth: item, f), which for unbiased estimates is the expected MSE."""
    joined = truth.crossJoin(F.broadcast(_moments(truth)))
    f, n, f2 = F.col("f"), F.col("n"), F.col("f2")
    value = {"onehot": one_hot_variance(f, n, f2, p), "hadamard": hadamard_variance(n, f2, p), "pooled_lh": local_hash_variance(n, f2, p)}[method]
    return joined.agg(F.avg(value).alias("variance"))


def split_theory(truth: DataFrame, boundary: float, p: Params) -> DataFrame:
    """One row for an exact split at the boundary: variance of light items (phase 2, scaled up) and of heavy ones (phase 1).

    total: their mean over the domain; bound: the published bound, for a light item of the mean light frequency, before scaling.
    """
    heavy = F.col("f") >= boundary
    sums = truth.agg(F.sum("f").alias("n"), F.sum(F.col("f") * F.col("f")).alias("f2"), F.sum(F.when(~heavy, F.col("f") * F.col("f")).otherwise(0)).alias("light_f2"), F.sum(F.when(heavy, 1).otherwise(0)).alias("n_heavy"), F.sum(F.when(heavy, F.col("f")).otherwise(0)).alias("heavy_n"), F.count("*").alias("d"))
    noise, size = (p.c**2 - 1) / 4, p.k * p.m
    light = F.lit(_factor(p)) * (F.col("n") * F.lit(noise / (1 - p.r)) + F.col("light_f2") / size)
    heavy_ = F.lit(_factor(p)) * (F.col("n") * F.lit(noise / p.r) + F.col("f2") / size)
    bound = light_bound((F.col("n") - F.col("heavy_n")) / (F.col("d") - F.col("n_heavy")), F.col("n"), F.col("light_f2"), p.theta, p)
    return sums.select(light.alias("light"), heavy_.alias("heavy"), ((light * (F.col("d") - F.col("n_heavy")) + heavy_ * F.col("n_heavy")) / F.col("d")).alias("total"), bound.alias("bound"))


def crossover(truth: DataFrame, boundary: float, p: Params) -> DataFrame:
    """One row gain, cost, split_wins: collisions saved on light items against the noise of fewer clients."""
    heavy = F.sum(F.when(F.col("f") >= boundary, F.col("f") * F.col("f")).otherwise(0))
    sums = truth.agg(heavy.alias("hf2"), F.sum("f").alias("n"))
    gain, cost = F.col("hf2") / (p.k * p.m), F.col("n") * F.lit(p.r / (1 - p.r) * (p.c**2 - 1) / 4)
    return sums.select(gain.alias("gain"), cost.alias("cost"), (gain > cost).alias("split_wins"))


def exact_light_variance(counts: list[int], heavy: int, f: int, p: Params) -> float:
    """Row-mean variance of a light item of frequency f among light counts and `heavy` dummy reports, before any bound."""
    m, k = p.m, p.k
    light, n = sum(counts), sum(counts) + heavy
    rest, squares = light - f, sum(x * x for x in counts) - f * f
    noise = n * (p.c**2 - 1) / 4
    return noise + rest * (1 / m - 1 / (m * m) - 1 / (k * m) + 1 / (k * m * m)) + squares * (1 / (k * m) - 1 / (k * m * m))


def privacy_ratio(spark: SparkSession, p: Params, inputs: DataFrame | None = None) -> DataFrame:
    """pair, max_ratio, bound: the largest ratio of chances of any output of m bits, by enumeration (small m).

    Reports: inputs (name, code: its +1 bits; the dummy's name is dummy), else a one-hot vector at each of two places, and the dummy.
    """
    q, half = p.q, math.exp(p.eps / 2)
    outputs = spark.range(2**p.m).withColumnRenamed("id", "o")
    if inputs is None:
        inputs = spark.createDataFrame([("dummy", 0), ("first", 1), ("second", 2)], "name string, code bigint")
    flips = F.bit_count(F.col("o").bitwiseXOR(F.col("code")))
    chance = outputs.crossJoin(F.broadcast(inputs)).select("o", "name", (F.pow(F.lit(q), flips) * F.pow(F.lit(1 - q), p.m - flips)).alias("pr"))
    a, b = chance.alias("a"), chance.alias("b")
    pairs = a.join(b, "o").where("a.name < b.name")
    pair = F.concat_ws("-", "a.name", "b.name")
    out = pairs.groupBy(pair.alias("pair")).agg(F.max(F.greatest(F.col("a.pr") / F.col("b.pr"), F.col("b.pr") / F.col("a.pr"))).alias("max_ratio"))
    return out.withColumn("bound", F.when(F.col("pair").startswith("dummy"), F.lit(half)).otherwise(F.lit(half * half)))


def sketch_bytes(p: Params, method: str) -> int:
    """State at 8 bytes a counter."""
    return 8 * {"split": p.k * p.m, "onehot": p.k * p.m, "hadamard": p.k * p.m, "pooled_lh": p.k_pool * p.g}[method]


def report_bytes(p: Params, method: str) -> int:
    """What a client sends: the vector or its part, and the row's number."""
    index = lambda n: max(1, math.ceil(math.log2(n) / 8))
    return {"split": -(-p.m // 8) + index(p.k), "onehot": -(-p.m // 8) + index(p.k), "hadamard": index(p.m * 2) + index(p.k), "pooled_lh": index(p.g) + index(p.k_pool)}[method]


METHODS = ("split", "onehot", "hadamard", "pooled_lh")


def space_table(spark: SparkSession, p: Params, truth: DataFrame) -> DataFrame:
    """method, sketch_bytes, report_bytes, all_report_bytes: sizes for the clients of truth (item, f); exact: a table of items and counts."""
    rows = [(name, sketch_bytes(p, name), report_bytes(p, name)) for name in METHODS]
    sizes = spark.createDataFrame(rows, "method string, sketch_bytes bigint, report_bytes bigint")
    count = truth.agg(F.coalesce(F.sum("f"), F.lit(0)).alias("n"), F.count("*").alias("d"))
    every = sizes.crossJoin(F.broadcast(count)).unionByName(count.select(F.lit("exact").alias("method"), (F.col("d") * 16).alias("sketch_bytes"), F.lit(8).cast("bigint").alias("report_bytes"), "n", "d"))
    return every.select("method", "sketch_bytes", "report_bytes", (F.col("report_bytes") * F.col("n")).alias("all_report_bytes"))


def countmin_violations(truth: DataFrame, estimates: DataFrame, eps: float) -> DataFrame:
    """One row n_items, violations, underestimates, share: items whose excess is beyond eps of the total."""
    joined = truth.join(estimates, "item").crossJoin(F.broadcast(truth.agg(F.sum("f").alias("n"))))
    over = F.col("f_hat") - F.col("f") > F.lit(eps) * F.col("n")
    return joined.agg(F.count("*").alias("n_items"), F.sum(over.cast("bigint")).alias("violations"), F.sum((F.col("f_hat") < F.col("f")).cast("bigint")).alias("underestimates"), F.avg(over.cast("double")).alias("share"))


def empirical_ratio(counts: DataFrame) -> DataFrame:
    """Audit: per output bit pattern counts (path, out, n) to the ratio of shares of the two paths, one row each pattern."""
    total = counts.groupBy("path").agg(F.sum("n").alias("t"))
    shares = counts.join(F.broadcast(total), "path").select("path", "out", (F.col("n") / F.col("t")).alias("share"))
    return shares.groupBy("out").agg((F.max("share") / F.min("share")).alias("ratio"), F.count("*").alias("paths"))


def audit(clients: DataFrame, p: Params) -> DataFrame:
    """paths, max_ratio, bound: what an observer of one-row reports (small m) sees of a client's path.

    Clients whose key is even send as light items, all others the dummy report; what they send is counted by its bits.
    With enough clients the ratio of the two paths' shares stays about within e^(eps/2).
    """
    from ..operators import reports

    marked = clients.withColumn("heavy", F.col("key") % 2 == 1)
    bits = reports.one_hot_bits(marked, p).groupBy("rid").agg(F.sum(F.expr("shiftleft(1, cast(b as int)) * cast(plus as int)")).alias("out"))
    sent = bits.join(marked.select("rid", F.when(F.col("heavy"), "heavy").otherwise("light").alias("path")), "rid")
    ratios = empirical_ratio(sent.groupBy("path", "out").agg(F.count("*").alias("n"))).where("paths = 2")
    return ratios.agg(F.lit("heavy-light").alias("paths"), F.max("ratio").alias("max_ratio")).withColumn("bound", F.lit(math.exp(p.eps / 2)))


#: Kinds of pairs of records, seen from the cells of one light item: of the same other light item, of different ones, with a dummy.
PAIRS = ("same_other", "different", "dummy")


def pair_covariance(p: Params, pair: str, k: int | None = None) -> float:
    """Covariance of two records' shares in the row mean of a third item, both records in one row given (else by chance 1/k)."""
    inside = 1 / p.m - 1 / p.m**2 if pair == "same_other" else 0.0
    return inside if k is None else inside / k


def covariance_table(spark: SparkSession, settings: list[Params]) -> DataFrame:
    """m, k, pair, covariance of records in the same row."""
    rows = [(p.m, p.k, pair, pair_covariance(p, pair)) for p in settings for pair in PAIRS]
    return spark.createDataFrame(rows, "m int, k int, pair string, covariance double")


def simulated_covariance(p: Params, pair: str, trials: int = 200_000, seed: int = 5) -> float:
    """pair_covariance by drawing hash places and flips."""
    import numpy as np

    random = np.random.default_rng(seed)
    probe, a = random.integers(0, p.m, trials), random.integers(0, p.m, trials)
    b = a if pair == "same_other" else random.integers(0, p.m, trials)
    value = []
    for place, dummy in ((a, False), (b, pair == "dummy")):
        plus = np.zeros(trials, bool) if dummy else place == probe
        plus = plus ^ (random.random(trials) < p.q)
        value.append((p.c * np.where(plus, 1, -1) + 1) / 2)
    return float(np.cov(value[0], value[1])[0, 1])
