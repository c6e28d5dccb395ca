"""Sketch states (integers only, so that they merge in any order) and the estimates read from them."""

from __future__ import annotations

from dataclasses import dataclass
from functools import reduce

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import bucket, sign
from ..params import Params
from ..plans.gather import butterfly, dense, gather
from . import reports


def one_hot_state(bits: DataFrame) -> DataFrame:
    """j, b, plus (bits that came as +1), reports (of row j), from spelled-out reports."""
    return bits.groupBy("j", "b").agg(F.sum(F.col("plus").cast("bigint")).alias("plus"), F.count("*").alias("reports"))


def hadamard_state(rows: DataFrame) -> DataFrame:
    return rows.groupBy("j", "l").agg(F.sum("sign").cast("bigint").alias("signed_sum"), F.count("*").alias("reports"))


def local_hash_state(rows: DataFrame) -> DataFrame:
    return rows.groupBy("j", "y").agg(F.count("*").alias("cnt"))


def merge_states(*states: DataFrame) -> DataFrame:
    """The state of all reports, from states of parts of them: days, shards or phases."""
    keys = [c for c in states[0].columns if c in ("j", "b", "l", "y")]
    return reduce(DataFrame.unionByName, states).groupBy(*keys).agg(*[F.sum(c).alias(c) for c in states[0].columns if c not in keys])


def cells(state: DataFrame, p: Params) -> DataFrame:
    """j, b, cell: the debiased, scaled sketch."""
    plus, n = F.col("plus"), F.col("reports")
    return state.select("j", "b", (F.lit(p.k / 2) * (F.lit(p.c) * (2 * plus - n) + n)).alias("cell"))


def state_as_array(state: DataFrame) -> DataFrame:
    """j, plus as an array in the order of b."""
    return state.groupBy("j").agg(F.transform(F.array_sort(F.collect_list(F.struct("b", "plus"))), lambda x: x["plus"]).alias("plus"))


def probes(items: DataFrame, p: Params, n: int | None = None, width: int | None = None) -> DataFrame:
    """item, j, b: where each row of the sketch keeps the item."""
    rows = items.select("item", "key", F.explode(F.sequence(F.lit(0), F.lit((n or p.k) - 1))).alias("j"))
    return rows.select("item", "j", bucket(F.col("key"), F.col("j"), p, n, width).cast("int").alias("b"))


def _reports(state: DataFrame) -> DataFrame:
    """One row: how many reports the state has."""
    return state.groupBy("j").agg(F.max("reports").alias("n")).agg(F.coalesce(F.sum("n"), F.lit(0)).alias("n"))


@dataclass(frozen=True)
class Cells:
    """A collected one-hot state: 2 plus - reports of every cell, all +1 bits, all reports. k*m numbers, whatever the data."""

    v: np.ndarray
    plus: int
    n: int


def collected(state: DataFrame | Cells, p: Params) -> Cells:
    """One run of the state, for everything that is read from it."""
    if isinstance(state, Cells):
        return state
    rows = state.toPandas()
    rows["v"] = 2 * rows["plus"] - rows["reports"]
    return Cells(dense(rows, p.k, p.m, "b", "v"), int(rows["plus"].sum()), int(rows.groupby("j")["reports"].max().sum()))


def row_sums(items: DataFrame, state: DataFrame, p: Params) -> DataFrame:
    """item, s1: sum over the item's cells of (2 plus - reports); integers, so any order of adding gives the same.

    The state has k*m rows, whatever the data: that side is broadcast.
    """
    small = F.broadcast(state.select("j", "b", (2 * F.col("plus") - F.col("reports")).alias("v")))
    return probes(items, p).join(small, ["j", "b"], "left").groupBy("item").agg(F.coalesce(F.sum("v"), F.lit(0)).alias("s1"))


def one_hot_value(s1: Column, n: Column, mass: Column, p: Params) -> Column:
    """(m/(m-1)) (row mean - mass/m), with the row mean written by integers."""
    return F.lit(p.m / (p.m - 1)) * ((F.lit(p.c) * s1 + n) / 2 - mass / p.m) + 0.0


def one_hot_estimate(items: DataFrame, state: DataFrame | Cells, p: Params, how: str = "gather") -> DataFrame:
    """item, f_hat for items (item, key). gather: the cells go to the items; join: by equal join, for checks."""
    if how == "join":
        with_n = row_sums(items, state, p).crossJoin(F.broadcast(_reports(state)))
    else:
        c = collected(state, p)
        with_n = gather(items.select("item", "key"), c.v, p.hashes(), "s1").withColumn("n", F.lit(c.n).cast("bigint"))
    return with_n.select("item", one_hot_value(F.col("s1"), F.col("n"), F.col("n"), p).alias("f_hat"))


def hadamard_inverse(state: DataFrame, p: Params) -> DataFrame:
    """j, b, s: each row's inverse transform, as k*m integers (SQL form; see plans.kernels for the butterfly)."""
    targets = state.select("j", "l", "signed_sum", F.explode(F.sequence(F.lit(0), F.lit(p.m - 1))).alias("b"))
    turn = 1 - 2 * (F.bit_count(F.col("l").bitwiseAND(F.col("b"))) % 2)
    return targets.groupBy("j", "b").agg(F.sum(F.col("signed_sum") * turn).alias("s"))


def hadamard_cells(state: DataFrame, p: Params) -> tuple[np.ndarray, int]:
    """The inverse transform of all rows by m log m steps, and the number of reports."""
    rows = state.toPandas()
    return butterfly(dense(rows, p.k, p.m, "l", "signed_sum")), int(rows["reports"].sum())


def hadamard_value(s: Column, n: Column, p: Params) -> Column:
    return F.lit(p.m / (p.m - 1)) * (F.lit(p.hadamard_c) * s - n / p.m)


def hadamard_estimate(items: DataFrame, state: DataFrame, p: Params, inverse: DataFrame | None = None, how: str = "join") -> DataFrame:
    """item, f_hat. join: with the transform by rows (k*m*m of them, so for small sketches); gather: see hadamard_cells."""
    if how == "gather":
        table, n = hadamard_cells(state, p)
        sums = gather(items.select("item", "key"), table, p.hashes()).withColumn("n", F.lit(n).cast("bigint"))
    else:
        table = hadamard_inverse(state, p) if inverse is None else inverse
        joined = probes(items, p).join(F.broadcast(table), ["j", "b"], "left").groupBy("item").agg(F.coalesce(F.sum("s"), F.lit(0)).alias("s"))
        sums = joined.crossJoin(F.broadcast(state.agg(F.sum("reports").alias("n"))))
    return sums.select("item", (hadamard_value(F.col("s"), F.col("n"), p) + 0.0).alias("f_hat"))


def local_hash_value(support: Column, n: Column, p: Params) -> Column:
    return (support - n / p.g) / F.lit(p.keep - 1 / p.g) + 0.0


def local_hash_estimate(items: DataFrame, state: DataFrame, p: Params, table: DataFrame | None = None) -> DataFrame:
    """item, f_hat: the k_pool*g counts go to the items, which read k_pool of them.

    table: the hash of every item under every function, where it was made beforehand (precompute).
    """
    if table is None:
        rows = state.toPandas()
        counts = dense(rows, p.k_pool, p.g, "y", "cnt")
        found, n = gather(items.select("item", "key"), counts, p.hashes(p.k_pool), "support"), F.lit(int(counts.sum())).cast("bigint")
    else:
        places = table.withColumnRenamed("b", "y").join(F.broadcast(state), ["j", "y"], "left")
        sums = places.groupBy("item").agg(F.coalesce(F.sum("cnt"), F.lit(0)).alias("support"))
        found, n = sums.crossJoin(F.broadcast(state.agg(F.sum("cnt").alias("n")))), F.col("n")
    return found.select("item", local_hash_value(F.col("support"), n, p).alias("f_hat"))


def precomputed_hashes(domain: DataFrame, p: Params) -> DataFrame:
    """item, j, b under all k_pool functions: k_pool times the domain, for small domains."""
    return probes(domain, p, p.k_pool, p.g)


def own_hash_estimate(domain: DataFrame, rows: DataFrame, p: Params) -> DataFrame:
    """Every report is tested against every item: for small domains."""
    hit = ((F.col("a") * F.col("key") + F.col("b")) % 2147483647 % p.g == F.col("y")).cast("bigint")
    found = rows.crossJoin(F.broadcast(domain.select("item", "key"))).groupBy("item").agg(F.sum(hit).alias("support"), F.count("*").alias("n"))
    return found.select("item", local_hash_value(F.col("support"), F.col("n"), p).alias("f_hat"))


def bit_vector_estimate(bits: DataFrame, p: Params, kind: str = "symmetric") -> DataFrame:
    keep, set_ = reports.bit_vector_rates(p, kind)
    sums = bits.groupBy("item").agg(F.sum(F.col("plus").cast("bigint")).alias("s"), F.count("*").alias("n"))
    return sums.select("item", ((F.col("s") - F.col("n") * F.lit(set_)) / F.lit(keep - set_) + 0.0).alias("f_hat"))


def bloom_estimate(domain: DataFrame, bits: DataFrame, p: Params, hashes: int = 2) -> DataFrame:
    """item, f_hat: the least of the item's debiased bit counts; items that share bits inflate each other."""
    flip = 1 / (2.718281828459045 ** (p.eps / (2 * hashes)) + 1)
    state = bits.groupBy("b").agg(F.sum(F.col("plus").cast("bigint")).alias("s"), F.count("*").alias("n"))
    value = (F.col("s") - F.col("n") * F.lit(flip)) / F.lit(1 - 2 * flip)
    return probes(domain, p, hashes).join(F.broadcast(state), "b").groupBy("item").agg((F.min(value) + 0.0).alias("f_hat"))


# Sketches without privacy.


def countmin_shape(eps: float, delta: float) -> tuple[int, int]:
    """Width and depth that keep the excess within eps of the total with chance 1 - delta."""
    import math

    return math.ceil(math.e / eps), math.ceil(math.log(1 / delta))


def count_state(clients: DataFrame, p: Params, signed: bool = False) -> DataFrame:
    """j, b, cnt: every client adds 1 (or its item's sign) in every row. Counted by item first: N clients, D items."""
    counts = clients.groupBy("item", "key").agg(F.count("*").alias("f"))
    rows = counts.select("key", "f", F.explode(F.sequence(F.lit(0), F.lit(p.k - 1))).alias("j"))
    value = F.col("f") * sign(F.col("key"), F.col("j"), p) if signed else F.col("f")
    return rows.select("j", bucket(F.col("key"), F.col("j"), p).cast("int").alias("b"), value.alias("v")).groupBy("j", "b").agg(F.sum("v").alias("cnt"))


def _counts(state: DataFrame, p: Params) -> np.ndarray:
    return dense(state.toPandas(), p.k, p.m, "b", "cnt")


def countmin_estimate(items: DataFrame, state: DataFrame, p: Params) -> DataFrame:
    return gather(items.select("item", "key"), _counts(state, p), p.hashes(), combine="min").select("item", F.col("s").cast("double").alias("f_hat"))


def countsketch_estimate(items: DataFrame, state: DataFrame, p: Params, combine: str = "mean") -> DataFrame:
    found = gather(items.select("item", "key"), _counts(state, p), p.hashes(), combine="sum" if combine == "mean" else combine, signs=p.hashes(family="s"))
    return found.select("item", ((F.col("s") / p.k if combine == "mean" else F.col("s")) + 0.0).alias("f_hat"))


def rowmean_estimate(items: DataFrame, state: DataFrame, p: Params) -> DataFrame:
    """The one-hot estimator without noise: what collisions alone cost."""
    cells_ = _counts(state, p)
    found = gather(items.select("item", "key"), cells_, p.hashes())
    return found.select("item", (F.lit(p.m / (p.m - 1)) * (F.col("s") / p.k - F.lit(int(cells_[0].sum())).cast("bigint") / p.m) + 0.0).alias("f_hat"))


def exact(clients: DataFrame) -> DataFrame:
    """item, f: true frequencies, for evaluation only."""
    return clients.groupBy("item").agg(F.count("*").alias("f"))


def domain_of(clients: DataFrame) -> DataFrame:
    return clients.select("item", "key").distinct()


def laplace_counts(counts: DataFrame, p: Params) -> DataFrame:
    """A trusted aggregator's answer: exact counts plus Laplace noise of scale 1/eps, from hashed uniform numbers."""
    u = (coin_of_item("laplace", p) + 0.5) / 268435456.0 - 0.5
    noise = -F.signum(u) * F.log(1 - 2 * F.abs(u)) / F.lit(p.eps)
    return counts.select("item", (F.col("f") + noise).alias("f_hat"))


def coin_of_item(tag: str, p: Params) -> Column:
    from ..functions.hashing import coin

    return coin(F.col("item").cast("string"), p, tag)


def two_round_heavy_hitters(clients: DataFrame, domain: DataFrame, p: Params, n_top: int) -> DataFrame:
    """The largest items by a first round of clients, estimated by the second round alone, scaled to all clients."""
    phased = reports.assign_phase(clients, p)
    first = one_hot_state(reports.one_hot_bits(phased.where("phase = 1"), p))
    top = one_hot_estimate(domain, first, p).orderBy(F.desc("f_hat"), "item").limit(n_top)
    second = one_hot_state(reports.one_hot_bits(phased.where("phase = 2"), p))
    return one_hot_estimate(domain.join(top, "item", "left_semi"), second, p).select("item", (F.col("f_hat") / F.lit(1 - p.r)).alias("f_hat"))


def heavy_hitters(estimates: DataFrame, n: int) -> DataFrame:
    return estimates.orderBy(F.desc("f_hat"), "item").limit(n)


def postprocess(estimates: DataFrame, kind: str, total: int | None = None, cut: float = 0.0, rounds: int = 60) -> DataFrame:
    """clip: at 0; scale: clip, then multiply to the total; shift: one number taken from all, then clip, so that the sum is
    the total (where that number is added, estimates of 0 or less are 0 still, unless none is above); significant: values
    below the cut become 0."""
    value = F.col("f_hat")
    clipped = estimates.withColumn("f_hat", F.greatest(value, F.lit(0.0)))
    if kind == "clip":
        return clipped
    if kind == "significant":
        return estimates.withColumn("f_hat", F.when(value >= cut, value).otherwise(0.0))
    if kind == "scale":
        whole = clipped.agg(F.sum("f_hat").alias("_t"))
        return clipped.crossJoin(F.broadcast(whole)).withColumn("f_hat", F.when(F.col("_t") > 0, value * F.lit(float(total)) / F.col("_t")).otherwise(0.0)).drop("_t")
    if kind == "shift":
        # the clipped sum falls as the shift grows: 64 shifts are tried in one pass, until they are close enough
        above = value > 0
        ends = estimates.agg(F.min("f_hat").alias("lo"), F.max("f_hat").alias("hi"), F.count("*").alias("d"), F.count_if(above).alias("up"), F.sum(F.when(above, value)).alias("sum")).first()
        if not ends["d"]:
            return estimates
        if ends["up"] and ends["sum"] <= float(total):
            return estimates.withColumn("f_hat", F.when(above, value + F.lit((float(total) - ends["sum"]) / ends["up"])).otherwise(0.0))
        low, high = ends["lo"] - float(total) / ends["d"], ends["hi"]
        while high - low > 1e-9 * max(1.0, abs(high), abs(low)) and rounds > 0:
            steps = [low + (high - low) * i / 64 for i in range(65)]
            sums = estimates.agg(*[F.sum(F.greatest(value - F.lit(x), F.lit(0.0))).alias(f"s{i}") for i, x in enumerate(steps)]).first()
            at = max(i for i in range(65) if sums[i] >= float(total) or i == 0)
            low, high, rounds = steps[at], steps[min(at + 1, 64)], rounds - 1
        return estimates.withColumn("f_hat", F.greatest(value - F.lit(low), F.lit(0.0)))
    raise ValueError(kind)
