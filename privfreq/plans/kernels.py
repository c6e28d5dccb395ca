"""Array kernels for the client side and for queries: a bounded k x m accumulator in each task, one short shuffle."""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


from ..operators import reports, sketch
from ..params import Params, threshold
from .gather import butterfly

STATE = "j int, b int, plus bigint, reports bigint"


def _mix(x: np.ndarray) -> np.ndarray:
    # fixed values: the multipliers of the public splitmix64 finaliser
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def counter_flips(seeds: np.ndarray, m: int, q: float) -> np.ndarray:
    """A row of m flips for each seed, by mixing counters: the same wherever and whenever the record is read again."""
    limit = np.uint64(int(q * 2.0**32))
    half = (m + 1) // 2
    with np.errstate(over="ignore"):
        words = _mix(_mix(seeds)[:, None] + np.arange(1, half + 1, dtype=np.uint64)[None, :] * np.uint64(0x9E3779B97F4A7C15))
    coins = np.empty((len(seeds), 2 * half), bool)
    coins[:, 0::2] = (words & np.uint64(0xFFFFFFFF)) < limit
    coins[:, 1::2] = (words >> np.uint64(32)) < limit
    return coins[:, :m]


def gap_flips(seeds: np.ndarray, m: int, q: float) -> tuple[np.ndarray, np.ndarray]:
    """Record and place of every flip among m coins of chance q for each seed, by drawing the gaps between flips.

    About m*q draws a record in place of m; the same for a seed wherever and whenever its record is read again.
    """
    draws = int(m * q + 6 * np.sqrt(m * q * (1 - q)) + 16)
    start, last, scale = _mix(seeds), np.full(len(seeds), -1, np.int64), 1 / np.log1p(-q)
    rows, places, open_, done = [], [], np.arange(len(seeds)), 0
    while len(open_):
        with np.errstate(over="ignore"):
            words = _mix(start[open_][:, None] + np.arange(done + 1, done + draws + 1, dtype=np.uint64)[None, :] * np.uint64(0x9E3779B97F4A7C15))
        gaps = np.log(((words >> np.uint64(11)).astype(np.float64) + 0.5) * 2.0**-53) * scale
        at = last[open_][:, None] + np.cumsum(np.minimum(gaps, m).astype(np.int64) + 1, axis=1)
        row, column = np.nonzero(at < m)
        rows.append(open_[row])
        places.append(at[row, column])
        last[open_] = at[:, -1]
        open_, done = open_[at[:, -1] < m], done + draws
    return np.concatenate(rows or [np.empty(0, np.int64)]), np.concatenate(places or [np.empty(0, np.int64)])


def portable_flips(rids: list[str], m: int, p: Params) -> np.ndarray:
    """The md5 coins of the expression form, for comparing the two."""
    limit, out = threshold(p.q), np.empty((len(rids), 4 * -(-m // 4)), bool)
    for r, rid in enumerate(rids):
        for i in range(-(-m // 4)):
            word = hashlib.md5(f"{rid}|{p.seed}|bit|{i}".encode()).hexdigest()
            out[r, 4 * i : 4 * i + 4] = [int(word[7 * s : 7 * s + 7], 16) < limit for s in range(4)]
    return out[:, :m]


def vector_state(clients: DataFrame, p: Params, coins: str = "counter") -> DataFrame:
    """The one-hot (or split) state: every task flips its clients' bits and adds them up in place.

    A task gives k*m rows at most, however many clients it reads; only those are shuffled.
    """
    drawn = reports.one_hot_rows(clients, p)
    rows = drawn.select("j", "pos", F.xxhash64("rid", F.lit(p.seed), F.lit("vector")).alias("seed") if coins == "counter" else F.col("rid").alias("seed"))

    def accumulate(batches):
        plus, n = np.zeros(p.k * p.m, np.int64), np.zeros(p.k, np.int64)
        step = max(1, 1_000_000 // max(16, int(p.m * p.q)))
        for batch in batches:
            row, pos = (batch.column(i).to_numpy(zero_copy_only=False).astype(np.int64) for i in (0, 1))
            seeds = batch.column(2).to_pylist() if coins != "counter" else batch.column(2).to_numpy(zero_copy_only=False).view(np.uint64)
            for at in range(0, len(row), step):
                r, b = row[at : at + step], pos[at : at + step]
                if coins == "counter":
                    of, place = gap_flips(seeds[at : at + step], p.m, p.q)
                else:
                    of, place = np.nonzero(portable_flips(seeds[at : at + step], p.m, p))
                plus += np.bincount(r[of] * p.m + place, minlength=p.k * p.m)
                # a light client's own place holds +1 unless it was flipped
                flipped = np.zeros(len(r), bool)
                flipped[of[place == b[of]]] = True
                light = b >= 0
                plus += np.bincount(r[light] * p.m + b[light], 1 - 2 * flipped[light], p.k * p.m).astype(np.int64)
                n += np.bincount(r, minlength=p.k)
        plus = plus.reshape(p.k, p.m)
        have = np.flatnonzero(n)
        j, b = np.repeat(have, p.m), np.tile(np.arange(p.m), len(have))
        yield pa.RecordBatch.from_arrays([pa.array(j, pa.int32()), pa.array(b, pa.int32()), pa.array(plus[have].ravel()), pa.array(np.repeat(n[have], p.m))], ["j", "b", "plus", "reports"])

    return rows.mapInArrow(accumulate, STATE).groupBy("j", "b").agg(F.sum("plus").alias("plus"), F.sum("reports").alias("reports"))


def drawn(ones: np.ndarray, n: np.ndarray, p: Params, seed: int = 1) -> np.ndarray:
    """The +1 bits of each cell, from the clients whose place it is and the clients of its row."""
    rng = np.random.default_rng(seed)
    return rng.binomial(ones, 1 - p.q) + rng.binomial(n[:, None] - ones, p.q)


def simulated_cells(counts: np.ndarray, p: Params, seed: int = 1) -> sketch.Cells:
    """simulated_state, collected, from the clients by row and place (k x (m + 1), the last place for dummy reports)."""
    n = counts.sum(1)
    plus = drawn(counts[:, : p.m], n, p, seed)
    return sketch.Cells(2 * plus - n[:, None], int(plus.sum()), int(n.sum()))


def simulated_state(clients: DataFrame, p: Params, seed: int = 1) -> DataFrame:
    """A state of the same distribution from true counts: binomial draws for k*m cells in place of m coins a client.

    It looks at true data, so it serves evaluation only.
    """
    rows = reports.one_hot_rows(clients, p).groupBy("j", "pos").agg(F.count("*").alias("ones"))
    found = rows.toPandas()  # at most k*(m+1) rows
    ones, n = np.zeros((p.k, p.m), np.int64), np.zeros(p.k, np.int64)
    np.add.at(n, found["j"], found["ones"])
    at = found[found["pos"] >= 0]
    ones[at["j"], at["pos"]] = at["ones"]
    plus = drawn(ones, n, p, seed)
    j, b = np.divmod(np.arange(p.k * p.m), p.m)
    import pandas as pd

    frame = pd.DataFrame({"j": j.astype(np.int32), "b": b.astype(np.int32), "plus": plus.ravel(), "reports": n[j]})
    return clients.sparkSession.createDataFrame(frame[frame["reports"] > 0], STATE)


def gather_estimate(items: DataFrame, state: DataFrame, p: Params) -> DataFrame:
    """one_hot_estimate with the cells sent to the items."""
    return sketch.one_hot_estimate(items, state, p, how="gather")


def hadamard_inverse(state: DataFrame, p: Params) -> DataFrame:
    """sketch.hadamard_inverse by m log m steps a row; one group has m numbers."""
    import pandas as pd

    def one(rows: pd.DataFrame) -> pd.DataFrame:
        x = np.zeros(p.m, np.int64)
        x[rows["l"]] = rows["signed_sum"]
        return pd.DataFrame({"j": rows["j"].iloc[0], "b": np.arange(p.m), "s": butterfly(x)})

    return state.select("j", "l", "signed_sum").groupBy("j").applyInPandas(one, "j int, b int, s bigint")


def fast_hadamard(clients: DataFrame, items: DataFrame, p: Params) -> DataFrame:
    return sketch.hadamard_estimate(items, sketch.hadamard_state(reports.hadamard_reports(clients, p)), p, how="gather")
