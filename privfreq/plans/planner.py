"""Physical choices by checked sizes: how to score, how to query, how to build."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators import reports, sketch
from ..params import Params
from . import kernels

#: Rows of a score table that a broadcast may hold, probes that a join may make, bits that may be spelled out as rows.
SCORES, PROBES, BITS = 5_000_000, 200_000, 20_000_000


def choose_scorer(rows: int) -> str:
    """broadcast: a listed score table beside the scan; merge: a join by item beyond the size that a broadcast may have."""
    return "broadcast" if rows <= SCORES else "merge"


def choose_query(rows: int, p: Params) -> str:
    """join: probes against broadcast cells; gather: items read the cells in place."""
    return "join" if rows * p.k <= PROBES else "gather"


def choose_build(rows: int, p: Params) -> str:
    return "expression" if rows * p.m <= BITS else "vector"


def build(clients: DataFrame, rows: int, p: Params) -> DataFrame:
    """The one-hot (or split) state of `rows` clients by the form that their number asks for. The forms use other coins."""
    if choose_build(rows, p) == "expression":
        return sketch.one_hot_state(reports.one_hot_bits(clients, p))
    return kernels.vector_state(clients, p)


def estimate(items: DataFrame, state: DataFrame, p: Params, rows: int) -> DataFrame:
    return sketch.one_hot_estimate(items, state, p, how=choose_query(rows, p))


def score_join(items: DataFrame, scores: DataFrame, rows: int) -> DataFrame:
    """Left join of scores, 0 where none: broadcast, shuffled hash (mid-size) or sort-merge."""
    side = F.broadcast(scores) if choose_scorer(rows) == "broadcast" else scores.hint("shuffle_hash" if rows <= 20 * SCORES else "merge")
    return items.join(side, "item", "left").withColumn("g", F.coalesce("g", F.lit(0.0)))
