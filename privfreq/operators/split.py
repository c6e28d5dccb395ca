"""The two-phase estimator: phase 1 learns which items are heavy, phase 2 sketches the light ones only."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..params import Params
from ..plans.gather import gather
from ..sources.sinks import materialize
from . import reports, sketch


@dataclass(frozen=True)
class Boundary:
    """p: the smallest score of the heavy path (infinite: no item is heavy); prefix_len: items in the prefix that set it."""

    p: float
    prefix_len: int
    total: float
    realised: float


def sample_domain(domain: DataFrame, t: int, seed: int = 7) -> DataFrame:
    """t items in the order of their hashes (a distributed top-t, not a sort)."""
    order = F.md5(F.concat_ws("|", F.col("item").cast("string"), F.lit(str(seed)), F.lit("domain")))
    return domain.withColumn("_o", order).orderBy("_o", "item").limit(t).drop("_o")


def phase1_targets(items: DataFrame, state, p: Params) -> DataFrame:
    """item, f_target (and further columns of items but key): the one-hot estimate of phase 1, scaled to all clients."""
    cells = sketch.collected(state, p)
    n = F.lit(cells.n).cast("bigint")
    value = sketch.one_hot_value(F.col("s1"), n, n, p) / F.lit(p.r)
    return gather(items, cells.v, p.hashes(), "s1").select("item", value.alias("f_target"), *[c for c in items.columns if c not in ("item", "key")])


def boundary_table(scores: DataFrame, theta: float, budget: Column | None = None) -> DataFrame:
    """One row p, prefix_len, total, realised: the longest run of falling scores whose sum stays within theta of the total.

    Scores are grouped first: tree ensembles give few different ones, and counts few as well, so the running sum is over
    distinct scores. p is infinite where the first score alone exceeds the budget; items that tie with p are all heavy.
    """
    distinct = scores.groupBy("g").agg(F.count("*").alias("n"))
    down = Window.orderBy(F.desc("g")).rowsBetween(Window.unboundedPreceding, -1)
    mass = F.col("g") * F.col("n")
    sums = distinct.withColumn("before", F.coalesce(F.sum(mass).over(down), F.lit(0.0))).crossJoin(F.broadcast(distinct.agg(F.sum(mass).alias("total"))))
    room = F.lit(theta) * F.col("total") if budget is None else budget
    fits = (F.col("g") > 0) & (F.col("before") + F.col("g") <= room)
    taken = F.least(F.col("n").cast("double"), F.floor((room - F.col("before")) / F.col("g")))
    found = sums.agg(F.min(F.when(fits, F.col("g"))).alias("p"), F.sum(F.when(fits, taken)).cast("bigint").alias("prefix_len"), F.sum(F.when(fits, mass)).alias("heavy"), F.max("total").alias("total"))
    return found.select(F.coalesce("p", F.lit(float("inf"))).alias("p"), F.coalesce("prefix_len", F.lit(0)).alias("prefix_len"), "total", F.coalesce(F.col("heavy") / F.col("total"), F.lit(0.0)).alias("realised"))


def find_boundary(scores: DataFrame, theta: float, known_total: float | None = None) -> Boundary:
    """known_total: theta times this public total is the budget, in place of theta times the sum of the scores."""
    row = boundary_table(scores, theta, None if known_total is None else F.lit(theta * known_total)).first()
    return Boundary(row["p"], row["prefix_len"], row["total"], row["realised"])


def find_boundary_scalable(scores: DataFrame, theta: float, parts: int = 16) -> DataFrame:
    """boundary_table for very many distinct scores: prefix sums over range partitions, then one short one over them.

    Columns p, prefix_len. No task sorts more than its range of scores.
    """
    distinct = scores.groupBy("g").agg(F.count("*").alias("n")).where("g > 0")
    cuts = distinct.agg(F.percentile_approx("g", [i / parts for i in range(1, parts)]).alias("c")).first()["c"] or []
    part = sum((F.when(F.col("g") < c, 1).otherwise(0) for c in sorted(set(cuts))), F.lit(0))
    ranged = distinct.withColumn("part", part)
    offsets = ranged.groupBy("part").agg(F.sum(F.col("g") * F.col("n")).alias("s"))
    offsets = offsets.select("part", F.coalesce(F.sum("s").over(Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0.0)).alias("skip"))
    inside = Window.partitionBy("part").orderBy(F.desc("g")).rowsBetween(Window.unboundedPreceding, -1)
    sums = ranged.withColumn("own", F.coalesce(F.sum(F.col("g") * F.col("n")).over(inside), F.lit(0.0))).join(F.broadcast(offsets), "part").withColumn("before", F.col("own") + F.col("skip"))
    room = scores.agg((F.lit(theta) * F.sum("g")).alias("room"))
    fits = sums.crossJoin(F.broadcast(room)).where(F.col("before") + F.col("g") <= F.col("room"))
    taken = F.least(F.col("n").cast("double"), F.floor((F.col("room") - F.col("before")) / F.col("g")))
    return fits.agg(F.coalesce(F.min("g"), F.lit(float("inf"))).alias("p"), F.coalesce(F.sum(taken).cast("bigint"), F.lit(0)).alias("prefix_len"))


def boundary_gap(scores: DataFrame, top: int = 20) -> DataFrame:
    """rank, g, gap to the next score, ratio to the first, among the largest distinct scores: where a cut is safe."""
    largest = scores.select("g").distinct().orderBy(F.desc("g")).limit(top)
    w = Window.orderBy(F.desc("g"))
    whole = w.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return largest.select(F.row_number().over(w).alias("rank"), "g", (F.col("g") - F.lead("g").over(w)).alias("gap"), (F.lag("g").over(w) - F.col("g")).alias("gap_before"), (F.col("g") / F.first_value("g").over(whole)).alias("ratio"), F.nth_value("g", 2).over(whole).alias("second"))


class TableScorer:
    """A shipped list of (item, g); items not listed score 0. Broadcast up to `limit` rows, joined by shuffle beyond."""

    def __init__(self, table: DataFrame, limit: int = 5_000_000, rows: int | None = None):
        self.table = table.select("item", F.col("g").cast("double").alias("g"))
        self.small = (table.count() if rows is None else rows) <= limit

    def score(self, items: DataFrame) -> DataFrame:
        table = F.broadcast(self.table) if self.small else self.table
        return items.join(table, "item", "left").withColumn("g", F.coalesce("g", F.lit(0.0)))


class ModelScorer:
    """A fitted model (pipeline or ensemble) scores each distinct item once; the scores then serve as a table."""

    def __init__(self, model, features):
        self.model, self.features = model, features

    def score(self, items: DataFrame) -> DataFrame:
        from . import model

        return model.scored(self.model, items, self.features)


def mark_heavy(scored: DataFrame, p: float, strict: bool = False) -> DataFrame:
    """heavy: g >= p; strict: g > p, the comparison that drops items tied with the boundary from both paths."""
    return scored.withColumn("heavy", F.col("g") > F.lit(p) if strict else F.col("g") >= F.lit(p))


def split_state(clients: DataFrame, scorer, p: float, params: Params, silent_heavy: bool = False) -> DataFrame:
    """Phase 2: heavy-path clients send the dummy report, which spreads evenly and says nothing."""
    return sketch.one_hot_state(reports.one_hot_bits(mark_heavy(scorer.score(clients), p), params, silent_heavy))


def light_mass(cells: sketch.Cells, theta: float, realised: float, params: Params, mass: str) -> float:
    """How many reports are taken to come from the light path.

    nominal: (1-theta) n; realised: by the scores' own heavy share; sketch: the sum of all cells over k, which a light
    report raises by 1 on average and a dummy by 0.
    """
    n, m = cells.n, params.m
    if mass == "sketch":
        return (params.c * (2 * cells.plus - m * n) + m * n) / 2
    return {"nominal": 1 - theta, "realised": 1 - realised}[mass] * n


def split_estimate(items: DataFrame, scorer, boundary: Boundary, state, params: Params, mass: str = "sketch", scale: str = "population", phase1=None, strict: bool = False) -> DataFrame:
    """item, f_hat, path (and further columns of items) for items (item, key).

    Heavy: the score. Light: the corrected row mean; raw: as the phase-2 count; population: divided by 1-r; pooled: plus
    the estimate of the same item from phase 1 (state phase1). The cells go to the scored items: no shuffle by item.
    """
    cells = sketch.collected(state, params)
    n = F.lit(cells.n).cast("bigint")
    rows = gather(mark_heavy(scorer.score(items), boundary.p, strict), cells.v, params.hashes(), "s1")
    light = sketch.one_hot_value(F.col("s1"), n, F.lit(light_mass(cells, params.theta, boundary.realised, params, mass)), params)
    if scale == "population":
        light = light / F.lit(1 - params.r)
    elif scale == "pooled":
        first = sketch.collected(phase1, params)
        rows = gather(rows, first.v, params.hashes(), "s0")
        n0 = F.lit(first.n).cast("bigint")
        light = light + sketch.one_hot_value(F.col("s0"), n0, n0, params)
    rest = [c for c in items.columns if c not in ("item", "key", "g", "heavy")]
    return rows.select("item", F.when(F.col("heavy"), F.col("g")).otherwise(light).alias("f_hat"), F.when(F.col("heavy"), "heavy").otherwise("light").alias("path"), *rest)


@dataclass
class SplitPathResult:
    state: sketch.Cells
    scorer: object
    boundary: Boundary
    n1: int
    n2: int
    phase1: sketch.Cells
    params: Params
    model: object = None

    def estimate(self, items: DataFrame, mass: str = "sketch", scale: str = "population") -> DataFrame:
        return split_estimate(items, self.scorer, self.boundary, self.state, self.params, mass, scale, self.phase1)


def split_fit(clients: DataFrame, domain: DataFrame, params: Params, spec=None, t: int = 200_000, build=None) -> SplitPathResult:
    """Both phases: sample clients, sketch them, fit the model on t items of the domain, cut at the boundary, sketch the rest.

    build(clients with heavy, params) makes a state from clients; by default the vector kernel.
    """
    from ..plans.kernels import vector_state
    from . import model

    build = build or vector_state
    phased = reports.assign_phase(clients, params)
    first, second = phased.where("phase = 1"), phased.where("phase = 2")
    phase1 = sketch.collected(build(first, params), params)
    train = sample_domain(domain, t, params.seed)
    targets = phase1_targets(train, phase1, params)
    spec = spec or model.ModelSpec.boosted(0.1, 20, 5)
    fitted = model.fit_frequency_model(targets, spec)
    every = materialize(ModelScorer(fitted, model.features).score(domain).select("item", "g"), "scores")
    cut = find_boundary(every, params.theta)
    scorer = TableScorer(every)
    state = sketch.collected(build(mark_heavy(scorer.score(second), cut.p), params), params)
    return SplitPathResult(state, scorer, cut, phase1.n, state.n, phase1, params, fitted)
