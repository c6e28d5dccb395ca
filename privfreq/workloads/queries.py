"""Registered queries: every method, variant, baseline and measure on the given tables, with small parameters."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..measures import errors, theory
from ..operators import model, relational, reports, sketch, split
from ..params import SENSOR, SMALL, ZIPF, Params
from ..plans import kernels, planner
from ..sources import tables
from ..sources.sinks import materialize
from ..streaming import windows
from . import sweeps
from .oracles import AUDIT, COUNT, GRIDS, WORDS

S = SparkSession


def fixture(name: str):
    return tables.FIXTURES[name]


def exact_of(name: str):
    return lambda spark, d: sketch.exact(fixture(name)(spark, d))


def truth_scores(clients: DataFrame) -> DataFrame:
    """item, g: true frequencies as scores, the best that any model could give."""
    return sketch.exact(clients).select("item", F.col("f").cast("double").alias("g"))


def one_hot_of(name: str, p: Params):
    def run(spark: S, d: str) -> DataFrame:
        c = fixture(name)(spark, d)
        return sketch.one_hot_estimate(sketch.domain_of(c), sketch.one_hot_state(reports.one_hot_bits(c, p)), p, how="join")

    return run


def hadamard_of(name: str, p: Params, fast: bool = False):
    def run(spark: S, d: str) -> DataFrame:
        c = fixture(name)(spark, d)
        if fast:
            return kernels.fast_hadamard(c, sketch.domain_of(c), p)
        return sketch.hadamard_estimate(sketch.domain_of(c), sketch.hadamard_state(reports.hadamard_reports(c, p)), p)

    return run


def local_hash_of(name: str, p: Params, precompute: bool = False):
    def run(spark: S, d: str) -> DataFrame:
        c = fixture(name)(spark, d)
        domain = sketch.domain_of(c)
        return sketch.local_hash_estimate(domain, sketch.local_hash_state(reports.local_hash_reports(c, p)), p, sketch.precomputed_hashes(domain, p) if precompute else None)

    return run


def counted_of(how: str, name: str = "words", p: Params = COUNT):
    def run(spark: S, d: str) -> DataFrame:
        c = fixture(name)(spark, d)
        domain, state = sketch.domain_of(c), sketch.count_state(c, p, signed=how in ("mean", "median"))
        if how == "min":
            return sketch.countmin_estimate(domain, state, p)
        return sketch.rowmean_estimate(domain, state, p) if how == "row" else sketch.countsketch_estimate(domain, state, p, how)

    return run


def split_parts(spark: S, d: str, p: Params, name: str):
    c = fixture(name)(spark, d)
    scores = materialize(truth_scores(c), "scores")
    cut = split.find_boundary(scores, p.theta)
    return c, split.TableScorer(scores), cut, reports.assign_phase(c, p)


def split_of(mass: str = "sketch", scale: str = "population", name: str = "parts", strict: bool = False, p: Params = SMALL):
    def run(spark: S, d: str) -> DataFrame:
        c, scorer, cut, phased = split_parts(spark, d, p, name)
        second = split.mark_heavy(scorer.score(phased.where("phase = 2")), cut.p, strict)
        state = sketch.one_hot_state(reports.one_hot_bits(second, p))
        first = sketch.one_hot_state(reports.one_hot_bits(phased.where("phase = 1"), p)) if scale == "pooled" else None
        return split.split_estimate(sketch.domain_of(c), scorer, cut, state, p, mass, scale, first, strict)

    return run


def split_state(spark: S, d: str) -> DataFrame:
    _, scorer, cut, phased = split_parts(spark, d, SMALL, "parts")
    return split.split_state(phased.where("phase = 2"), scorer, cut.p, SMALL)


def split_silent(spark: S, d: str) -> DataFrame:
    """What the strawman gives away: how many clients of phase 2 send nothing."""
    _, scorer, cut, phased = split_parts(spark, d, SMALL, "parts")
    marked = split.mark_heavy(scorer.score(phased.where("phase = 2")), cut.p)
    sent = reports.one_hot_rows(marked, SMALL, silent_heavy=True).agg(F.count("*").alias("sent"))
    return sent.crossJoin(marked.agg(F.count("*").alias("n"))).select((F.col("n") - F.col("sent")).alias("withheld"), "sent")


def state_of(name: str, p: Params = SMALL):
    return lambda spark, d: sketch.one_hot_state(reports.one_hot_bits(fixture(name)(spark, d), p))


def arrays(spark: S, d: str) -> DataFrame:
    return sketch.state_as_array(state_of("types")(spark, d)).select("j", F.array_join(F.transform("plus", lambda x: x.cast("string")), ",").alias("plus"))


def merged(spark: S, d: str) -> DataFrame:
    """The state of all clients from the states of both phases."""
    phased = reports.assign_phase(fixture("types")(spark, d), SMALL)
    return sketch.merge_states(*[sketch.one_hot_state(reports.one_hot_bits(phased.where(F.col("phase") == n), SMALL)) for n in (1, 2)])


def gathered(spark: S, d: str) -> DataFrame:
    c = fixture("parts")(spark, d)
    return kernels.gather_estimate(sketch.domain_of(c), state_of("parts")(spark, d), SMALL)


def places(spark: S, d: str, m: int) -> DataFrame:
    return tables.load(spark, d, "lineitem").select(((F.col("l_linenumber") - 1) % m).alias("place"))


def encode_example(spark: S, d: str) -> DataFrame:
    """The vectors of m = 6 that order lines send by their line number, and the dummy (place -1), with how many lines send each."""
    lines = places(spark, d, 6).groupBy("place").agg(F.count("*").alias("n"))
    sent = lines.select(F.lit("light").alias("kind"), "place", "n").unionByName(lines.agg(F.lit("dummy").alias("kind"), F.lit(-1).alias("place"), F.coalesce(F.sum("n"), F.lit(0)).alias("n")))
    encoded = F.udf(lambda at: reports.encode(at if at >= 0 else None, 6), "array<int>")
    return sent.select("kind", "place", F.posexplode(encoded("place")).alias("b", "bit"), "n")


def phases(spark: S, d: str) -> DataFrame:
    return reports.assign_phase(fixture("parts")(spark, d), SMALL).groupBy("phase").agg(F.count("*").alias("n"), F.sum("key").alias("key_sum"))


def stats(spark: S, d: str) -> DataFrame:
    return reduce(DataFrame.unionByName, [relational.domain_stats(fixture(n)(spark, d)).select(F.lit(n).alias("fixture"), "n", "d", "f_max") for n in ("words", "parts", "sensor_fine", "types")])


def targets(spark: S, d: str) -> DataFrame:
    c = fixture("parts")(spark, d)
    first = reports.assign_phase(c, SMALL).where("phase = 1")
    return split.phase1_targets(sketch.domain_of(c), sketch.one_hot_state(reports.one_hot_bits(first, SMALL)), SMALL)


def word_scores(spark: S, d: str) -> DataFrame:
    return truth_scores(fixture("words")(spark, d))


def known_total(spark: S, d: str) -> DataFrame:
    c = fixture("words")(spark, d)
    return split.boundary_table(truth_scores(c), 0.3, F.lit(0.3 * c.count()))


METHODS = {"onehot": one_hot_of("types", SMALL), "hadamard": hadamard_of("types", SMALL), "pooled_lh": local_hash_of("types", SMALL), "split": split_of(name="types")}


def estimates(spark: S, d: str) -> dict[str, DataFrame]:
    return {name: f(spark, d).select("item", "f_hat") for name, f in METHODS.items()}


def scored(spark: S, d: str) -> DataFrame:
    truth = sketch.exact(fixture("types")(spark, d))
    return reduce(DataFrame.unionByName, [errors.score(truth, e).withColumn("method", F.lit(n)) for n, e in estimates(spark, d).items()])


def method_errors(spark: S, d: str) -> DataFrame:
    table = errors.method_errors(sketch.exact(fixture("types")(spark, d)), estimates(spark, d))
    return table.select("method", F.round("mse", 3).alias("mse"), F.round("sse", 2).alias("sse"), "n_items")


def report(kind: str):
    return lambda spark, d: errors.error_report(scored(spark, d), "method", "item", kind=kind).select("method", "item", F.round("sse", 2).alias("sse"), "n_items")


def pivoted(spark: S, d: str) -> DataFrame:
    rows = scored(spark, d).select("item", "method", F.round("e2", 2).alias("mse"))
    return errors.pivot_methods(rows, "item", list(METHODS))


def quantiles(spark: S, d: str) -> DataFrame:
    truth = sketch.exact(fixture("words")(spark, d))
    found = errors.error_quantiles(errors.score(truth, hadamard_of("words", WORDS)(spark, d)))
    return found.select(*[F.round(c, 2).alias(c) for c in found.columns])


def by_path(spark: S, d: str) -> DataFrame:
    rows = errors.sse_by_path(sketch.exact(fixture("parts")(spark, d)), split_of()(spark, d))
    return rows.select("path", F.round("sse", 2).alias("sse"), F.round("mse", 3).alias("mse"), "n_items")


def countmin_bound(spark: S, d: str) -> DataFrame:
    import math

    truth = sketch.exact(fixture("words")(spark, d))
    return theory.countmin_violations(truth, counted_of("min")(spark, d), math.e / COUNT.m).select("n_items", "violations", "underestimates")


def variances(spark: S, d: str) -> DataFrame:
    truth = sketch.exact(fixture("words")(spark, d))
    return reduce(DataFrame.unionByName, [theory.theory_variance(truth, WORDS, m).select(F.lit(m).alias("method"), F.round("variance", 3).alias("variance")) for m in ("onehot", "hadamard", "pooled_lh")])


def crossing(spark: S, d: str) -> DataFrame:
    truth = sketch.exact(fixture("words")(spark, d))
    return theory.crossover(truth, split.find_boundary(word_scores(spark, d), 0.5).p, WORDS)


def ratio(spark: S, d: str) -> DataFrame:
    place = places(spark, d, 6).distinct().select(F.concat(F.lit("place "), "place").alias("name"), F.expr("shiftleft(1L, place)").alias("code"))
    inputs = place.unionByName(spark.range(1).select(F.lit("dummy").alias("name"), F.lit(0).cast("bigint").alias("code")))
    return theory.privacy_ratio(spark, SMALL.but(m=6, k=1), inputs).select("pair", F.round("max_ratio", 6).alias("max_ratio"), F.round("bound", 6).alias("bound"))


def laplace(spark: S, d: str) -> DataFrame:
    return sketch.laplace_counts(sketch.exact(fixture("types")(spark, d)), SMALL).select("item", F.round("f_hat", 6).alias("f_hat"))


def bit_vectors(kind: str):
    def run(spark: S, d: str) -> DataFrame:
        c = fixture("types")(spark, d)
        return sketch.bit_vector_estimate(reports.bit_vector_reports(c, sketch.domain_of(c), SMALL, kind), SMALL, kind)

    return run


def own_hash(spark: S, d: str) -> DataFrame:
    c = fixture("types")(spark, d)
    return sketch.own_hash_estimate(sketch.domain_of(c), reports.own_hash_reports(c, SMALL), SMALL)


def bloom(spark: S, d: str) -> DataFrame:
    c = fixture("types")(spark, d)
    return sketch.bloom_estimate(sketch.domain_of(c), reports.bloom_reports(c, SMALL), SMALL)


def two_rounds(spark: S, d: str) -> DataFrame:
    c = fixture("types")(spark, d)
    return sketch.two_round_heavy_hitters(c, sketch.domain_of(c), SMALL, 3)


def events(spark: S, d: str) -> DataFrame:
    return tables.load(spark, d, "events").withColumn("ts", F.col("ts").cast("timestamp"))


def windowed(slide: str | None):
    def run(spark: S, d: str) -> DataFrame:
        rows = windows.window_sketch(windows.event_reports(events(spark, d), SMALL), "7 days" if slide else "1 day", slide)
        return rows.select(F.date_format("start", "yyyy-MM-dd").alias("day"), "j", "l", "signed_sum", "reports")

    return run


def versions(spark: S, d: str) -> DataFrame:
    first = events(spark, d).agg(F.date_trunc("day", F.min("ts")).alias("t0"))
    weeks = first.select("t0", F.explode(F.sequence(F.lit(0), F.lit(3))).alias("i"))
    start = F.col("t0") + F.make_dt_interval(F.col("i") * 7)
    return weeks.select(F.concat(F.lit("v"), F.col("i")).alias("version"), start.alias("valid_from"), (start + F.make_dt_interval(F.lit(7))).alias("valid_to"))


def ranges(spark: S, d: str) -> DataFrame:
    bands = spark.range(41).select(F.concat(F.lit("b"), F.col("id")).alias("band"), (F.col("id") * 7.5).alias("lo"), ((F.col("id") + 1) * 7.5).alias("hi"))
    return relational.binned_range_join(tables.load(spark, d, "events").select("value"), bands, "value", 10.0).groupBy("band").agg(F.count("*").alias("n"))


def segments(spark: S, d: str) -> DataFrame:
    """One local-hash sketch for each market segment, through the customer's dimensions."""
    from ..functions.hashing import string_key

    p = SMALL
    rows = relational.segment_clients(*[tables.load(spark, d, n) for n in ("orders", "customer", "nation", "region")]).withColumn("key", string_key(F.col("item")))
    sent = rows.select("rid", "segment").join(reports.local_hash_reports(rows, p), "rid")
    state = sent.groupBy("segment", "j", "y").agg(F.count("*").alias("cnt"))
    n = state.groupBy("segment").agg(F.sum("cnt").alias("n"))
    domain = rows.select("segment", "item", "key").distinct()
    places = sketch.probes(domain.select(F.struct("segment", "item").alias("item"), "key"), p, p.k_pool, p.g).select("item.segment", "item.item", "j", F.col("b").alias("y"))
    found = places.join(F.broadcast(state), ["segment", "j", "y"], "left").groupBy("segment", "item").agg(F.coalesce(F.sum("cnt"), F.lit(0)).alias("support"))
    return found.join(F.broadcast(n), "segment").select("segment", "item", sketch.local_hash_value(F.col("support"), F.col("n"), p).alias("f_hat"))


def groups(spark: S, d: str) -> DataFrame:
    counts = tables.load(spark, d, "events").groupBy(F.col("event_type").alias("grp"), F.col("user_id").alias("item")).agg(F.count("*").alias("f"))
    return relational.top_by_group(counts, "grp", 3).select("grp", "item", "f", "rn")


def moving(spark: S, d: str) -> DataFrame:
    day = F.datediff(F.to_date("ts"), F.lit("1970-01-01").cast("date"))
    return relational.moving_count(tables.load(spark, d, "events").groupBy(F.col("event_type").alias("item"), day.alias("day")).agg(F.count("*").alias("f")))


def candidates(spark: S, d: str) -> DataFrame:
    c = fixture("words")(spark, d)
    top = sketch.exact(c).orderBy(F.desc("f"), "item").limit(20)
    return sketch.exact(relational.restrict_candidates(c, top))


def both_domains(f):
    return lambda spark, d: f(fixture("words")(spark, d), fixture("chat_words")(spark, d))


def differences(a: DataFrame, b: DataFrame) -> DataFrame:
    return errors.diff_estimates(a.select("item").distinct(), b.select("item").distinct()).groupBy("side").agg(F.count("*").alias("n"))


def good_words(spark: S, d: str) -> DataFrame:
    good = tables.filter_labels(tables.load(spark, d, "documents"), tables.load(spark, d, "labels"))
    return relational.domain_stats(tables._words(good, "doc_id")).select("n", "d")


def one_report_each(spark: S, d: str) -> DataFrame:
    return tables.bound_contribution(tables.load(spark, d, "events").select("user_id", "event_id"), "user_id", "event_id")


def scores_joined(spark: S, d: str) -> DataFrame:
    c = fixture("parts")(spark, d)
    listed = truth_scores(c).where("g >= 30")
    return planner.score_join(c, listed, listed.count()).agg(F.count("*").alias("n"), F.sum("g").alias("g_sum"))


def clipped(spark: S, d: str) -> DataFrame:
    return sketch.postprocess(hadamard_of("types", SMALL)(spark, d), "clip")


def curve(spark: S, d: str) -> DataFrame:
    return errors.sse_curve(sketch.exact(fixture("words")(spark, d)), counted_of("min")(spark, d), None)


def fitted(spec: model.ModelSpec, name: str = "zipf", p: Params = ZIPF):
    """The two-phase estimator with a fitted model, every client's bits flipped."""

    def run(spark: S, d: str) -> DataFrame:
        c = fixture(name)(spark, d)
        domain = materialize(sketch.domain_of(c), "domain")
        return split.split_fit(c, domain, p, spec, t=50_000).estimate(domain)

    return run


def cluster_fitted(spark: S, d: str) -> DataFrame:
    """item, g: the frequency model fitted by the cluster's own regressor, on the phase-1 targets."""
    c, p = fixture("zipf")(spark, d), SMALL.but(m=256, k=16)
    first = kernels.vector_state(reports.assign_phase(c, p).where("phase = 1"), p)
    domain = sketch.domain_of(c)
    targets = split.phase1_targets(split.sample_domain(domain, 20_000), first, p)
    return model.scored(model.fit_frequency_model(targets, model.ModelSpec.boosted(0.1, 5, 4), "cluster"), domain).select("item", "g")


def tuned(spark: S, d: str) -> DataFrame:
    c = fixture("sensor_coarse")(spark, d)
    first = kernels.vector_state(reports.assign_phase(c, SENSOR).where("phase = 1"), SENSOR)
    spec = model.tune(split.phase1_targets(sketch.domain_of(c), first, SENSOR))
    return spark.createDataFrame([(spec.kind, spec.step, spec.trees, spec.depth)], "kind string, step double, trees int, depth int")


def checked_point(p: Params, name: str = "types") -> dict:
    """Estimates of all methods on one small set with coins that another engine reproduces; true frequencies as scores."""
    return {"onehot": one_hot_of(name, p), "hadamard": hadamard_of(name, p, fast=True), "pooled_lh": local_hash_of(name, p), "split": split_of(name=name, p=p)}


def checked_grid(param: str, values):
    """value, method, mse, n_items for each point of a sweep: the experiments' grids at a size that SQL can follow bit by bit."""

    def run(spark: S, d: str) -> DataFrame:
        truth = materialize(sketch.exact(fixture("types")(spark, d)), "truth")
        rows = [errors.mse(truth, f(spark, d).select("item", "f_hat")).select(F.lit(float(v)).alias("value"), F.lit(m).alias("method"), F.round("mse", 3).alias("mse"), "n_items") for v in values for m, f in checked_point(SMALL.but(**{param: v})).items()]
        return reduce(DataFrame.unionByName, rows)

    return run


def grouping_sets(spark: S, d: str) -> DataFrame:
    return errors.error_report(scored(spark, d), "method", "item", kind="sets").select("method", "item", F.round("sse", 2).alias("sse"), "n_items")


def shifted(spark: S, d: str) -> DataFrame:
    """How much was taken from all, and what is left: the sum of the answers is the number of clients."""
    c = fixture("types")(spark, d)
    out = sketch.postprocess(hadamard_of("types", SMALL)(spark, d), "shift", total=c.count())
    return out.agg(F.round(F.sum("f_hat"), 3).alias("total"), F.count_if(F.col("f_hat") < 0).alias("negative"), F.count("*").alias("n_items"))


def significant(spark: S, d: str) -> DataFrame:
    return sketch.postprocess(hadamard_of("types", SMALL)(spark, d), "significant", cut=1000.0)


def split_variance(spark: S, d: str) -> DataFrame:
    """Variance of light and heavy items of an exact split, and the published bound for a light item of mean frequency."""
    truth = sketch.exact(fixture("words")(spark, d))
    cut = split.find_boundary(word_scores(spark, d), WORDS.theta).p
    return theory.split_theory(truth, cut, WORDS).select(*[F.round(c, 3).alias(c) for c in ("light", "heavy", "total", "bound")])


def audit(spark: S, d: str) -> DataFrame:
    """The largest ratio between shares of output patterns of two groups of clients, told apart by what they hold."""
    return theory.audit(fixture("types")(spark, d), AUDIT).select("paths", F.round("max_ratio", 6).alias("max_ratio"), F.round("bound", 6).alias("bound"))


def covariance(spark: S, d: str) -> DataFrame:
    """Covariances, and how many ordered pairs of order lines are of each kind where parts of odd numbers send the dummy."""
    odd = F.col("item") % 2 == 1
    light = F.when(~odd, F.col("f")).otherwise(0)
    sums = sketch.exact(fixture("parts")(spark, d)).agg(F.sum(light).alias("n"), F.sum(light * light).alias("f2"), F.sum(F.when(odd, F.col("f")).otherwise(0)).alias("h"))
    n, f2, h = F.col("n"), F.col("f2"), F.col("h")
    count = F.when(F.col("pair") == "same_other", f2 - n).when(F.col("pair") == "different", n * n - f2).otherwise(2 * n * h)
    table = theory.covariance_table(spark, [SMALL.but(m=m, k=k) for m, k in ((8, 2), (64, 8), (1024, 64))])
    return table.crossJoin(F.broadcast(sums)).select("m", "k", "pair", F.round("covariance", 9).alias("covariance"), count.alias("pairs"))


def queries() -> dict:
    out = {f"exact_{n}": exact_of(n) for n in ("words", "parts", "customers", "sensor_fine", "sensor_coarse", "types", "props", "users", "chat_words", "hosts")}
    out |= {
        "domain_stats": stats,
        "phase_split": phases,
        "domain_sample": lambda s, d: split.sample_domain(sketch.domain_of(fixture("words")(s, d)), 1000),
        "encode_example": encode_example,
        "onehot_state": state_of("parts"),
        "onehot_cells": lambda s, d: sketch.cells(state_of("types")(s, d), SMALL),
        "state_as_array": arrays,
        "merge_states": merged,
        "onehot_estimate": one_hot_of("parts", SMALL),
        "gather_estimate": gathered,
        "hadamard_state": lambda s, d: sketch.hadamard_state(reports.hadamard_reports(fixture("words")(s, d), WORDS)),
        "hadamard_estimate": hadamard_of("words", WORDS),
        "hadamard_butterfly_estimate": hadamard_of("words", WORDS, fast=True),
        "hadamard_half_estimate": hadamard_of("words", WORDS.but(flip="half")),
        "pooled_lh_state": lambda s, d: sketch.local_hash_state(reports.local_hash_reports(fixture("words")(s, d), WORDS)),
        "pooled_lh_estimate": local_hash_of("words", WORDS),
        "pooled_lh_gexp_estimate": local_hash_of("words", WORDS.but(g_rule="exp")),
        "pooled_lh_precomputed_estimate": local_hash_of("parts", SMALL, precompute=True),
        "countmin_estimate": counted_of("min"),
        "countmin_bound": countmin_bound,
        "countsketch_mean_estimate": counted_of("mean"),
        "countsketch_median_estimate": counted_of("median"),
        "rowmean_estimate": counted_of("row"),
        "phase1_targets": targets,
        "boundary_table": lambda s, d: split.boundary_table(word_scores(s, d), 0.5),
        "boundary_scalable": lambda s, d: split.find_boundary_scalable(word_scores(s, d), 0.5),
        "boundary_known_total": known_total,
        "boundary_ties": lambda s, d: split.boundary_table(truth_scores(fixture("customers")(s, d)), 0.65),
        "boundary_empty": lambda s, d: split.boundary_table(truth_scores(fixture("types")(s, d)), 0.1).select((F.col("p") == float("inf")).alias("no_heavy"), "prefix_len"),
        "boundary_gap": lambda s, d: split.boundary_gap(word_scores(s, d)),
        "theta_realised": lambda s, d: split.boundary_table(truth_scores(fixture("parts")(s, d)), 0.5).select("realised"),
        "split_state": split_state,
        "split_estimate_sketch": split_of(),
        "split_estimate_nominal": split_of("nominal", "raw"),
        "split_estimate_realised": split_of("realised"),
        "split_estimate_raw": split_of("sketch", "raw"),
        "split_estimate_pooled": split_of("sketch", "pooled", "types"),
        "split_strict_estimate": split_of(strict=True),
        "split_silent": split_silent,
        "heavy_hitters": lambda s, d: sketch.heavy_hitters(hadamard_of("words", WORDS)(s, d), 50),
        "method_errors": method_errors,
        "error_rollup": report("rollup"),
        "error_cube": report("cube"),
        "pivot_methods": pivoted,
        "unpivot_errors": lambda s, d: errors.unpivot_errors(pivoted(s, d), "item"),
        "error_quantiles": quantiles,
        "sse_curve": curve,
        "sse_by_path": by_path,
        "theory_variance": variances,
        "crossover": crossing,
        "privacy_ratio": ratio,
        "space_table": lambda s, d: theory.space_table(s, SMALL.but(m=1024, k=64, k_pool=128, eps=4.0), sketch.exact(fixture("parts")(s, d))),
        "laplace_counts": laplace,
        "bound_contribution": one_report_each,
        "daily_sketch": windowed(None),
        "sliding_sketch": windowed("1 day"),
        "attach_version": lambda s, d: relational.attach_version(events(s, d), versions(s, d)),
        "asof_version": lambda s, d: relational.asof_version(events(s, d), versions(s, d)),
        "range_join": ranges,
        "rank_items": lambda s, d: relational.rank_items(sketch.exact(fixture("words")(s, d)), 100),
        "top_by_group": groups,
        "moving_count": moving,
        "unseen_items": lambda s, d: relational.unseen_items(reports.assign_phase(fixture("words")(s, d), SMALL)),
        "restrict_candidates": candidates,
        "domain_diff": both_domains(relational.domain_diff),
        "diff_estimates": both_domains(differences),
        "filter_labels": good_words,
        "postprocess_clip": clipped,
        "score_join": scores_joined,
        "bitvector_symmetric_estimate": bit_vectors("symmetric"),
        "bitvector_asymmetric_estimate": bit_vectors("asymmetric"),
        "own_hash_estimate": own_hash,
        "bloom_bits_estimate": bloom,
        "segment_report": segments,
        "two_round_heavy_hitters": two_rounds,
        "split_gbt": fitted(model.ZIPF_BOOSTED),
        "split_forest": fitted(model.ModelSpec.forest(100, 5)),
        "split_gbt_sensor": fitted(model.SENSOR_BOOSTED, "sensor_coarse", SENSOR),
        "model_cluster": cluster_fitted,
        "tune_model": tuned,
        "error_grouping_sets": grouping_sets,
        "postprocess_shift": shifted,
        "postprocess_significant": significant,
        "theory_split": split_variance,
        "privacy_audit": audit,
        "theory_covariance": covariance,
        **{f"grid_{name}": checked_grid(name, values) for name, values in GRIDS.items()},
        "zipf_stats": lambda s, d: relational.domain_stats(fixture("zipf")(s, d)),
    }
    return out | sweeps.QUERIES
