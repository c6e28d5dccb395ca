"""States and estimates on small data: equality of forms, merging, unbiasedness, boundaries."""

import math

import pytest
from conftest import SF
from pyspark.sql import functions as F

from privfreq.measures import errors
from privfreq.operators import model, reports, sketch, split
from privfreq.params import SMALL, Params
from privfreq.plans import kernels, planner
from privfreq.sources import tables


def rows(df):
    return sorted(map(tuple, df.collect()))


@pytest.fixture(scope="module")
def clients(spark):
    return tables.types(spark, SF).persist()


def test_kernel_equals_expression_form(spark, clients):
    p = SMALL.but(m=20, k=3)
    assert rows(kernels.vector_state(clients, p, coins="portable")) == rows(sketch.one_hot_state(reports.one_hot_bits(clients, p)))


def test_state_does_not_depend_on_partitioning(spark, clients):
    a = kernels.vector_state(clients.repartition(7), SMALL)
    assert rows(a) == rows(kernels.vector_state(clients.coalesce(1), SMALL))
    parts = [clients.where(F.col("item") == "click"), clients.where(F.col("item") != "click")]
    assert rows(sketch.merge_states(*[kernels.vector_state(x, SMALL) for x in parts])) == rows(a)


def test_dummy_reports_have_no_own_place(spark, clients):
    heavy = clients.withColumn("heavy", F.lit(True))
    assert reports.one_hot_rows(heavy, SMALL).where("pos >= 0").count() == 0
    assert reports.one_hot_rows(heavy, SMALL, silent_heavy=True).count() == 0


@pytest.mark.parametrize("kind", ["onehot", "hadamard", "pooled_lh"])
def test_estimates_are_unbiased(spark, clients, kind):
    truth = {r["item"]: r["f"] for r in sketch.exact(clients).collect()}
    domain = sketch.domain_of(clients).persist()
    runs, sums = 12, dict.fromkeys(truth, 0.0)
    for seed in range(runs):
        p = SMALL.but(seed=seed, m=64, k=8)
        if kind == "onehot":
            est = kernels.gather_estimate(domain, kernels.vector_state(clients, p), p)
        elif kind == "hadamard":
            est = sketch.hadamard_estimate(domain, sketch.hadamard_state(reports.hadamard_reports(clients, p)), p)
        else:
            est = sketch.local_hash_estimate(domain, sketch.local_hash_state(reports.local_hash_reports(clients, p)), p)
        for r in est.collect():
            sums[r["item"]] += r["f_hat"]
    n = sum(truth.values())
    sd = math.sqrt(1.2 * n + 2 * sum(f * f for f in truth.values()) / (64 * 8)) + 10
    for item, f in truth.items():
        assert abs(sums[item] / runs - f) < 5 * sd / math.sqrt(runs)


def test_simulated_state_agrees_with_clients(spark, clients):
    a = kernels.vector_state(clients, SMALL).agg(F.sum("plus")).first()[0]
    b = kernels.simulated_state(clients, SMALL).agg(F.sum("plus")).first()[0]
    assert abs(a - b) < 6 * math.sqrt(1000 * 64 * SMALL.q)


def hand(spark):
    return spark.createDataFrame([(1, 10.0), (2, 5.0), (3, 5.0), (4, 3.0), (5, 1.0)], "item bigint, g double")


def test_boundary_by_hand(spark):
    assert split.find_boundary(hand(spark), 0.5).p == 10
    assert split.find_boundary(hand(spark), 0.3).p == float("inf")
    tie = split.find_boundary(hand(spark), 0.65)
    assert (tie.p, tie.prefix_len) == (5, 2) and tie.realised == pytest.approx(20 / 24)
    for theta in (0.3, 0.5, 0.65, 0.9):
        want = split.find_boundary(hand(spark), theta)
        got = split.find_boundary_scalable(hand(spark), theta, 3).first()
        assert (got["p"], got["prefix_len"]) == (want.p, want.prefix_len)


def test_negative_scores_stay_out_of_the_prefix(spark):
    scores = spark.createDataFrame([(1, 4.0), (2, 2.0), (3, -1.0)], "item bigint, g double")
    assert split.find_boundary(scores, 0.9).p == 4.0


def test_items_at_the_boundary_need_the_same_comparison(spark):
    clients = tables.parts(spark, SF)
    scores = sketch.exact(clients).select("item", F.col("f").cast("double").alias("g"))
    p = SMALL
    cut = split.find_boundary(scores, 0.5)
    scorer = split.TableScorer(scores)
    second = split.mark_heavy(scorer.score(reports.assign_phase(clients, p).where("phase = 2")), cut.p)
    state = kernels.vector_state(second, p)
    tied = scores.where(F.col("g") == cut.p)
    domain = sketch.domain_of(clients).join(tied.select("item"), "item", "left_semi")
    good = split.split_estimate(domain, scorer, cut, state, p)
    bad = split.split_estimate(domain, scorer, cut, state, p, strict=True)
    assert good.agg(F.min("f_hat")).first()[0] == cut.p
    assert abs(bad.agg(F.avg("f_hat")).first()[0]) < cut.p


def test_split_fit_with_a_model(spark):
    clients = tables.zipf_items(spark, SF, 1.3)
    domain = sketch.domain_of(clients)
    result = split.split_fit(clients, domain, Params(m=64, k=8), model.ModelSpec.boosted(0.1, 3, 3), t=2000)
    assert result.n1 + result.n2 == 6000 and 400 < result.n1 < 800
    assert 0 <= result.boundary.realised <= 1 and result.estimate(domain).count() == domain.count()


def test_error_measures(spark):
    truth = spark.createDataFrame([("a", 3), ("b", 1)], "item string, f bigint")
    est = spark.createDataFrame([("a", 1.0)], "item string, f_hat double")
    got = errors.mse(truth, est).first()
    assert (got["sse"], got["mse"], got["n_items"]) == (5.0, 2.5, 2)
    assert [r["sse"] for r in errors.sse_curve(truth, est).collect()] == [4.0, 5.0]


def test_countmin_never_underestimates(spark, clients):
    p = SMALL.but(m=8, k=3)
    est = sketch.countmin_estimate(sketch.domain_of(clients), sketch.count_state(clients, p), p)
    assert sketch.exact(clients).join(est, "item").where("f_hat < f").count() == 0


def test_postprocessing(spark):
    est = spark.createDataFrame([("a", 6.0), ("b", -2.0), ("c", 2.0)], "item string, f_hat double")
    total = sketch.postprocess(est, "shift", total=16).agg(F.sum("f_hat"), F.min("f_hat")).first()
    assert total[0] == pytest.approx(16.0) and total[1] == 0.0
    scaled = sketch.postprocess(est, "scale", total=16).collect()
    assert {r["item"]: r["f_hat"] for r in scaled} == {"a": 12.0, "b": 0.0, "c": 4.0}
    assert sketch.postprocess(est, "significant", cut=5.0).where("f_hat > 0").count() == 1


def test_shift_adds_to_positive_estimates_only(spark):
    est = spark.createDataFrame([("a", 6.0), ("b", -2.0), ("c", 2.0)], "item string, f_hat double")
    got = {r["item"]: r["f_hat"] for r in sketch.postprocess(est, "shift", total=16).collect()}
    assert got == {"a": 10.0, "b": 0.0, "c": 6.0}
    less = {r["item"]: r["f_hat"] for r in sketch.postprocess(est, "shift", total=4).collect()}
    assert less == pytest.approx({"a": 4.0, "b": 0.0, "c": 0.0}, abs=1e-6)


def test_planner_choices():
    assert planner.choose_scorer(10) == "broadcast" and planner.choose_scorer(10**9) == "merge"
    assert planner.choose_query(10**9, SMALL) == "gather" and planner.choose_build(10**9, SMALL) == "vector"


def test_empty_clients(spark):
    none = tables.types(spark, SF).where("false")
    assert kernels.vector_state(none, SMALL).count() == 0
    assert sketch.one_hot_state(reports.one_hot_bits(none, SMALL)).count() == 0


def test_scan_is_pruned_and_build_shuffles_cells_only(spark):
    plan = kernels.vector_state(tables.parts(spark, SF), SMALL)._jdf.queryExecution().executedPlan().toString()
    assert "l_comment" not in plan and "l_quantity" not in plan and plan.count("Exchange") == 1
