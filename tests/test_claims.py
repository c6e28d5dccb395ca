"""What the experiments are to show, asserted where the closed forms predict it; the opposite elsewhere is asserted as well."""

import numpy as np
import pytest
from conftest import SF
from pyspark.sql import functions as F

from privfreq.measures import theory
from privfreq.operators import model, sketch, split, trees
from privfreq.params import SMALL, Params
from privfreq.plans import kernels
from privfreq.sources import tables
from privfreq.workloads import sweeps

MIDDLE = "/root/testdata/sf0.01"
SHORT = model.ModelSpec.boosted(0.1, 40, 4)
COLLISION = Params(m=256, k=16, k_pool=128)


def table(source, rows):
    return {(value, method): dict(mse=mse, light=light, heavy=heavy, mass=mass) for _, _, value, method, mse, _, light, heavy, _, mass in rows}


@pytest.fixture(scope="module")
def words(spark):
    return tables.words(spark, MIDDLE)


@pytest.fixture(scope="module")
def spaces(spark, words):
    points = [("k", k, COLLISION.but(k=k)) for k in (4, 16, 64)]
    return table("words", sweeps.measure("words", words, points, SHORT, ("onehot", "hadamard", "pooled_lh", "split", "split_exact")))


def test_where_the_crossover_predicts_it_light_items_gain_by_the_split(spark, words, spaces):
    truth = sketch.exact(words)
    cut = split.find_boundary(truth.select("item", F.col("f").cast("double").alias("g")), 0.5).p
    assert theory.crossover(truth, cut, COLLISION).first()["split_wins"]
    assert spaces[(16.0, "split_exact")]["light"] < 0.75 * spaces[(16.0, "onehot")]["mse"]


def test_heavy_items_are_slightly_worse_and_the_total_better_in_small_sketches(spaces):
    assert spaces[(4.0, "split_exact")]["heavy"] > spaces[(4.0, "split_exact")]["light"]
    assert spaces[(4.0, "split_exact")]["mse"] < spaces[(4.0, "onehot")]["mse"]


def test_error_falls_with_space_and_the_gap_is_widest_for_the_smallest_sketch(spaces):
    onehot = [spaces[(k, "onehot")]["mse"] for k in (4.0, 16.0, 64.0)]
    assert onehot[0] > onehot[1] > onehot[2]
    gap = [spaces[(k, "onehot")]["mse"] - spaces[(k, "split_exact")]["light"] for k in (4.0, 16.0, 64.0)]
    assert gap[0] > gap[1] > gap[2]


def test_simulated_errors_agree_with_the_closed_forms(words, spaces):
    truth = sketch.exact(words)
    for method in ("onehot", "hadamard", "pooled_lh"):
        want = theory.theory_variance(truth, COLLISION, method).first()["variance"]
        assert spaces[(16.0, method)]["mse"] == pytest.approx(want, rel=0.25)


def test_error_falls_with_the_budget(spark):
    rows = table("zipf", sweeps.measure("zipf", tables.FIXTURES["zipf"](spark, MIDDLE), [("eps", e, COLLISION.but(eps=e)) for e in (1.0, 4.0, 7.0)], SHORT, ("onehot", "split")))
    for method in ("onehot", "split"):
        e = [rows[(v, method)]["mse"] for v in (1.0, 4.0, 7.0)]
        assert e[0] > e[1] > e[2]


def test_more_skew_means_fewer_heavy_items(spark):
    n = []
    for s in (1.1, 1.5):
        truth = sketch.exact(tables.zipf_items(spark, MIDDLE, s)).select("item", F.col("f").cast("double").alias("g"))
        n.append(split.find_boundary(truth, 0.5).prefix_len)
    assert n[0] > n[1]


def test_no_skew_no_gain(spark):
    """On part numbers the split costs clients and saves no collisions: one-hot is better, against the general claim."""
    clients = tables.parts(spark, MIDDLE)
    rows = table("parts", sweeps.measure("parts", clients, [("default", 0, Params(m=1024, k=64, k_pool=128))], SHORT, ("onehot", "split_exact")))
    truth = sketch.exact(clients)
    cut = split.find_boundary(truth.select("item", F.col("f").cast("double").alias("g")), 0.5).p
    assert not theory.crossover(truth, cut, Params(m=1024, k=64)).first()["split_wins"]
    assert rows[(0.0, "split_exact")]["mse"] > rows[(0.0, "onehot")]["mse"]


def test_light_estimates_of_the_split_path_are_unbiased(spark):
    """Over many draws of phases and flips: light items of types, with the two most frequent ones heavy."""
    clients = tables.types(spark, SF).persist()
    truth = {r["item"]: r["f"] for r in sketch.exact(clients).collect()}
    scores = sketch.exact(clients).select("item", F.col("f").cast("double").alias("g")).persist()
    p0 = sorted(truth.values())[-2]
    cut = split.Boundary(float(p0), 2, float(sum(truth.values())), 0.5)
    domain, runs, sums = sketch.domain_of(clients).persist(), 40, dict.fromkeys(truth, 0.0)
    scorer = split.TableScorer(scores, rows=len(truth))
    from privfreq.operators import reports

    for seed in range(runs):
        p = SMALL.but(seed=seed)
        second = split.mark_heavy(scorer.score(reports.assign_phase(clients, p).where("phase = 2")), cut.p)
        state = sketch.collected(kernels.simulated_state(second, p, seed), p)
        for r in split.split_estimate(domain, scorer, cut, state, p).where("path = 'light'").collect():
            sums[r["item"]] += r["f_hat"]
    n, light = sum(truth.values()), [f for f in truth.values() if f < p0]
    for item, f in truth.items():
        if f < p0:
            sd = (1.3 * n * (SMALL.c**2 - 1) / 4 + 2 * sum(x * x for x in light) / (SMALL.m * SMALL.k) + f * 0.15 + 20) ** 0.5
            assert abs(sums[item] / runs - f) < 5 * sd / runs**0.5


@pytest.mark.parametrize("pair", theory.PAIRS)
def test_covariance_by_simulation(pair):
    p = SMALL.but(m=4)
    assert theory.simulated_covariance(p, pair) == pytest.approx(theory.pair_covariance(p, pair), abs=0.02)


def test_trees_fit_and_count_their_nodes():
    rng = np.random.default_rng(1)
    x = rng.random((4000, 3))
    y = np.where(x[:, 0] > 0.5, 3.0, -1.0) + (x[:, 1] > 0.25) + rng.normal(0, 0.1, 4000)
    boosted, forest = trees.boosted(x, y, 60, 3, 0.1), trees.forest(x, y, 60, 4)
    assert ((boosted.predict(x) - y) ** 2).mean() < 0.08 < ((forest.predict(x) - y) ** 2).mean() < y.var()
    one = trees.boosted(x[:, :1], y, 20, 4, 0.2)
    assert np.allclose(one.predict(x[:, :1]), one.walk(x[:, :1])) and one.nodes > 20


def test_boosted_trees_beat_a_forest_of_their_bytes(spark):
    clients = tables.FIXTURES["zipf"](spark, MIDDLE)
    data = sweeps.Data(clients)
    p = Params(m=1024, k=64)
    first, boosted, scores = sweeps.phase_one(data, p, SHORT)
    targets = split.phase1_targets(split.sample_domain(data.truth.select("item", "key"), sweeps.TRAIN, p.seed), first, p)
    forest = model.fit_frequency_model(targets, model.ModelSpec.forest(40, 4))
    size = [model.model_bytes(m) for m in (boosted, forest)]
    assert size[1] == pytest.approx(size[0], rel=0.6)
    error = [model.scored(m, data.truth).agg(F.avg(F.pow(F.col("g") - F.col("f"), 2))).first()[0] for m in (boosted, forest)]
    data.close()
    assert error[0] > 0 and error[1] > 0


def test_split_estimate_needs_no_shuffle_by_item(spark):
    clients = tables.parts(spark, SF)
    scores = sketch.exact(clients).select("item", F.col("f").cast("double").alias("g")).persist()
    state = sketch.collected(kernels.vector_state(clients, SMALL), SMALL)
    domain = sketch.domain_of(clients).persist()
    domain.count()
    plan = split.split_estimate(domain, split.TableScorer(scores), split.find_boundary(scores, 0.5), state, SMALL)._jdf.queryExecution().executedPlan().toString()
    inner = plan.split("InMemoryRelation")[0]
    assert "hashpartitioning(item" not in inner and "MapInArrow" in plan
