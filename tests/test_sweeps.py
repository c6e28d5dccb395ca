"""The experiments' work is shared by the cores, and trees are what sums over all rows give."""

import numpy as np
import pyarrow as pa
from conftest import SF

from privfreq.functions.hashing import coin
from privfreq.operators import model, reports, split, trees
from privfreq.params import COIN, Params, threshold
from privfreq.plans import batch, kernels
from privfreq.plans.gather import gather
from privfreq.sources import tables
from privfreq.workloads import sweeps


def test_words_are_dealt_to_all_cores_and_are_the_same(spark):
    clients = sweeps.clients_of(spark, SF, "words")
    assert clients.rdd.getNumPartitions() >= spark.sparkContext.defaultParallelism
    assert clients.exceptAll(tables.words(spark, SF)).count() == 0 and clients.count() == tables.words(spark, SF).count()
    data = sweeps.Data(clients)
    assert data.truth.rdd.getNumPartitions() >= spark.sparkContext.defaultParallelism
    data.close()


def test_first_split_is_the_best_of_all(spark):
    random = np.random.default_rng(4)
    x = np.column_stack([random.poisson(0.2, 3000), random.integers(0, 9, 3000)]).astype(float)
    y = 3.0 * (x[:, 0] > 0) + (x[:, 1] > 5) + random.normal(size=3000) / 9
    made = trees.boosted(x, y, 1, 1, 1.0)
    gains = {(c, v): sum(y[side].sum() ** 2 / side.sum() for side in (x[:, c] <= v, x[:, c] > v)) for c in (0, 1) for v in np.unique(x[:, c])[:-1] if (x[:, c] > v).sum() >= trees.LEAF}
    best = max(gains, key=gains.get)
    assert (made.feature[0, 0], made.threshold[0, 0]) == best
    assert np.allclose(made.predict(x)[x[:, best[0]] > best[1]], y[x[:, best[0]] > best[1]].mean())
    # three in four of the rows are in one bin of the first feature and aren't looked at for it
    assert len(trees._listed(trees._binned(x)[0])[0][1]) < 1000


SHORT = model.ModelSpec.boosted(0.1, 5, 2)
SETTINGS = [Params(m=64, k=8, k_pool=16), Params(m=128, k=6, eps=2.0, r=0.3, k_pool=16)]


def test_settings_share_readings_and_errors_are_those_of_each_alone(spark, monkeypatch):
    clients = sweeps.clients_of(spark, SF, "words")
    data = sweeps.Data(clients)
    alone = [{m: sweeps.RUNS[m](data, p, SHORT) for m in sweeps.METHODS} for p in SETTINGS]
    data.close()

    def refuse(*a, **b):
        raise AssertionError("a score table of the domain's size is sent around")

    monkeypatch.setattr(split, "TableScorer", refuse)  # it was broadcast through the driver, for each point anew
    monkeypatch.setattr(kernels, "simulated_state", refuse)  # it read all clients, for each point anew
    rows = sweeps.measure("words", clients, [("p", i, p) for i, p in enumerate(SETTINGS)], SHORT)
    for _, _, i, method, mse, sse, light, heavy, n, mass in rows:
        if method != "all_zero":
            want = alone[int(i)][method]
            for c, v in zip(("mse", "sse", "mse_light", "mse_heavy", "n_heavy", "mass_heavy"), (mse, sse, light, heavy, n, mass), strict=True):
                assert v == want[c] or np.isclose(v, want[c], rtol=1e-9), (i, method, c)


def test_items_counted_in_many_parts_are_put_together(spark, monkeypatch):
    monkeypatch.setattr(batch, "MANY", 1 << 12)
    clients = tables.words(spark, SF)
    counted = batch.tally(clients, SETTINGS, 3)
    truth = clients.groupBy("item", "key").count().selectExpr("item", "key", "cast(count as double) f")
    assert counted.count() == truth.count() and counted.select("item", "key", "f").exceptAll(truth).count() == 0


def test_coins_are_those_of_the_expressions(spark):
    p = SETTINGS[0]
    names = ["1|2", "", "é", "a" * 43, "b" * 50, "c" * 200, None]
    frame = spark.createDataFrame([(i, v) for i, v in enumerate(names)], "i int, rid string")
    for tag, found in zip(("row", "coordinate"), batch.coins(pa.array(names), p, ("row", "coordinate")), strict=True):
        assert found.tolist() == [r["c"] for r in frame.select("i", coin(frame["rid"], p, tag).alias("c")).orderBy("i").collect()]


def test_codes_give_the_row_and_phase_of_every_setting(spark):
    # one table of clients serves all k, so no point joins or broadcasts the domain
    settings = [Params(k=k, r=r) for k, r in ((8, 0.1), (128, 0.1), (5, 0.3), (316, 0.25))]
    layout, coins = batch.Layout.of(settings), np.random.default_rng(1).integers(0, COIN, 20_000)
    at = np.searchsorted(layout.rows, coins, side="right")
    code = at * (len(layout.phases) + 1) + np.searchsorted(layout.phases, coins[::-1], side="right")
    for p in settings:
        assert (layout.rows_of(p.k)[code] == (coins * p.k) >> 28).all()
        assert (layout.phase_of(p.r)[code] == np.where(coins[::-1] < threshold(p.r), 1, 2)).all()


def test_tables_of_any_width_are_read_at_once(spark):
    # the tables of all m go to the items together; numbers as items
    clients = tables.parts(spark, SF)
    settings = [Params(m=m, k=k, k_pool=16) for m, k in ((64, 8), (100, 5), (256, 8))]
    counted = batch.tally(clients, settings, 3).persist()
    counts = batch.place_counts(counted, batch.Layout.of(settings), [(p, 0, None, 0.0) for p in settings])
    for p, found in zip(settings, counts, strict=True):
        for r in reports.one_hot_rows(clients, p).groupBy("j", "pos").count().collect():
            assert found[r["j"], r["pos"]] == r["count"]
    names = {f"s{i}": c[:, :-1] for i, c in enumerate(counts)}
    items = counted.select("item", "key")
    together = {r["item"]: r for r in batch.gather_all(items, names, settings[0]).collect()}
    for p, (name, table) in zip(settings, names.items(), strict=True):
        assert all(together[r["item"]][name] == r["s"] for r in gather(items, table, p.hashes()).collect())
    rows = sweeps.measure("parts", clients, [("m", p.m, p) for p in settings[::2]], SHORT, ("onehot", "split", "split_exact"))
    assert len(rows) == 8 and all(r[4] > 0 for r in rows)
    counted.unpersist()
