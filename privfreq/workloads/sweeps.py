"""The experiments: accuracy, model choice, space, query time, and sweeps of k, m, eps, r, theta and s.

Simulated states have the clients' distribution (binomial cells) at the cost of a count, so that a sweep of many settings
stays cheap; each point's error is measured against true frequencies over the whole domain. The points of a sweep share
their readings: clients are read twice for all points (reports of every setting, and clients counted by item, row and
phase), the domain a few times, and nothing that grows with the domain is sent to the driver or to all executors.

`split` is the two-phase estimator as it would run: phase 1 is sketched, a model is fitted to its estimates, heavy items
are answered by the model. `split_exact` is an ablation that no deployment has: true frequencies choose the heavy items,
which are then read from the phase-1 sketch.
"""

from __future__ import annotations

import time
from functools import reduce

from pyspark import StorageLevel
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..measures import theory
from ..operators import model, reports, sketch, split
from ..params import SENSOR, ZIPF, Params
from ..plans import batch, kernels
from ..plans.gather import butterfly, gather
from ..sources import tables

#: Published settings of each data set: sketch, shares and boosted trees. Words stand for a second skewed set; strings say
#: little about frequencies, so they have the smaller of the two models.
SETS = {"zipf": (ZIPF, model.ZIPF_BOOSTED), "words": (ZIPF, model.SENSOR_BOOSTED), "sensor_coarse": (SENSOR, model.SENSOR_BOOSTED)}
#: The control without skew has the Zipf sets' settings.
CONTROL = {"parts": (ZIPF, model.ZIPF_BOOSTED)}
METHODS = ("onehot", "hadamard", "pooled_lh", "split", "split_exact")
#: Items of the domain that the model learns from.
TRAIN = 50_000
RESULT = "source string, param string, value double, method string, mse double, sse double, mse_light double, mse_heavy double, n_heavy bigint, mass_heavy double"


class Data:
    """Clients and the true frequencies of a data set, kept while its points are measured."""

    def __init__(self, clients: DataFrame):
        self.clients = clients.persist()
        # a number of parts asked for is kept: small tables would be joined into one task, which then reads every sketch alone
        parts = 2 * clients.sparkSession.sparkContext.defaultParallelism
        self.truth = clients.groupBy("item", "key").agg(F.count("*").cast("double").alias("f")).repartition(parts).persist()
        row = self.truth.agg(F.count("*").alias("d"), F.sum("f").alias("n"), F.avg(F.col("f") * F.col("f")).alias("zero")).first()
        self.d, self.n, self.zero = row["d"], row["n"], row["zero"]
        self.fits: dict = {}

    def close(self) -> None:
        self.clients.unpersist()
        self.truth.unpersist()


def clients_of(spark: SparkSession, sf_dir: str, source: str) -> DataFrame:
    """A data set's clients; the words in as many parts as all cores can share."""
    if source == "words":
        cores = spark.sparkContext.defaultParallelism
        few = tables.load(spark, sf_dir, "documents").rdd.getNumPartitions() < cores
        return tables.words(spark, sf_dir, 2 * cores if few else None)
    return tables.FIXTURES[source](spark, sf_dir)


def _error_columns(f_hat, path=None) -> dict:
    """The aggregates of _errors for estimates; path: whether they are of the heavy path, where there is one."""
    e2 = F.pow(f_hat - F.col("f"), 2)
    whole = {"mse": F.avg(e2), "sse": F.sum(e2)}
    if path is None:
        return whole
    return whole | {"mse_light": F.avg(F.when(~path, e2)), "mse_heavy": F.avg(F.when(path, e2)), "n_heavy": F.count_if(path), "mass_heavy": F.sum(F.when(path, F.col("f")).otherwise(0.0)) / F.sum("f")}


def _errors(rows: DataFrame) -> dict:
    """Mean and summed squared errors of rows (f, f_hat, path), and of either path."""
    return rows.agg(*[v.alias(c) for c, v in _error_columns(F.col("f_hat"), F.col("path") == "heavy").items()]).first().asDict()


def _plain(data: Data, table, hashes, value) -> dict:
    return _errors(gather(data.truth, table, hashes).select("f", value(F.col("s")).alias("f_hat"), F.lit("light").alias("path"))) | {"n_heavy": None, "mass_heavy": None, "mse_light": None, "mse_heavy": None}


def one_hot_errors(data: Data, p: Params, spec=None) -> dict:
    cells = sketch.collected(kernels.simulated_state(data.clients, p), p)
    n = F.lit(cells.n)
    return _plain(data, cells.v, p.hashes(), lambda s: sketch.one_hot_value(s, n, n, p))


def hadamard_errors(data: Data, p: Params, spec=None) -> dict:
    table, n = sketch.hadamard_cells(sketch.hadamard_state(reports.hadamard_reports(data.clients, p)), p)
    return _plain(data, table, p.hashes(), lambda s: sketch.hadamard_value(s, F.lit(n), p))


def local_hash_errors(data: Data, p: Params, spec=None) -> dict:
    from ..plans.gather import dense

    counts = dense(sketch.local_hash_state(reports.local_hash_reports(data.clients, p)).toPandas(), p.k_pool, p.g, "y", "cnt")
    return _plain(data, counts, p.hashes(p.k_pool), lambda s: sketch.local_hash_value(s, F.lit(int(counts.sum())), p))


def phase_one(data: Data, p: Params, spec: model.ModelSpec) -> tuple[sketch.Cells, object, DataFrame]:
    """The sketch of phase 1, the model fitted to its estimates, and the domain's scores; once for each of their settings."""
    key = (p.eps, p.m, p.k, p.r, spec)
    if key not in data.fits:
        first = sketch.collected(kernels.simulated_state(reports.assign_phase(data.clients, p).where("phase = 1"), p), p)
        train = split.sample_domain(data.truth.select("item", "key"), TRAIN, p.seed)
        fitted = model.fit_frequency_model(split.phase1_targets(train, first, p), spec)
        data.fits[key] = first, fitted, model.scored(fitted, data.truth)
    return data.fits[key]


def split_errors(data: Data, p: Params, spec: model.ModelSpec, exact: bool = False) -> dict:
    first, _, scores = phase_one(data, p, spec)
    if exact:
        scores = data.truth.withColumn("g", F.col("f"))
    cut = split.find_boundary(scores, p.theta)
    second = reports.assign_phase(data.clients, p).where("phase = 2")
    marked = split.mark_heavy(split.TableScorer(scores, rows=data.d).score(second), cut.p)
    state = sketch.collected(kernels.simulated_state(marked, p), p)
    rows = gather(scores.withColumn("heavy", F.col("g") >= F.lit(cut.p)), state.v, p.hashes(), "s1")
    mass = split.light_mass(state, p.theta, cut.realised, p, "sketch")
    light = sketch.one_hot_value(F.col("s1"), F.lit(state.n), F.lit(mass), p) / F.lit(1 - p.r)
    heavy = F.col("g")
    if exact:
        rows = gather(rows, first.v, p.hashes(), "s0")
        heavy = sketch.one_hot_value(F.col("s0"), F.lit(first.n), F.lit(first.n), p) / F.lit(p.r)
    return _errors(rows.select("f", F.when(F.col("heavy"), heavy).otherwise(light).alias("f_hat"), F.when(F.col("heavy"), "heavy").otherwise("light").alias("path")))


RUNS = {"onehot": one_hot_errors, "hadamard": hadamard_errors, "pooled_lh": local_hash_errors, "split": split_errors, "split_exact": lambda d, p, s: split_errors(d, p, s, True)}


def _models(counted: DataFrame, firsts: dict, spec: model.ModelSpec) -> dict:
    """phase_one's models, for each of its settings: the training items are the same for all (of one seed)."""
    train = split.sample_domain(counted.select("item", "key"), TRAIN, next(iter(firsts.values()))[0].seed).coalesce(1).persist()
    targets = [split.phase1_targets(train, first, p).select("f_target").toArrow()["f_target"].to_numpy() for p, first in firsts.values()]
    fits = dict(zip(firsts, model.fit_for_all(train, targets, spec), strict=True))
    train.unpersist()
    return fits


def _errors_of_all(counted: DataFrame, reports_: tuple[dict, dict], n_clients: int, points: list[Params], spec: model.ModelSpec, methods) -> list[dict]:
    """For every setting the errors of each method: what RUNS gives for one of them, at a few readings of the domain for all.

    counted: item, key, f, cells (plans.batch.tally of the same settings); reports_: plans.batch.report_states; n_clients: how many sent
    them.
    """
    layout, paths = batch.Layout.of(points), [m for m in ("split", "split_exact") if m in methods]
    # states and fits that several points share are made once
    whole = lambda p: ("onehot", p.eps, p.m, p.k)
    early = lambda p: ("first", p.eps, p.m, p.k, p.r)
    wanted = {whole(p): (p, 0, None, 0.0) for p in points if "onehot" in methods} | {early(p): (p, 1, None, 0.0) for p in points if paths}
    made = batch.place_counts(counted, layout, list(wanted.values())) if wanted else []
    cells = {name: kernels.simulated_cells(c, wanted[name][0]) for name, c in zip(wanted, made, strict=True)}
    scores, column = counted.select("key", "f", "cells"), {}
    if "split" in paths:
        column = {name: f"g{i}" for i, name in enumerate(n for n in wanted if n[0] == "first")}
        fits = _models(counted, {g: (wanted[name][0], cells[name]) for name, g in column.items()}, spec)
        scores = model.scored_by_all(fits, counted).select("key", "f", "cells", *fits).persist(StorageLevel.DISK_ONLY)
    cuts, exact = {}, {}
    for i, p in enumerate(points):
        if "split" in paths:
            g = column[early(p)]
            cuts["split", i] = g, split.find_boundary(scores.select(F.col(g).alias("g")), p.theta)
        if "split_exact" in paths:
            if p.theta not in exact:
                exact[p.theta] = split.find_boundary(scores.select(F.col("f").alias("g")), p.theta)
            cuts["split_exact", i] = "f", exact[p.theta]
    if column:
        counted.unpersist()  # the scored table has what is read from here on
    if cuts:
        made = batch.place_counts(scores, layout, [(points[i], 2, g, cut.p) for (_, i), (g, cut) in cuts.items()])
        cells |= {name: kernels.simulated_cells(c, points[name[1]]) for name, c in zip(cuts, made, strict=True)}

    read, columns = {name: c.v for name, c in cells.items() if name[0] != "first" or "split_exact" in paths}, {}
    read |= {("hadamard", *name): butterfly(signed) for name, signed in reports_[0].items()} | {("pooled_lh", *name): counts for name, counts in reports_[1].items()}
    place = {name: f"s{i}" for i, name in enumerate(read)}
    for i, p in enumerate(points):
        for method in methods:
            if method == "onehot":
                n = F.lit(cells[whole(p)].n)
                columns[method, i] = sketch.one_hot_value(F.col(place[whole(p)]), n, n, p), None
            elif method == "hadamard":
                name = ("hadamard", *batch.hadamard_key(p))
                columns[method, i] = sketch.hadamard_value(F.col(place[name]), F.lit(n_clients), p), None
            elif method == "pooled_lh":
                name = ("pooled_lh", *batch.local_key(p))
                columns[method, i] = sketch.local_hash_value(F.col(place[name]), F.lit(int(read[name].sum())), p), None
            else:
                g, cut = cuts[method, i]
                state, first = cells[method, i], cells[early(p)]
                mass = split.light_mass(state, p.theta, cut.realised, p, "sketch")
                light = sketch.one_hot_value(F.col(place[method, i]), F.lit(state.n), F.lit(mass), p) / F.lit(1 - p.r)
                heavy = F.col(g)
                if method == "split_exact":
                    heavy = sketch.one_hot_value(F.col(place[early(p)]), F.lit(first.n), F.lit(first.n), p) / F.lit(p.r)
                path = F.col(g) >= F.lit(cut.p)
                columns[method, i] = F.when(path, heavy).otherwise(light), path
    named = {(m, i, c): v for (m, i), (f_hat, path) in columns.items() for c, v in _error_columns(f_hat, path).items()}
    found = batch.gather_all(scores.drop("cells"), {place[name]: table for name, table in read.items()}, points[0]).agg(*[v.alias(f"e{n}") for n, v in enumerate(named.values())]).first()
    if column:
        scores.unpersist()
    out = [{m: {} for m in methods} for _ in points]
    for (m, i, c), v in zip(named, found, strict=True):
        out[i][m][c] = v
    return out


def measure(source: str, clients: DataFrame, points: list[tuple[str, float, Params]], spec: model.ModelSpec, methods=METHODS) -> list[tuple]:
    """Rows of RESULT for every setting and method; `all_zero` is the error of answering 0 for everything."""
    settings, rows = [p for _, _, p in points], []
    parts = max(2 * clients.sparkSession.sparkContext.defaultParallelism, clients.rdd.getNumPartitions())
    counted = batch.tally(clients, settings, parts).persist(StorageLevel.DISK_ONLY)
    try:
        row = counted.agg(F.count("*").alias("d"), F.sum("f").alias("n"), F.avg(F.col("f") * F.col("f")).alias("zero")).first()
        sent = batch.report_states(clients, settings, "hadamard" in methods, "pooled_lh" in methods)
        found = _errors_of_all(counted, sent, int(row["n"] or 0), settings, spec, methods)
        for (name, value, _), errors in zip(points, found, strict=True):
            for method in methods:
                rows.append((source, name, float(value), method, *[errors[method].get(c) for c in ("mse", "sse", "mse_light", "mse_heavy", "n_heavy", "mass_heavy")]))
            rows.append((source, name, float(value), "all_zero", row["zero"], row["zero"] * row["d"], None, None, None, None))
    finally:
        counted.unpersist()
    return rows


def sweep(spark: SparkSession, sf_dir: str, param: str, values, source: str, methods=METHODS, **base) -> DataFrame:
    """One parameter (k, m, eps, r, theta) on one data set, or the skew s of the Zipf set; the others as published."""
    if param == "s":
        p, spec = SETS["zipf"]
        rows = [r for s in values for r in measure("zipf", tables.zipf_items(spark, sf_dir, s), [("s", s, p.but(**base))], spec, methods)]
    else:
        p, spec = (SETS | CONTROL)[source]
        rows = measure(source, clients_of(spark, sf_dir, source), [(param, v, p.but(**base).but(**{param: v})) for v in values], spec, methods)
    return spark.createDataFrame(rows, RESULT)


def accuracy(spark: SparkSession, sf_dir: str, **base) -> DataFrame:
    """All methods on all data sets and on the control without skew, at the published settings or with others."""
    rows = []
    for source, (p, spec) in (SETS | CONTROL).items():
        rows += measure(source, clients_of(spark, sf_dir, source), [("default", 0, p.but(**base))], spec)
    return spark.createDataFrame(rows, RESULT)


def model_choice(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Boosted trees at the published settings against a forest of as many bytes: error on true frequencies."""
    rows = []
    for source, (p, spec) in SETS.items():
        data = Data(clients_of(spark, sf_dir, source))
        first, boosted, scores = phase_one(data, p, spec)
        size = model.model_bytes(boosted)
        targets = split.phase1_targets(split.sample_domain(data.truth.select("item", "key"), TRAIN, p.seed), first, p).persist()
        probe = model.fit_frequency_model(targets, model.ModelSpec.forest(10, spec.depth))
        n = max(1, round(10 * size / model.model_bytes(probe)))
        forest = model.fit_frequency_model(targets, model.ModelSpec.forest(n, spec.depth))
        for kind, fitted, trees, table in (("boosted", boosted, spec.trees, scores), ("forest", forest, n, model.scored(forest, data.truth))):
            e2 = F.pow(F.col("g") - F.col("f"), 2)
            r = table.agg(F.avg(e2).alias("mse"), F.sum(e2).alias("sse")).first()
            rows.append((source, kind, trees, spec.depth, spec.step if kind == "boosted" else None, r["mse"], r["sse"], model.model_bytes(fitted)))
        targets.unpersist()
        data.close()
    return spark.createDataFrame(rows, "source string, model string, trees int, depth int, step double, mse double, sse double, bytes bigint")


#: Rows of the published space table as k at m = 1024: of the split path's sketch, and of the one-hot and Hadamard sketches.
SPACE = ((8, 32), (32, 64), (64, 128), (128, 256), (256, 316))


def space_accuracy(spark: SparkSession, sf_dir: str, rows=SPACE, source: str = "zipf") -> DataFrame:
    """budget, method, k, m, model_bytes, sketch_bytes, total_bytes, mse, sse: the five budgets, models included."""
    p, spec = SETS[source]
    data, out = Data(clients_of(spark, sf_dir, source)), []
    for i, (small, large) in enumerate(rows, 1):
        for method in ("onehot", "hadamard", "split"):
            q = p.but(k=small if method == "split" else large)
            r = RUNS[method](data, q, spec)
            model_size = model.model_bytes(phase_one(data, q, spec)[1]) if method == "split" else 0
            size = theory.sketch_bytes(q, method)
            out.append((i, method, q.k, q.m, model_size, size, model_size + size, r["mse"], r["sse"]))
    data.close()
    return spark.createDataFrame(out, "budget int, method string, k int, m int, model_bytes bigint, sketch_bytes bigint, total_bytes bigint, mse double, sse double")


def query_latency(spark: SparkSession, sf_dir: str, n: int = 50_000, source: str = "zipf", runs: int = 3) -> DataFrame:
    """method, micros, n: mean time of a lookup over n items by the estimators themselves, the best of some runs.

    Every method reads its own collected state; the split path predicts with its model and reads its sketch. Items beyond
    the domain's size repeat. pooled_lh_table reads the items' hashes out of a table made beforehand.
    """
    p, spec = SETS[source]
    data = Data(clients_of(spark, sf_dir, source))
    copies = -(-n // max(1, data.d))
    domain = data.truth.select("item", "key")
    many = split.sample_domain(domain, n, p.seed)
    if copies > 1:
        many = domain.withColumn("c", F.explode(F.sequence(F.lit(1), F.lit(copies)))).orderBy("c", "item").limit(n).select("item", "key")
    items = many.repartition(spark.sparkContext.defaultParallelism).persist()
    count = items.count()
    result = split.split_fit(data.clients, domain, p, spec, TRAIN, kernels.simulated_state)
    onehot = sketch.collected(kernels.simulated_state(data.clients, p), p)
    hadamard, total = sketch.hadamard_cells(sketch.hadamard_state(reports.hadamard_reports(data.clients, p)), p)
    local = sketch.local_hash_state(reports.local_hash_reports(data.clients, p)).persist()
    hashed = sketch.precomputed_hashes(items, p).persist()
    hashed.count()
    by_model = split.ModelScorer(result.model, model.features)
    plans = {
        "onehot": sketch.one_hot_estimate(items, onehot, p),
        "hadamard": gather(items, hadamard, p.hashes()).select("item", F.lit(p.m / (p.m - 1)) * (F.lit(p.hadamard_c) * F.col("s") - total / p.m)),
        "pooled_lh": sketch.local_hash_estimate(items, local, p),
        "pooled_lh_table": sketch.local_hash_estimate(items, local, p, hashed),
        "split": split.split_estimate(items, by_model, result.boundary, result.state, p),
    }
    out = []
    for name, plan in plans.items():
        took = []
        for _ in range(runs):
            began = time.perf_counter()
            plan.write.format("noop").mode("overwrite").save()
            took.append(time.perf_counter() - began)
        out.append((name, min(took) / max(1, count) * 1e6, count))
    for df in (items, local, hashed):
        df.unpersist()
    data.close()
    return spark.createDataFrame(out, "method string, micros double, n bigint")


#: The sweeps' points; those of k and m are lost in print, so these are powers of two around the defaults.
K, M, EPS = (8, 16, 32, 64, 128), (128, 256, 512, 1024, 2048), tuple(float(e) for e in range(1, 8))
R, THETA, S = (0.1, 0.15, 0.2, 0.25, 0.3), (0.3, 0.35, 0.4, 0.45, 0.5, 0.55, 0.6), (1.1, 1.2, 1.3, 1.4, 1.5)

QUERIES = {
    **{f"sweep_{name}_{source}": (lambda s, d, name=name, values=values, source=source: sweep(s, d, name, values, source)) for name, values in (("k", K), ("m", M), ("eps", EPS)) for source in SETS},
    "sweep_r": lambda s, d: sweep(s, d, "r", R, "zipf"),
    "sweep_theta": lambda s, d: sweep(s, d, "theta", THETA, "zipf"),
    "sweep_s": lambda s, d: sweep(s, d, "s", S, "zipf"),
    "accuracy_methods": accuracy,
    "accuracy_small_sketch": lambda s, d: accuracy(s, d, m=256, k=16),
    "model_choice": model_choice,
    "space_accuracy": space_accuracy,
    "query_latency": query_latency,
}
