"""The frequency model: tree ensembles that predict an item's frequency from the item alone."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark import cloudpickle
from pyspark.ml import PipelineModel
from pyspark.ml.evaluation import RegressionEvaluator
from pyspark.ml.feature import VectorAssembler
from pyspark.ml.functions import vector_to_array
from pyspark.ml.regression import GBTRegressor, RandomForestRegressor
from pyspark.ml.tuning import CrossValidator, ParamGridBuilder
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import DoubleType, StructField, StructType

from . import trees


@dataclass(frozen=True)
class ModelSpec:
    kind: str
    trees: int
    depth: int
    step: float = 0.1
    seed: int = 7

    @classmethod
    def boosted(cls, step: float, trees: int, depth: int) -> ModelSpec:
        return cls("boosted", trees, depth, step)

    @classmethod
    def forest(cls, trees: int, depth: int) -> ModelSpec:
        return cls("forest", trees, depth)


#: Settings found by grid search for the rank-numbered sets and for the sensor set.
ZIPF_BOOSTED, SENSOR_BOOSTED = ModelSpec.boosted(0.05, 350, 5), ModelSpec.boosted(0.1, 100, 3)
GRAMS = 32


def features(items: DataFrame) -> DataFrame:
    """Adds x: for numbers the value and its log; for strings length, end characters and hashed character pairs."""
    if dict(items.dtypes)["item"] == "string":
        text = F.lower("item")
        pairs = F.transform(F.sequence(F.lit(1), F.greatest(F.length(text) - 1, F.lit(1))), lambda i: F.pmod(F.xxhash64(F.substr(text, i, F.lit(2))), F.lit(GRAMS)))
        columns = {"_n": F.length(text).cast("double"), "_a": F.ascii(text).cast("double"), "_z": F.ascii(F.right(text, F.lit(1))).cast("double"), "_p": pairs}
        items = items.withColumns(columns).withColumns({f"_g{i}": F.size(F.filter("_p", lambda x, i=i: x == i)).cast("double") for i in range(GRAMS)}).drop("_p")
        names = ["_n", "_a", "_z", *[f"_g{i}" for i in range(GRAMS)]]
    else:
        value = F.col("item").cast("double")
        items = items.withColumns({"_v": value, "_l": F.signum(value) * F.log1p(F.abs(value))})
        names = ["_v", "_l"]
    return VectorAssembler(inputCols=names, outputCol="x", handleInvalid="keep").transform(items).drop(*names)


def regressor(spec: ModelSpec):
    if spec.kind == "boosted":
        return GBTRegressor(featuresCol="x", labelCol="f_target", maxIter=spec.trees, maxDepth=spec.depth, stepSize=spec.step, seed=spec.seed, maxBins=64)
    return RandomForestRegressor(featuresCol="x", labelCol="f_target", numTrees=spec.trees, maxDepth=spec.depth, seed=spec.seed, maxBins=64)


def _matrix(column: pa.Array) -> np.ndarray:
    return column.flatten().to_numpy(zero_copy_only=False).reshape(len(column), -1) if len(column) else np.empty((0, 1))


def _inputs(items: DataFrame) -> Column:
    """The features as an array; a number's logarithm orders as the number does, so trees over bins need one of them."""
    x = vector_to_array("x")
    return x if dict(items.dtypes)["item"] == "string" else F.slice(x, 1, 1)


def _training(rows: DataFrame) -> pa.Table:
    found = rows.limit(trees.MOST_ROWS + 1).toArrow().combine_chunks()
    if found.num_rows > trees.MOST_ROWS:
        raise ValueError(f"more than {trees.MOST_ROWS} training items: fit them on the cluster")
    return found


def _fitted(x: np.ndarray, y: np.ndarray, spec: ModelSpec) -> trees.Ensemble:
    return trees.boosted(x, y, spec.trees, spec.depth, spec.step) if spec.kind == "boosted" else trees.forest(x, y, spec.trees, spec.depth, spec.seed)


def fit_for_all(train: DataFrame, targets: list[np.ndarray], spec: ModelSpec) -> list[trees.Ensemble]:
    """fit_frequency_model for many targets of the same items (in the order of train): each is fitted in a task of its own."""
    context = train.sparkSession.sparkContext
    x = context.broadcast(_matrix(_training(features(train).select(_inputs(train).alias("x")))["x"].combine_chunks()))

    def fit(y):
        return cloudpickle.dumps(_fitted(x.value, y, spec))

    return [cloudpickle.loads(v) for v in context.parallelize(targets, len(targets)).map(fit).collect()]


def fit_frequency_model(train: DataFrame, spec: ModelSpec, where: str = "process") -> PipelineModel | trees.Ensemble:
    """train: item, f_target. process: the t rows, whose number is a parameter, are fitted in one process; cluster: by jobs."""
    if where == "process":
        rows = _training(features(train).select(_inputs(train).alias("x"), "f_target"))
        return _fitted(_matrix(rows["x"].combine_chunks()), rows["f_target"].to_numpy(), spec)
    rows = features(train).select("x", "f_target").coalesce(8).persist()
    model = regressor(spec).fit(rows)
    rows.unpersist()
    return PipelineModel([model])


def scored(model: PipelineModel | trees.Ensemble, items: DataFrame, features_=None) -> DataFrame:
    """items with g, the model's prediction."""
    with_x = (features_ or features)(items)
    if not isinstance(model, trees.Ensemble):
        return model.transform(with_x).select(*items.columns, F.col("prediction").alias("g"))
    sent = items.sparkSession.sparkContext.broadcast(cloudpickle.dumps(model))  # classes travel by value, as functions do
    names = items.columns

    def run(batches):
        import pickle

        ensemble = pickle.loads(sent.value)
        for batch in batches:
            g = ensemble.predict(_matrix(batch.column(len(names)))) if len(batch) else np.empty(0)
            yield pa.RecordBatch.from_arrays([*batch.columns[: len(names)], pa.array(g)], [*names, "g"])

    return with_x.select(*names, _inputs(items).alias("x")).mapInArrow(run, StructType([*items.schema.fields, StructField("g", DoubleType())]))


def scored_by_all(models: dict[str, trees.Ensemble], items: DataFrame) -> DataFrame:
    """scored() by many ensembles, each in a column of its name; the features are made once."""
    sent = items.sparkSession.sparkContext.broadcast(cloudpickle.dumps(models))
    names = items.columns

    def run(batches):
        import pickle

        ensembles = pickle.loads(sent.value)
        for batch in batches:
            x = _matrix(batch.column(len(names)))
            g = [pa.array(e.predict(x) if len(batch) else np.empty(0)) for e in ensembles.values()]
            yield pa.RecordBatch.from_arrays([*batch.columns[: len(names)], *g], [*names, *ensembles])

    schema = StructType([*items.schema.fields, *(StructField(n, DoubleType()) for n in models)])
    return features(items).select(*names, _inputs(items).alias("x")).mapInArrow(run, schema)


def tune(train: DataFrame, steps=(0.05, 0.1), depths=(3, 5), counts=(100, 350), folds: int = 3) -> ModelSpec:
    """The boosted setting of least error on a grid, by cross-validation over the training items (fitted in one process).

    The rows of a fold are what a hash of their order gives; ties go to the smaller setting.
    """
    rows = features(train).select(_inputs(train).alias("x"), "f_target", F.xxhash64("item").alias("h")).toArrow().combine_chunks()
    x, y, fold = _matrix(rows["x"].combine_chunks()), rows["f_target"].to_numpy(), rows["h"].to_numpy() % folds
    best = None
    for step in steps:
        for depth in depths:
            errors = dict.fromkeys(counts, 0.0)
            for f in range(folds):
                inside = fold != f
                for n in counts:
                    model = trees.boosted(x[inside], y[inside], n, depth, step)
                    errors[n] += float(((model.predict(x[~inside]) - y[~inside]) ** 2).sum())
            for n, e in errors.items():
                if best is None or e < best[0]:
                    best = e, ModelSpec.boosted(step, n, depth)
    return best[1]


def tune_on_cluster(train: DataFrame, steps=(0.05, 0.1), depths=(3, 5), trees_: int = 10, folds: int = 2) -> ModelSpec:
    """tune() by the cluster's regressor and cross-validator, for samples too large for one process."""
    base = regressor(ModelSpec.boosted(steps[0], trees_, depths[0]))
    grid = ParamGridBuilder().addGrid(base.stepSize, list(steps)).addGrid(base.maxDepth, list(depths)).build()
    judge = RegressionEvaluator(labelCol="f_target", metricName="rmse")
    found = CrossValidator(estimator=base, estimatorParamMaps=grid, evaluator=judge, numFolds=folds, seed=7).fit(features(train).select("x", "f_target"))
    best = min(zip(found.avgMetrics, grid, strict=True), key=lambda v: v[0])[1]
    return ModelSpec.boosted(best[base.stepSize], trees_, best[base.maxDepth])


def model_error(truth: DataFrame, scores: DataFrame) -> DataFrame:
    """One row: the regression's mean squared error against true frequencies."""
    return truth.join(scores, "item").agg(F.avg(F.pow(F.col("g") - F.col("f"), 2)).alias("mse"))


def model_bytes(model: PipelineModel | trees.Ensemble) -> int:
    """A model's size at 16 bytes a node (feature, threshold, two children or a value)."""
    if isinstance(model, trees.Ensemble):
        return 16 * model.nodes
    return 16 * sum(s.totalNumNodes for s in model.stages if hasattr(s, "totalNumNodes"))
