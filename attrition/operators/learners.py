"""The four learners behind one interface, cross-validation and comparisons."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.scratch import kept
from . import measures
from .resample import BALANCINGS, folds, weighted
from .second_order import Booster, binned, boosted_second, own_tree


@dataclass
class Fitted:
    """A fitted learner: scores rows, tells what its features are worth."""

    name: str
    features: list[str]
    model: object

    def score(self, df: DataFrame, key: str = "sub_id", label: str = "label") -> DataFrame:
        """(key, label, score)."""
        if isinstance(self.model, Booster):
            return self.model.score(df, [key, label])
        from pyspark.ml.functions import vector_to_array

        return self.model.transform(vectors(df, self.features)).select(key, label, vector_to_array("probability")[1].alias("score"))

    def importance(self, spark) -> DataFrame:
        if isinstance(self.model, Booster):
            return self.model.importance(spark)
        return spark.createDataFrame([(f, float(v)) for f, v in zip(self.features, self.model.featureImportances.toArray())], "feature STRING, gain DOUBLE")


def vectors(df: DataFrame, features: list[str]) -> DataFrame:
    """Adds features, a vector; gaps that refining has not filled are 0 (the second-order booster gives them a side)."""
    from pyspark.ml.feature import VectorAssembler

    if "features" in df.columns:  # from `prepared`
        return df
    filled = df.withColumns({c: F.coalesce(F.col(c).cast("double"), F.lit(0.0)) for c in features})
    return VectorAssembler(inputCols=features, outputCol="features").transform(filled)


def prepared(df: DataFrame, features: list[str]) -> DataFrame:
    """df with its vectors, written once for many fits on these features; df itself where there are none."""
    return kept(vectors(df, features), "vectors") if features else df


def _ml(name: str, make: Callable) -> Callable:
    def fit(df: DataFrame, features: list[str], label: str = "label", weight: str | None = None, **options) -> Fitted:
        rows = vectors(df, features).withColumn("_y", F.col(label).cast("double"))
        learner = make(**options).setLabelCol("_y").setFeaturesCol("features")
        return Fitted(name, features, (learner if weight is None else learner.setWeightCol(weight)).fit(rows))

    return fit


def _tree(depth: int = 20, max_bins: int = 32, min_rows: int = 1, **more):
    from pyspark.ml.classification import DecisionTreeClassifier

    return DecisionTreeClassifier(maxDepth=depth, maxBins=max_bins, minInstancesPerNode=min_rows, maxMemoryInMB=512, seed=1, **more)


def _forest(trees: int = 200, depth: int = 10, **more):
    from pyspark.ml.classification import RandomForestClassifier

    return RandomForestClassifier(numTrees=trees, maxDepth=depth, maxBins=32, maxMemoryInMB=512, seed=1, **more)


def _first(trees: int = 200, depth: int = 4, rate: float = 0.1, **more):
    from pyspark.ml.classification import GBTClassifier

    return GBTClassifier(maxIter=trees, maxDepth=depth, stepSize=rate, maxBins=32, maxMemoryInMB=512, checkpointInterval=10, seed=1, **more)


decision_tree, random_forest, boosted_first = _ml("decision_tree", _tree), _ml("random_forest", _forest), _ml("boosted_first", _first)


def second(df: DataFrame, features: list[str], label: str = "label", **options) -> Fitted:
    return Fitted("boosted_second", features, boosted_second(df, features, label, **options))


def capped_tree(df: DataFrame, features: list[str], label: str = "label", **options) -> Fitted:
    return Fitted("capped_tree", features, own_tree(df, features, label=label, **options))


LEARNERS = {"decision_tree": decision_tree, "random_forest": random_forest, "boosted_first": boosted_first, "boosted_second": second, "capped_tree": capped_tree}
#: The best settings reported, and settings that suit the small tables of tests.
BEST = {"decision_tree": {"depth": 20}, "random_forest": {"trees": 200}, "boosted_first": {"trees": 200}, "boosted_second": {"trees": 180}, "capped_tree": {"depth": 20, "max_nodes": 398}}
SMALL = {
    "decision_tree": {"depth": 5, "min_rows": 5}, "random_forest": {"trees": 20, "depth": 6}, "boosted_first": {"trees": 12, "depth": 3},
    "boosted_second": {"trees": 12, "depth": 3}, "capped_tree": {"depth": 6, "max_nodes": 20},
}


def balanced(train: DataFrame, balance: str) -> DataFrame:
    return weighted(train) if balance == "weight" else BALANCINGS[balance](train)


def evaluate(train: DataFrame, test: DataFrame, features: list[str], learner: str, options: dict, balance: str = "none", made: DataFrame | None = None) -> float:
    """AUC on the test part after fitting on the balanced training part; balance "weight" gives class weights to learners
    that take them (all but the second-order booster). made: the balanced part, where it is at hand."""
    more = {"weight": "weight"} if balance == "weight" else {}
    model = LEARNERS[learner](balanced(train, balance) if made is None else made, features, **more, **options)
    return measures.auc_value(model.score(test), bins=100_000)


def cross_validate(df: DataFrame, features: list[str], learner: str, grid: list[dict], k: int = 10, balance: str = "none", threads: int = 2) -> DataFrame:
    """(setting, fold, auc): every setting on every fold; only the training folds are balanced. Independent fits are
    submitted from a few threads, so small jobs overlap."""
    return cross_validate_all(df, features, {learner: grid}, k, balance, threads).drop("learner")


def cross_validate_all(df: DataFrame, features: list[str], grids: dict[str, list[dict]], k: int = 10, balance: str = "none", threads: int = 2) -> DataFrame:
    """(setting, fold, auc, learner): `cross_validate` of several learners. A fold's two parts, the balanced one with what
    the second-order learners bin, are written once for all settings."""
    from concurrent.futures import ThreadPoolExecutor

    parts = prepared(folds(df, k), features)
    second_order = [n for n in grids if n in ("boosted_second", "capped_tree")]

    def dealt(fold):
        train = kept(balanced(parts.where(F.col("fold") != fold), balance), "fold")
        return train, parts.where(F.col("fold") == fold), binned(train, features) if second_order else None

    def one(job):
        name, setting, fold = job
        train, test, bins = made[fold]
        options = {**setting, "ready": bins} if name in second_order else setting
        return str(setting), fold, evaluate(train, test, features, name, options, balance, train), name

    with ThreadPoolExecutor(threads) as pool:
        made = list(pool.map(dealt, range(k)))
        rows = list(pool.map(one, [(n, s, f) for n, grid in grids.items() for s in grid for f in range(k)]))
    return df.sparkSession.createDataFrame(rows, "setting STRING, fold INT, auc DOUBLE, learner STRING")


def repeated(train: DataFrame, test: DataFrame, features: list[str], learner: str, options: dict, times: int = 3) -> DataFrame:
    """(seed, auc) over several draws of the undersampled training part."""
    from .resample import undersample

    rows = []
    for seed in range(times):
        model = LEARNERS[learner](undersample(train, seed=f"under{seed}", exact=False), features, **options)
        rows.append((seed, measures.auc_value(model.score(test), bins=100_000)))
    return train.sparkSession.createDataFrame(rows, "seed INT, auc DOUBLE")
