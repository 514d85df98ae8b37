"""Five one-vs-rest forests in a chain: each sees the distances and the probabilities of the classes before it."""

from __future__ import annotations

import json
import time
from dataclasses import dataclass, field

from pyspark.ml import Pipeline
from pyspark.ml.classification import RandomForestClassificationModel, RandomForestClassifier
from pyspark.ml.evaluation import BinaryClassificationEvaluator
from pyspark.ml.feature import VectorAssembler
from pyspark.ml.functions import vector_to_array
from pyspark.ml.tuning import CrossValidator, ParamGridBuilder
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .pairs import FEATURES
from .training import balanced, class_counts

#: Bins, depth and trees selected for each class; the grid they were searched in.
BEST = {0: (55, 25, 120), 1: (40, 25, 100), 2: (40, 30, 120), 3: (60, 30, 80), 4: (45, 20, 120)}
GRID = {"maxBins": (35, 40, 45, 50, 55, 60), "maxDepth": (20, 25, 30), "numTrees": (64, 70, 80, 90, 100, 110, 120, 128)}
#: Preset for tests and interactive work.
SMALL = {c: (32, 8, 16) for c in range(5)}
SEED = 42
#: Training rows to a partition.
ROWS = 100_000


def _inputs(cls: int, chained: bool) -> list[str]:
    return [*FEATURES, *(f"p{i}" for i in range(cls) if chained)]


def _forest(params: tuple[int, int, int]) -> RandomForestClassifier:
    bins, depth, trees = params
    return RandomForestClassifier(featuresCol="_x", labelCol="target", probabilityCol="_p", rawPredictionCol="_r", predictionCol="_y", maxBins=bins, maxDepth=depth, numTrees=trees, seed=SEED)


@dataclass
class ChainModel:
    forests: list[RandomForestClassificationModel]
    chained: bool = True
    seconds: list[float] = field(default_factory=list)

    def probabilities(self, df: DataFrame) -> DataFrame:
        """Adds p0..p4; five narrow projections, nothing is shuffled."""
        for cls, forest in enumerate(self.forests):
            df = VectorAssembler(inputCols=_inputs(cls, self.chained), outputCol="_x", handleInvalid="keep").transform(df)
            df = forest.transform(df).withColumn(f"p{cls}", vector_to_array("_p")[1]).drop("_x", "_p", "_r", "_y")
        return df

    def save(self, path: str) -> None:
        for cls, forest in enumerate(self.forests):
            forest.write().overwrite().save(f"{path}/forest{cls}")
        spark = SparkSession.getActiveSession()
        spark.createDataFrame([(json.dumps({"chained": self.chained, "n": len(self.forests), "seconds": self.seconds}),)], "meta string").coalesce(1).write.mode("overwrite").text(f"{path}/meta")

    @classmethod
    def load(cls, path: str) -> "ChainModel":
        meta = json.loads(SparkSession.getActiveSession().read.text(f"{path}/meta").first()[0])
        return cls([RandomForestClassificationModel.load(f"{path}/forest{i}") for i in range(meta["n"])], meta["chained"], meta["seconds"])


def fit_forest(sample: DataFrame, cls: int, params: tuple[int, int, int], chained: bool) -> RandomForestClassificationModel:
    """Rows are put in a fixed order and partition first, so the forest doesn't depend on how they came."""
    x = VectorAssembler(inputCols=_inputs(cls, chained), outputCol="_x", handleInvalid="keep").transform(sample)
    return _forest(params).fit(_ordered(x))


def _ordered(x: DataFrame) -> DataFrame:
    """Rows in the order of their ids, in one partition for each ``ROWS`` of them."""
    parts = max(4, -(-x.count() // ROWS))
    return x.select("_x", "target", "pair_id").repartitionByRange(parts, "pair_id").sortWithinPartitions("pair_id")


def fit_chain(labelled: DataFrame, params: dict[int, tuple[int, int, int]] = SMALL, chained: bool = True, out_of_fold: bool = False, balance: bool = True) -> ChainModel:
    """``out_of_fold`` gives each forest the earlier probabilities of models that haven't seen the row; ``balance`` off trains each
    on all rows (an ablation)."""
    counts = {r["label"]: r["n"] for r in class_counts(labelled).collect()}
    now, forests, seconds = labelled, [], []
    for cls in range(5):
        began = time.time()
        sample = balanced(now, cls, counts) if balance else now.withColumn("target", F.when(F.col("label") == cls, 1.0).otherwise(0.0))
        forest = fit_forest(sample, cls, params[cls], chained)
        forests.append(forest)
        seconds.append(round(time.time() - began, 3))
        if chained and cls < 4:
            if out_of_fold:
                fold = F.pmod(F.xxhash64("pair_id"), F.lit(2))
                halves = [ChainModel([fit_forest(balanced(now.where(fold != k), cls), cls, params[cls], chained)]).forests[0] for k in (0, 1)]
                parts = [_one(halves[k], now.where(fold == k), cls, chained) for k in (0, 1)]
                now = parts[0].unionByName(parts[1])
            else:
                now = _one(forest, now, cls, chained)
    return ChainModel(forests, chained, seconds)


def _one(forest: RandomForestClassificationModel, df: DataFrame, cls: int, chained: bool) -> DataFrame:
    x = VectorAssembler(inputCols=_inputs(cls, chained), outputCol="_x", handleInvalid="keep").transform(df)
    return forest.transform(x).withColumn(f"p{cls}", vector_to_array("_p")[1]).drop("_x", "_p", "_r", "_y")


def fit_multiclass(labelled: DataFrame, params: tuple[int, int, int] = SMALL[0]):
    """One forest over all five classes, unbalanced: the ablation of the one-vs-rest chain."""
    x = VectorAssembler(inputCols=list(FEATURES), outputCol="_x", handleInvalid="keep").transform(labelled.withColumn("target", F.col("label").cast("double")))
    return _forest(params).fit(_ordered(x))


def predict_multiclass(model, df: DataFrame) -> DataFrame:
    x = VectorAssembler(inputCols=list(FEATURES), outputCol="_x", handleInvalid="keep").transform(df)
    return model.transform(x).withColumn("pred_class", F.col("_y").cast("int")).drop("_x", "_p", "_r", "_y")


def tune(labelled: DataFrame, grid: dict[str, tuple[int, ...]] = GRID, folds: int = 5, split: float = 0.8, parallelism: int = 4, chained: bool = True) -> dict:
    """Grid search of every forest with k-fold cross-validation on ``split`` of its sample; the rest is the report."""
    now, out = labelled, {}
    for cls in range(5):
        began = time.time()
        cut = F.pmod(F.xxhash64("pair_id", F.lit(cls)), F.lit(1000)) < int(1000 * split)
        sample = balanced(now, cls)
        assembler = VectorAssembler(inputCols=_inputs(cls, chained), outputCol="_x", handleInvalid="keep")
        forest = _forest((32, 8, 16))
        builder = ParamGridBuilder()
        for name, values in grid.items():
            builder = builder.addGrid(getattr(forest, name), list(values))
        judge = BinaryClassificationEvaluator(rawPredictionCol="_r", labelCol="target")
        search = CrossValidator(estimator=Pipeline(stages=[assembler, forest]), estimatorParamMaps=builder.build(), evaluator=judge, numFolds=folds, parallelism=parallelism, seed=SEED)
        found = search.fit(sample.where(cut))
        best = found.bestModel.stages[-1]
        out[cls] = {"maxBins": best.getMaxBins(), "maxDepth": best.getMaxDepth(), "numTrees": best.getNumTrees, "cv_auc": max(found.avgMetrics), "test_auc": judge.evaluate(found.transform(sample.where(~cut))), "seconds": round(time.time() - began, 2)}
        now = _one(best, now, cls, chained)
    return out
