"""Which meta-features matter: principal components of vectors, and importances in the forests."""

from __future__ import annotations

from pyspark.ml.feature import PCA, StandardScaler
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .chain import ChainModel
from .pairs import FEATURES, PLAIN, SETS, assemble
from .scaling import SCALED

_CARD = ("cardinality", "entropy", "uniqueness", "incompleteness")


def category(feature: str) -> str:
    name = feature.removeprefix("d_")
    if name in ("best_containment", "flipped_containment", "name_distance"):
        return "pair"
    if name in _CARD:
        return "cardinalities"
    if name in (*PLAIN, *SETS) or name.startswith("freq") and name in SCALED:
        return "value distribution"
    return "syntactic"


def pca(vectors: DataFrame, k: int = 10) -> DataFrame:
    """(component, variance): share of variance explained by each of the first k components."""
    scaled = StandardScaler(inputCol="features", outputCol="scaled", withMean=True, withStd=True)
    x = assemble(vectors)
    model = PCA(k=k, inputCol="scaled", outputCol="pc").fit(scaled.fit(x).transform(x))
    return vectors.sparkSession.createDataFrame([(i + 1, float(v)) for i, v in enumerate(model.explainedVariance)], "component int, variance double")


def importances(df: DataFrame, model: ChainModel) -> DataFrame:
    """(cls, feature, category, importance)"""
    rows = []
    for cls, forest in enumerate(model.forests):
        names = [*FEATURES, *(f"p{i}" for i in range(cls) if model.chained)]
        rows += [(cls, n, "chain" if n[0] == "p" and n[1:].isdigit() else category(n), float(v)) for n, v in zip(names, forest.featureImportances.toArray())]
    return df.sparkSession.createDataFrame(rows, "cls int, feature string, category string, importance double")


def by_category(importance: DataFrame) -> DataFrame:
    return importance.groupBy("cls", "category").agg(F.sum("importance").alias("importance"))
