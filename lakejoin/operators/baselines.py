"""Small baselines: attribute names alone, and rankings by one exact measure."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import pairs


def by_name(ref: DataFrame, lake: DataFrame, t: float = 0.3) -> DataFrame:
    """Pairs of different datasets whose names are at most ``t`` apart; (dataset, attr) tables in."""
    names = pairs.name_distances(ref, lake).where(F.col("name_distance") <= t)
    left = ref.select(F.col("dataset").alias("ref_dataset"), F.col("attr").alias("ref_attr"))
    right = lake.select(F.col("dataset").alias("cand_dataset"), F.col("attr").alias("cand_attr"))
    return left.join(names, "ref_attr").join(right, "cand_attr").where(F.col("ref_dataset") != F.col("cand_dataset")).select(*pairs.ID, "name_distance")


def measure_rank(truth: DataFrame, measure: str = "containment", k: int | None = None) -> DataFrame:
    """Pairs by an exact measure (containment or jaccard), best first."""
    ranked = truth.orderBy(F.desc(measure), *pairs.ID)
    return (ranked.limit(k) if k else ranked).select(*pairs.ID, measure, "quality")
