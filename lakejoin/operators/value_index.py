"""Comparison by value: an inverted index of values, exact and expensive."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def build(freq: DataFrame) -> DataFrame:
    """(value, dataset, attr), distinct values only."""
    return freq.where(F.col("value").isNotNull()).select("value", "dataset", "attr")


def save(index: DataFrame, table: str, buckets: int = 32) -> None:
    """Bucketed by value, so that repeated queries don't shuffle the index."""
    index.write.bucketBy(buckets, "value").sortBy("value").mode("overwrite").saveAsTable(table)


def query(index: DataFrame, dataset: str, attr: str, threshold: float = 0.5, measure: str = "containment") -> DataFrame:
    """(cand_dataset, cand_attr, n_common, score) of attributes of other datasets at or over the threshold."""
    mine = (F.col("dataset") == dataset) & (F.col("attr") == attr)
    ref = index.where(mine).select("value")
    size = ref.agg(F.count(F.lit(1)).alias("ref_card"))
    others = index.where(F.col("dataset") != dataset)
    hits = others.join(ref, "value", "left_semi").groupBy("dataset", "attr").agg(F.count(F.lit(1)).alias("n_common"))
    if measure == "containment":
        score = F.col("n_common") / F.col("ref_card")
    else:
        hits = hits.join(others.groupBy("dataset", "attr").agg(F.count(F.lit(1)).alias("card")), ["dataset", "attr"])
        score = F.col("n_common") / (F.col("ref_card") + F.col("card") - F.col("n_common"))
    scored = hits.crossJoin(F.broadcast(size)).withColumn("score", score)
    return scored.where(F.col("score") >= threshold).select(F.col("dataset").alias("cand_dataset"), F.col("attr").alias("cand_attr"), "n_common", "score")


def coverage(index: DataFrame, left: tuple[str, str], right: tuple[str, str]) -> DataFrame:
    """(covered, missing): values of one attribute that another has and lacks, by semi and anti join."""
    of = lambda k: index.where((F.col("dataset") == k[0]) & (F.col("attr") == k[1])).select("value")
    count = lambda df, name: df.agg(F.count(F.lit(1)).alias(name))
    return count(of(left).join(of(right), "value", "left_semi"), "covered").crossJoin(count(of(left).join(of(right), "value", "left_anti"), "missing"))
