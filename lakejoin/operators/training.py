"""Labelled pairs and the balanced one-vs-rest samples a forest is trained on."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .pairs import ID, pair_id


#: Hex digits of the md5 that make a bucket of the sample's counts.
DIGITS = 3


def labelled_pairs(distances: DataFrame, truth: DataFrame) -> DataFrame:
    """Distance vectors with the true class in ``label``; pairs without a shared value are class 0."""
    return distances.join(truth.select(*ID, F.col("quality")), list(ID), "left").withColumn("label", F.coalesce("quality", F.lit(0))).drop("quality").withColumn("pair_id", pair_id())


def class_counts(labelled: DataFrame) -> DataFrame:
    return labelled.groupBy("label").agg(F.count(F.lit(1)).alias("n"))


def quotas(counts: dict[int, int], cls: int) -> dict[int, int]:
    """Rows of each class for the forest of ``cls``: as many negatives as positives, spread evenly over the other
    classes from the smallest on, what a small class can't give going to the rest."""
    others = sorted(((n, c) for c, n in counts.items() if c != cls))
    total = min(counts.get(cls, 0), sum(n for n, _ in others))
    out, left = {cls: total}, total
    for i, (n, c) in enumerate(others):
        give = left if i == len(others) - 1 else min(n, left // (len(others) - i))
        out[c] = min(n, give)
        left -= out[c]
    return out


def balanced(labelled: DataFrame, cls: int, counts: dict[int, int] | None = None) -> DataFrame:
    """Sample for the forest of ``cls``, picked by the md5 of the pair's id, with ``target`` 1 for the class.

    A class gives the rows of least md5 up to its quota. Counts by the first ``DIGITS`` hex digits tell how far whole buckets
    go; only the bucket in which the quota ends is ranked, so no task sorts a class, however large.
    """
    counts = counts or {r["label"]: r["n"] for r in class_counts(labelled).collect()}  # five rows
    quota = F.lit(0)
    for c, n in quotas(counts, cls).items():
        quota = F.when(F.col("label") == c, n).otherwise(quota)
    key = F.md5("pair_id")
    bucket = F.conv(F.substring(key, 1, DIGITS), 16, 10).cast("int")
    sizes = labelled.groupBy("label", bucket.alias("_bucket")).agg(F.count(F.lit(1)).alias("_n"))
    upto = F.sum("_n").over(Window.partitionBy("label").orderBy("_bucket"))  # at most 16 ** DIGITS rows a class
    ends = sizes.withColumn("_upto", upto).where(F.col("_upto") >= quota).groupBy("label").agg(F.min(F.struct("_bucket", (F.col("_upto") - F.col("_n")).alias("_before"))).alias("_end"))
    ends = ends.select("label", F.col("_end._bucket").alias("_end"), F.col("_end._before").alias("_before"))
    marked = labelled.withColumn("_bucket", bucket).join(F.broadcast(ends), "label")  # five rows
    whole = marked.where(F.col("_bucket") < F.col("_end"))
    order = Window.partitionBy("label", "_bucket").orderBy(key, "pair_id")
    part = marked.where(F.col("_bucket") == F.col("_end")).withColumn("_n", F.row_number().over(order)).where(F.col("_n") <= quota - F.col("_before")).drop("_n")
    return whole.unionByName(part).drop("_bucket", "_end", "_before").withColumn("target", F.when(F.col("label") == cls, 1.0).otherwise(0.0))
