"""Accuracy measures on pairs with a true and a predicted class."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def confusion(df: DataFrame, by: str | None = None, truth: str = "label", pred: str = "pred_class") -> DataFrame:
    """(truth, pred, n) with all 25 cells, zeros included; for each value of ``by`` too."""
    spark = df.sparkSession
    cells = spark.range(5).select(F.col("id").cast("int").alias("truth")).join(spark.range(5).select(F.col("id").cast("int").alias("pred")), F.lit(True))
    keys = ["truth", "pred"]
    got = df.select(F.col(truth).cast("int").alias("truth"), F.col(pred).cast("int").alias("pred"), *([F.col(by)] if by else []))
    if by:
        cells, keys = cells.join(got.select(by).distinct(), F.lit(True)), [by, *keys]
    counts = got.groupBy(*keys).agg(F.count(F.lit(1)).alias("n"))
    return cells.join(counts, keys, "left").withColumn("n", F.coalesce("n", F.lit(0)).cast("bigint"))


def matrix(cm: DataFrame) -> DataFrame:
    """One row a true class, columns pred0..pred4."""
    wide = cm.groupBy("truth").pivot("pred", list(range(5))).agg(F.sum("n"))
    return wide.select("truth", *[F.coalesce(F.col(str(i)), F.lit(0)).alias(f"pred{i}") for i in range(5)])


def _ratio(a: Column, b: Column) -> Column:
    return F.when(b > 0, a / b)


def _prf(tp: Column, pred: Column, true: Column) -> list[Column]:
    p, r = _ratio(tp, pred), _ratio(tp, true)
    return [p.alias("precision"), r.alias("recall"), F.when(p + r > 0, 2 * p * r / (p + r)).alias("f1")]


def per_class(cm: DataFrame, by: list[str] | None = None) -> DataFrame:
    """Precision, recall and F1 of each class; null where nothing was predicted or is true."""
    keys = by or []
    long = cm.select(*keys, F.explode(F.array(F.struct(F.col("truth").alias("cls"), F.lit("t").alias("side")), F.struct(F.col("pred").alias("cls"), F.lit("p").alias("side")))).alias("s"), "n", (F.col("truth") == F.col("pred")).alias("hit"))
    summed = long.groupBy(*keys, F.col("s.cls").alias("cls")).agg(
        F.sum(F.when((F.col("s.side") == "t") & F.col("hit"), F.col("n")).otherwise(0)).alias("tp"),
        F.sum(F.when(F.col("s.side") == "p", F.col("n")).otherwise(0)).alias("predicted"),
        F.sum(F.when(F.col("s.side") == "t", F.col("n")).otherwise(0)).alias("actual"),
    )
    return summed.select(*keys, "cls", *_prf(F.col("tp"), F.col("predicted"), F.col("actual")))


def binary(cm: DataFrame, cut: int = 3, by: list[str] | None = None) -> DataFrame:
    """TN, FP, FN, TP, precision, recall and F1 with the classes from ``cut`` on as interesting."""
    t, p = F.col("truth") >= cut, F.col("pred") >= cut
    cell = lambda c, name: F.sum(F.when(c, F.col("n")).otherwise(0)).alias(name)
    one = cm.groupBy(*(by or [])).agg(cell(~t & ~p, "tn"), cell(~t & p, "fp"), cell(t & ~p, "fn"), cell(t & p, "tp"))
    return one.select("*", *_prf(F.col("tp"), F.col("tp") + F.col("fp"), F.col("tp") + F.col("fn")))


def error_profile(cm: DataFrame) -> DataFrame:
    """(step, n): how far predictions fall from the truth; negative is too cautious."""
    return cm.groupBy((F.col("pred") - F.col("truth")).alias("step")).agg(F.sum("n").alias("n"))


def semantic_share(df: DataFrame, pred: str = "pred_class", same: str = "same_domain", cut: int = 3) -> DataFrame:
    """Share of proposed interesting pairs whose columns mean the same."""
    return df.where(F.col(pred) >= cut).agg(F.count(F.lit(1)).alias("proposed"), F.avg(F.col(same).cast("double")).alias("semantic_share"))


def share_predicted(cm: DataFrame, classes: tuple[int, ...] = (1, 2, 3), truth: tuple[int, ...] | None = None) -> DataFrame:
    """Share of pairs (of the true classes given) predicted in ``classes``."""
    rows = cm if truth is None else cm.where(F.col("truth").isin(*truth))
    hit = F.sum(F.when(F.col("pred").isin(*classes), F.col("n")).otherwise(0))
    return rows.agg(hit.alias("hit"), F.sum("n").alias("total")).select("hit", "total", _ratio(F.col("hit"), F.col("total")).alias("share"))
