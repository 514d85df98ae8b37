"""From five probabilities to one class, with two downgrades that guard class 0, and to a ranking."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .pairs import ID

_P = F.array


def _probabilities() -> Column:
    return F.array(*[F.col(f"p{i}") for i in range(5)])


def argmax_class(p: Column) -> Column:
    """Smallest index of the maximum: ties go to the lower class."""
    return (F.array_position(p, F.array_max(p)) - 1).cast("int")


def assign(df: DataFrame, tau: float = 0.10, rule1: bool = True, rule2: bool = True) -> DataFrame:
    """Adds raw_class, rule (0, 1 or 2), pred_class and score. A rule downgrades once, to the best lower class."""
    p, raw, eps = _probabilities(), F.col("raw_class"), 1e-12
    df = df.withColumn("raw_class", argmax_class(p))
    fires1 = F.lit(rule1) & (F.col("p0") > 0.5) & (raw >= 1)
    fires2 = F.lit(rule2) & (F.array_max(p) < 0.5) & (raw >= 1) & (F.array_max(p) - F.col("p0") <= tau + eps)
    df = df.withColumn("rule", F.when(fires1, 1).when(fires2, 2).otherwise(0))
    lower = argmax_class(F.slice(p, F.lit(1), F.greatest(raw, F.lit(1))))
    df = df.withColumn("pred_class", F.when(F.col("rule") > 0, lower).otherwise(raw))
    return df.withColumn("score", F.element_at(p, F.col("pred_class") + 1))


def rank(df: DataFrame, top: int | None = None) -> DataFrame:
    """Best class first, then its probability, then names; ``rank`` is the place of the class in the partial order."""
    order = [F.desc("pred_class"), F.desc("score"), *ID]
    ranked = df.orderBy(*order) if top is None else df.orderBy(*order).limit(top)
    return ranked.withColumn("rank", 5 - F.col("pred_class"))


def best_per_attribute(df: DataFrame, k: int = 3) -> DataFrame:
    order = Window.partitionBy("ref_dataset", "ref_attr").orderBy(F.desc("pred_class"), F.desc("score"), "cand_dataset", "cand_attr")
    return df.withColumn("place", F.row_number().over(order)).where(F.col("place") <= k)


def page(df: DataFrame, level: str = "interesting") -> DataFrame:
    """What a user sees: classes 4 and 3 at first, 2 and 1 on demand."""
    return df.where(F.col("pred_class") >= (3 if level == "interesting" else 1))
