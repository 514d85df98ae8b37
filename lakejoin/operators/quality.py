"""Similarity and quality of a join on the values themselves: the truth that profiles are held against."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

CLASSES = ("None", "Poor", "Moderate", "Good", "High")


@dataclass(frozen=True)
class Thresholds:
    """Least containment and least ratio of distinct counts of the classes 4, 3, 2 and, for containment, 1."""

    c: tuple[float, float, float, float] = (0.75, 0.5, 0.25, 0.1)
    k: tuple[float, float, float] = (1 / 4, 1 / 8, 1 / 12)

    def __post_init__(self):
        for name, xs in (("containment", self.c), ("ratio", self.k)):
            if any(a <= b for a, b in zip(xs, xs[1:])) or min(xs) <= 0:
                raise ValueError(f"{name} thresholds must fall strictly from class to class")


def quality_class(c: Column, k: Column, th: Thresholds = Thresholds(), use_ratio: bool = True) -> Column:
    """0..4 from containment and ratio |A| / |B|; a larger reference is never penalised by the ratio."""
    out = F.when(c >= th.c[3], 1).otherwise(0)
    for cls in (2, 3, 4):
        enough = c >= th.c[4 - cls]
        out = F.when(enough & (k >= th.k[4 - cls]) if use_ratio else enough, cls).otherwise(out)
    return out.cast("int")


def class_name(cls: Column) -> Column:
    return F.element_at(F.array(*map(F.lit, CLASSES)), cls + 1)


def max_feasible_class(ca: Column, cb: Column, th: Thresholds = Thresholds()) -> Column:
    """Best class two distinct counts allow: containment is at most min(1, |B| / |A|)."""
    return quality_class(F.least(F.lit(1.0), cb / ca), ca / cb, th)


def relation(n_common: Column, same_domain: Column) -> Column:
    """Syntactic and semantic relationship of a pair."""
    return F.when((n_common > 0) & same_domain, "semantic").when(n_common > 0, "syntactic only").when(same_domain, "semantic non-syntactic").otherwise("none")


#: Owners that one row of pairs is made from; larger sets are cut into blocks that spread over tasks.
BLOCK = 256


def attribute_id() -> Column:
    """An attribute is named by the two fields, whatever characters they hold."""
    return F.struct("dataset", "attr")


def intersections(freq: DataFrame, max_group: int | None = None) -> DataFrame:
    """(a, b, n_common): for each ordered pair of attributes of different datasets the distinct values they share.

    ``a`` and ``b`` are structs (dataset, attr). Values are shuffled once; those with the same owners collapse into one row
    before any pair is made, so pairs are made from owner sets (few), not from values (many). An owner set has at most one
    entry an attribute; one of more than ``BLOCK`` owners becomes a row for each two blocks of it, dealt out anew, so that
    no task pairs off all attributes of a lake. ``max_group`` leaves out owner sets beyond it, for lakes where values such as
    Y and N belong to all; the counts are then lower bounds. By default none is left out.
    """
    owners = freq.where(F.col("value").isNotNull()).groupBy("value").agg(F.sort_array(F.collect_set(attribute_id())).alias("owners"))
    owners = owners.where(F.size("owners") > 1 if max_group is None else F.size("owners").between(2, max_group))
    sets = owners.groupBy("owners").agg(F.count(F.lit(1)).alias("n"))
    small = sets.where(F.size("owners") <= BLOCK).select("n", F.col("owners").alias("left"), F.col("owners").alias("right"))
    block = lambda i: F.slice("owners", i * BLOCK + 1, F.lit(BLOCK))
    blocks = F.sequence(F.lit(0), F.floor((F.size("owners") - 1) / BLOCK).cast("int"))
    large = sets.where(F.size("owners") > BLOCK).select("n", "owners", F.explode(blocks).alias("i")).select("n", block(F.col("i")).alias("left"), "owners")
    large = large.select("n", "left", "owners", F.explode(blocks).alias("j")).select("n", "left", block(F.col("j")).alias("right")).hint("REPARTITION")
    paired = small.union(large).select("n", "right", F.explode("left").alias("a")).select("a", F.explode("right").alias("b"), "n")
    return paired.where(F.col("a.dataset") != F.col("b.dataset")).groupBy("a", "b").agg(F.sum("n").alias("n_common"))


def cardinalities(freq: DataFrame) -> DataFrame:
    """(id, dataset, attr, card)"""
    return freq.groupBy("dataset", "attr").agg(F.count("value").alias("card")).select(attribute_id().alias("id"), "dataset", "attr", "card")


def truth(freq: DataFrame, th: Thresholds = Thresholds(), use_ratio: bool = True) -> DataFrame:
    """Ids, n_common, containment, jaccard, ratio and class of all ordered pairs with a shared value."""
    cards = cardinalities(freq)
    side = lambda p: cards.select(F.col("id").alias(p), F.col("dataset").alias(f"{p}_d"), F.col("attr").alias(f"{p}_a"), F.col("card").alias(f"card_{p}"))
    met = intersections(freq).join(side("a"), "a").join(side("b"), "b")
    ca, cb, n = F.col("card_a"), F.col("card_b"), F.col("n_common")
    shaped = met.select(
        F.col("a_d").alias("ref_dataset"), F.col("a_a").alias("ref_attr"), F.col("b_d").alias("cand_dataset"), F.col("b_a").alias("cand_attr"),
        "n_common", F.col("card_a").alias("ref_card"), F.col("card_b").alias("cand_card"),
        (n / ca).alias("containment"), (n / (ca + cb - n)).alias("jaccard"), (ca / cb).alias("ratio"),
    )
    return shaped.withColumn("quality", quality_class(F.col("containment"), F.col("ratio"), th, use_ratio))


#: Hashes that a theta sketch holds at most, nominally (Spark's default, 2 to the 12th).
NOMINAL = 4096


def sketches(melted: DataFrame) -> DataFrame:
    """(dataset, attr, sketch): theta sketches of the distinct values, a few KB an attribute."""
    return melted.where(F.col("value").isNotNull()).groupBy("dataset", "attr").agg(F.theta_sketch_agg("value").alias("sketch"))


def sketch_error(n: Column, theta: Column) -> Column:
    """How far the estimate of ``n`` shared values may be off if each is seen with probability ``theta`` and counts 1 / theta. Four standard
    errors of a normal law are right for many seen values alone: a single one that is seen counts far more. So this is Bernstein's
    bound, with the exponent that four standard errors have; nothing where all values are seen."""
    most = F.when(theta < 1, F.greatest(F.lit(1.0), 1 / theta - 1)).otherwise(0.0)
    linear = most * 8 / 3
    return linear + F.sqrt(linear * linear + 16 * n * (1 / theta - 1))


def sketch_containment(left: DataFrame, right: DataFrame) -> DataFrame:
    """Approximate containment of pairs of different datasets from sketches alone."""
    l = left.select(F.col("dataset").alias("ref_dataset"), F.col("attr").alias("ref_attr"), F.col("sketch").alias("s"))  # noqa: E741
    r = right.select(F.col("dataset").alias("cand_dataset"), F.col("attr").alias("cand_attr"), F.col("sketch").alias("t"))
    both = l.join(r, F.col("ref_dataset") != F.col("cand_dataset"))
    size = F.theta_sketch_estimate("s")
    return both.select("ref_dataset", "ref_attr", "cand_dataset", "cand_attr", (F.theta_sketch_estimate(F.theta_intersection("s", "t")) / F.greatest(size, F.lit(1))).alias("containment"))
