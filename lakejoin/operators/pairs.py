"""Pairs of attributes and their distance vectors; 0 means alike."""

from __future__ import annotations

from pyspark.ml.feature import VectorAssembler
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.valuetypes import BROAD, SPECIFIC
from .quality import Thresholds
from .scaling import SCALED

PLAIN = ("uniqueness", "incompleteness", *(f"octile{k}" for k in range(1, 8)), "pct_min", "pct_max", "pct_sd", "constancy")
SETS, KINDS = ("top_words", "top_soundex"), ("data_type", "specific_type")
SHARES = tuple(f"share_{t}" for t in (*BROAD, *SPECIFIC))
#: The 45 features of a pair, in order.
FEATURES = (*(f"d_{c}" for c in (*SCALED, *PLAIN, *SETS, *KINDS, *SHARES)), "best_containment", "flipped_containment", "name_distance")
ID = ("ref_dataset", "ref_attr", "cand_dataset", "cand_attr")


def best_containment(a: Column, b: Column) -> Column:
    """Containment if every distinct value of the smaller attribute were in the other."""
    return F.least(a, b) / a


def flipped_containment(a: Column, b: Column) -> Column:
    return F.least(a, b) / F.greatest(a, b)


def name_distance(a: Column, b: Column) -> Column:
    """Levenshtein distance over the longer name's length."""
    longer = F.greatest(F.length(a), F.length(b))
    return F.when(longer == 0, 0.0).otherwise(F.levenshtein(a, b) / longer)


def name_distances(left: DataFrame, right: DataFrame) -> DataFrame:
    """(ref_attr, cand_attr, name_distance), once for each distinct pair of names."""
    names = left.select(F.col("attr").alias("ref_attr")).distinct().join(right.select(F.col("attr").alias("cand_attr")).distinct(), F.lit(True))
    return names.withColumn("name_distance", name_distance(F.col("ref_attr"), F.col("cand_attr")))


def pair_id() -> Column:
    """One string for the four names; bars and backslashes inside a name are escaped, so no two pairs share one."""
    plain = lambda c: F.replace(F.replace(F.col(c), F.lit("\\"), F.lit("\\\\")), F.lit("|"), F.lit("\\|"))
    return F.concat_ws("|", *map(plain, ID))


def _sides(ref: DataFrame, lake: DataFrame) -> tuple[DataFrame, DataFrame]:
    return tuple(df.select(*[F.col(c).alias(f"{p}_{c}") for c in df.columns]) for df, p in ((ref, "ref"), (lake, "cand")))


def candidates(ref: DataFrame, lake: DataFrame, small_ref: bool = False) -> DataFrame:
    """Every attribute of ``ref`` with every attribute of another dataset. A reference of a few attributes (its
    columns bound it) is broadcast, so that the store is read once and never shuffled."""
    left, right = _sides(ref, lake)
    return right.join(F.broadcast(left) if small_ref else left, F.col("ref_dataset") != F.col("cand_dataset"))


def pruned_candidates(ref: DataFrame, lake: DataFrame, min_class: int = 1, th: Thresholds = Thresholds()) -> DataFrame:
    """Only pairs whose cardinalities let the class reach ``min_class``: an equi-join of doubling cardinality buckets with
    a range check. Loses no pair that truly reaches the class; work follows the band, not all pairs."""
    c, k = th.c[4 - min_class], th.k[4 - min_class] if min_class > 1 else None
    left, right = _sides(ref, lake)
    bucket = lambda x: F.floor(F.log2(F.greatest(x, F.lit(1)).cast("double"))).cast("int")
    a, b = F.col("ref_cardinality"), F.col("cand_cardinality")
    # |A| / |B| lies in [k, 1 / c]
    low = F.when(F.lit(k is None), F.lit(62)).otherwise(F.ceil(F.log2(F.lit(1.0 / (k or 1.0)))) + 1)
    reach = F.sequence(F.greatest(F.lit(0), bucket(a) - int(-(-_log2(1 / c) // 1)) - 1), F.least(F.lit(62), bucket(a) + low.cast("int")))
    spread = left.withColumn("bucket", F.explode(reach))
    near = spread.join(right.withColumn("bucket", bucket(b)), "bucket").where(F.col("ref_dataset") != F.col("cand_dataset"))
    fits = (a * c <= b) if k is None else (a * c <= b) & (a >= b * k - 1e-9)
    return near.where(fits).drop("bucket")


def _log2(x: float) -> float:
    from math import log2

    return log2(x)


def _jaccard_distance(a: Column, b: Column) -> Column:
    every = F.size(F.array_union(a, b))
    return F.when(every == 0, 0.0).otherwise(1 - F.size(F.array_intersect(a, b)) / every)


def distances(paired: DataFrame, signed: bool = False) -> DataFrame:
    """Ids and the 45 features. ``signed`` keeps the direction of differences (an ablation)."""
    l, r = (lambda c: F.col(f"ref_{c}")), (lambda c: F.col(f"cand_{c}"))  # noqa: E741
    size = (lambda x: x) if signed else F.abs
    gap = lambda a, b: size(F.coalesce(a, F.lit(0.0)) - F.coalesce(b, F.lit(0.0)))
    octile = lambda side, k: F.get(side("octiles"), F.lit(k - 1))
    out = [gap(l(f"z_{c}"), r(f"z_{c}")).alias(f"d_{c}") for c in SCALED]
    out += [(gap(octile(l, int(c[-1])), octile(r, int(c[-1]))) if c.startswith("octile") else gap(l(c), r(c))).alias(f"d_{c}") for c in PLAIN]
    out += [_jaccard_distance(l(c), r(c)).alias(f"d_{c}") for c in SETS]
    out += [F.when(l(c).eqNullSafe(r(c)), 0.0).otherwise(1.0).alias(f"d_{c}") for c in KINDS]
    out += [gap(l(c), r(c)).alias(f"d_{c}") for c in SHARES]
    ca, cb = l("cardinality"), r("cardinality")
    out += [best_containment(ca, cb).alias("best_containment"), flipped_containment(ca, cb).alias("flipped_containment"), name_distance(l("attr"), r("attr")).alias("name_distance")]
    return paired.select(*ID, ca.alias("ref_cardinality"), cb.alias("cand_cardinality"), *out)


def assemble(df: DataFrame, extra: tuple[str, ...] = (), to: str = "features") -> DataFrame:
    return VectorAssembler(inputCols=[*FEATURES, *extra], outputCol=to, handleInvalid="keep").transform(df)
