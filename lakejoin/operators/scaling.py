"""Bringing meta-features of different magnitude together: z-scores, and min-max as the rejected alternative."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: The meta-features that are normalised.
SCALED = ("cardinality", "entropy", "freq_avg", "freq_min", "freq_max", "freq_sd", "len_max", "len_min", "len_avg", "words_total", "words_avg", "words_min", "words_max", "words_sd")


def fit_zscore(profiled: DataFrame) -> DataFrame:
    """One row: mean and population deviation of each meta-feature over the attributes given."""
    return profiled.agg(*[f(F.col(c).cast("double")).alias(f"{c}__{n}") for c in SCALED for n, f in (("mean", F.avg), ("sd", F.stddev_pop))])


def apply_zscore(profiled: DataFrame, stats: DataFrame) -> DataFrame:
    """``z_<feature>`` columns; no spread gives 0, a missing value 0. ``stats`` is one row, so it is broadcast."""
    both = profiled.crossJoin(F.broadcast(stats))
    z = lambda c: F.coalesce(F.when(F.col(f"{c}__sd") > 0, (F.col(c) - F.col(f"{c}__mean")) / F.col(f"{c}__sd")), F.lit(0.0))
    return both.withColumns({f"z_{c}": z(c) for c in SCALED}).drop(*[f"{c}__{n}" for c in SCALED for n in ("mean", "sd")])


def fit_minmax(profiled: DataFrame) -> DataFrame:
    return profiled.agg(*[f(F.col(c).cast("double")).alias(f"{c}__{n}") for c in SCALED for n, f in (("lo", F.min), ("hi", F.max))])


def apply_minmax(profiled: DataFrame, stats: DataFrame) -> DataFrame:
    both = profiled.crossJoin(F.broadcast(stats))
    m = lambda c: F.coalesce(F.when(F.col(f"{c}__hi") > F.col(f"{c}__lo"), (F.col(c) - F.col(f"{c}__lo")) / (F.col(f"{c}__hi") - F.col(f"{c}__lo"))), F.lit(0.0))
    return both.withColumns({f"z_{c}": m(c) for c in SCALED}).drop(*[f"{c}__{n}" for c in SCALED for n in ("lo", "hi")])
