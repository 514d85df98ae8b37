"""Discovery: which attributes of a lake join well with one reference attribute, or with a reference table."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import pairs, profile, ranking, scaling
from .chain import ChainModel


def vectors(ref: DataFrame, lake: DataFrame, small_ref: bool = True, min_class: int = 0, stats: DataFrame | None = None) -> DataFrame:
    """Distance vectors of reference profiles against lake profiles, z-scored by the statistics of the lake (or by ``stats``).

    The lake's own statistics, which a profile store can keep, are the same for every reference: so a pair has one vector,
    whether its attribute or its whole dataset is asked about.
    """
    if stats is None:
        stats = scaling.fit_zscore(lake)
    a, b = scaling.apply_zscore(ref, stats), scaling.apply_zscore(lake, stats)
    paired = pairs.pruned_candidates(a, b, min_class) if min_class > 1 else pairs.candidates(a, b, small_ref)
    return pairs.distances(paired)


def predict(vector_table: DataFrame, model: ChainModel, **rules) -> DataFrame:
    """Class of each pair from its vector alone; no value is looked at."""
    scored = ranking.assign(model.probabilities(vector_table), **rules)
    return scored.select(*pairs.ID, *[f"p{i}" for i in range(5)], "raw_class", "rule", "pred_class", "score")


def by_attribute(ref: DataFrame, attr: str, lake: DataFrame, model: ChainModel, min_class: int = 1, top: int | None = None, stats: DataFrame | None = None) -> DataFrame:
    """Ranking for one attribute; ``ref`` and ``lake`` are profiles. Cost follows attributes, not rows."""
    return by_dataset(ref.where(F.col("attr") == attr), lake, model, min_class, top, stats)


def by_dataset(ref: DataFrame, lake: DataFrame, model: ChainModel, min_class: int = 1, top: int | None = None, stats: DataFrame | None = None) -> DataFrame:
    found = predict(vectors(profile.string_attributes(ref), profile.string_attributes(lake), stats=stats), model)
    return ranking.rank(found.where(F.col("pred_class") >= min_class), top)


def all_pairs(lake: DataFrame, model: ChainModel, min_class: int = 0, stats: DataFrame | None = None) -> DataFrame:
    """Every pair of the lake; from ``min_class`` 1 on only pairs whose cardinalities allow that class are made, by an
    equi-join, and those the chain puts there are returned: no pair that is truly of the class is left out."""
    strings = profile.string_attributes(lake)
    stats = scaling.fit_zscore(strings) if stats is None else stats
    a = scaling.apply_zscore(strings, stats)
    if min_class < 1:
        return predict(pairs.distances(pairs.candidates(a, a)), model)
    return predict(pairs.distances(pairs.pruned_candidates(a, a, min_class)), model).where(F.col("pred_class") >= min_class)
