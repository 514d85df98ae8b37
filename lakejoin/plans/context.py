"""Tables that many queries share, computed once for a session and folder and kept in the shared folder."""

from __future__ import annotations

from functools import cached_property

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import chain, discover, pairs, profile, quality, scaling, size_lsh, training
from ..session import stored
from ..sources import derived, lake

_made: dict[tuple[str, str], "Context"] = {}


def context(spark: SparkSession, sf_dir: str) -> "Context":
    key = (spark.sparkContext.applicationId, sf_dir)
    if key not in _made:
        _made[key] = Context(spark, sf_dir)
    return _made[key]


def split_of(dataset) -> F.Column:
    return F.expr(derived.split_sql("dataset")) if dataset is None else dataset


class Context:
    def __init__(self, spark: SparkSession, sf_dir: str):
        self.spark, self.dir = spark, sf_dir

    def table(self, name: str) -> DataFrame:
        return self.spark.read.parquet(f"{self.dir}/{name}.parquet")

    @cached_property
    def freq(self) -> DataFrame:
        return stored(profile.frequencies(lake.derived_melted(self.spark, self.dir)))

    @cached_property
    def profiles(self) -> DataFrame:
        return stored(profile.profiles(self.freq))

    @cached_property
    def strings(self) -> DataFrame:
        """Profiles past the second gate."""
        return stored(profile.string_attributes(self.profiles))

    @cached_property
    def scaled(self) -> DataFrame:
        return stored(scaling.apply_zscore(self.strings, scaling.fit_zscore(self.strings)))

    @cached_property
    def string_freq(self) -> DataFrame:
        """Frequency table of the gated attributes."""
        return stored(self.freq.join(self.strings.select("dataset", "attr"), ["dataset", "attr"], "left_semi"))

    @cached_property
    def vectors(self) -> DataFrame:
        return stored(pairs.distances(pairs.candidates(self.scaled, self.scaled)))

    @cached_property
    def truth(self) -> DataFrame:
        return stored(quality.truth(self.string_freq))

    def part(self, which: str) -> DataFrame:
        """Labelled vectors of pairs inside the train or the test lake, scaled over that lake alone."""
        own = stored(self.strings.where(F.expr(derived.split_sql("dataset")) == which))
        return stored(training.labelled_pairs(discover.vectors(own, own, small_ref=False), self.truth))

    @cached_property
    def train(self) -> DataFrame:
        return self.part("train")

    @cached_property
    def test(self) -> DataFrame:
        return self.part("test")

    @cached_property
    def model(self) -> chain.ChainModel:
        return chain.fit_chain(self.train, chain.BEST)

    @cached_property
    def unchained(self) -> chain.ChainModel:
        return chain.fit_chain(self.train, chain.BEST, chained=False)

    @cached_property
    def predicted(self) -> DataFrame:
        """Test pairs with label and prediction."""
        return stored(discover.predict(self.test, self.model).join(self.test.select(*pairs.ID, "label"), list(pairs.ID)))

    @cached_property
    def signatures(self) -> DataFrame:
        return stored(size_lsh.partitions(size_lsh.signatures(self.string_freq)))

    @cached_property
    def matched(self) -> DataFrame:
        """Pairs of the test lake that the matcher proposes."""
        from .comparison import matcher_hits

        found = matcher_hits(self)
        return stored(self.test.select(*pairs.ID).limit(0) if found is None else found)
