"""Unary profiles: one row a string attribute, folded from one shared frequency table.

A lake is scanned once. Values are counted by attribute (the one shuffle of data size; near-unique columns can take
the sketch form, which shuffles no values); syntax is looked at once a distinct value; all statistics
fold in one aggregation, and the most frequent words in a second.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions import normalize, valuetypes
from ..session import stored

KEY = ("dataset", "attr")
OCTILES = tuple(k / 8 for k in range(1, 8))
TOP = 10


def frequencies(melted: DataFrame) -> DataFrame:
    """(dataset, attr, value, cnt); a null value counts the missing ones."""
    return melted.groupBy("dataset", "attr", "value").agg(F.count(F.lit(1)).alias("cnt"))


def value_table(freq: DataFrame) -> DataFrame:
    """The frequency table with what each distinct value's text shows."""
    n = normalize.lowered(F.col("value"))
    return freq.withColumn("n", n).select(
        *KEY, "value", "cnt",
        valuetypes.broad_type(F.col("n")).alias("broad"),
        valuetypes.specific_type(F.col("n")).alias("specific"),
        normalize.char_length(F.col("n")).alias("chars"),
        F.size(normalize.tokens(F.col("n"))).alias("n_words"),
    )


def _dominant(shares: list[tuple[str, Column]]) -> Column:
    """Name of the largest share; the first listed wins ties."""
    top = F.greatest(*[s for _, s in shares])
    out = F.lit(None).cast("string")
    for name, share in reversed(shares):
        out = F.when(share == top, name).otherwise(out)
    return out


def statistics(values: DataFrame, weight: str = "rows", entropy_kind: str = "shannon", blank_as_null: bool = False) -> DataFrame:
    """All single-number features and octiles. ``weight`` 'distinct' counts each distinct value's words once."""
    c, here = F.col("cnt"), F.col("value").isNotNull()
    if blank_as_null:
        here = here & (F.trim("value") != "")
    v = lambda x: F.when(here, x)
    w = v(c) if weight == "rows" else v(F.lit(1))
    words, chars = F.col("n_words"), F.col("chars")
    one = values.groupBy(*KEY).agg(
        F.sum("cnt").alias("n_rows"),
        F.coalesce(F.sum(v(c)), F.lit(0)).alias("n_nonnull"),
        F.count(v(c)).alias("cardinality"),
        F.sum(v(c * F.log2(c))).alias("_clogc"),
        F.sum(v(c * c)).alias("_c2"),
        F.avg(v(c)).alias("freq_avg"),
        F.min(v(c)).alias("freq_min"),
        F.max(v(c)).alias("freq_max"),
        F.stddev_pop(v(c)).alias("freq_sd"),
        F.percentile(v(c), F.array(*map(F.lit, OCTILES))).alias("_octiles"),
        F.max(v(chars)).alias("len_max"),
        F.min(v(chars)).alias("len_min"),
        F.sum(v(chars * c)).alias("_chars"),
        F.sum(words * w).alias("words_total"),
        F.min(v(words)).alias("words_min"),
        F.max(v(words)).alias("words_max"),
        F.sum(words * words * w).alias("_words2"),
        F.sum(w).alias("_w"),
        *[F.sum(v(F.when(F.col("broad") == t, c).otherwise(0))).alias(f"_b_{t}") for t in valuetypes.BROAD],
        *[F.sum(v(F.when(F.col("specific") == t, c).otherwise(0))).alias(f"_s_{t}") for t in valuetypes.SPECIFIC],
    )
    n = F.when(F.col("n_nonnull") > 0, F.col("n_nonnull"))
    entropy = F.log2(n) - F.col("_clogc") / n if entropy_kind == "shannon" else 1 - F.col("_c2") / (n * n)
    mean = F.col("words_total") / F.col("_w")
    return one.select(
        *KEY, "n_rows", "n_nonnull", "cardinality",
        (F.col("cardinality") / n).alias("uniqueness"),
        ((F.col("n_rows") - F.col("n_nonnull")) / F.col("n_rows")).alias("incompleteness"),
        entropy.alias("entropy"),
        "freq_avg", "freq_min", "freq_max", "freq_sd",
        F.transform("_octiles", lambda q: q / n).alias("octiles"),
        (F.col("freq_min") / n).alias("pct_min"),
        (F.col("freq_max") / n).alias("pct_max"),
        (F.col("freq_sd") / n).alias("pct_sd"),
        (F.col("freq_max") / F.col("n_rows")).alias("constancy"),
        F.when(n.isNotNull(), _dominant([(t, F.col(f"_b_{t}")) for t in valuetypes.BROAD])).alias("data_type"),
        F.when(n.isNotNull(), _dominant([(t, F.col(f"_s_{t}")) for t in valuetypes.SPECIFIC])).alias("specific_type"),
        *[(F.col(f"_b_{t}") / n).alias(f"share_{t}") for t in valuetypes.BROAD],
        *[(F.col(f"_s_{t}") / n).alias(f"share_{t}") for t in valuetypes.SPECIFIC],
        "len_max", "len_min", (F.col("_chars") / n).alias("len_avg"),
        F.col("words_total").cast("bigint").alias("words_total"),
        mean.alias("words_avg"), "words_min", "words_max",
        F.sqrt(F.greatest(F.col("_words2") / F.col("_w") - mean * mean, F.lit(0.0))).alias("words_sd"),
    )


def top_words(freq: DataFrame, k: int = TOP, unit: str = "word") -> DataFrame:
    """(dataset, attr, word, weight, place): the k most frequent words (or values) of each attribute."""
    present = freq.where(F.col("value").isNotNull())
    if unit == "word":
        items = present.select(*KEY, "cnt", F.explode(normalize.tokens(normalize.lowered(F.col("value")))).alias("word"))
    else:
        items = present.select(*KEY, "cnt", F.col("value").alias("word"))
    weighed = items.groupBy(*KEY, "word").agg(F.sum("cnt").alias("weight"))
    order = Window.partitionBy(*KEY).orderBy(F.desc("weight"), "word")
    return weighed.withColumn("place", F.row_number().over(order)).where(F.col("place") <= k)


def word_lists(top: DataFrame) -> DataFrame:
    """(dataset, attr, top_words, top_soundex), most frequent first; sounds without repeats."""
    listed = top.groupBy(*KEY).agg(F.transform(F.array_sort(F.collect_list(F.struct("place", "word"))), lambda s: s["word"]).alias("top_words"))
    return listed.withColumn("top_soundex", F.array_distinct(F.transform("top_words", F.soundex)))


def profiles(freq: DataFrame, values: DataFrame | None = None) -> DataFrame:
    """Whole profiles, one row an attribute."""
    stats = statistics(value_table(freq) if values is None else values)
    lists = word_lists(top_words(freq))
    empty = F.array().cast("array<string>")
    return stats.join(lists, list(KEY), "left").withColumns({c: F.coalesce(c, empty) for c in ("top_words", "top_soundex")})


def profile_dataset(df: DataFrame, name: str, mode: str = "exact") -> DataFrame:
    from ..sources.lake import melt

    return approximate(melt(df, name)) if mode == "sketch" else profiles(frequencies(melt(df, name)))


def sketched(melted: DataFrame, relative_error: float = 0.02) -> DataFrame:
    """The part of an approximate profile that comes straight from the cells: no value is shuffled, state is a few KB an attribute
    and task. Counts, lengths, words and shares are exact."""
    n, here = normalize.lowered(F.col("value")), F.col("value").isNotNull()
    rows = melted.withColumn("n", n).select(*KEY, "value", F.size(normalize.tokens(F.col("n"))).alias("w"), normalize.char_length(F.col("n")).alias("c"), valuetypes.broad_type(F.col("n")).alias("broad"), valuetypes.specific_type(F.col("n")).alias("specific"))
    v = lambda x: F.when(here, x)
    share = lambda col, t: F.avg(v(F.when(F.col(col) == t, 1.0).otherwise(0.0))).alias(f"share_{t}")
    return rows.groupBy(*KEY).agg(
        F.count(F.lit(1)).alias("n_rows"),
        F.count("value").alias("n_nonnull"),
        F.approx_count_distinct("value", relative_error).alias("cardinality"),
        F.expr(f"approx_top_k(value, {TOP})").alias("top_values"),
        F.max(v(F.col("c"))).alias("len_max"), F.min(v(F.col("c"))).alias("len_min"), F.avg(v(F.col("c"))).alias("len_avg"),
        F.sum(v(F.col("w"))).alias("words_total"), F.avg(v(F.col("w"))).alias("words_avg"),
        F.min(v(F.col("w"))).alias("words_min"), F.max(v(F.col("w"))).alias("words_max"), F.stddev_pop(v(F.col("w"))).alias("words_sd"),
        *[share("broad", t) for t in valuetypes.BROAD],
        *[share("specific", t) for t in valuetypes.SPECIFIC],
    )


#: Distinct values of an attribute whose counts stand for all in an approximate profile.
SAMPLED = 4_096


def approximate(melted: DataFrame) -> DataFrame:
    """Whole profiles of the same columns as ``profiles``, for attributes whose distinct values are too many to shuffle.

    After the cells' own pass, the values whose hash falls under a share of ``SAMPLED`` over the attribute's cardinality are counted
    exactly: at most about that many of an attribute travel, all of a smaller one. Their counts give the distribution
    (averages, deviations, octiles, entropy), the most frequent value of both passes the maximum. Frequent words come from a
    sketch too. Where an attribute has no more than ``SAMPLED`` values, only its cardinality and words are approximate.
    """
    # stored, since two steps read it; and of known size, a row an attribute, so that rates are broadcast and no cell is shuffled
    base = stored(sketched(melted))
    share = F.least(F.lit(1.0), SAMPLED / F.greatest(F.col("cardinality"), F.lit(1)))
    rates = base.select(*KEY, share.alias("rate"))
    place = F.pmod(F.xxhash64("value"), F.lit(1 << 30)) / (1 << 30)
    some = melted.where(F.col("value").isNotNull()).join(rates, list(KEY)).where(place < F.col("rate")).groupBy(*KEY, "value", "rate").agg(F.count(F.lit(1)).alias("c"))
    c = F.col("c")
    spread = some.groupBy(*KEY).agg(
        F.avg(c).alias("freq_avg"), F.min(c).alias("freq_min"), F.max(c).alias("_max"), F.stddev_pop(c).alias("freq_sd"),
        F.percentile(c, F.array(*map(F.lit, OCTILES))).alias("_octiles"), (F.sum(c * F.log2(c)) / F.sum(c)).alias("_bits"),
    )
    words = melted.where(F.col("value").isNotNull()).select(*KEY, F.explode(normalize.tokens(normalize.lowered(F.col("value")))).alias("word"))
    lists = words.groupBy(*KEY).agg(F.expr(f"approx_top_k(word, {TOP})").alias("k")).select(*KEY, F.transform("k", lambda x: x["item"]).alias("top_words"))
    n = F.when(F.col("n_nonnull") > 0, F.col("n_nonnull"))
    most = F.greatest(F.col("_max"), F.get(F.transform("top_values", lambda x: x["count"]), F.lit(0)))
    empty = F.array().cast("array<string>")
    joined = base.join(spread, list(KEY), "left").join(lists, list(KEY), "left").withColumn("freq_max", most).withColumn("cardinality", F.when(n.isNull(), 0).otherwise(F.col("cardinality")))
    top = F.coalesce("top_words", empty)
    dominant = lambda kinds: F.when(n.isNotNull(), _dominant([(t, F.col(f"share_{t}")) for t in kinds]))
    return joined.select(
        *KEY, "n_rows", "n_nonnull", "cardinality",
        F.when(n.isNotNull(), F.least(F.lit(1.0), F.col("cardinality") / n)).alias("uniqueness"),
        ((F.col("n_rows") - F.col("n_nonnull")) / F.col("n_rows")).alias("incompleteness"),
        F.when(n.isNotNull(), F.greatest(F.lit(0.0), F.log2(n) - F.col("_bits"))).alias("entropy"),
        "freq_avg", "freq_min", "freq_max", "freq_sd",
        F.transform("_octiles", lambda q: q / n).alias("octiles"),
        (F.col("freq_min") / n).alias("pct_min"), (F.col("freq_max") / n).alias("pct_max"), (F.col("freq_sd") / n).alias("pct_sd"), (F.col("freq_max") / F.col("n_rows")).alias("constancy"),
        dominant(valuetypes.BROAD).alias("data_type"), dominant(valuetypes.SPECIFIC).alias("specific_type"),
        *[F.col(f"share_{t}") for t in (*valuetypes.BROAD, *valuetypes.SPECIFIC)],
        "len_max", "len_min", "len_avg", F.col("words_total").cast("bigint").alias("words_total"), "words_avg", "words_min", "words_max", "words_sd",
        top.alias("top_words"), F.array_distinct(F.transform(top, F.soundex)).alias("top_soundex"),
    )


def string_attributes(profiled: DataFrame, ruled_out: tuple[str, ...] = ("numeric", "datetime"), phones: bool = False) -> DataFrame:
    """The second gate, by what the values are: numbers, dates and phone numbers in text columns, and empty columns, go."""
    kept = F.col("data_type").isNotNull() & ~F.col("data_type").isin(*ruled_out)
    return profiled.where(kept if phones else kept & (F.col("specific_type") != "phone"))
