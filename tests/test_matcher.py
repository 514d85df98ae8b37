from pyspark.sql import functions as F

from lakejoin.operators import matcher

FREQ = "dataset string, attr string, value string, n bigint"


def test_references_are_all_datasets_of_several_attributes(spark):
    rows = [("a", "x", "1", 1), ("a", "y", "1", 1), ("b", "x", "1", 1), ("b", "x", "2", 1), ("c", "x", "1", 1), ("c", "y", None, 1), ("d", "p", "1", 1), ("d", "q", "2", 1)]
    assert matcher.references(spark.createDataFrame(rows, FREQ)) == ["a", "d"]


def test_grams_cover_whole_texts(spark):
    rows = [("a", "x", "z" * 250), ("a", "x", "z" * 250 + "qqqqq")]
    got = matcher._featured(spark.createDataFrame(rows, "dataset string, attr string, value string")).select(F.array_contains("grams", "qqq").alias("q")).collect()
    assert sorted(r.q for r in got) == [False, True]


def test_candidates_are_averaged_over_all_values(spark, monkeypatch):
    words, numbers = [f"alpha beta{chr(97 + i)}" for i in range(12)], [str(1000 + i) for i in range(12)]
    rows = [("r", "w", x, 1) for x in words] + [("r", "k", x, 1) for x in numbers] + [("c", "mix", x, 1) for x in words + numbers[:5]]
    freq = spark.createDataFrame(rows, FREQ)
    model = matcher.fit(freq, "r")
    whole = model.match(freq, "r").first().probability
    monkeypatch.setattr(matcher, "VALUES", 1)
    assert abs(model.match(freq, "r").first().probability - whole) < 1e-9
