import math

import pytest
from pyspark.sql import functions as F

from lakejoin.functions import normalize, sqlsurface, valuetypes
from lakejoin.operators import pairs, profile, scaling
from lakejoin.sources.lake import melt


@pytest.fixture(scope="module")
def table(spark):
    rows = [("Red cat", "1", "a@b.org", None, " "), ("red cat", "2", "c@d.org", None, " "), ("Red cat", "3", "a@b.org", None, " "), ("blue dog!", "4", "www.x.y", None, " ")]
    return spark.createDataFrame(rows, "name string, code string, mail string, none string, blank string")


def test_statistics(spark, table):
    p = {r.attr: r for r in profile.profile_dataset(table, "t").collect()}
    name = p["name"]
    assert (name.n_rows, name.cardinality, name.freq_max, name.freq_min) == (4, 3, 2, 1)
    assert name.uniqueness == 0.75 and name.constancy == 0.5 and name.incompleteness == 0
    assert name.entropy == pytest.approx(-(0.5 * math.log2(0.5) + 2 * 0.25 * math.log2(0.25)))
    assert name.top_words[:3] == ["cat", "red", "blue"] and len(name.top_soundex) == 4
    assert (name.words_total, name.words_min, name.words_max, name.words_sd) == (8, 2, 2, 0)
    assert name.octiles == sorted(name.octiles) and name.data_type == "alphabetic" and name.specific_type == "phrases"
    assert p["mail"].specific_type == "email" and p["mail"].share_email == 0.75 and p["mail"].share_url == 0.25
    assert p["none"].cardinality == 0 and p["none"].entropy is None and p["none"].incompleteness == 1 and p["none"].top_words == []
    assert p["blank"].data_type == "nonalphanumeric" and p["blank"].words_total == 0


def test_gate(spark, table):
    kept = {r.attr for r in profile.string_attributes(profile.profile_dataset(table, "t")).collect()}
    assert kept == {"name", "mail", "blank"}


@pytest.mark.parametrize(
    ("value", "broad", "specific"),
    [
        ("2001-02-03", "datetime", "phrases"), ("12:30", "datetime", "username"), ("1,234.5", "numeric", "phrases"), ("-3e5", "numeric", "username"), ("abc def", "alphabetic", "phrases"),
        ("Ábc", "alphabetic", "username"), ("abc 12", "alphanumeric", "phrases"), ("a_b", "nonalphanumeric", "username"), ("10.0.0.1", "nonalphanumeric", "ip"), ("+34 600 123 456", "nonalphanumeric", "phone"),
        ("https://x.org/a", "nonalphanumeric", "url"), ("x@y.zz", "nonalphanumeric", "email"), ("abcdef", "alphabetic", "phrases"), ("abcde", "alphabetic", "username"),
    ],
)
def test_types(spark, value, broad, specific):
    sqlsurface.register(spark)
    df = spark.createDataFrame([(value,)], "v string")
    n = normalize.lowered(F.col("v"))
    assert tuple(df.select(valuetypes.broad_type(n), valuetypes.specific_type(n)).first()) == (broad, specific)
    assert tuple(df.selectExpr("broad_type(v)", "specific_type(v)").first()) == (broad, specific)


def test_name_distance_three_ways(spark):
    sqlsurface.register(spark)
    df = spark.createDataFrame([("buyer", "client"), ("name", "name"), ("", ""), ("a", "")], "a string, b string")
    rows = df.select(pairs.name_distance(F.col("a"), F.col("b")), F.expr("name_distance(a, b)"), sqlsurface.name_distance_pandas(spark)("a", "b")).collect()
    for x, y, z in rows:
        assert x == pytest.approx(y) == pytest.approx(z)


def test_bands_table_function(spark):
    spark.udtf.register("bands", sqlsurface.bands_udtf())
    assert [tuple(r) for r in spark.sql("SELECT * FROM bands(array(1L, 2L, 3L, 4L), 2, 2)").collect()] == [(0, "1-2"), (1, "3-4")]


def test_zscores(spark):
    p = spark.createDataFrame([("d", str(i), float(i)) for i in range(1, 6)], "dataset string, attr string, x double")
    p = p.select("dataset", "attr", *[F.col("x").alias(c) for c in scaling.SCALED if c != "entropy"], F.lit(7.0).alias("entropy"))
    z = scaling.apply_zscore(p, scaling.fit_zscore(p))
    mean, sd, flat = z.agg(F.avg("z_cardinality"), F.stddev_pop("z_cardinality"), F.max(F.abs("z_entropy"))).first()
    assert (mean, sd, flat) == pytest.approx((0, 1, 0), abs=1e-12)
    assert scaling.apply_minmax(p, scaling.fit_minmax(p)).agg(F.max("z_cardinality")).first()[0] == 1


def test_sketch_near_exact(spark):
    df = spark.range(3000).select(F.concat(F.lit("v"), F.col("id") % 700).alias("x"))
    exact, sketch = profile.profile_dataset(df, "d").first(), profile.profile_dataset(df, "d", mode="sketch").first()
    assert abs(exact.cardinality - sketch.cardinality) <= 0.08 * exact.cardinality
    assert (exact.n_rows, exact.len_max, exact.words_total) == (sketch.n_rows, sketch.len_max, sketch.words_total)


def test_approximate_profiles_serve_the_model(spark, monkeypatch):
    """The same columns as exact profiles; equal where all values are counted, close where a share of them is."""
    skew = "CASE WHEN id % 3 = 0 THEN concat('top ', id % 5) ELSE concat('value ', id % 4001) END AS x"
    df = spark.range(30_000).selectExpr(skew, "concat('k', id) AS y", "CAST(NULL AS STRING) AS z")
    exact = {r.attr: r for r in profile.profile_dataset(df, "d").collect()}
    whole = profile.profile_dataset(df, "d", mode="sketch")
    assert set(whole.columns) == set(profile.profile_dataset(df, "d").columns)
    monkeypatch.setattr(profile, "SAMPLED", 500)
    part = {r.attr: r for r in profile.profile_dataset(df, "d", mode="sketch").collect()}
    whole = {r.attr: r for r in whole.collect()}
    x, a, b = exact["x"], whole["x"], part["x"]
    assert a.entropy == pytest.approx(x.entropy) and a.octiles == pytest.approx(x.octiles) and (a.freq_max, a.freq_min, a.data_type) == (x.freq_max, x.freq_min, x.data_type)
    assert b.freq_max == x.freq_max and b.octiles == pytest.approx(x.octiles, rel=0.3) and abs(b.cardinality - x.cardinality) < 0.08 * x.cardinality
    assert set(a.top_words[:2]) == set(x.top_words[:2]) and part["y"].entropy == pytest.approx(exact["y"].entropy, rel=0.02)
    assert whole["z"].cardinality == 0 and whole["z"].entropy is None and whole["z"].data_type is None and whole["z"].top_words == []
    strings = profile.string_attributes(profile.profile_dataset(df, "d", mode="sketch"))
    assert pairs.distances(pairs.candidates(*[scaling.apply_zscore(t, scaling.fit_zscore(strings)) for t in (strings, strings.withColumn("dataset", F.lit("e")))])).count() == 4


def test_plan_reads_strings_once(spark, sf):
    part = spark.read.parquet(f"{sf}/part.parquet")
    plan = profile.frequencies(melt(part, "part"))._jdf.queryExecution().executedPlan().toString()
    assert plan.count("FileScan") == 1 and "p_retailprice" not in plan.split("ReadSchema")[1]
    top = profile.top_words(profile.frequencies(melt(part, "part")))._jdf.queryExecution().executedPlan().toString()
    assert "WindowGroupLimit" in top
