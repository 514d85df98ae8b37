"""Lake methods, SQL functions, grouped aggregate, table functions, and formats."""

import pytest
from pyspark.sql import functions as F

from lakejoin.functions import sqlsurface
from lakejoin.operators import chain, discover, pairs, size_lsh, training
from lakejoin.operators.profile import frequencies
from lakejoin.plans.context import context
from lakejoin.sources.lake import Lake


@pytest.fixture(scope="module")
def small_model(spark, sf):
    return chain.fit_chain(context(spark, sf).train, chain.SMALL)


def test_lake_profiles_and_discovers(spark, sf, small_model):
    read = lambda t: spark.read.parquet(f"{sf}/{t}.parquet")
    lake = Lake(spark).add("clients", read("customer").select("c_name", "c_mktsegment")).add("some", read("customer").where("c_custkey % 2 = 0").select(F.col("c_name").alias("who"))).add("parts", read("part").select("p_name"))
    profiles = lake.profile().cache()
    assert {(r.dataset, r.attr) for r in profiles.collect()} == {("clients", "c_name"), ("clients", "c_mktsegment"), ("some", "who"), ("parts", "p_name")}
    assert lake.profile("sketch").count() == 4
    one = lake.discover("some", small_model, "who", min_class=0, profiles=profiles).collect()
    assert {(r.cand_dataset, r.cand_attr) for r in one} == {("clients", "c_name"), ("clients", "c_mktsegment"), ("parts", "p_name")}
    assert {r.cand_dataset for r in lake.discover("clients", small_model, min_class=0, profiles=profiles).collect()} == {"some", "parts"}


def test_discovery_from_sql(spark, sf, small_model):
    c = context(spark, sf)
    predicted = discover.all_pairs(c.strings, small_model, min_class=1)
    sqlsurface.register_discovery(spark, predicted)
    got = {tuple(r) for r in spark.sql("SELECT cand_dataset, cand_attr, pred_class FROM discover_joins('orders_1996', 'buyer')").collect()}
    want = {tuple(r) for r in predicted.where("ref_dataset = 'orders_1996' AND ref_attr = 'buyer'").select("cand_dataset", "cand_attr", "pred_class").collect()}
    assert got == want and got


def test_grouped_aggregate_equals_the_built_in_signature(spark):
    rows = [("d", f"a{i % 3}", f"v{i * i % 50}") for i in range(120)] + [("d", "a0", None)]
    df = spark.createDataFrame(rows, "dataset string, attr string, value string")
    want = {r.attr: r.sig for r in size_lsh.signatures(frequencies(df), m=8).collect()}
    got = {r.attr: r.sig for r in df.groupBy("attr").agg(sqlsurface.minhash_udaf(spark)("value").alias("sig")).collect()}
    assert got == want


@pytest.mark.parametrize("fmt", ["json", "orc", "xml", "csv", "parquet"])
def test_formats(spark, tmp_path, fmt):
    df = spark.createDataFrame([("a b", "1"), ("c", "2")], "name string, code string")
    options = {"rowTag": "row"} if fmt == "xml" else {"header": "true"} if fmt == "csv" else {}
    df.write.format(fmt).options(**options).save(f"{tmp_path}/t")
    got = Lake(spark).add_file("t", f"{tmp_path}/t", fmt).profile().collect()
    assert ("t", "name") in {(r.dataset, r.attr) for r in got}


def test_unknown_formats_and_names(spark):
    lake = Lake(spark)
    with pytest.raises(ValueError, match="unknown format"):
        lake.add_file("t", "/nowhere", "tape")
    with pytest.raises(Exception, match="(?i)avro"):
        lake.add_file("t", "/nowhere", "avro")
    lake.add("x", spark.range(1))
    with pytest.raises(ValueError, match="already"):
        lake.add("x", spark.range(1))


def test_catalog_tables(spark):
    spark.createDataFrame([("u",), ("v",)], "word string").write.mode("overwrite").saveAsTable("lake_words")
    try:
        assert Lake(spark).add_table("words", "lake_words").profile().first().cardinality == 2
    finally:
        spark.sql("DROP TABLE lake_words")


def test_the_order_of_the_methods(spark, sf):
    """As published: the chain's interesting pairs are more precise than the hash baseline's, whose recall is higher; the
    matcher's precision is far below both. The small forests are enough for that."""
    from lakejoin.operators import metrics
    from lakejoin.plans import comparison

    c = context(spark, "/root/testdata/sf0.01")
    model = chain.fit_chain(c.train, chain.SMALL)
    found = discover.predict(c.test, model).join(c.test.select(*pairs.ID, "label"), list(pairs.ID))
    ours = metrics.binary(metrics.confusion(found)).first()
    hits = comparison.simple_hits(c)
    theirs = {n: metrics.binary(metrics.confusion(comparison._with_label(c, comparison._interesting(hits[n])))).first() for n in ("hash", "names")}
    assert ours.precision > theirs["hash"].precision > theirs["names"].precision
    assert ours.recall > 0.8 and theirs["hash"].recall > 0.8
    counts = {r["label"]: r["n"] for r in training.class_counts(c.train).collect()}
    assert counts[0] > 0.8 * sum(counts.values())
