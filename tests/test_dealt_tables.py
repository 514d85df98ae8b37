from pyspark.sql import functions as F

from lakejoin.sources import derived, lake


def test_rows_of_one_file_are_dealt_over_the_cores(spark, sf, monkeypatch):
    """A file of one row group was one task, and so were all its cells; the cells are the same ones."""
    as_read = lake.derived_melted(spark, sf)
    monkeypatch.setattr(lake, "DEALT", 1)
    out = lake.derived_melted(spark, sf)
    total = lambda df: df.groupBy("dataset").agg(F.count(F.lit(1)).alias("n"), F.sum(F.xxhash64("attr", "value").cast("decimal(38,0)")).alias("h"))
    assert sorted(map(tuple, total(out).collect())) == sorted(map(tuple, total(as_read).collect()))
    lines = next(g for g in derived.GROUPS if g.name == "shipments")
    path = f"{sf}/lineitem.parquet"
    assert lake.group_frame(spark, sf, lines, {"lineitem": lake.dealt(spark, path)}).rdd.getNumPartitions() == 2 * spark.sparkContext.defaultParallelism
    assert spark.read.parquet(path).rdd.getNumPartitions() < spark.sparkContext.defaultParallelism
    monkeypatch.setattr(lake, "DEALT", 1 << 60)
    assert lake.dealt(spark, path) == 0
