"""Profile store: profiles kept beside the data, one partition a dataset, refreshed only where data changed."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def write(profiled: DataFrame, path: str, mode: str = "overwrite") -> None:
    """Sorted by type and cardinality, so that row-group statistics skip."""
    profiled.repartition("dataset").sortWithinPartitions("dataset", "data_type", "cardinality").write.partitionBy("dataset").mode(mode).parquet(path)


def read(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.parquet(path)


def fingerprints(lake) -> DataFrame:
    """(dataset, fingerprint) from file names, sizes and times; frames without files give their schema."""
    rows = []
    for name, df in lake.frames.items():
        files = sorted(df.inputFiles())
        rows.append((name, files or [df.schema.simpleString()]))
    table = lake.spark.createDataFrame(rows, "dataset string, files array<string>")
    listed = [f for _, fs in rows for f in fs if "/" in f]
    if not listed:
        return table.select("dataset", F.sha2(F.array_join("files", "|"), 256).alias("fingerprint"))
    stat = lake.spark.read.format("binaryFile").load(listed).select("path", "length", "modificationTime")
    each = table.select("dataset", F.explode("files").alias("path"))
    tail = F.regexp_replace("path", "^file:/+", "/")
    joined = each.withColumn("p", tail).join(stat.withColumn("p", tail).drop("path"), "p", "left")
    text = F.concat_ws(":", "p", F.col("length").cast("string"), F.col("modificationTime").cast("string"))
    return joined.groupBy("dataset").agg(F.sha2(F.array_join(F.array_sort(F.collect_list(text)), "|"), 256).alias("fingerprint"))


def refresh(lake, path: str, profile_fn) -> list[str]:
    """Profile the new and changed datasets of a lake; returns their names. ``profile_fn(df, name)`` makes a profile."""
    spark = lake.spark
    now = fingerprints(lake)
    try:
        seen = spark.read.parquet(f"{path}/fingerprints")
        stale = now.join(seen, ["dataset", "fingerprint"], "left_anti")
    except Exception as e:
        if "PATH_NOT_FOUND" not in str(e):
            raise
        stale = now
    names = sorted(r["dataset"] for r in stale.select("dataset").collect())
    for name in names:
        profile_fn(lake.frames[name], name).drop("dataset").coalesce(1).write.mode("overwrite").parquet(f"{path}/profiles/dataset={name}")
    now.coalesce(1).write.mode("overwrite").parquet(f"{path}/fingerprints.new")
    spark.read.parquet(f"{path}/fingerprints.new").coalesce(1).write.mode("overwrite").parquet(f"{path}/fingerprints")
    return names
