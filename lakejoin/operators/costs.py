"""Cost measures: seconds, linearity, bytes of profiles, shape of plans."""

from __future__ import annotations

import re
import time
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def timed(what: str, make: Callable[[], DataFrame]) -> dict:
    """Seconds to compute a frame in full; it goes to a sink that keeps nothing."""
    began = time.time()
    make().write.format("noop").mode("overwrite").save()
    return {"what": what, "seconds": round(time.time() - began, 3)}


def linear_fit(df: DataFrame, x: str = "x", y: str = "y") -> DataFrame:
    return df.agg(F.regr_slope(y, x).alias("slope"), F.regr_intercept(y, x).alias("intercept"), F.regr_r2(y, x).alias("r2"))


def profile_size(spark: SparkSession, path: str) -> DataFrame:
    """(dataset, bytes) of a profile store partitioned by dataset, from the file listing alone."""
    files = spark.read.format("binaryFile").option("recursiveFileLookup", "true").load(path).select("path", "length")
    named = files.withColumn("dataset", F.regexp_extract("path", "dataset=([^/]+)/", 1)).where("dataset <> ''")
    return named.groupBy("dataset").agg(F.sum("length").alias("bytes"))


def plan_metrics(df: DataFrame) -> dict[str, int]:
    """Operators of the physical plan that decide its cost."""
    text = df._jdf.queryExecution().executedPlan().toString()
    words = ("Exchange", "BroadcastExchange", "FileScan", "SortMergeJoin", "BroadcastHashJoin", "BroadcastNestedLoopJoin", "CartesianProduct", "WindowGroupLimit", "ArrowEvalPython", "BatchEvalPython")
    return {w: len(re.findall(rf"(?<![A-Za-z]){w}\b", text)) for w in words}
