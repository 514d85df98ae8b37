"""The measures applied to confusion matrices: those of judged orders, and published ones; testbeds.

Rows are true classes, columns predicted ones.
"""

from __future__ import annotations

from pyspark.sql import functions as F

from ..operators import costs, metrics
from ..sources import lake
from .registry import query

#: All testbeds; three testbeds by the chain and by the hash baseline; pairs that join after a transformation.
ALL = ((455084, 2370, 660, 56, 1), (6903, 737, 349, 1, 0), (92, 17, 312, 98, 1), (7, 7, 151, 348, 4), (5, 2, 68, 299, 393))
CHAIN = ((410433, 2270, 604, 56, 1), (4586, 640, 257, 1, 0), (92, 3, 234, 70, 1), (5, 6, 111, 324, 1), (3, 0, 41, 253, 337))
HASH = ((412425, 447, 260, 227, 5), (4606, 191, 185, 497, 5), (17, 27, 180, 111, 65), (0, 0, 54, 84, 309), (1, 0, 0, 5, 628))
TRANSFORMED = ((41, 19, 1, 0, 0), (68, 23, 3, 1, 0), (37, 15, 20, 0, 0), (36, 24, 32, 7, 0), (90, 46, 47, 22, 0))
MATRICES = {"all": ALL, "chain": CHAIN, "hash": HASH, "transformed": TRANSFORMED}

_ROWS = [(name, t, p, n) for name, m in MATRICES.items() for t, row in enumerate(m) for p, n in enumerate(row)]
_CM = f"WITH cm(method, truth, pred, n) AS (VALUES {', '.join(f"('{m}', {t}, {p}, CAST({n} AS BIGINT))" for m, t, p, n in _ROWS)})"


def cells(spark):
    return spark.createDataFrame(_ROWS, "method string, truth int, pred int, n bigint")


#: Orders as judged rows: true class by price, class that the priority predicts, one method a status.
_JUDGED = "SELECT o_orderstatus AS method, CAST(least(4, greatest(0, floor(o_totalprice / 100000))) AS INT) AS truth, 5 - CAST(substr(o_orderpriority, 1, 1) AS INT) AS pred FROM {orders}"
_CM_ORDERS = f"WITH cm AS (SELECT method, truth, pred, CAST(count(*) AS BIGINT) AS n FROM ({_JUDGED.format(orders='orders')}) j GROUP BY ALL)"


def judged(spark, sf_dir):
    return spark.sql(_JUDGED.format(orders=f"parquet.`{sf_dir}/orders.parquet`"))


def counted(spark, sf_dir):
    """The cells that the rows of a given table make."""
    return judged(spark, sf_dir).groupBy("method", "truth", "pred").agg(F.count(F.lit(1)).alias("n"))


def _rounded(df):
    return df.withColumns({c: F.round(c, 6) for c in ("precision", "recall", "f1")})


_PRF = "round(CASE WHEN {p} > 0 THEN {tp} / {p} END, 6) AS precision, round(CASE WHEN {a} > 0 THEN {tp} / {a} END, 6) AS recall, round(CASE WHEN {p} > 0 AND {a} > 0 AND {tp} > 0 THEN 2 * ({tp} / {p}) * ({tp} / {a}) / ({tp} / {p} + {tp} / {a}) END, 6) AS f1"


@query("confusion_published", f"{_CM_ORDERS} SELECT method, truth, CAST(sum(n) FILTER (pred = 0) AS BIGINT) AS pred0, CAST(sum(n) FILTER (pred = 1) AS BIGINT) AS pred1, CAST(sum(n) FILTER (pred = 2) AS BIGINT) AS pred2, CAST(sum(n) FILTER (pred = 3) AS BIGINT) AS pred3, CAST(sum(n) FILTER (pred = 4) AS BIGINT) AS pred4 FROM cm GROUP BY ALL")
def confusion(spark, sf_dir):
    wide = counted(spark, sf_dir).groupBy("method", "truth").pivot("pred", list(range(5))).agg(F.sum("n"))
    return wide.select("method", "truth", *[F.col(str(i)).alias(f"pred{i}") for i in range(5)])


@query("metrics_published", f"{_CM_ORDERS}, s AS (SELECT method, c AS cls, CAST(coalesce(sum(n) FILTER (truth = c AND pred = c), 0) AS DOUBLE) AS tp, CAST(coalesce(sum(n) FILTER (pred = c), 0) AS DOUBLE) AS p, CAST(coalesce(sum(n) FILTER (truth = c), 0) AS DOUBLE) AS a FROM cm, range(5) r(c) GROUP BY ALL) SELECT method, CAST(cls AS INT) AS cls, {_PRF.format(tp='tp', p='p', a='a')} FROM s")
def per_class(spark, sf_dir):
    return _rounded(metrics.per_class(counted(spark, sf_dir), ["method"]))


@query("binary_published", f"{_CM_ORDERS}, s AS (SELECT method, CAST(coalesce(sum(n) FILTER (truth < 3 AND pred < 3), 0) AS BIGINT) AS tn, CAST(coalesce(sum(n) FILTER (truth < 3 AND pred >= 3), 0) AS BIGINT) AS fp, CAST(coalesce(sum(n) FILTER (truth >= 3 AND pred < 3), 0) AS BIGINT) AS fn, CAST(coalesce(sum(n) FILTER (truth >= 3 AND pred >= 3), 0) AS BIGINT) AS tp FROM cm GROUP BY ALL) SELECT *, {_PRF.format(tp='tp', p='(tp + fp)', a='(tp + fn)')} FROM s")
def binary(spark, sf_dir):
    return _rounded(metrics.binary(counted(spark, sf_dir), by=["method"]))


@query("error_profile_published", f"{_CM_ORDERS} SELECT CAST(pred - truth AS INT) AS step, CAST(sum(n) AS BIGINT) AS n FROM cm GROUP BY ALL")
def errors(spark, sf_dir):
    return metrics.error_profile(counted(spark, sf_dir))


@query("confusion_by_testbed", f"{_CM_ORDERS} SELECT method, truth, CAST(sum(n) AS BIGINT) AS n, CAST(coalesce(sum(n) FILTER (truth = pred), 0) AS BIGINT) AS hits FROM cm GROUP BY ROLLUP (method, truth)")
def by_testbed(spark, sf_dir):
    """One pass gives every group and the whole."""
    return counted(spark, sf_dir).rollup("method", "truth").agg(F.sum("n").alias("n"), F.sum(F.when(F.col("truth") == F.col("pred"), F.col("n")).otherwise(0)).alias("hits"))


@query("share_predicted", f"{_CM} SELECT CAST(sum(n) FILTER (pred IN (1, 2, 3)) AS BIGINT) AS hit, CAST(sum(n) AS BIGINT) AS total, round(CAST(sum(n) FILTER (pred IN (1, 2, 3)) AS DOUBLE) / sum(n), 6) AS share FROM cm WHERE method = 'transformed'")
def share(spark, sf_dir):
    """Over all the transformed pairs."""
    return metrics.share_predicted(cells(spark).where("method = 'transformed'")).withColumn("share", F.round("share", 6))


@query("share_predicted_joinable", f"{_CM} SELECT CAST(sum(n) FILTER (pred IN (1, 2, 3)) AS BIGINT) AS hit, CAST(sum(n) AS BIGINT) AS total, round(CAST(sum(n) FILTER (pred IN (1, 2, 3)) AS DOUBLE) / sum(n), 6) AS share FROM cm WHERE method = 'transformed' AND truth > 0")
def share_joinable(spark, sf_dir):
    """Over those that are joinable after it."""
    return metrics.share_predicted(cells(spark).where("method = 'transformed'"), truth=(1, 2, 3, 4)).withColumn("share", F.round("share", 6))


@query("semantic_share", f"SELECT CAST(count(*) AS BIGINT) AS proposed, round(avg(CAST(same AS DOUBLE)), 6) AS semantic_share FROM (SELECT pred, truth >= 3 AS same FROM ({_JUDGED.format(orders='orders')}) j) t WHERE pred >= 3")
def semantic(spark, sf_dir):
    rows = judged(spark, sf_dir).select(F.col("pred").alias("pred_class"), (F.col("truth") >= 3).alias("same_domain"))
    return metrics.semantic_share(rows).withColumn("semantic_share", F.round("semantic_share", 6))


@query("linear_fit", "SELECT round(regr_slope(o_totalprice, o_orderkey), 6) AS slope, round(regr_intercept(o_totalprice, o_orderkey), 4) AS intercept, round(regr_r2(o_totalprice, o_orderkey), 6) AS r2 FROM orders")
def fit(spark, sf_dir):
    orders = spark.read.parquet(f"{sf_dir}/orders.parquet")
    fitted = costs.linear_fit(orders, "o_orderkey", "o_totalprice")
    return fitted.select(F.round("slope", 6).alias("slope"), F.round("intercept", 4).alias("intercept"), F.round("r2", 6).alias("r2"))


@query("testbeds", "SELECT n, CASE WHEN n <= 1048576 THEN 'XS' WHEN n <= 104857600 THEN 'S' WHEN n <= 1073741824 THEN 'M' ELSE 'L' END AS testbed FROM (VALUES (0), (1048576), (1048577), (104857600), (104857601), (1073741824), (1073741825)) v(n)")
def testbeds(spark, sf_dir):
    sizes = spark.createDataFrame([(n,) for n in (0, 1 << 20, (1 << 20) + 1, 100 << 20, (100 << 20) + 1, 1 << 30, (1 << 30) + 1)], "n int")
    return sizes.withColumn("testbed", lake.testbed_of(F.col("n")))
