"""Relational operators that a user of the methods needs around them, one query each."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from ..functions import normalize, valuetypes
from ..operators import size_lsh
from .context import context
from .registry import query


def _t(spark, sf_dir, name):
    return context(spark, sf_dir).table(name)


@query("rel_filter_project", "SELECT p_partkey, p_name, upper(p_brand) AS brand FROM part WHERE p_size BETWEEN 5 AND 10 AND p_type IN ('SMALL', 'LARGE', 'MEDIUM') OR regexp_matches(p_name, '^part')")
def filter_project(spark, sf_dir):
    p = _t(spark, sf_dir, "part")
    return p.where((F.col("p_size").between(5, 10) & F.col("p_type").isin("SMALL", "LARGE", "MEDIUM")) | F.col("p_name").rlike("^part")).select("p_partkey", "p_name", F.upper("p_brand").alias("brand"))


@query("rel_broadcast_join", "SELECT c_custkey, n_name, r_name FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey")
def broadcast_join(spark, sf_dir):
    """Nations and regions are dimensions of fixed size; the planner broadcasts them by their file sizes."""
    n = _t(spark, sf_dir, "nation").join(_t(spark, sf_dir, "region"), F.col("n_regionkey") == F.col("r_regionkey"))
    return _t(spark, sf_dir, "customer").join(n, F.col("c_nationkey") == F.col("n_nationkey")).select("c_custkey", "n_name", "r_name")


@query("rel_merge_join", "SELECT o_orderkey, o_orderpriority, CAST(count(*) AS BIGINT) AS n, round(sum(l_quantity), 4) AS quantity FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY ALL")
def merge_join(spark, sf_dir):
    return _t(spark, sf_dir, "orders").hint("merge").join(_t(spark, sf_dir, "lineitem"), F.col("o_orderkey") == F.col("l_orderkey")).groupBy("o_orderkey", "o_orderpriority").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("l_quantity"), 4).alias("quantity"))


@query("rel_hash_join", "SELECT l_orderkey, l_linenumber, p_brand FROM lineitem JOIN part ON l_partkey = p_partkey WHERE p_size > 40")
def hash_join(spark, sf_dir):
    return _t(spark, sf_dir, "lineitem").join(_t(spark, sf_dir, "part").where("p_size > 40").hint("shuffle_hash"), F.col("l_partkey") == F.col("p_partkey")).select("l_orderkey", "l_linenumber", "p_brand")


@query("rel_theta_join", "SELECT a.n_name AS a, b.n_name AS b FROM nation a JOIN nation b ON a.n_regionkey < b.n_regionkey")
def theta_join(spark, sf_dir):
    n = _t(spark, sf_dir, "nation")
    return n.select(F.col("n_name").alias("a"), F.col("n_regionkey").alias("ra")).join(n.select(F.col("n_name").alias("b"), F.col("n_regionkey").alias("rb")), F.col("ra") < F.col("rb")).select("a", "b")


def range_join(points, ranges, x: str, lo: str, hi: str, width: float):
    """Points within [lo, hi]: ranges are dealt to buckets of ``width``, so the join is an equi-join with a check."""
    bucket = lambda c: F.floor(F.col(c) / width)
    dealt = ranges.withColumn("_b", F.explode(F.sequence(bucket(lo), bucket(hi))))
    return points.withColumn("_b", bucket(x)).join(dealt, "_b").where(F.col(x).between(F.col(lo), F.col(hi))).drop("_b")


@query("rel_range_join", "SELECT p_partkey, p_retailprice, b.lo FROM part JOIN (SELECT 900 + 50 * i AS lo, 900 + 50 * i + 60 AS hi FROM range(0, 24) r(i)) b ON p_retailprice BETWEEN b.lo AND b.hi")
def ranges(spark, sf_dir):
    bands = spark.range(24).select((900 + 50 * F.col("id")).alias("lo"), (960 + 50 * F.col("id")).alias("hi"))
    return range_join(_t(spark, sf_dir, "part").select("p_partkey", "p_retailprice"), bands, "p_retailprice", "lo", "hi", 100.0).select("p_partkey", "p_retailprice", "lo")


@query("rel_interval_join", "WITH q AS (SELECT source, min(n_chars) AS lo, quantile_disc(n_chars, 0.125) AS hi FROM documents GROUP BY source) SELECT d.source, q.source AS other, CAST(count(*) AS BIGINT) AS n FROM documents d JOIN q ON d.n_chars BETWEEN q.lo AND q.hi AND d.source <> q.source GROUP BY ALL")
def interval_join(spark, sf_dir):
    """Documents whose length falls in the lowest octile of another source."""
    d = _t(spark, sf_dir, "documents").select("source", "n_chars")
    q = d.groupBy(F.col("source").alias("other")).agg(F.min("n_chars").alias("lo"), F.expr("percentile_disc(0.125) within group (order by n_chars)").cast("bigint").alias("hi"))
    return range_join(d, q, "n_chars", "lo", "hi", 500.0).where("source <> other").groupBy("source", "other").agg(F.count(F.lit(1)).alias("n"))


def as_of_join(left, right, key: str, at: str, value: str):
    """The last ``value`` of ``right`` at or before each row of ``left``, by key: one union and one window, no range join."""
    both = left.select(key, at, F.lit(None).cast(dict(right.dtypes)[value]).alias(value), F.lit(1).alias("_side"), *[c for c in left.columns if c not in (key, at)])
    others = [F.lit(None).cast(t).alias(c) for c, t in left.dtypes if c not in (key, at)]
    both = both.unionByName(right.select(key, at, value, F.lit(0).alias("_side"), *others))
    order = Window.partitionBy(key).orderBy(at, "_side", value).rowsBetween(Window.unboundedPreceding, 0)
    return both.withColumn(value, F.last(value, ignorenulls=True).over(order)).where("_side = 1").drop("_side")


@query("rel_as_of_join", "WITH o AS (SELECT o_custkey AS user_id, o_orderdate AS ts, max(o_orderkey) AS o_orderkey FROM orders GROUP BY ALL), m AS (SELECT user_id, max(ts) AS ts FROM (SELECT e.event_id, o.user_id, o.ts FROM events e JOIN o ON e.user_id = o.user_id AND o.ts <= e.ts) GROUP BY event_id, user_id) SELECT e.event_id, (SELECT arg_max(o.o_orderkey, o.ts) FROM o WHERE o.user_id = e.user_id AND o.ts <= e.ts) AS o_orderkey FROM events e")
def as_of(spark, sf_dir):
    orders = _t(spark, sf_dir, "orders").groupBy(F.col("o_custkey").alias("user_id"), F.col("o_orderdate").alias("ts")).agg(F.max("o_orderkey").alias("o_orderkey"))
    return as_of_join(_t(spark, sf_dir, "events").select("user_id", "ts", "event_id"), orders, "user_id", "ts", "o_orderkey").select("event_id", "o_orderkey")


@query("rel_semi_join", "SELECT c_custkey FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_orderpriority = '1-URGENT')")
def semi(spark, sf_dir):
    return _t(spark, sf_dir, "customer").join(_t(spark, sf_dir, "orders").where("o_orderpriority = '1-URGENT'"), F.col("c_custkey") == F.col("o_custkey"), "left_semi").select("c_custkey")


@query("rel_anti_join", "SELECT c_custkey FROM customer WHERE NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey)")
def anti(spark, sf_dir):
    return _t(spark, sf_dir, "customer").join(_t(spark, sf_dir, "orders"), F.col("c_custkey") == F.col("o_custkey"), "left_anti").select("c_custkey")


@query("rel_full_join", "SELECT coalesce(a.k, b.k) AS k, a.n AS parts, b.n AS suppliers FROM (SELECT p_size AS k, count(*) AS n FROM part GROUP BY ALL) a FULL JOIN (SELECT s_nationkey AS k, count(*) AS n FROM supplier GROUP BY ALL) b ON a.k = b.k")
def full(spark, sf_dir):
    a = _t(spark, sf_dir, "part").groupBy(F.col("p_size").alias("k")).agg(F.count(F.lit(1)).alias("parts"))
    b = _t(spark, sf_dir, "supplier").groupBy(F.col("s_nationkey").alias("k")).agg(F.count(F.lit(1)).alias("suppliers"))
    return a.join(b, "k", "full")


@query("rel_left_join", "SELECT c_custkey, CAST(count(o_orderkey) AS BIGINT) AS n FROM customer LEFT JOIN orders ON o_custkey = c_custkey GROUP BY ALL")
def left(spark, sf_dir):
    return _t(spark, sf_dir, "customer").join(_t(spark, sf_dir, "orders"), F.col("c_custkey") == F.col("o_custkey"), "left").groupBy("c_custkey").agg(F.count("o_orderkey").alias("n"))


@query("rel_replicas", "SELECT n_nationkey, k FROM nation, (SELECT i AS k FROM range(0, 3) r(i))")
def replicas(spark, sf_dir):
    """Scale replicas: a product with a range of fixed size."""
    return _t(spark, sf_dir, "nation").select("n_nationkey").crossJoin(F.broadcast(spark.range(3).withColumnRenamed("id", "k")))


@query("rel_distinct_agg", "SELECT l_returnflag, CAST(count(DISTINCT l_partkey) AS BIGINT) AS parts, CAST(count(DISTINCT l_suppkey) AS BIGINT) AS suppliers FROM lineitem GROUP BY ALL")
def distinct(spark, sf_dir):
    return _t(spark, sf_dir, "lineitem").groupBy("l_returnflag").agg(F.count_distinct("l_partkey").alias("parts"), F.count_distinct("l_suppkey").alias("suppliers"))


@query("rel_approx_distinct", "SELECT l_returnflag, CAST(count(DISTINCT l_partkey) AS BIGINT) AS parts, true AS within FROM lineitem GROUP BY ALL")
def approx(spark, sf_dir):
    """Exact count, and whether the approximate one lies within four standard errors of it."""
    both = _t(spark, sf_dir, "lineitem").groupBy("l_returnflag").agg(F.count_distinct("l_partkey").alias("parts"), F.approx_count_distinct("l_partkey", 0.02).alias("about"))
    return both.select("l_returnflag", "parts", (F.abs(F.col("about") - F.col("parts")) <= 0.08 * F.col("parts")).alias("within"))


_SETS = "CAST(count(*) AS BIGINT) AS n, round(sum(o_totalprice), 2) AS price FROM orders GROUP BY"


@query("rel_rollup", f"SELECT o_orderstatus, o_orderpriority, {_SETS} ROLLUP (o_orderstatus, o_orderpriority)")
def rollup(spark, sf_dir):
    return _t(spark, sf_dir, "orders").rollup("o_orderstatus", "o_orderpriority").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("o_totalprice"), 2).alias("price"))


@query("rel_cube", f"SELECT o_orderstatus, o_orderpriority, {_SETS} CUBE (o_orderstatus, o_orderpriority)")
def cube(spark, sf_dir):
    return _t(spark, sf_dir, "orders").cube("o_orderstatus", "o_orderpriority").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("o_totalprice"), 2).alias("price"))


@query("rel_grouping_sets", "SELECT o_orderstatus, o_orderpriority, CAST(grouping_id(o_orderstatus, o_orderpriority) AS BIGINT) AS level, CAST(count(*) AS BIGINT) AS n FROM orders GROUP BY GROUPING SETS ((o_orderstatus), (o_orderpriority), ())")
def grouping_sets(spark, sf_dir):
    src = f"parquet.`{sf_dir}/orders.parquet`"
    return spark.sql(f"SELECT o_orderstatus, o_orderpriority, grouping_id(o_orderstatus, o_orderpriority) AS level, count(*) AS n FROM {src} GROUP BY GROUPING SETS ((o_orderstatus), (o_orderpriority), ())")


@query("rel_pivot", "SELECT o_orderpriority, CAST(count(*) FILTER (o_orderstatus = 'F') AS BIGINT) AS f, CAST(count(*) FILTER (o_orderstatus = 'O') AS BIGINT) AS o, CAST(count(*) FILTER (o_orderstatus = 'P') AS BIGINT) AS p FROM orders GROUP BY ALL")
def pivot(spark, sf_dir):
    wide = _t(spark, sf_dir, "orders").groupBy("o_orderpriority").pivot("o_orderstatus", ["F", "O", "P"]).agg(F.count(F.lit(1)))
    return wide.select("o_orderpriority", *[F.coalesce(F.col(c), F.lit(0)).alias(c.lower()) for c in "FOP"])


@query("rel_unpivot", "SELECT p_partkey, attr, value FROM (SELECT p_partkey, p_name, p_brand, p_type FROM part) UNPIVOT (value FOR attr IN (p_name, p_brand, p_type))")
def unpivot(spark, sf_dir):
    return _t(spark, sf_dir, "part").unpivot("p_partkey", ["p_name", "p_brand", "p_type"], "attr", "value")


@query("rel_argmax", "SELECT o_custkey, arg_max(o_orderkey, (o_totalprice, o_orderkey)) AS dearest, CAST(len(list_distinct(list(o_orderpriority))) AS INT) AS priorities FROM orders GROUP BY ALL")
def argmax(spark, sf_dir):
    return _t(spark, sf_dir, "orders").groupBy("o_custkey").agg(F.max_by("o_orderkey", F.struct("o_totalprice", "o_orderkey")).alias("dearest"), F.size(F.collect_set("o_orderpriority")).alias("priorities"))


@query("rel_statistics", "SELECT l_returnflag, round(stddev_pop(l_quantity), 6) AS sd, round(quantile_cont(l_extendedprice, 0.5), 4) AS median, round(corr(l_quantity, l_extendedprice), 6) AS r, round(regr_slope(l_extendedprice, l_quantity), 4) AS slope FROM lineitem GROUP BY ALL")
def statistics(spark, sf_dir):
    return _t(spark, sf_dir, "lineitem").groupBy("l_returnflag").agg(F.round(F.stddev_pop("l_quantity"), 6).alias("sd"), F.round(F.percentile("l_extendedprice", 0.5), 4).alias("median"), F.round(F.corr("l_quantity", "l_extendedprice"), 6).alias("r"), F.round(F.regr_slope("l_extendedprice", "l_quantity"), 4).alias("slope"))


@query("rel_window_rank", "SELECT o_orderkey, CAST(row_number() OVER w AS INT) AS rn, CAST(rank() OVER v AS INT) AS rk, CAST(dense_rank() OVER v AS INT) AS dr, CAST(ntile(4) OVER w AS INT) AS quarter, round(percent_rank() OVER v, 6) AS pr FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey), v AS (PARTITION BY o_custkey ORDER BY o_orderpriority)")
def window_rank(spark, sf_dir):
    w, v = Window.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey"), Window.partitionBy("o_custkey").orderBy("o_orderpriority")
    return _t(spark, sf_dir, "orders").select("o_orderkey", F.row_number().over(w).alias("rn"), F.rank().over(v).alias("rk"), F.dense_rank().over(v).alias("dr"), F.ntile(4).over(w).alias("quarter"), F.round(F.percent_rank().over(v), 6).alias("pr"))


@query("rel_window_analytic", "SELECT o_orderkey, lag(o_orderkey) OVER w AS before, lead(o_orderkey) OVER w AS after, first_value(o_orderkey) OVER w AS first FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey)")
def window_analytic(spark, sf_dir):
    w = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")
    return _t(spark, sf_dir, "orders").select("o_orderkey", F.lag("o_orderkey").over(w).alias("before"), F.lead("o_orderkey").over(w).alias("after"), F.first("o_orderkey").over(w).alias("first"))


@query("rel_window_frames", "WITH d AS (SELECT event_type, CAST(ts AS DATE) AS day, count(DISTINCT user_id) AS users FROM events GROUP BY ALL) SELECT event_type, CAST(day AS VARCHAR) AS day, CAST(sum(users) OVER (PARTITION BY event_type ORDER BY day ROWS UNBOUNDED PRECEDING) AS BIGINT) AS running, round(avg(users) OVER (PARTITION BY event_type ORDER BY datediff('day', DATE '1970-01-01', day) RANGE BETWEEN 6 PRECEDING AND CURRENT ROW), 6) AS week FROM d")
def window_frames(spark, sf_dir):
    d = _t(spark, sf_dir, "events").groupBy("event_type", F.to_date("ts").alias("day")).agg(F.count_distinct("user_id").alias("users")).withColumn("n", F.unix_date("day"))
    w = Window.partitionBy("event_type").orderBy("n")
    return d.select("event_type", F.col("day").cast("string").alias("day"), F.sum("users").over(w.rowsBetween(Window.unboundedPreceding, 0)).alias("running"), F.round(F.avg("users").over(w.rangeBetween(-6, 0)), 6).alias("week"))


@query("rel_top_k", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 20")
def top_k(spark, sf_dir):
    """A top-k report: the limit is the feature."""
    return _t(spark, sf_dir, "orders").select("o_orderkey", "o_totalprice").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(20)


@query("rel_set_operations", "SELECT 'both' AS op, v FROM (SELECT o_orderstatus AS v FROM orders INTERSECT SELECT l_linestatus FROM lineitem) UNION ALL SELECT 'left', v FROM (SELECT o_orderstatus AS v FROM orders EXCEPT SELECT l_linestatus FROM lineitem) UNION ALL SELECT 'any', v FROM (SELECT o_orderstatus AS v FROM orders UNION SELECT l_linestatus FROM lineitem)")
def sets(spark, sf_dir):
    """Containment and Jaccard by set algebra: both over left side, both over any."""
    a = _t(spark, sf_dir, "orders").select(F.col("o_orderstatus").alias("v"))
    b = _t(spark, sf_dir, "lineitem").select(F.col("l_linestatus").alias("v"))
    tag = lambda name, df: df.select(F.lit(name).alias("op"), "v")
    return tag("both", a.intersect(b)).union(tag("left", a.subtract(b))).union(tag("any", a.union(b).distinct()))


@query("rel_bag_operations", "SELECT 'both' AS op, k FROM (SELECT p_size AS k FROM part INTERSECT ALL SELECT s_nationkey FROM supplier) UNION ALL SELECT 'left', k FROM (SELECT p_size AS k FROM part EXCEPT ALL SELECT s_nationkey FROM supplier)")
def bags(spark, sf_dir):
    a, b = _t(spark, sf_dir, "part").select(F.col("p_size").alias("k")), _t(spark, sf_dir, "supplier").select(F.col("s_nationkey").alias("k"))
    return a.intersectAll(b).select(F.lit("both").alias("op"), "k").union(a.exceptAll(b).select(F.lit("left").alias("op"), "k"))


@query("rel_subqueries", "SELECT p_partkey FROM part WHERE p_retailprice > (SELECT avg(p_retailprice) FROM part) AND p_partkey IN (SELECT l_partkey FROM lineitem WHERE l_returnflag = 'R')")
def subqueries(spark, sf_dir):
    p = f"parquet.`{sf_dir}/part.parquet`"
    return spark.sql(f"SELECT p_partkey FROM {p} WHERE p_retailprice > (SELECT avg(p_retailprice) FROM {p}) AND p_partkey IN (SELECT l_partkey FROM parquet.`{sf_dir}/lineitem.parquet` WHERE l_returnflag = 'R')")


@query("rel_json", "SELECT CAST(json_extract_string(props, '$.k') AS BIGINT) AS k, CAST(count(*) AS BIGINT) AS n FROM events GROUP BY ALL")
def json(spark, sf_dir):
    return _t(spark, sf_dir, "events").groupBy(F.get_json_object("props", "$.k").cast("bigint").alias("k")).agg(F.count(F.lit(1)).alias("n"))


@query("rel_html_title", "SELECT page_id, regexp_extract(html, '<title>([^<]*)</title>', 1) AS title, regexp_extract(url, '^https?://([^/]+)', 1) AS host FROM pages")
def html(spark, sf_dir):
    return _t(spark, sf_dir, "pages").select("page_id", F.regexp_extract("html", "<title>([^<]*)</title>", 1).alias("title"), F.regexp_extract("url", "^https?://([^/]+)", 1).alias("host"))


_LOW = normalize.sql_lowered("s")
_DISTANCE = "CASE WHEN greatest(length(s), length(o)) = 0 THEN 0 ELSE levenshtein(s, o) / CAST(greatest(length(s), length(o)) AS DOUBLE) END"
_STRINGS = "SELECT DISTINCT p_type AS s, p_brand AS o FROM {part} UNION SELECT url, '' FROM {pages} UNION SELECT c_name, c_mktsegment FROM {customer} UNION SELECT props, event_type FROM {events} UNION SELECT concat('+34 600 123 ', 100 + c_custkey % 900), 'x@y.org' FROM {customer} UNION SELECT 'x@y.org', '10.0.0.1' FROM {region}"


@query(
    "sql_functions",
    f"WITH v AS ({_STRINGS.format(part='part', pages='pages', customer='customer', events='events', region='region')}), n AS (SELECT *, {_LOW} AS n, length(s) / CAST(length(s) + length(o) AS DOUBLE) AS c FROM v) "
    f"SELECT s, o, round({_DISTANCE}, 6) AS distance, trim(regexp_replace(n, '{normalize.NOT_WORD}', ' ', 'g')) AS cleaned, {valuetypes.sql_broad('n')} AS broad, {valuetypes.sql_specific('n')} AS specific, "
    "CAST(CASE WHEN c >= 0.75 AND 1 - c >= 0.25 THEN 4 WHEN c >= 0.5 AND 1 - c >= 0.125 THEN 3 WHEN c >= 0.25 AND 1 - c >= CAST(1 AS DOUBLE) / 12 THEN 2 WHEN c >= 0.1 THEN 1 ELSE 0 END AS INT) AS quality FROM n",
)
def sql_functions(spark, sf_dir):
    """All five SQL functions over columns of several kinds."""
    from ..functions import sqlsurface

    sqlsurface.register(spark)
    tables = {t: f"parquet.`{sf_dir}/{t}.parquet`" for t in ("part", "pages", "customer", "events", "region")}
    return spark.sql(
        f"SELECT s, o, round(name_distance(s, o), 6) AS distance, clean_text(s) AS cleaned, broad_type(s) AS broad, specific_type(s) AS specific, join_quality(c, 1 - c) AS quality "
        f"FROM (SELECT s, o, CAST(length(s) AS DOUBLE) / (length(s) + length(o)) AS c FROM ({_STRINGS.format(**tables)}))"
    )


@query("udaf_minhash", "WITH f AS (SELECT DISTINCT n_regionkey AS k, ('0x' || substr(md5(n_name), 1, 15))::BIGINT % {p} AS h FROM nation), perm AS (SELECT * FROM (VALUES {v}) p(i, a, b)) SELECT k, CAST(i AS INT) AS i, min((a * h + b) % {p}) AS v FROM f, perm GROUP BY ALL".format(p=size_lsh.PRIME, v=", ".join(f"({i}, {a}::BIGINT, {b}::BIGINT)" for i, (a, b) in enumerate(size_lsh.PERMUTATIONS[:8]))))
def udaf(spark, sf_dir):
    """A grouped pandas aggregate beside the built-in signatures."""
    from ..functions import sqlsurface

    signed = _t(spark, sf_dir, "nation").groupBy(F.col("n_regionkey").alias("k")).agg(sqlsurface.minhash_udaf(spark)("n_name").alias("sig"))
    return signed.select("k", F.posexplode("sig").alias("i", "v"))
