"""Mixing sources to target weights under a time-varying curriculum; DataFrame functions alone.

Targets: the sources, in code-point order with null last, weigh 3, 1, 2, 3, ...; they share ``SHARE`` times all words
by weight, no source above ``MOST`` times its own, the excess going to the others by weight (water filling, solved
in closed form from the caps in the order of cap per weight). A source's quota is its target rounded to words. It
is taken in whole passes over the source, then from the documents in the order of the md5 of their id until the quota
is full; the document at the end gives the words that are left.

Positions: each source has a weight schedule over training time 0 to 1, piecewise linear between ``KNOTS``. The
integral of the schedule, scaled to the quota, is the source's cumulative demand; the piece that starts after c
words of its source stands at the time when demand reaches c. Documents are range-sorted by position.

Prefix sums are taken in hash ranges of about ``RANGE_ROWS`` documents of a source, plus the sums of the ranges before, so a
source of any size spreads over many tasks. Null texts have size 0; so do empty ones, and they are taken with 0
words. Repeated rows count each for itself. A null id sorts as the empty text. An empty table gives no row.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import WORD, documents, fresh, stored

WEIGHTS, SHARE, MOST = (3, 1, 2), 1.5, 2
RANGE_ROWS = 5_000
#: Weight schedules, dealt to the sources in turn: heavy early, heavy late, even.
KNOTS, CURVES = (0.0, 0.5, 1.0), ((1.5, 1.0, 0.5), (0.5, 1.0, 1.5), (1.0, 1.0, 1.0))


def sizes(docs: DataFrame) -> DataFrame:
    return docs.select("doc_id", "source", F.regexp_count(F.coalesce("text", F.lit("")), F.lit(WORD)).cast("bigint").alias("size"))


def targets(sized: DataFrame) -> DataFrame:
    """(source, source_size, n_docs, rank, target, quota): one row a source."""
    each = sized.groupBy("source").agg(F.sum("size").alias("source_size"), F.count(F.lit(1)).alias("n_docs"))
    rank = F.row_number().over(Window.orderBy(F.asc_nulls_last("source"))) - 1
    weighed = each.withColumn("rank", rank).withColumn("weight", F.element_at(F.array(*map(F.lit, WEIGHTS)), (F.col("rank") % len(WEIGHTS) + 1).cast("int")))
    by_cap = Window.orderBy(F.col("source_size") / F.col("weight"), "rank")
    before, all_ = by_cap.rowsBetween(Window.unboundedPreceding, -1), Window.orderBy(F.lit(1)).rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    level = (SHARE * F.sum("source_size").over(all_) - MOST * F.coalesce(F.sum("source_size").over(before), F.lit(0))) / F.sum("weight").over(by_cap.rowsBetween(0, Window.unboundedFollowing))
    filled = weighed.withColumn("level", level).withColumn("capped", F.col("level") > MOST * F.col("source_size") / F.col("weight"))
    free = F.min_by(F.when(~F.col("capped"), F.col("level")), F.when(~F.col("capped"), F.col("source_size") / F.col("weight"))).over(all_)
    named = filled.withColumn("target", F.when(F.col("capped"), (MOST * F.col("source_size")).cast("double")).otherwise(free * F.col("weight")))
    return named.select("source", "source_size", "n_docs", "rank", "target", F.floor(F.col("target") + 0.5).cast("bigint").alias("quota"))


def demand_time(part: Column, curve: tuple[float, ...]) -> Column:
    """Time at which the integral of the schedule reaches the share ``part`` of its whole."""
    pieces, total = [], 0.0
    for t0, t1, v0, v1 in zip(KNOTS, KNOTS[1:], curve, curve[1:]):
        pieces.append((t0, t1, v0, (v1 - v0) / (t1 - t0), total))
        total += (v0 + v1) / 2 * (t1 - t0)
    out = F.lit(None).cast("double")
    for t0, t1, v0, slope, done in reversed(pieces):
        left = F.greatest(part * total - done, F.lit(0.0))
        root = F.lit(v0) + F.sqrt(F.greatest(F.lit(v0 * v0) + 2 * slope * left, F.lit(0.0)))
        at = F.least(F.lit(t0) + F.when(root > 0, 2 * left / root).otherwise(0.0), F.lit(t1))
        out = at if t1 == KNOTS[-1] else F.when(left < (v0 + v0 + slope * (t1 - t0)) / 2 * (t1 - t0), at).otherwise(out)
    return out


def position(words_before: Column, quota: Column, rank: Column) -> Column:
    part = words_before / F.greatest(quota, F.lit(1))
    out = demand_time(part, CURVES[-1])
    for k in range(len(CURVES) - 1):
        out = F.when(rank % len(CURVES) == k, demand_time(part, CURVES[k])).otherwise(out)
    return F.round(out, 9)


def plan(docs: DataFrame) -> DataFrame:
    """(doc_id, source, size, source_size, target, quota, rank, before, taken): one row a document."""
    sized = stored(sizes(docs))
    sources = stored(targets(sized))
    key = F.md5(F.coalesce(F.col("doc_id").cast("string"), F.lit("")))
    rows = sized.join(sources.withColumnRenamed("source", "s"), F.col("source").eqNullSafe(F.col("s"))).drop("s")
    ranges = F.greatest(F.lit(1), F.ceil(F.col("n_docs") / RANGE_ROWS))
    rows = rows.withColumn("key", key).withColumn("part", F.shiftright(F.conv(F.substring("key", 1, 8), 16, 10).cast("bigint") * ranges, 32))
    sums = rows.groupBy("rank", "part").agg(F.sum("size").alias("words"))
    starts = stored(sums.select("rank", "part", F.coalesce(F.sum("words").over(Window.partitionBy("rank").orderBy("part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("start")))
    inside = Window.partitionBy("rank", "part").orderBy("key", "doc_id", "size").rowsBetween(Window.unboundedPreceding, -1)
    ordered = rows.withColumn("inside", F.coalesce(F.sum("size").over(inside), F.lit(0))).join(starts, ["rank", "part"])
    before = F.col("start") + F.col("inside")
    size_or_1 = F.greatest(F.col("source_size"), F.lit(1))
    whole = F.floor(F.col("quota") / size_or_1).cast("bigint")
    rest = F.col("quota") - F.col("whole") * F.col("source_size")
    out = ordered.withColumn("before", before).withColumn("whole", whole).withColumn("taken", F.col("whole") * F.col("size") + F.least(F.col("size"), F.greatest(F.lit(0), rest - F.col("before"))))
    return out.select("doc_id", "source", "size", "source_size", "target", "quota", "rank", "before", "taken")


def op5_curriculum_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What the mix reads of each document and where first, from the pieces in training order; documents not read come last."""
    planned = stored(plan(documents(spark, sf_dir)))
    order = stored(pieces(planned).orderBy("position", "source", "doc_id", "pass"))
    own = ["doc_id", "size", "source_size", "target"]
    read = order.groupBy(*own, "rank", "before").agg(F.sum("words").alias("taken"), F.min("position").alias("position")).select(*own, "taken", "position")
    rest = planned.where("taken = 0").select(*own, "taken", F.lit(None).cast("double").alias("position"))
    return read.unionByName(rest).orderBy(F.asc_nulls_last("position"), "doc_id")


def pieces(planned: DataFrame) -> DataFrame:
    """(doc_id, source, size, pass, words, position), and the document's place in the plan: one row for each time a document is read."""
    each = F.explode(F.sequence(F.lit(0), (F.ceil(F.col("taken") / F.greatest(F.col("size"), F.lit(1))) - 1).cast("int")))
    passes = planned.where("taken > 0").select("*", each.alias("pass"))
    at = position(F.col("pass") * F.col("source_size") + F.col("before"), F.col("quota"), F.col("rank"))
    return passes.select("doc_id", "source", "size", "pass", F.least(F.col("size"), F.col("taken") - F.col("pass") * F.col("size")).alias("words"), at.alias("position"), "source_size", "target", "rank", "before")


def mix(docs: DataFrame) -> DataFrame:
    """``docs`` as often as the mix reads them, with ``mix_pass``, ``mix_words`` and ``mix_position`` (longer names where
    the table has these), range-sorted by position.

    Rows alike in id, source and size are read alike. A document read in part keeps its first words, one blank apart.
    """
    key = ["doc_id", "source", "size", "pass"]
    m = {c: fresh(docs, f"mix_{c}") for c in (*key, "words", "position", "n")}
    todo = pieces(plan(docs)).groupBy(*key).agg(F.max("words").alias("words"), F.min("position").alias("position"))
    todo = todo.select(*[F.col(c).alias(m[c]) for c in (*key, "words", "position")])
    counted = docs.withColumn(m["n"], F.regexp_count(F.coalesce("text", F.lit("")), F.lit(WORD)).cast("bigint"))
    same = F.col("doc_id").eqNullSafe(F.col(m["doc_id"])) & F.col("source").eqNullSafe(F.col(m["source"])) & (F.col(m["n"]) == F.col(m["size"]))
    blank = F.lit(r"[\x20\x09-\x0D]+")
    some = F.array_join(F.slice(F.filter(F.split("text", blank), lambda w: w != ""), 1, F.col(m["words"]).cast("int")), " ")
    read = counted.join(todo, same).withColumn("text", F.when(F.col(m["words"]) < F.col(m["n"]), some).otherwise(F.col("text")))
    out = read.select(*[F.col(f"`{c}`") for c in docs.columns], m["pass"], m["words"], m["position"])
    return out.orderBy(m["position"], "source", "doc_id", m["pass"])


def stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents in training order, each as often as the mix takes it; ``n_chars``, if there, follows the text.

    The columns are those of ``docs``. Written as files, the order is that of the files' numbers and of the rows in
    each (``pieces.placed`` reads it back).
    """
    out = mix(docs)
    if "n_chars" in docs.columns:
        out = out.withColumn("n_chars", F.length("text").cast(dict(docs.dtypes)["n_chars"]))
    return out.select(*[F.col(f"`{c}`") for c in docs.columns])


ORACLE = f"""
WITH d AS (SELECT doc_id, source, CAST(len(regexp_extract_all(coalesce(text, ''), '{WORD}')) AS BIGINT) AS size FROM documents),
s AS (SELECT source, CAST(sum(size) AS BIGINT) AS source_size FROM d GROUP BY source),
r AS (SELECT *, row_number() OVER (ORDER BY source NULLS LAST) - 1 AS rnk FROM s),
w AS (SELECT *, CASE rnk % 3 WHEN 0 THEN 3 WHEN 1 THEN 1 ELSE 2 END AS weight FROM r),
l AS (SELECT *, (1.5 * CAST((SELECT sum(source_size) FROM w) AS DOUBLE) - 2 * CAST(coalesce(sum(source_size) OVER (ORDER BY source_size / weight, rnk ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS DOUBLE))
      / CAST(sum(weight) OVER (ORDER BY source_size / weight, rnk ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS DOUBLE) AS level FROM w),
t AS (SELECT *, CASE WHEN level > 2 * source_size / weight THEN CAST(2 * source_size AS DOUBLE)
      ELSE (SELECT arg_min(level, source_size / weight) FROM l WHERE NOT level > 2 * source_size / weight) * weight END AS target FROM l),
q AS (SELECT *, CAST(floor(target + 0.5) AS BIGINT) AS quota FROM t),
o AS (SELECT d.doc_id, d.size, q.*, CAST(coalesce(sum(d.size) OVER (PARTITION BY q.rnk ORDER BY md5(coalesce(CAST(d.doc_id AS VARCHAR), '')), d.doc_id, d.size ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS BIGINT) AS before
      FROM d JOIN q ON d.source IS NOT DISTINCT FROM q.source),
k AS (SELECT *, quota // greatest(source_size, 1) AS whole FROM o),
m AS (SELECT *, CAST(whole * size + least(size, greatest(0, quota - whole * source_size - before)) AS BIGINT) AS taken, before / greatest(quota, 1) AS part FROM k)
SELECT doc_id, size, source_size, target, taken,
  CASE WHEN taken > 0 THEN round(CASE rnk % 3
    WHEN 0 THEN CASE WHEN greatest(part * 1.0 - 0.0, 0.0) < 0.625 THEN least(2 * part / (1.5 + sqrt(2.25 - 2.0 * part)), 0.5)
                     ELSE least(0.5 + 2 * greatest(part - 0.625, 0.0) / (1.0 + sqrt(greatest(1.0 - 2.0 * greatest(part - 0.625, 0.0), 0.0))), 1.0) END
    WHEN 1 THEN CASE WHEN part < 0.375 THEN least(2 * part / (0.5 + sqrt(0.25 + 2.0 * part)), 0.5)
                     ELSE least(0.5 + 2 * greatest(part - 0.375, 0.0) / (1.0 + sqrt(1.0 + 2.0 * greatest(part - 0.375, 0.0))), 1.0) END
    ELSE CASE WHEN part < 0.5 THEN part ELSE least(0.5 + (part - 0.5), 1.0) END END, 9) END AS position
FROM m
"""
