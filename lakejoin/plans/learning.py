"""Queries on learning, discovery and accuracy."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..operators import analysis, discover, metrics, pairs, ranking, training
from ..sources import derived
from .context import context
from .pairing import TRUTH_SQL, _CLASS
from .registry import query

_LABELLED = f"""{TRUTH_SQL}, lab AS (SELECT a.dataset AS ref_dataset, a.attr AS ref_attr, b.dataset AS cand_dataset, b.attr AS cand_attr, CAST(coalesce({_CLASS.format(c='containment', k='ratio')}, 0) AS INT) AS label,
  concat_ws('|', a.dataset, a.attr, b.dataset, b.attr) AS pair_id
  FROM strs a JOIN strs b ON a.dataset <> b.dataset AND {derived.split_sql('a.dataset')} = 'train' AND {derived.split_sql('b.dataset')} = 'train'
  LEFT JOIN truth t ON t.ref_dataset = a.dataset AND t.ref_attr = a.attr AND t.cand_dataset = b.dataset AND t.cand_attr = b.attr)"""


@query("class_distribution", f"{_LABELLED} SELECT label, CAST(count(*) AS BIGINT) AS n FROM lab GROUP BY ALL")
def distribution(spark, sf_dir):
    return training.class_counts(context(spark, sf_dir).train)


def _quota(cls: int) -> str:
    """CTEs up to ``quota<cls>(label, q)``: the rule of the balanced sample, written as arithmetic on the sorted class sizes."""
    total = f"(SELECT least((SELECT coalesce(max(n), 0) FROM cnt WHERE label = {cls}), (SELECT sum(n) FROM cnt WHERE label <> {cls})))"
    out = [f"o{cls} AS (SELECT label, n, row_number() OVER (ORDER BY n, label) AS i FROM cnt WHERE label <> {cls})"]
    given = total
    for i in range(1, 5):
        share = f"least(n, ({given}) // {5 - i})" if i < 4 else f"least(n, {given})"
        out.append(f"s{cls}_{i} AS (SELECT label, {share} AS q FROM o{cls} WHERE i = {i})")
        given += f" - (SELECT q FROM s{cls}_{i})"
    parts = " UNION ALL ".join(f"SELECT * FROM s{cls}_{i}" for i in range(1, 5))
    return ", ".join(out) + f", quota{cls} AS ({parts} UNION ALL SELECT {cls}, {total})"


_COUNTS = "cnt AS (SELECT label, count(*) AS n FROM lab GROUP BY ALL)"


@query("balanced_sample", f"{_LABELLED}, {_COUNTS}, {_quota(3)} SELECT pair_id, label, CAST(label = 3 AS INT) AS target FROM (SELECT *, row_number() OVER (PARTITION BY label ORDER BY md5(pair_id), pair_id) AS i FROM lab) JOIN quota3 USING (label) WHERE i <= q")
def balanced(spark, sf_dir):
    return training.balanced(context(spark, sf_dir).train, 3).select("pair_id", "label", F.col("target").cast("int").alias("target"))


@query("balanced_counts", f"{_LABELLED}, {_COUNTS}, {', '.join(_quota(c) for c in range(5))} {' UNION ALL '.join(f'SELECT {c} AS forest, label, CAST(q AS BIGINT) AS n FROM quota{c}' for c in range(5))}")
def balanced_counts(spark, sf_dir):
    """Rows of each class in the sample of each forest."""
    train = context(spark, sf_dir).train
    counts = {r["label"]: r["n"] for r in training.class_counts(train).collect()}
    rows = [(cls, c, n) for cls in range(5) for c, n in training.quotas(counts, cls).items()]
    return spark.createDataFrame(rows, "forest int, label int, n bigint")


@query("chain_probabilities")
def probabilities(spark, sf_dir):
    c = context(spark, sf_dir)
    return c.model.probabilities(c.test).select(*pairs.ID, *[f"p{i}" for i in range(5)])


#: Five probabilities of each part, from its key and size.
_SCORED = "SELECT p_partkey, " + ", ".join(f"CAST((p_partkey * {m} + p_size * {k}) % 101 AS DOUBLE) / 100 AS p{i}" for i, (m, k) in enumerate(((37, 11), (59, 29), (71, 43), (83, 7), (97, 61)))) + " FROM {part}"
_LOW = "list_position(list_slice(ps, 1, greatest(raw, 1)), list_max(list_slice(ps, 1, greatest(raw, 1)))) - 1"


@query(
    "downgrade_rules",
    f"""WITH v AS (SELECT *, [p0, p1, p2, p3, p4] AS ps FROM ({_SCORED.format(part='part')}) t), r AS (SELECT *, list_position(ps, list_max(ps)) - 1 AS raw FROM v),
u AS (SELECT *, CASE WHEN p0 > 0.5 AND raw >= 1 THEN 1 WHEN list_max(ps) < 0.5 AND raw >= 1 AND list_max(ps) - p0 <= 0.1 + 1e-12 THEN 2 ELSE 0 END AS rule FROM r)
SELECT p_partkey, p0, p1, p2, p3, p4, CAST(raw AS INT) AS raw_class, rule, CAST(CASE WHEN rule > 0 THEN {_LOW} ELSE raw END AS INT) AS pred_class FROM u""",
)
def rules(spark, sf_dir):
    rows = spark.sql(_SCORED.format(part=f"parquet.`{sf_dir}/part.parquet`"))
    return ranking.assign(rows).select("p_partkey", *[f"p{i}" for i in range(5)], "raw_class", "rule", "pred_class")


def _without(c, dataset):
    return c.strings.where(F.col("dataset") == dataset), c.strings.where(F.col("dataset") != dataset)


@query("discover_by_attribute")
def by_attribute(spark, sf_dir):
    c = context(spark, sf_dir)
    return discover.by_attribute(*(lambda r, o: (r, "buyer", o))(*_without(c, "orders_1996")), c.model)


def flagship(spark, sf_dir):
    c = context(spark, sf_dir)
    ref, rest = _without(c, "customer_geo")
    return discover.by_attribute(ref, "client", rest, c.model)


@query("discover_by_dataset")
def by_dataset(spark, sf_dir):
    c = context(spark, sf_dir)
    return discover.by_dataset(*_without(c, "orders_1996"), c.model)


@query("discover_top")
def top(spark, sf_dir):
    """Best three candidates of each reference attribute: the limit is the feature."""
    c = context(spark, sf_dir)
    ref, rest = _without(c, "shipments")
    return ranking.best_per_attribute(discover.by_dataset(ref, rest, c.model))


@query("discover_interesting")
def interesting(spark, sf_dir):
    return ranking.page(by_dataset(spark, sf_dir))


@query("discover_all_pairs")
def all_pairs(spark, sf_dir):
    """All pairs of the lake that the chain finds joinable; pairs whose cardinalities rule that out are never made."""
    c = context(spark, sf_dir)
    return discover.all_pairs(c.strings, c.model, min_class=1)


@query("discover_no_chain")
def no_chain(spark, sf_dir):
    c = context(spark, sf_dir)
    return discover.by_attribute(*(lambda r, o: (r, "buyer", o))(*_without(c, "orders_1996")), c.unchained)


@query("feature_importance")
def importance(spark, sf_dir):
    return analysis.importances(spark.range(0).toDF("x"), context(spark, sf_dir).model)


@query("importance_by_category")
def importance_by_category(spark, sf_dir):
    return analysis.by_category(importance(spark, sf_dir))


@query("pca_variance")
def pca(spark, sf_dir):
    return analysis.pca(context(spark, sf_dir).vectors)


# accuracy of the methods on the test lake


@query("accuracy_confusion")
def confusion(spark, sf_dir):
    return metrics.confusion(context(spark, sf_dir).predicted)


@query("accuracy_per_class")
def per_class(spark, sf_dir):
    return metrics.per_class(confusion(spark, sf_dir))


@query("accuracy_errors")
def errors(spark, sf_dir):
    return metrics.error_profile(confusion(spark, sf_dir))


@query("accuracy_semantic_share")
def semantic(spark, sf_dir):
    same = F.expr(f"{derived.domain_sql('ref_attr')} = {derived.domain_sql('cand_attr')}")
    return metrics.semantic_share(context(spark, sf_dir).predicted.withColumn("same_domain", same))
