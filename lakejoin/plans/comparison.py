"""The methods against one another, on the same pairs: the test lake's, or what a ranking shows first."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..operators import baselines, chain, discover, matcher, metrics, pairs, size_lsh
from ..session import stored
from ..sources import derived, lake
from .context import context
from .learning import _LABELLED
from .pairing import _BAND, _CLASS, _ID, _NAME, _PART, _SIG, ROUNDED, TRUTH_SQL, lsh_classes_sql, lsh_hits_sql
from .profiling import PROFILE_SQL
from .registry import query


def _with_label(c, hits: DataFrame) -> DataFrame:
    """Predictions of another method on the pairs of the test lake; pairs it doesn't name are class 0."""
    return c.test.select(*pairs.ID, "label").join(hits, list(pairs.ID), "left").withColumn("pred_class", F.coalesce("pred_class", F.lit(0)))


def _interesting(hits: DataFrame) -> DataFrame:
    return hits.select(*pairs.ID, F.lit(3).alias("pred_class"))


def _union(frames: dict[str, DataFrame]) -> DataFrame:
    return reduce(DataFrame.unionByName, [df.select(F.lit(name).alias("method"), "*") for name, df in frames.items()])


def lsh_test(c) -> DataFrame:
    own = c.string_freq.where(F.expr(derived.split_sql("dataset")) == "test")
    return size_lsh.partitions(size_lsh.signatures(own))


def simple_hits(c) -> dict[str, DataFrame]:
    """What the methods without a learned model find interesting on the test lake."""
    names = c.test.select(F.col("ref_dataset").alias("dataset"), F.col("ref_attr").alias("attr")).distinct()
    return {
        "hash": size_lsh.all_hits(lsh_test(c), 0.5),
        "names": baselines.by_name(names, names),
        "jaccard at 0.5": c.truth.where("jaccard >= 0.5"),
        "containment at 0.5": c.truth.where("containment >= 0.5"),
    }


# the same methods for DuckDB

_TEST = _LABELLED.replace("= 'train'", "= 'test'")
_LABELS = _TEST[_TEST.index(", lab AS") :]
_IN_TEST = f"SELECT f.dataset, f.attr, ('0x' || substr(md5(value), 1, 15))::BIGINT % {size_lsh.PRIME} AS h FROM freq f JOIN strs s ON f.dataset = s.dataset AND f.attr = s.attr WHERE value IS NOT NULL AND {derived.split_sql('f.dataset')} = 'test'"


def _test_signatures() -> str:
    """CTEs of truth, labels, signatures, parts and bands of the test lake."""
    tail = _SIG[_SIG.index(",\nperm AS") :]
    return f"{TRUTH_SQL}{_LABELS}, hv AS ({_IN_TEST}){tail}{_PART}{_BAND}"


def _prf(tn: str, fp: str, fn: str, tp: str) -> str:
    ratio = lambda b: f"CASE WHEN {tp} + {b} > 0 THEN {tp} / CAST({tp} + {b} AS DOUBLE) END"
    return f"round({ratio(fp)}, 6) AS precision, round({ratio(fn)}, 6) AS recall, round(CASE WHEN {tp} > 0 THEN 2.0 * {tp} / (2 * {tp} + {fp} + {fn}) END, 6) AS f1"


def _baselines_sql() -> str:
    hits = {
        "hash": lsh_hits_sql(0.5, ROUNDED),
        "names": f"SELECT {_ID} FROM (SELECT a.dataset AS ref_dataset, a.attr AS ref_attr, b.dataset AS cand_dataset, b.attr AS cand_attr FROM strs a JOIN strs b ON a.dataset <> b.dataset WHERE {_NAME} <= 0.3) y",
        "jaccard at 0.5": f"SELECT {_ID} FROM truth WHERE jaccard >= 0.5",
        "containment at 0.5": f"SELECT {_ID} FROM truth WHERE containment >= 0.5",
    }
    ctes = "".join(f", m{i} AS (SELECT DISTINCT {_ID} FROM ({sql}) u{i})" for i, sql in enumerate(hits.values()))
    cell = lambda want, got: f"CAST(count(*) FILTER ((label >= 3) = {want} AND found = {got}) AS BIGINT)"
    each = " UNION ALL ".join(f"SELECT '{name}' AS method, label, m.ref_dataset IS NOT NULL AS found FROM lab LEFT JOIN m{i} m USING ({_ID})" for i, name in enumerate(hits))
    return f"{_test_signatures()}{ctes}, c AS (SELECT method, {cell('false', 'false')} AS tn, {cell('false', 'true')} AS fp, {cell('true', 'false')} AS fn, {cell('true', 'true')} AS tp FROM ({each}) e GROUP BY method) SELECT *, {_prf('tn', 'fp', 'fn', 'tp')} FROM c"


def _hash_confusion_sql() -> str:
    return f"{_test_signatures()}, h AS ({lsh_classes_sql()}), k AS (SELECT label AS truth, coalesce(h.pred_class, 0) AS pred, count(*) AS n FROM lab LEFT JOIN h USING ({_ID}) GROUP BY ALL) SELECT CAST(t AS INT) AS truth, CAST(p AS INT) AS pred, CAST(coalesce(n, 0) AS BIGINT) AS n FROM range(5) a(t), range(5) b(p) LEFT JOIN k ON k.truth = t AND k.pred = p"


@query("accuracy_baselines", _baselines_sql)
def baseline_accuracy(spark, sf_dir):
    """Binary accuracy of the methods without a learned model on the test pairs."""
    c = context(spark, sf_dir)
    measured = _union({name: metrics.binary(metrics.confusion(_with_label(c, _interesting(hits)))) for name, hits in simple_hits(c).items()})
    return measured.withColumns({x: F.round(x, 6) for x in ("precision", "recall", "f1")})


@query("accuracy_hash_five_class", _hash_confusion_sql)
def hash_five(spark, sf_dir):
    """Five classes from four searches of the hash baseline: the confusion matrix on the test pairs."""
    c = context(spark, sf_dir)
    return metrics.confusion(_with_label(c, size_lsh.classify(lsh_test(c))))


@query("accuracy_five_class_compared")
def five_compared(spark, sf_dir):
    """Precision, recall and F1 of each class, chain and hash baseline on the same pairs."""
    c = context(spark, sf_dir)
    return _union({"chain": metrics.per_class(metrics.confusion(c.predicted)), "hash": metrics.per_class(hash_five(spark, sf_dir))})


def matcher_hits(c) -> DataFrame | None:
    """Pairs the matcher proposes; it is trained on every test dataset that has several string attributes."""
    freq = stored(c.string_freq.where(F.expr(derived.split_sql("dataset")) == "test"))
    model = matcher.fit_all(freq)
    return None if model is None else model.match(freq).select(*pairs.ID)


@query("accuracy_matcher")
def matcher_accuracy(spark, sf_dir):
    """Binary accuracy of the matcher on all test pairs."""
    c = context(spark, sf_dir)
    return metrics.binary(metrics.confusion(_with_label(c, _interesting(c.matched))))


@query("accuracy_compared")
def compared(spark, sf_dir):
    """Binary accuracy of the chain, its ablations, the hash baseline, the matcher and the simple baselines on the same test
    pairs."""
    c = context(spark, sf_dir)
    methods = {
        "chain": c.predicted.select(*pairs.ID, "pred_class"),
        "chain without rules": discover.predict(c.test, c.model, rule1=False, rule2=False).select(*pairs.ID, "pred_class"),
        "forests without chain": discover.predict(c.test, c.unchained).select(*pairs.ID, "pred_class"),
        "one multiclass forest": chain.predict_multiclass(chain.fit_multiclass(c.train, chain.BEST[0]), c.test).select(*pairs.ID, "pred_class"),
        "matcher": _interesting(c.matched),
    }
    methods |= {name: _interesting(hits) for name, hits in simple_hits(c).items()}
    return _union({name: metrics.binary(metrics.confusion(_with_label(c, hits))) for name, hits in methods.items()})


#: Bytes of a dataset's values up to which it is of a testbed here: the published limits over 2 ** 10, since the given tables are small.
SMALL_TESTBEDS = tuple((name, limit >> 10) for name, limit in lake.TESTBEDS)
_SIZES = "sz AS (SELECT dataset, CAST(sum(cnt * strlen(value)) AS BIGINT) AS n_bytes FROM freq GROUP BY ALL)"
_BED = f"CASE {' '.join(f"WHEN n_bytes <= {limit} THEN '{name}'" for name, limit in SMALL_TESTBEDS)} ELSE 'L' END"


def sizes(c) -> DataFrame:
    """(dataset, n_bytes, testbed): bytes of the string values."""
    measured = c.freq.groupBy("dataset").agg(F.sum(F.col("cnt") * F.octet_length("value")).cast("bigint").alias("n_bytes"))
    return measured.withColumn("testbed", lake.testbed_of(F.col("n_bytes"), SMALL_TESTBEDS))


@query("testbed_sizes", f"{PROFILE_SQL}, {_SIZES} SELECT dataset, n_bytes, {_BED} AS testbed FROM sz")
def testbed_sizes(spark, sf_dir):
    return sizes(context(spark, sf_dir))


@query("class_distribution_by_testbed", f"{_TEST}, {_SIZES} SELECT {_BED} AS testbed, label, CAST(count(*) AS BIGINT) AS n FROM lab JOIN sz ON dataset = ref_dataset GROUP BY ALL")
def classes_by_testbed(spark, sf_dir):
    """True classes of the test pairs by the testbed of the reference's dataset."""
    c = context(spark, sf_dir)
    return _beds(c, c.test).groupBy("testbed", "label").agg(F.count(F.lit(1)).alias("n"))


def _beds(c, rows: DataFrame) -> DataFrame:
    return rows.join(sizes(c).select(F.col("dataset").alias("ref_dataset"), "testbed"), "ref_dataset")


@query("accuracy_by_testbed")
def by_testbed(spark, sf_dir):
    """The chain's own confusion matrix on the test pairs, for each testbed of the reference's dataset."""
    c = context(spark, sf_dir)
    return metrics.confusion(_beds(c, c.predicted), by="testbed")


@query("accuracy_by_testbed_per_class")
def by_testbed_per_class(spark, sf_dir):
    return metrics.per_class(by_testbed(spark, sf_dir), ["testbed"])


_RANKED = f"""{TRUTH_SQL}, every AS (SELECT a.dataset AS ref_dataset, a.attr AS ref_attr, b.dataset AS cand_dataset, b.attr AS cand_attr, round({_NAME}, 9) AS name_distance FROM strs a JOIN strs b ON a.dataset <> b.dataset),
j AS (SELECT e.*, coalesce(round(containment, 9), 0) AS containment, coalesce(round(jaccard, 9), 0) AS jaccard, coalesce({_CLASS.format(c='containment', k='ratio')}, 0) AS quality FROM every e LEFT JOIN truth USING ({_ID})),
v AS (SELECT 'containment' AS method, *, -containment AS worse FROM j UNION ALL SELECT 'jaccard', *, -jaccard FROM j UNION ALL SELECT 'names', *, name_distance FROM j),
p AS (SELECT *, row_number() OVER (PARTITION BY method, ref_dataset, ref_attr ORDER BY worse, cand_dataset, cand_attr) AS place FROM v)
SELECT method, ref_dataset, ref_attr, CAST(coalesce(min(place) FILTER (quality < 3) - 1, count(*)) AS BIGINT) AS looked_at, CAST(count(*) FILTER (quality >= 3) AS BIGINT) AS interesting FROM p GROUP BY ALL"""


@query("ranking_cost", _RANKED)
def ranking_cost(spark, sf_dir):
    """For each reference attribute and each ranking by one measure: pairs a user looks at before the first that isn't worth joining
    (true class under 3), and how many there are that are."""
    c = context(spark, sf_dir)
    strings = c.strings.select("dataset", "attr")
    every = pairs.candidates(strings, strings).select(*pairs.ID, F.round(pairs.name_distance(F.col("ref_attr"), F.col("cand_attr")), 9).alias("name_distance"))
    known = every.join(c.truth.select(*pairs.ID, "containment", "jaccard", "quality"), list(pairs.ID), "left")
    measure = lambda x: F.coalesce(F.round(x, 9), F.lit(0.0))
    worse = F.explode(F.array(*[F.struct(F.lit(n).alias("method"), w.alias("worse")) for n, w in (("containment", -measure("containment")), ("jaccard", -measure("jaccard")), ("names", F.col("name_distance")))]))
    ranked = known.select(*pairs.ID, F.coalesce("quality", F.lit(0)).alias("quality"), worse.alias("m")).select(*pairs.ID, "quality", "m.*")
    by = Window.partitionBy("method", "ref_dataset", "ref_attr").orderBy("worse", "cand_dataset", "cand_attr")
    placed = ranked.withColumn("place", F.row_number().over(by))
    first = F.min(F.when(F.col("quality") < 3, F.col("place"))) - 1
    return placed.groupBy("method", "ref_dataset", "ref_attr").agg(F.coalesce(first, F.count(F.lit(1))).cast("bigint").alias("looked_at"), F.sum(F.when(F.col("quality") >= 3, 1).otherwise(0)).cast("bigint").alias("interesting"))
