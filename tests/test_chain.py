import pytest
from pyspark.sql import functions as F

from lakejoin.operators import chain, ranking, training
from lakejoin.operators.pairs import FEATURES, ID


@pytest.mark.parametrize(
    ("p", "raw", "rule", "final"),
    [
        ((0.9, 0.1, 0.1, 0.1, 0.1), 0, 0, 0), ((0.6, 0.2, 0.1, 0.8, 0.3), 3, 1, 0), ((0.55, 0.2, 0.7, 0.8, 0.1), 3, 1, 2), ((0.30, 0.1, 0.1, 0.35, 0.2), 3, 2, 0), ((0.20, 0.1, 0.1, 0.45, 0.3), 3, 0, 3),
        ((0.5, 0.1, 0.1, 0.6, 0.1), 3, 0, 3), ((0.35, 0.1, 0.1, 0.45, 0.1), 3, 2, 0), ((0.4, 0.4, 0.4, 0.4, 0.4), 0, 0, 0),
    ],
)
def test_rules(spark, p, raw, rule, final):
    r = ranking.assign(spark.createDataFrame([p], "p0 double, p1 double, p2 double, p3 double, p4 double")).first()
    assert (r.raw_class, r.rule, r.pred_class, r.score) == (raw, rule, final, p[final])


def test_rules_can_be_switched_off(spark):
    df = spark.createDataFrame([(0.6, 0.2, 0.1, 0.8, 0.3)], "p0 double, p1 double, p2 double, p3 double, p4 double")
    assert ranking.assign(df, rule1=False).first().pred_class == 3


def test_quotas():
    assert training.quotas({0: 105974, 1: 2000, 2: 1000, 3: 804, 4: 600}, 0) == {0: 4404, 4: 600, 3: 804, 2: 1000, 1: 2000}
    assert training.quotas({0: 100, 1: 8, 2: 8, 3: 2, 4: 8}, 4) == {4: 8, 3: 2, 1: 2, 2: 2, 0: 2}
    assert training.quotas({0: 10}, 3) == {3: 0, 0: 0}


@pytest.fixture(scope="module")
def labelled(spark):
    """Pairs whose class shows in one feature."""
    rows = spark.range(500).withColumn("label", F.pmod(F.col("id"), F.lit(5)).cast("int")).withColumn("pair_id", F.concat(F.lit("p"), F.col("id")))
    noise = F.pmod(F.xxhash64("id"), F.lit(100)) / 400
    return rows.select("pair_id", "label", *[F.lit("x").alias(c) for c in ID], *[((4 - F.col("label")) / 4 + noise if f == "d_cardinality" else noise).alias(f) for f in FEATURES]).cache()


TINY = {c: (16, 4, 5) for c in range(5)}


def test_chain_learns_saves_and_loads(spark, labelled, tmp_path):
    model = chain.fit_chain(labelled, TINY)
    scored = ranking.assign(model.probabilities(labelled))
    assert scored.where("label = pred_class").count() > 450
    model.save(str(tmp_path / "m"))
    again = chain.ChainModel.load(str(tmp_path / "m"))
    a, b = (m.probabilities(labelled).orderBy("pair_id").select("p0", "p4").collect() for m in (model, again))
    assert a == b and again.chained


def test_fit_ignores_partitioning(spark, labelled):
    a, b = (chain.fit_forest(training.balanced(df, 4), 4, (16, 4, 5), False) for df in (labelled, labelled.repartition(7)))
    assert a.toDebugString.partition("\n")[2] == b.toDebugString.partition("\n")[2]


def test_balanced_sample(spark, labelled):
    counts = {(r.label, r.target): r.n for r in training.balanced(labelled, 2).groupBy("label", "target").agg(F.count(F.lit(1)).alias("n")).collect()}
    assert counts == {(2, 1.0): 100, (0, 0.0): 25, (1, 0.0): 25, (3, 0.0): 25, (4, 0.0): 25}
