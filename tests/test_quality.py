import itertools

import pytest
from pyspark.sql import functions as F

from lakejoin.operators import quality
from lakejoin.operators.profile import frequencies


def classes(spark, rows, **kw):
    df = spark.createDataFrame([(float(c), float(a), float(b)) for c, a, b in rows], "c double, a double, b double")
    return [r[0] for r in df.select(quality.quality_class(F.col("c"), F.col("a") / F.col("b"), **kw)).collect()]


def test_worked_examples(spark):
    assert classes(spark, [(0.8, 5, 4), (0.2, 5, 1), (1, 1, 1), (0, 5, 5), (0.8, 8124, 54500), (0.95, 8124, 982921), (2 / 3, 3, 1_000_001)]) == [4, 1, 4, 0, 3, 1, 1]


def test_ratio_matters(spark):
    assert classes(spark, [(0.95, 8124, 982921)], use_ratio=False) == [4]


def test_larger_reference_is_not_penalised(spark):
    assert classes(spark, [(0.75, 1000, 1), (0.5, 10**6, 1)]) == [4, 3]


def test_boundaries(spark):
    assert classes(spark, [(0.75, 1, 4), (0.5, 1, 8), (0.25, 1, 12), (0.1, 1, 10**6), (0.0999, 1, 1)]) == [4, 3, 2, 1, 0]


def test_thresholds_are_validated():
    with pytest.raises(ValueError):
        quality.Thresholds(c=(0.5, 0.5, 0.2, 0.1))


def test_intersections_against_sets(spark):
    sets = {("d1", "a"): {"x", "y", "z"}, ("d1", "b"): {"x"}, ("d2", "a"): {"x", "y", "q"}, ("d3", "c"): {"q", "z"}, ("d4", "n"): set()}
    rows = [(d, a, v) for (d, a), vs in sets.items() for v in vs] * 2 + [("d4", "n", None)]
    freq = frequencies(spark.createDataFrame(rows, "dataset string, attr string, value string"))
    got = {(r.ref_dataset, r.ref_attr, r.cand_dataset, r.cand_attr): r for r in quality.truth(freq).collect()}
    expected = {}
    for (k, a), (m, b) in itertools.permutations(sets.items(), 2):
        if k[0] != m[0] and a & b:
            expected[(*k, *m)] = len(a & b)
            r = got[(*k, *m)]
            assert r.containment == len(a & b) / len(a) and r.jaccard == len(a & b) / len(a | b)
            assert 0 <= r.jaccard <= r.containment <= 1
    assert {k: r.n_common for k, r in got.items()} == expected


def test_class_never_passes_the_feasible_one(spark):
    rows = [(n / a, a, b) for a in (1, 3, 8, 40, 100) for b in (1, 5, 12, 33, 100, 900) for n in range(0, min(a, b) + 1)]
    df = spark.createDataFrame([(float(c), a, b) for c, a, b in rows], "c double, a bigint, b bigint")
    both = df.select(quality.quality_class(F.col("c"), F.col("a") / F.col("b")).alias("q"), quality.max_feasible_class(F.col("a"), F.col("b")).alias("m"))
    assert both.where("q > m").count() == 0
