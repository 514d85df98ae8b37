"""Queries that once made their rows up read a given table, and agree with their oracles on it."""

import pytest

from lakejoin.plans import catalog
from test_queries import duck, rows  # noqa: F401

NAMES = ["semantic_share", "quality_worked_examples", "metrics_published", "error_profile_published", "downgrade_rules", "confusion_published", "confusion_by_testbed", "binary_published"]


@pytest.mark.parametrize("name", NAMES)
def test_reads_a_given_table(spark, sf, duck, name):  # noqa: F811
    df = catalog.QUERIES[name](spark, sf)
    assert any(f.endswith(".parquet") and sf in f for f in df.inputFiles())
    ours, theirs = df.toPandas(), duck.execute(catalog.oracle_sql()[name]).df()
    assert len(ours) and sorted(ours.columns) == sorted(theirs.columns) and rows(ours) == rows(theirs)
