"""Queries against their oracles on the smallest tables, and the entry without the subpackage of text operators."""

import subprocess
import sys

import duckdb
import pandas as pd
import pytest

import __spark_entry__ as entry
from lakejoin.plans import catalog

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
ORACLES = catalog.oracle_sql()
NAMES = [n for n in ORACLES if n in ("profile_full", "profile_octiles", "profile_top_words", "string_gate", "zscore", "pair_distances", "quality_all", "quality_boundaries", "relation_kinds", "candidate_pairs_pruned", "balanced_sample", "downgrade_rules", "minhash_signature", "lsh_candidates", "clean_pairs", "profile_soundex", "containment_sketch", "lsh_query", "lsh_five_class", "balanced_counts", "ranking_cost", "testbed_sizes", "class_distribution_by_testbed", "nonsyntactic_pairs", "sql_functions", "udaf_minhash", "rel_approx_distinct", "stream_late", "stream_first_seen", "stream_enriched", "stream_sliding", "metrics_published", "cq_multi", "rel_as_of_join", "rel_window_frames", "rel_grouping_sets", "stream_profile", "stream_sessions")]


@pytest.fixture(scope="module")
def duck(sf):
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"create view {t} as select * from '{sf}/{t}.parquet'")
    return con


def rows(df):
    text = lambda v: "null" if v is None or v is pd.NA or v != v else f"{float(v):.5f}" if isinstance(v, (int, float)) and not isinstance(v, bool) else str(v)
    return sorted(tuple(text(v) for v in r) for r in df[sorted(df.columns)].astype(object).itertuples(index=False))


@pytest.mark.parametrize("name", NAMES)
def test_oracle(spark, sf, duck, name):
    ours, theirs = catalog.QUERIES[name](spark, sf).toPandas(), duck.execute(ORACLES[name]).df()
    assert sorted(ours.columns) == sorted(theirs.columns)
    mine, other = rows(ours), rows(theirs)
    assert len(mine) == len(other)
    for a, b in zip(mine, other):
        for x, y in zip(a, b):
            assert x == y or abs(float(x) - float(y)) <= 2e-5


def test_discovery_ranks_joinable_columns_first(spark, sf):
    found = entry.entry(spark).collect()
    assert found and [r.pred_class for r in found] == sorted((r.pred_class for r in found), reverse=True)
    top = {(r.cand_attr) for r in found if r.pred_class == 4}
    assert top & {"buyer", "customer", "entity"}


def test_every_oracle_has_a_query():
    assert set(entry.oracle_sql()) <= set(entry.queries())


def test_without_text_operators():
    code = "import sys; sys.modules['lakejoin.llm'] = None; sys.modules['corpus_pipeline'] = None\nimport __spark_entry__ as e; assert e.llm is None; assert 'pipeline' not in e.queries() and len(e.queries()) > 90"
    subprocess.run([sys.executable, "-c", code], check=True, cwd=entry._here)
