"""Corpus pipeline: each stage reads what the one before wrote.

Low-quality documents go; one document of each near-duplicate component stays; passages that a smaller document
holds are cut out; sources are mixed to their target weights in training order; texts become pieces.
"""

from __future__ import annotations

from lakejoin.llm import chaining, curriculum, nbsvm, pieces, simhash
from lakejoin.llm.common import documents, stored

#: Each takes (spark, docs, sf_dir) and returns a DataFrame; all but the last return the columns of documents.
STAGES = [
    ("quality_classifier", nbsvm.stage),
    ("simhash_near_dedup", simhash.stage),
    ("substring_dedup", chaining.stage),
    ("source_mixing", curriculum.stage),
    ("piece_encoding", pieces.stage),
]

#: The first stage is a learned classifier, which SQL can't express; tests hold each stage against brute force.
ORACLE_SQL = None


def run(spark, sf_dir):
    docs = documents(spark, sf_dir)
    for k, (_, stage) in enumerate(STAGES):
        docs = stage(spark, docs if k == 0 else stored(docs), sf_dir)
    return docs
