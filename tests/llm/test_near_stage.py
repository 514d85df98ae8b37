import numpy as np

from lakejoin.llm import nearcopies, simhash


def test_stage_links_near_fingerprints(spark):
    """Texts whose fingerprints are near are one component, though few of their distinct five-word runs are shared."""
    base = " ".join(f"word{i}" for i in range(21))
    rows = [(1, " ".join([base] * 50)), (2, " ".join([base] * 50 + [f"other{i}" for i in range(10)])), (3, "a text that is like neither of the two others")]
    a, b = (simhash.fingerprint(t) & (2**64 - 1) for _, t in rows[:2])
    x, y = (set(nearcopies.shingles(t).tolist()) for _, t in rows[:2])
    assert (a ^ b).bit_count() <= simhash.RADIUS and len(x & y) < 0.8 * len(x | y)
    docs = spark.createDataFrame(rows, "doc_id bigint, text string")
    assert {r.doc_id for r in simhash.stage(spark, docs, "").collect()} == {1, 3}


def test_common_shingles_come_last_however_many_there_are(spark):
    line = "the same line of seven words here"
    rows = [(i, " ".join([line, *(f"w{i}x{k}" for k in range(200))])) for i in range(800)]
    known, n = nearcopies.commonness(spark.createDataFrame(rows, "doc_id bigint, text string"))
    assert set(known.tolist()) == set(nearcopies.shingles(line).tolist()) and (n == n[0]).all() and 20 < n[0] < 100
    codes = nearcopies.shingles(rows[0][1])
    got = nearcopies.ordered(codes, (known, n))
    assert sorted(got.tolist()) == codes.tolist() and set(got[-len(known) :].tolist()) == set(known.tolist())
    assert (nearcopies.ordered(codes, (known[:0], n[:0])) == codes).all() and got.dtype == np.uint64


def test_no_pair_is_verified_twice(spark, monkeypatch):
    """Texts that share half of their words all meet, but are not similar; each pair is looked at once."""
    seen, old = [], nearcopies.verified

    def verified(docs, found, each, pairs):
        seen.extend((r.a, r.b) for r in pairs.collect())
        return old(docs, found, each, pairs)

    monkeypatch.setattr(nearcopies, "verified", verified)
    rows = [(i, " ".join([*(f"same{k}" for k in range(44)), *(f"w{i}x{k}" for k in range(6))])) for i in range(12)]
    docs = spark.createDataFrame(rows, "doc_id bigint, text string")
    assert simhash.stage(spark, docs, "").count() == 12
    assert seen and len(seen) == len(set(seen))
