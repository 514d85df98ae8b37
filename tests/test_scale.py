"""Steps that must hold when a lake grows: no step pairs, sorts or ranks a whole group in one task, and names may hold anything."""

import random

import pytest
from pyspark.sql import functions as F

from lakejoin.operators import chain, discover, pairs, profile, quality, scaling, size_lsh, training
from lakejoin.operators.profile import frequencies


def melted(spark, rows):
    return spark.createDataFrame(rows, "dataset string, attr string, value string")


def test_names_may_hold_any_character(spark):
    """Datasets that differ only behind a bar are two datasets."""
    freq = frequencies(melted(spark, [("x|1", "a", "v"), ("x|2", "a", "v"), ("x", "1|a", "v"), ("x\\", "a|", "v")]))
    got = {(r.ref_dataset, r.ref_attr, r.cand_dataset, r.cand_attr) for r in quality.truth(freq).collect()}
    ids = [("x|1", "a"), ("x|2", "a"), ("x", "1|a"), ("x\\", "a|")]
    assert got == {(*a, *b) for a in ids for b in ids if a[0] != b[0]}
    rows = spark.createDataFrame([(a, b, c, d) for a, b in ids for c, d in ids], list(pairs.ID))
    assert rows.select(pairs.pair_id().alias("i")).distinct().count() == 16
    parts = size_lsh.partitions(size_lsh.signatures(freq, m=4), 2)
    assert parts.count() == 4 and parts.select("id").distinct().count() == 4


def test_large_owner_sets_are_cut_into_blocks(spark, monkeypatch):
    rng = random.Random(1)
    rows = [(f"d{i}", "a", "everywhere") for i in range(23)] + [(f"d{rng.randrange(23)}", "a", f"v{rng.randrange(40)}") for _ in range(300)]
    freq = frequencies(melted(spark, rows))
    want = {(r.a, r.b): r.n_common for r in quality.intersections(freq).collect()}
    monkeypatch.setattr(quality, "BLOCK", 4)
    got = {(r.a, r.b): r.n_common for r in quality.intersections(freq).collect()}
    assert got == want and len(got) == 23 * 22


@pytest.mark.parametrize("cls", range(5))
def test_balanced_sample_is_the_least_md5_of_each_class(spark, cls):
    import hashlib

    rng = random.Random(2)
    rows = [(f"p{i}", rng.choices(range(5), (900, 60, 25, 5, 40))[0]) for i in range(3_000)]
    labelled = spark.createDataFrame(rows, "pair_id string, label int")
    counts = {c: sum(label == c for _, label in rows) for c in range(5)}
    want = set()
    for c, n in training.quotas(counts, cls).items():
        want |= set(sorted((p for p, label in rows if label == c), key=lambda p: (hashlib.md5(p.encode()).hexdigest(), p))[:n])
    got = training.balanced(labelled, cls).collect()
    assert {r.pair_id for r in got} == want and len(got) == len(want) and all((r.target == 1.0) == (r.label == cls) for r in got)


def test_partitions_by_size_are_as_equal_as_can_be(spark):
    rng = random.Random(3)
    rows = [(f"d{i:03d}", "a", f"v{j}") for i in range(70) for j in range(rng.choice((1, 1, 1, 2, 5, 9, 30)))]
    found = size_lsh.partitions(size_lsh.signatures(frequencies(melted(spark, rows)), m=4), 8).collect()
    sizes = sorted((r.card, r.dataset) for r in found)
    part = {d: k for k, chunk in enumerate([sizes[i * 9 : i * 9 + 9] for i in range(6)] + [sizes[54:62], sizes[62:]], 1) for _, d in chunk}
    assert {r.dataset: r.part for r in found} == part
    assert all(r.upper == max(x.card for x in found if x.part == r.part) for r in found)


def test_one_pair_has_one_vector(spark):
    """Scales come from the lake, so a pair looks the same by attribute and by dataset."""
    rows = [(f"d{i}", a, f"{a}{j % (7 + 3 * i)}") for i in range(5) for a in ("x", "y") for j in range(60)]
    profiles = profile.profiles(frequencies(melted(spark, rows)))
    ref, lake = profiles.where("dataset = 'd0'"), profiles.where("dataset <> 'd0'")
    whole = {tuple(r[c] for c in pairs.ID): r for r in discover.vectors(ref, lake).collect()}
    one = discover.vectors(ref.where("attr = 'y'"), lake).collect()
    assert one and all(whole[tuple(r[c] for c in pairs.ID)] == r for r in one)


def test_pruned_pairs_lose_none_that_qualifies(spark):
    rng = random.Random(4)
    rows = [(f"d{i}", "a", f"v{j}") for i in range(30) for j in rng.sample(range(400), rng.choice((2, 5, 30, 120, 390)))]
    freq = frequencies(melted(spark, rows))
    profiles = profile.profiles(freq)
    for k in (1, 2, 3, 4):
        want = {tuple(r) for r in quality.truth(freq).where(F.col("quality") >= k).select(*pairs.ID).collect()}
        got = {tuple(r) for r in pairs.pruned_candidates(profiles, profiles, k).select(*pairs.ID).collect()}
        assert want and want <= got
    model = chain.ChainModel([], True)
    assert model.forests == [] and scaling.SCALED


def test_thresholds_are_data(spark):
    """Other limits give other classes, by the same rule."""
    freq = frequencies(melted(spark, [("a", "x", str(i)) for i in range(10)] + [("b", "x", str(i)) for i in range(4)]))
    strict = quality.Thresholds(c=(0.9, 0.8, 0.7, 0.6), k=(0.5, 0.4, 0.3))
    of = lambda **kw: {(r.ref_dataset, r.cand_dataset): r.quality for r in quality.truth(freq, **kw).collect()}
    assert of() == {("a", "b"): 2, ("b", "a"): 4} and of(th=strict) == {("a", "b"): 0, ("b", "a"): 3}
    with pytest.raises(ValueError, match="fall strictly"):
        quality.Thresholds(c=(0.5, 0.5, 0.25, 0.1))
