from pyspark.sql import functions as F

from lakejoin.operators import costs, cq, pairs, size_lsh, transforms, value_index
from lakejoin.operators.profile import frequencies
from lakejoin.plans.surround import as_of_join, range_join
from lakejoin.sources import store
from lakejoin.sources.lake import Lake, melt


def test_conjunctive_query(spark):
    a = spark.createDataFrame([("x", 1), ("x", 1), ("y", 2), (None, 3)], "k string, v int")
    b = spark.createDataFrame([("x", "p"), ("z", "q"), (None, "r")], "k string, w string")
    q = cq.CQ(["a", "b"], [cq.Predicate("a", "k", "b", "k")])
    out = q.run({"a": a, "b": b})
    assert [tuple(r) for r in out.collect()] == [("x", 1, "x", "p")]
    assert costs.plan_metrics(out)["CartesianProduct"] == 0
    for name, df in (("a", a), ("b", b)):
        df.createOrReplaceTempView(name)
    assert spark.sql(q.to_sql({"a": a, "b": b})).collect() == out.collect()


def test_transformations(spark):
    df = spark.createDataFrame([("NATION_7", ["p", "q"], "a; b")], "n string, l array<string>, s string")
    assert df.select(transforms.clean(F.col("n"))).first()[0] == "nation 7"
    assert [r.l for r in transforms.unwind(df, "l").collect()] == ["p", "q"]
    assert [r.s for r in transforms.unwind(df, "s", ";").collect()] == ["a", "b"]
    mapping = spark.createDataFrame([("NATION_7", "seven")], "key string, mapped string")
    assert transforms.lookup(df, "n", mapping).first().n == "seven"


def test_pruning_loses_no_feasible_pair(spark):
    profiles = spark.createDataFrame([(f"d{i}", "a", c) for i, c in enumerate((1, 2, 3, 5, 8, 9, 31, 32, 33, 100, 1000, 1024, 5000))], "dataset string, attr string, cardinality bigint")
    for cls, c, k in ((4, 0.75, 1 / 4), (3, 0.5, 1 / 8), (2, 0.25, 1 / 12), (1, 0.1, 0)):
        every = pairs.candidates(profiles, profiles).where(f"ref_cardinality * {c} <= cand_cardinality and ref_cardinality >= cand_cardinality * {k} - 1e-9")
        got = pairs.pruned_candidates(profiles, profiles, cls)
        assert {tuple(r) for r in got.select("ref_dataset", "cand_dataset").collect()} == {tuple(r) for r in every.select("ref_dataset", "cand_dataset").collect()}
        assert got.count() == every.count()


def test_reference_side_is_broadcast(spark):
    p = spark.createDataFrame([("d", "a", 1)], "dataset string, attr string, cardinality bigint")
    assert costs.plan_metrics(pairs.candidates(p, p.union(p), small_ref=True))["BroadcastNestedLoopJoin"] >= 1


def test_minhash_containment_search(spark):
    sets = {"all": range(1000), "half": range(500), "tenth": range(100), "other": range(5000, 6000), "near": range(20, 1020)}
    rows = [(d, "a", f"v{i}") for d, r in sets.items() for i in r]
    sig = size_lsh.partitions(size_lsh.signatures(frequencies(spark.createDataFrame(rows, "dataset string, attr string, value string"))), 3).cache()
    s = {r.dataset: r.sig for r in sig.collect()}
    estimate = sum(x == y for x, y in zip(s["all"], s["near"])) / size_lsh.M
    assert abs(estimate - 980 / 1020) < 3 * (0.96 * 0.04 / size_lsh.M) ** 0.5 + 0.02
    hits = {r.cand_dataset for r in size_lsh.query(sig, size_lsh.index(sig), "tenth", "a", 0.8).collect()}
    assert {"all", "half"} <= hits and "other" not in hits
    every = {(r.ref_dataset, r.cand_dataset) for r in size_lsh.all_hits(sig, 0.75).collect()}
    assert {("half", "all"), ("all", "near"), ("near", "all")} <= every
    one = size_lsh.signatures(frequencies(spark.createDataFrame(rows, "dataset string, attr string, value string")), scheme="one")
    o = {r.dataset: r.sig for r in one.collect()}
    assert len(o["tenth"]) == size_lsh.M and sum(x == y for x, y in zip(o["all"], o["near"])) > 100


def test_threshold_conversion():
    for t in (0.1, 0.5, 0.75):
        for q, x in ((10, 10), (100, 5000), (300, 40)):
            exact = t * q / (q + x - t * q)
            assert size_lsh.jaccard_threshold(t, x, q) <= exact + 1e-12 <= size_lsh.jaccard_threshold(t, x / 2, q) + 1
    assert size_lsh.banding(0.9)[1] >= size_lsh.banding(0.2)[1]


def test_value_index(spark):
    rows = [("d", "a", v) for v in "xyz"] + [("e", "b", v) for v in "xyq"] + [("f", "c", "z")]
    index = value_index.build(frequencies(spark.createDataFrame(rows, "dataset string, attr string, value string")))
    assert [(r.cand_dataset, r.n_common) for r in value_index.query(index, "d", "a", 0.5).collect()] == [("e", 2)]
    assert tuple(value_index.coverage(index, ("d", "a"), ("e", "b")).first()) == (2, 1)


def test_as_of_and_range(spark):
    left = spark.createDataFrame([(1, 5, "a"), (1, 1, "b"), (2, 9, "c")], "k int, t int, x string")
    right = spark.createDataFrame([(1, 2, "p"), (1, 5, "q"), (2, 10, "r")], "k int, t int, v string")
    assert {(r.x, r.v) for r in as_of_join(left, right, "k", "t", "v").collect()} == {("a", "q"), ("b", None), ("c", None)}
    points, ranges = spark.createDataFrame([(1.0,), (7.5,), (10.0,)], "x double"), spark.createDataFrame([(0.0, 7.5), (7.5, 30.0)], "lo double, hi double")
    assert range_join(points, ranges, "x", "lo", "hi", 4.0).count() == 4


def test_lake_and_store(spark, tmp_path):
    df = spark.createDataFrame([("a", 1), ("b", 2)], "s string, i int")
    df.write.csv(str(tmp_path / "c"), header=True)
    lake = Lake(spark).add("one", df).add_file("two", str(tmp_path / "c"), "csv")
    assert {(r.dataset, r.attr, r.declared_type) for r in lake.catalog().collect()} == {("one", "s", "string"), ("one", "i", "int"), ("two", "s", "string"), ("two", "i", "string")}
    assert lake.melted().count() == 6
    profile_fn = lambda frame, name: frequencies(melt(frame, name)).withColumnRenamed("cnt", "n")
    assert store.refresh(lake, str(tmp_path / "s"), profile_fn) == ["one", "two"]
    assert store.refresh(lake, str(tmp_path / "s"), profile_fn) == []
    spark.createDataFrame([("z", 9)], "s string, i int").write.mode("append").csv(str(tmp_path / "c"), header=True)
    again = Lake(spark).add("one", df).add_file("two", str(tmp_path / "c"), "csv")
    assert store.refresh(again, str(tmp_path / "s"), profile_fn) == ["two"]
    sizes = {r.dataset: r.bytes for r in costs.profile_size(spark, str(tmp_path / "s/profiles")).collect()}
    assert set(sizes) == {"one", "two"} and min(sizes.values()) > 0


def test_crawl(spark, tmp_path):
    spark.createDataFrame([("a",)], "s string").coalesce(1).write.parquet(str(tmp_path / "x"))
    (tmp_path / "n.csv").write_text("s,t\n1,2\n")
    lake = Lake.crawl(spark, str(tmp_path))
    assert "n" in lake.frames and len(lake.frames) == 2 and lake.bytes["n"] == 8
