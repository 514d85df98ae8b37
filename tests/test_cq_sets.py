from lakejoin.operators import cq


def frames(spark):
    a = spark.createDataFrame([("x", "1", "p"), ("x", "1", "p"), ("y", "2", "q"), ("z", None, "r")], "name string, k string, more string")
    b = spark.createDataFrame([("1", "u"), ("1", "u"), ("1", "v"), ("2", "u"), (None, "w")], "k string, val string")
    return {"a": a, "b": b}


LINK = cq.Predicate("a", "k", "b", "k")


def test_rows_are_distinct_before_they_multiply(spark):
    got = cq.CQ(["a", "b"], [LINK], [("a", "name"), ("b", "k"), ("b", "val")]).run(frames(spark))
    assert sorted(map(tuple, got.collect())) == [("x", "1", "u"), ("x", "1", "v"), ("y", "2", "u")]
    assert not got._jdf.queryExecution().optimizedPlan().nodeName().startswith("Aggregate")


def test_a_hidden_column_still_needs_the_last_distinct(spark):
    got = cq.CQ(["a", "b"], [LINK], [("b", "val")]).run(frames(spark))
    assert sorted(r[0] for r in got.collect()) == ["u", "v"]
    mixed = frames(spark) | {"b": spark.createDataFrame([(1, "u"), (2, "u")], "k int, val string")}
    assert cq.CQ(["a", "b"], [LINK], [("b", "k"), ("b", "val")]).run(mixed | {"a": spark.createDataFrame([("1",), ("01",)], "k string")}).count() == 1
