from lakejoin.operators import profile


def test_cells_are_read_twice_more_and_not_shuffled(spark):
    """After the cells' own pass there are two: the sampled counts, for which rates are broadcast, and the words."""
    cells = spark.createDataFrame(spark.sparkContext.parallelize([("d", "x", f"v{i % 50} w{i % 7}") for i in range(500)], 2), "dataset string, attr string, value string")
    found = profile.approximate(cells)
    plan = found._jdf.queryExecution().sparkPlan().toString()
    assert plan.count("ExistingRDD") == 2 and "BroadcastHashJoin" in plan
    row, exact = found.first(), profile.profiles(profile.frequencies(cells)).first()
    assert (row.n_rows, row.freq_max, row.words_total) == (500, exact.freq_max, exact.words_total)
