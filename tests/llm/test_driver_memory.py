import random
import types
import weakref

import numpy as np

from lakejoin.llm import components, nbsvm


def test_the_fit_gives_the_drivers_memory_back(monkeypatch):
    rng, held, left = np.random.default_rng(3), [], []

    def gathered(_):
        sets = [np.unique(rng.integers(0, nbsvm.BUCKETS, 90, np.int32)) for _ in range(200)]
        held.extend(map(weakref.ref, sets))
        return sets, np.arange(200) % 2

    monkeypatch.setattr(nbsvm, "_gathered", gathered)
    monkeypatch.setattr(nbsvm, "released", lambda: left.append(sum(x() is not None for x in held)))
    nbsvm.fit(types.SimpleNamespace())
    assert len(held) == 200 and left == [0]


def roots(edges):
    out = {}
    for a, b in edges:
        if a != b:
            x, y = out.setdefault(a, {a}), out.setdefault(b, {b})
            if x is not y:
                x |= y
                for n in y:
                    out[n] = x
    return {n: min(x) for n, x in out.items()}


def mixed():
    rng = random.Random(4)
    path = [rng.randrange(-(2**62), 2**62) for _ in range(120)]
    edges = list(zip(path, path[1:])) + [(i, i + 1) for i in range(90)] + [(500, 1000 + i) for i in range(150)] + [(9_999, 300 + i) for i in range(50)]
    edges += [tuple(rng.sample(range(3_000, 3_400), 2)) for _ in range(180)] + [(7, 7), (123_456, 123_456), (3, 2), (2, 3)]
    rng.shuffle(edges)
    return edges


def test_components_by_contraction_and_in_one_task(spark):
    edges = mixed()
    df = spark.createDataFrame(edges, "a bigint, b bigint").repartition(5).cache()
    for small in (components.SMALL, 100, 0):
        got = components.components(df, small=small).collect()
        assert len(got) == len({r.node for r in got}) and {r.node: r.root for r in got} == roots(edges)


def test_no_edges(spark):
    for small in (components.SMALL, 0):
        assert components.components(spark.createDataFrame([(5, 5)], "a bigint, b bigint"), small=small).collect() == []


def test_a_small_graph_costs_three_plans(spark):
    df = spark.createDataFrame(mixed(), "a bigint, b bigint")
    plans = lambda: spark._jsparkSession.sharedState().statusStore().executionsCount()
    spark.sparkContext._jsc.sc().listenerBus().waitUntilEmpty(30_000)
    before = plans()
    components.components(df)
    spark.sparkContext._jsc.sc().listenerBus().waitUntilEmpty(30_000)
    assert plans() - before <= 3
