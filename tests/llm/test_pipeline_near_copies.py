import random

import numpy as np
from pyspark.sql import functions as F

from lakejoin.llm import nearcopies, simhash


def shingles(text):
    w = text.lower().split()
    return {tuple(w[i : i + 5]) for i in range(len(w) - 4)} or {tuple(w)}


def similar(x, y):
    return 5 * len(x & y) >= 4 * len(x | y)


def survivors(rows):
    """Smallest id of each component of all pairs of five-word similarity 0.8, by brute force."""
    sets, root = [shingles(t) for _, t in rows], list(range(len(rows)))
    pairs = [(a, b) for b in range(len(rows)) for a in range(b) if similar(sets[a], sets[b])]

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for a, b in pairs:
        a, b = find(a), find(b)
        root[max(a, b)] = min(a, b)
    return {rows[i][0] for i in range(len(rows)) if find(i) == i}, len(pairs)


def planted():
    rng = random.Random(11)
    new = lambda n: ["".join(rng.choice("abcdefgh") for _ in range(6)) for _ in range(n)]
    line, texts = new(12), []
    for size in (30, 200, 400):
        for _ in range(6):
            base = new(size)
            texts.append(base)
            for changed in (1, 2, 4, 8, 9, 12):
                copy = list(base)
                for at in rng.sample(range(size), changed * size // 400 + 1):
                    copy[at] = new(1)[0]
                texts.append(copy)
    texts += [line + new(20) for _ in range(40)]
    # a chain of small steps from one text, more than are paired off at once
    step = new(60)
    for _ in range(45):
        step = list(step)
        step[rng.randrange(60)] = new(1)[0]
        texts.append(step)
    # copies of one text, each with a few words of its own: some pairs are similar, some are not
    base = new(250)
    for _ in range(40):
        copy = list(base)
        for at in rng.sample(range(250), rng.choice((2, 3, 4, 5))):
            copy[at] = new(1)[0]
        texts.append(copy)
    rng.shuffle(texts)
    return [(i, " ".join(t)) for i, t in enumerate(texts)]


def test_stage_keeps_what_brute_force_keeps(spark):
    rows = planted()
    want, pairs = survivors(rows)
    assert pairs > 300 and 80 < len(want) < len(rows) - 80
    docs = spark.createDataFrame(rows, "doc_id bigint, text string")
    assert {r.doc_id for r in simhash.stage(spark, docs, "").collect()} == want


def test_bitmaps_bound_the_difference(spark):
    """Of sets of unlike sizes, folded where they must be: never more than the codes that only one has, and close to them."""
    rng = np.random.default_rng(3)
    rows = []
    for n in (0, 1, 5, 250, 260, 500, 520, 1_000, 5_000):
        a = rng.integers(0, 1 << 63, n, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
        for gone in (0, n // 20, n // 5):
            b = np.concatenate([a[gone:], rng.integers(0, 1 << 63, n // 20, dtype=np.uint64) * np.uint64(2)])
            rows.append((nearcopies.parity(a).tolist(), nearcopies.parity(b).tolist(), gone + n // 20))
    df = spark.createDataFrame(rows, "a array<bigint>, b array<bigint>, d int")
    got = df.select(nearcopies.apart(F.col("a"), F.col("b")).alias("n"), "d").collect()
    assert all(r.n <= r.d and r.n % 2 == r.d % 2 and r.n >= 0.7 * r.d - 4 for r in got)
