import random

import numpy as np
import pytest
import xxhash
from pyspark.sql import functions as F

from lakejoin.llm import chaining, components, simhash


def brute_fingerprint(text):
    words = "".join(c.lower() if "A" <= c <= "Z" else c for c in text or "").encode().split()
    if not words:
        return 0
    runs = [b" ".join(words[i : i + 3]) for i in range(len(words) - 2)] or [b" ".join(words)]
    h = [xxhash.xxh64_intdigest(r, 42) for r in runs]
    return sum(1 << k for k in range(64) if 2 * sum(x >> k & 1 for x in h) > len(h))


def groups(pairs, nodes):
    parent = {n: n for n in nodes}

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for a, b in pairs:
        a, b = find(a), find(b)
        parent[max(a, b)] = min(a, b)
    return {n: find(n) for n in nodes}


def test_fingerprint(spark):
    for t in ("", None, "One", "one TWO", "A b c d e f g h", "Él niño ÉL x y"):
        assert simhash.fingerprint(t) & (2**64 - 1) == brute_fingerprint(t)
    t = "a b c"
    assert spark.sql("SELECT xxhash64('a b c') AS h").first().h == simhash.fingerprint(t)


def test_links_against_brute_force(spark):
    rng = random.Random(5)
    seeds = [rng.getrandbits(64) for _ in range(60)]
    prints = set(seeds)
    for s in seeds[:20]:
        for _ in range(rng.choice((1, 2, 30))):
            s ^= sum(1 << b for b in rng.sample(range(64), rng.choice((1, 2, 3))))
            prints.add(s)
    rows = [(i, p - (1 << 64) if p >> 63 else p) for i, p in enumerate(sorted(prints))] + [(10_000 + i, 0) for i in range(3)]
    got = {r.doc_id: r.component_id for r in simhash.assign(spark.createDataFrame(rows, "doc_id bigint, fp bigint")).collect()}
    links = [(a, b) for i, (a, x) in enumerate(rows) for b, y in rows[:i] if ((x ^ y) & (2**64 - 1)).bit_count() <= 2]
    assert got == groups(links, [r[0] for r in rows])


def test_components_of_a_long_path_and_a_star(spark):
    edges = [(i, i + 1) for i in range(60)] + [(1000, 2000 + i) for i in range(200)] + [(5, 5)]
    got = {r.node: r.root for r in components.components(spark.createDataFrame(edges, "a bigint, b bigint")).collect()}
    assert got == {n: r for n, r in groups(edges, {x for e in edges for x in e}).items()}


def test_simhash_odd_rows(spark, odd, nothing):
    got = simhash.assign(simhash.fingerprints(odd)).collect()
    assert len(got) == 10 and {r.component_id for r in got if r.doc_id in (3, 4, 5)} == {3} and {r.component_id for r in got if r.doc_id in (1, 2)} == {1}
    kept = simhash.stage(spark, odd, "")
    assert kept.columns == odd.columns
    assert sorted((r.doc_id or 0) for r in kept.collect()) == [0, 1, 3, 6, 7, 8]
    assert simhash.stage(spark, nothing, "").count() == 0


def test_common_words():
    rng = random.Random(1)
    for _ in range(50):
        a, b = ([rng.choice("abcde") for _ in range(rng.randrange(1, 30))] for _ in range(2))
        row = [[0] * (len(b) + 1) for _ in range(len(a) + 1)]
        for i in range(len(a)):
            for j in range(len(b)):
                row[i + 1][j + 1] = row[i][j] + 1 if a[i] == b[j] else max(row[i][j + 1], row[i + 1][j])
        assert chaining.common_words(a, b) == row[-1][-1]


def test_chains_have_the_best_score():
    rng = random.Random(2)
    for _ in range(60):
        n = rng.randrange(2, 9)
        c = np.array(sorted(rng.sample(range(0, 400), n)))
        o = np.array(rng.sample(range(0, 400), n))
        best = 0.0
        for mask in range(1, 1 << n):
            at = [i for i in range(n) if mask >> i & 1]
            if all(o[x] < o[y] for x, y in zip(at, at[1:])):
                best = max(best, len(at) * chaining.ANCHOR - chaining.GAP * sum(int(c[y] - c[x]) + int(o[y] - o[x]) for x, y in zip(at, at[1:])))
        score = lambda p: len(p) * chaining.ANCHOR - chaining.GAP * (int(c[p[-1]] - c[p[0]]) + int(o[p[-1]] - o[p[0]]))  # noqa: B023, E731
        whole = [x for x in chaining.best_chains(c, o)]
        if whole and not (np.diff(o) > 0).all() and best > chaining.ANCHOR and max(np.diff(c).max(), 0) <= chaining.BREAK:
            assert max(map(score, whole)) <= best + 1e-9
    assert [p.tolist() for p in chaining.best_chains(np.array([0, 30, 60, 90]), np.array([500, 30, 560, 600]))] == [[0, 2, 3]]


def words(rng, n):
    return ["".join(rng.choice("abcdefghijklmnop") for _ in range(rng.randrange(2, 9))) for _ in range(n)]


@pytest.fixture(scope="module")
def planted():
    rng = random.Random(3)
    passage = words(rng, 70)
    fuzzy = [w if i % 12 else "changed" for i, w in enumerate(passage)]
    rows = [(i, " ".join(words(rng, 150))) for i in range(30)]
    for i in (31, 35, 39):
        rows.append((i, " ".join(words(rng, 40) + passage + words(rng, 60))))
    rows.append((41, " ".join(words(rng, 90) + fuzzy + words(rng, 20))))
    rows.append((50, " ".join(words(rng, 30) + passage[:40] + words(rng, 60))))
    rows += [(60, rows[3][1]), (61, rows[3][1]), (62, "short text"), (63, "short text"), (64, None), (65, "")]
    return rows, passage


def test_passages(spark, planted):
    rows, passage = planted
    df = spark.createDataFrame([(*r, "en", "s", 0) for r in rows], "doc_id bigint, text string, lang string, source string, n_chars bigint")
    got = {r.doc_id: r for r in chaining.passages(df).collect()}
    assert set(got) == {35, 39, 41, 60, 61}
    text = dict(rows)
    for i in (35, 39):
        assert text[i][got[i].start : got[i].end].split() == passage and got[i].owner == 31 and got[i].similarity == 1
    assert got[41].words >= 65 and got[41].similarity >= 0.8
    assert got[60].owner == 3 and got[60].end == len(text[3])
    rest = {r.doc_id: r.text for r in chaining.stage(spark, df, "").collect()}
    assert rest[31] == text[31] and len(rest[35].split()) == 100 and 60 not in rest and 64 in rest and rest[50] == text[50]


def test_passages_of_odd_rows(spark, odd, nothing):
    assert chaining.passages(odd).count() == 0 and chaining.passages(nothing).count() == 0
    out = chaining.stage(spark, odd, "")
    assert out.columns == odd.columns and out.count() == 10


def test_passages_on_the_tables(docs):
    """Every document that repeats 60 words of a smaller one in a row is reported."""
    rows = [(r.doc_id, (r.text or "").lower().split()) for r in docs.select("doc_id", "text").collect()]
    first, repeats = {}, set()
    for d, w in sorted(rows):
        for i in range(len(w) - 59):
            if first.setdefault(tuple(w[i : i + 60]), d) < d:
                repeats.add(d)
    got = {r.doc_id for r in chaining.passages(docs).select("doc_id").collect()}
    assert repeats <= got and len(repeats) > 3


def test_hot_group_stays_linear(spark):
    rows = spark.range(400).select(F.col("id").alias("doc_id"), F.pmod(F.col("id"), F.lit(200)).alias("b")).select("doc_id", (F.lit(1 << 40) + F.pow(F.lit(2), F.pmod("b", F.lit(40))).cast("bigint")).alias("fp"))
    assert simhash.links(rows.select("fp").distinct()).count() <= 65 * 41
    assert simhash.assign(rows).select("component_id").distinct().count() == 1
