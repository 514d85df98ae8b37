import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from lakejoin.llm import boosting, compression_lid, nbsvm, outliers, toxicity


def test_dual_coordinate_descent_against_subgradient():
    rng = np.random.default_rng(0)
    x = rng.normal(size=(120, 4))
    y = np.where(x @ np.array([1.0, -2.0, 0.5, 0.0]) + 0.3 * rng.normal(size=120) > 0, 1.0, -1.0)
    rows, values, c = [np.arange(4)] * 120, list(x), np.full(120, 0.5)
    w = nbsvm.dual_coordinate_descent(rows, values, y, 4, c, epochs=500)
    loss = lambda v: 0.5 * v @ v + 0.5 * np.maximum(0, 1 - y * (x @ v)).sum()
    v = np.zeros(4)
    for t in range(1, 20_000):
        m = y * (x @ v) < 1
        v = v - 1 / t * (v - 0.5 * (y[m, None] * x[m]).sum(0))
    assert loss(w) <= loss(v) + 1e-2


def test_quality_fit_and_odd_texts():
    rng = random.Random(0)
    good = [" ".join(rng.choice(["the", "cat", "sat", "warm", "house", "garden"]) for _ in range(60)) for _ in range(60)]
    bad = [" ".join(rng.choice(["THE!!", "CAT!!", "x***", "|"]) for _ in range(60)) for _ in range(40)]
    sets = [nbsvm.indicators(t) for t in good + bad]
    model = nbsvm.fit_rows(sets[::2], np.array([1] * 30 + [0] * 20))
    p = [model.score(s) for s in sets]
    assert min(p[:60]) > 0.5 > max(p[60:])
    assert 0 <= model.score(nbsvm.indicators("")) <= 1 and model.score(nbsvm.indicators(None)) == model.score(nbsvm.indicators(" \n"))
    assert 0 <= nbsvm.fit_rows([], np.array([])).score(nbsvm.indicators("a b")) <= 1


def auc(score, y):
    r = np.argsort(np.argsort(score)) + 1
    n1 = y.sum()
    return (r[y == 1].sum() - n1 * (n1 + 1) / 2) / (n1 * (len(y) - n1))


@pytest.mark.parametrize(("make", "column", "least"), [(nbsvm.op10_nbsvm_quality, "quality", 0.95), (toxicity.op4_toxicity_boosted, "toxic", 0.85)])
def test_held_out_accuracy(spark, make, column, least):
    sf = "/root/testdata/sf0.01"
    got = make(spark, sf)
    assert got.columns[:4] == ["doc_id", "held_out", "score", "predicted"]
    rows = got.join(spark.read.parquet(f"{sf}/labels.parquet"), "doc_id").where("held_out").select("score", column, "predicted").toPandas()
    assert auc(rows.score.to_numpy(), rows[column].to_numpy()) >= least
    assert got.count() == spark.read.parquet(f"{sf}/documents.parquet").count() and rows.score.between(0, 1).all() and ((rows.score >= 0.5) == (rows.predicted == 1)).all()


def test_scoring_odd_rows(odd, nothing):
    model = nbsvm.fit_rows([nbsvm.indicators("good words here"), nbsvm.indicators("BAD!! ***")], np.array([1, 0]))
    assert nbsvm.score(odd, model).count() == 10 and nbsvm.score(nothing, model).count() == 0
    tox = toxicity.fit_rows(toxicity.Features({"moron": 5.0}), np.zeros((0, toxicity.Features.SIZE)), np.zeros(0))
    scored = {r.doc_id: r.score for r in toxicity.score(odd, tox).collect()}
    assert len(scored) == 9 and all(0 <= s <= 1 for s in scored.values()) and toxicity.score(nothing, tox).count() == 0


def test_toxic_features():
    f = toxicity.Features({"moron": 5.0, "stup~": 3.0})
    plain, hit, tricked, inflected = (f(t) for t in ("You are a kind person", "You are a moron!", "You are a m0r0n", "such stupidity"))
    assert plain[0] == 0 and hit[0] > 0 and hit[8] > 0 and tricked[0] > 0 and tricked[15] > 0 and inflected[2] == 3.0
    assert not f("").any() and not f(None).any()


def test_boosting_and_isotonic():
    rng = np.random.default_rng(1)
    x = rng.normal(size=(800, 3))
    y = ((x[:, 0] > 0) ^ (x[:, 1] > 0)).astype(float)
    m = boosting.fit(x[:600], y[:600], rounds=60).margin(x[600:])
    assert ((m > 0) == (y[600:] > 0)).mean() > 0.9
    xs, ys = boosting.isotonic(np.array([1.0, 2, 3, 4, 4]), np.array([0.0, 1, 0, 1, 1]))
    assert (np.diff(ys) >= 0).all() and ys[0] == 0 and ys[-1] == 1 and np.interp(2.5, xs, ys) == 0.5
    assert boosting.fit(x[:5], np.ones(5)).margin(x[:2]).shape == (2,)


def test_language_by_compression(spark, odd, nothing):
    sf = "/root/testdata/sf0.01"
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    model = compression_lid.train(docs, ~compression_lid.held_out())
    got = compression_lid.op7_compression_lid(spark, sf).join(docs.select("doc_id", "lang"), "doc_id").where("held_out")
    right, n = got.agg(F.avg((F.col("lang") == F.col("lang_pred")).cast("double")), F.count("*")).first()
    assert right >= 0.97 and n > 100
    odd_rows = {r.doc_id: r for r in compression_lid.predict(odd, model).collect()}
    assert odd_rows[4].lang_pred == odd_rows[3].lang_pred == odd_rows[5].lang_pred == "und" and odd_rows[3].score == 0
    assert odd_rows[6].lang_pred in model.contents and compression_lid.predict(nothing, model).count() == 0
    assert compression_lid.predict(odd, compression_lid.train(nothing, F.lit(True))).where("lang_pred <> 'und'").count() == 0


def brute_counts(text):
    text = text or ""
    words = [w for w in text.translate({9: 32, 10: 32, 11: 32, 12: 32, 13: 32}).split(" ") if w]
    seen, dup = set(), 0
    for line in text.split("\n"):
        if line.strip(" \t\r\x0b\x0c"):
            dup += line in seen
            seen.add(line)
    runs = [tuple(words[i : i + 3]) for i in range(len(words) - 2)]
    hit = {j for i, r in enumerate(runs) if runs.count(r) > 1 for j in (i, i + 1, i + 2)}
    return len(words), sum(map(len, words)), sum(c in "#*$%&|<>" for c in text), dup, len(hit)


def test_base_counts(docs):
    texts = [r.text for r in docs.select("text").collect() if len(r.text or "") < 4000] + ["", None, "a b a b a b a", "x\nx\n\n \n \nx", "#|é ▁\x0b<"]
    for t in texts:
        assert outliers.statistics(t)[:5] == brute_counts(t)


def test_mcd_resists_contamination(spark):
    rng = np.random.default_rng(2)
    cov = np.full((6, 6), 0.3) + np.eye(6) * 0.7
    clean = rng.multivariate_normal(np.zeros(6), cov, 800)
    bad = rng.normal(8, 0.5, size=(200, 6))
    rows = [("g", "w", *map(float, r)) for r in np.vstack([clean, bad])]
    df = spark.createDataFrame(rows, "own string, wide string, " + ", ".join(f"x{j} double" for j in range(6)))
    e = outliers.estimates(df).where("g = 'g'").first()
    assert np.abs(np.array(e.e_m)).max() < 0.25 and np.abs(np.array(rows)[:, 2:].astype(float).mean(0)).min() > 1
    d = np.einsum("ni,ij,nj->n", np.vstack([clean, bad]) - e.e_m, np.array(e.e_v).reshape(6, 6), np.vstack([clean, bad]) - e.e_m) * e.scale
    assert (d[800:] > outliers.chi_square(outliers.LEVEL)).all() and (d[:800] > outliers.chi_square(outliers.LEVEL)).mean() < 0.02


def test_outliers_on_odd_and_whole_tables(spark, odd, nothing, sf):
    got = outliers.judged(odd)
    assert got.count() == 10 and got.where("kept and base_failed").count() == 0 and outliers.judged(nothing).count() == 0
    whole = outliers.op1_robust_outliers(spark, "/root/testdata/sf0.01").join(spark.read.parquet("/root/testdata/sf0.01/labels.parquet"), "doc_id").where("not base_failed")
    assert whole.where("quality = 1").agg(F.avg(F.col("kept").cast("double"))).first()[0] > 0.97
    assert whole.where("quality = 0").agg(F.avg(F.col("kept").cast("double"))).first()[0] < 0.3


def brute_kept(rows):
    """Verdicts of rows (own, wide, vector) by plain numpy: the same rule, one group at a time."""
    P, o = 6, outliers
    x = np.array([r[2] for r in rows])
    names = {"all": (None, np.arange(len(rows)))}
    for own, wide, _ in rows:
        names.setdefault(wide, ("all", np.flatnonzero([r[1] == wide for r in rows])))
        names.setdefault(own, (wide, np.flatnonzero([r[0] == own for r in rows])))

    def lean(sums):
        out = {}
        for g, (above, _) in names.items():
            w, s = sums[g]
            out[g] = s / w if above is None else (s + o.PRIOR * out[above]) / (w + o.PRIOR)
        return out

    def quantile(bins, share):
        bins = np.sort(bins)
        return bins[int(np.ceil(share * len(bins))) - 1]

    binned = lambda d: np.floor(np.log(d + 1e-4) * o.COARSE).astype(int)
    far = lambda g, m, v: np.einsum("ni,ij,nj->n", x[names[g][1]] - m, v, x[names[g][1]] - m)

    def medians(values):
        return lean({g: (len(values[g]), len(values[g]) * np.array([(quantile(np.floor(values[g][:, j] * o.FINE), 0.5) + 0.5) / o.FINE for j in range(P)])) for g in names})

    def solve(keep):
        first = lean({g: (k.sum(), x[names[g][1]][k].sum(0)) for g, k in keep.items()})
        second = lean({g: (k.sum(), x[names[g][1]][k].T @ x[names[g][1]][k]) for g, k in keep.items()})
        cov = {g: second[g] - np.outer(first[g], first[g]) + o.FLOOR**2 * np.eye(P) for g in names}
        return {g: (first[g], np.linalg.inv(cov[g]), np.linalg.slogdet(cov[g])[1]) for g in names}

    mid = medians({g: x[at] for g, (_, at) in names.items()})
    mad = {g: np.sqrt((1.4826 * v) ** 2 + o.FLOOR**2) for g, v in medians({g: np.abs(x[at] - mid[g]) for g, (_, at) in names.items()}).items()}
    bent = {g: np.tanh((x[at] - mid[g]) / mad[g]) for g, (_, at) in names.items()}
    cor = lean({g: (len(b), b.T @ b) for g, b in bent.items()})
    starts = [{g: (mid[g], np.diag(1 / mad[g] ** 2)) for g in names}, {}]
    for g in names:
        d = np.sqrt(np.maximum(np.diag(cor[g]), 1e-6))
        starts[1][g] = mid[g], np.linalg.inv((0.95 * cor[g] / np.outer(d, d) + 0.05 * np.eye(P)) * np.outer(mad[g], mad[g]))
    dets = None
    for _ in range(o.STEPS):
        for k, state in enumerate(starts):
            keep = {}
            for g in names:
                d = binned(far(g, *state[g][:2]))
                keep[g] = d <= quantile(d, o.SUBSET)
            starts[k] = solve(keep)
        now = [sum(s[g][2] for g in names) for s in starts]
        if dets is not None and max(abs(a - b) for a, b in zip(now, dets)) <= o.SETTLED * len(names):
            break
        dets = now
    best = {g: starts[0][g][:2] if starts[0][g][2] <= starts[1][g][2] else starts[1][g][:2] for g in names}

    def scaled(state):
        half = lean({g: (len(names[g][1]), len(names[g][1]) * np.array([np.exp((quantile(binned(far(g, *state[g])), 0.5) + 0.5) / o.COARSE)])) for g in names})
        return {g: o.chi_square(0.0) / max(half[g][0], o.chi_square(0.0)) for g in names}

    scale = scaled(best)
    last = {g: v[:2] for g, v in solve({g: far(g, *best[g]) * scale[g] <= o.chi_square(1.96) for g in names}).items()}
    scale = scaled(last)
    return [float(np.einsum("i,ij,j", v - last[own][0], last[own][1], v - last[own][0]) * scale[own]) for own, _, v in rows]


def test_verdicts_against_plain_numpy(spark, docs):
    """Distances of every document, groups of one row to the largest, against the same rule without Spark."""
    few = docs.withColumn("source", F.when(F.col("doc_id") % 97 == 0, F.concat(F.lit("lone"), F.col("doc_id"))).otherwise(F.col("source")))
    got = outliers.judged(few).where("not base_failed").orderBy("doc_id", "x0").collect()
    want = brute_kept([(r.own, r.wide, [r[f"x{j}"] for j in range(6)]) for r in got])
    assert len(got) > 100 and all(r.distance is not None for r in got)
    assert [r.distance for r in got] == pytest.approx(want, rel=1e-6, abs=1e-9)
    assert [r.kept for r in got] == [d <= outliers.chi_square(outliers.LEVEL) for d in want]


def test_dictionaries_and_predictions_against_plain_python(spark, docs):
    """Dictionaries built row by row, and every whole text compressed with each by a compressor of its own."""
    import struct

    import xxhash
    import zstandard

    lid = compression_lid
    model = lid.train(docs, F.col("doc_id") % 3 != 0)
    texts: dict = {}
    rows = docs.select("doc_id", "lang", "text").collect()
    learned = [r for r in rows if r.doc_id % 3 and r.lang is not None and r.text is not None]
    for r in learned:
        h = xxhash.xxh64_intdigest(struct.pack("<q", r.doc_id), seed=42)
        place = (h - (1 << 64) if h >> 63 else h) % (1 << 31)
        if place < lid.SAMPLE * (1 << 31) / sum(x.lang == r.lang for x in learned):
            size = lid.EACH // lid.CUTS
            cuts = [r.text[int(i * (len(r.text) - size) / (lid.CUTS - 1)) :][:size] for i in range(lid.CUTS)]
            texts.setdefault(r.lang, []).append((place, r.text if len(r.text) <= lid.EACH else "\n".join(cuts)))
    want = {}
    for lang, some in texts.items():
        out, size = [], 0
        for _, t in sorted(some):
            piece = t.casefold().encode()
            if piece and piece not in out and size < lid.DICTIONARY:
                out.append(piece)
                size += len(piece) + 1
        want[lang] = b"\n".join(out)[: lid.DICTIONARY]
    assert model.contents == want
    got = {r.doc_id: r for r in lid.predict(docs, model).collect()}
    for r in rows:
        if not r.text or not any(c.isalpha() for c in r.text):
            assert got[r.doc_id].lang_pred == "und"
            continue
        sizes = {}
        for lang, content in sorted(want.items()):
            d = zstandard.ZstdCompressionDict(content, dict_type=zstandard.DICT_TYPE_RAWCONTENT)
            c = zstandard.ZstdCompressor(level=lid.LEVEL, dict_data=d, write_checksum=False, write_content_size=False, write_dict_id=False)
            sizes[lang] = len(c.compress(r.text.casefold().encode()))
        least = sorted(sizes.values())
        assert sizes[got[r.doc_id].lang_pred] == least[0]
        assert got[r.doc_id].rejected == ((least[1] - least[0]) / least[1] < lid.NARROW)


def test_every_language_is_learned(spark):
    rows = [(i, f"wort{i % 60}a wort{i % 60}b " * 5, f"l{i % 60}") for i in range(600)]
    model = compression_lid.train(spark.createDataFrame(rows, "doc_id bigint, text string, lang string"), F.lit(True))
    assert len(model.contents) == 60


def brute_fit(x, y, rounds, depth=3, rate=0.15, bins=64, least=1.0, ridge=1.0):
    """Boosted trees by trying every cut of every node with plain sums; margins of the rows."""
    n, m = x.shape
    edges = [np.unique(np.quantile(x[:, j], np.linspace(0, 1, bins + 1)[1:-1])) for j in range(m)]
    p = (y.sum() + 0.5) / (n + 1)
    f = np.full(n, np.log(p / (1 - p)))
    for _ in range(rounds):
        q = 1 / (1 + np.exp(-f))
        g, h = q - y, np.maximum(q * (1 - q), 1e-9)
        groups = [np.arange(n)]
        for _ in range(depth):
            split = []
            for rows in groups:
                best, at = 1e-6, None
                for j in range(m):
                    top = None
                    for e in edges[j]:
                        left = rows[x[rows, j] <= e]
                        right = rows[x[rows, j] > e]
                        if h[left].sum() < least or h[right].sum() < least:
                            continue
                        gain = g[left].sum() ** 2 / (h[left].sum() + ridge) + g[right].sum() ** 2 / (h[right].sum() + ridge) - g[rows].sum() ** 2 / (h[rows].sum() + ridge)
                        if top is None or gain > top[0] + 1e-12:
                            top = gain, j, e
                    if top is not None and top[0] > best + 1e-12:
                        best, at = top[0], top
                split += [rows[x[rows, at[1]] <= at[2]], rows[x[rows, at[1]] > at[2]]] if at else [rows, rows[:0]]
            groups = split
        for rows in groups:
            f[rows] += -rate * g[rows].sum() / (h[rows].sum() + ridge)
    return f


def test_trees_against_trying_every_cut():
    rng = np.random.default_rng(5)
    x = np.round(rng.normal(size=(160, 4)), 1)
    y = (x[:, 0] + 0.5 * x[:, 1] * x[:, 2] + 0.3 * rng.normal(size=160) > 0).astype(float)
    assert boosting.fit(x, y, rounds=6).margin(x) == pytest.approx(brute_fit(x, y, 6), abs=1e-9)


def brute_features(text, lexicon):
    """The 18 features word by word."""
    import math

    t = toxicity
    raw = (text or "").encode()
    words = raw.lower().split()
    if not words:
        return [0.0] * 18
    kinds, weights, tricked = [], [], 0
    for w in words:
        word = w.decode()
        plain = t._plain(word)
        best = lambda x: max([lexicon.get(k, 0.0) for k in t._keys(x)] or [0.0])
        if plain in t.SECOND_PERSON:
            kinds.append("you")
            weights.append(0.0)
        elif best(plain):
            kinds.append("hit")
            weights.append(best(plain))
        elif not plain.isalpha() and t._undone(word) != plain and best(t._undone(word)):
            kinds.append("hit")
            weights.append(best(t._undone(word)))
            tricked += 1
        else:
            kinds.append("")
            weights.append(0.0)
    n, size, hits, you = len(words), len(raw), [i for i, k in enumerate(kinds) if k == "hit"], [i for i, k in enumerate(kinds) if k == "you"]
    near = sum(any(abs(i - j) <= t.NEAR for j in you) for i in hits)
    strong = sum(w >= 3 for w in weights)
    capitals = sum(65 <= c < 91 for c in raw)
    letters = max(1, capitals + sum(97 <= c < 123 or c >= 192 for c in raw))
    signs = sum(33 <= c < 48 or 58 <= c < 65 or 91 <= c < 97 or 123 <= c < 127 for c in raw)
    return [
        sum(weights) / n, math.log1p(len(hits)), max(weights), math.log1p(len({words[i] for i in hits})), len(hits) / n,
        math.log1p(strong), strong / n, len(you) / n, near / n, math.log1p(near), capitals / letters, raw.count(b"!") / size, raw.count(b"?") / size, signs / size,
        sum(48 <= c < 58 for c in raw) / size, (len(t._ODD.findall(raw)) + tricked) / n, math.log1p(n), size / n,
    ]


def test_toxic_features_word_by_word(spark, docs, sf):
    marks = spark.read.parquet(f"{sf}/labels.parquet").select("doc_id", F.col("toxic").alias("y"))
    sample = docs.join(marks, "doc_id").select("doc_id", "text", "y")
    lexicon = {"moron": 5.0, "stup~": 3.0} | toxicity.learn_lexicon(sample)
    of = toxicity.Features(lexicon)
    for r in docs.collect() + [type("R", (), {"text": t})() for t in ("You M0R0N!!", "st.upid? you", "", None)]:
        assert of(r.text).tolist() == pytest.approx(brute_features(r.text, lexicon))
