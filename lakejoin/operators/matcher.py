"""Matcher baseline: a learned schema matcher that is trained on the reference table for every discovery task.

Classes are the attributes of the reference. Base learners: naive Bayes on character 3-grams, naive Bayes on words, and a
logistic model on shape; a logistic meta learner stacks their out-of-fold probabilities. A candidate column takes the
mean probability of all its values and is matched to its best attribute whenever that beats chance, which is what makes such
matchers eager. A reference with one string attribute has nothing to tell apart and gives no match.
A learner on the 3-grams of attribute names is left out.

All references are fitted in one job, each in a task of its own, on a bounded number of values; and all values of the lake are
looked at once for all references: only sums by column leave a task.
"""

from __future__ import annotations

import pickle
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import normalize, valuetypes
from ..session import ship, stored

#: Most distinct values of a reference attribute that a fit uses, taken by hash; buckets of hashed grams.
VALUES, BUCKETS, FOLDS = 1_000, 1 << 12, 5


def _featured(values: DataFrame) -> DataFrame:
    n = normalize.lowered(F.col("value"))
    rows = values.withColumn("n", n).withColumn("words", normalize.tokens(F.col("n")))
    padded = F.concat(F.lit("#"), F.col("n"), F.lit("#"))
    grams = F.transform(F.sequence(F.lit(1), F.greatest(F.length(padded) - 2, F.lit(1))), lambda i: F.substring(padded, i, F.lit(3)))
    kind = F.array_position(F.array(*map(F.lit, valuetypes.BROAD)), valuetypes.broad_type(F.col("n"))).cast("int")
    return rows.select("*", grams.alias("grams"), kind.alias("kind"))


@lru_cache(1 << 16)
def _bucket(term: bytes) -> int:
    """Murmur3 of 32 bits, seed 42, modulo ``BUCKETS``."""
    h, full = 42, 0xFFFFFFFF
    for i in range(0, len(term), 4):
        part = term[i : i + 4]
        k = int.from_bytes(part, "little") * 0xCC9E2D51 & full
        h ^= (k << 15 | k >> 17) * 0x1B873593 & full
        if len(part) == 4:
            h = ((h << 13 | h >> 19) & full) * 5 + 0xE6546B64 & full
    h ^= len(term)
    h = (h ^ h >> 16) * 0x85EBCA6B & full
    h = (h ^ h >> 13) * 0xC2B2AE35 & full
    h ^= h >> 16
    return (h if h < 1 << 31 else h - (1 << 32)) % BUCKETS


_NONE = 0x1FFFFF  # no code point


def _gram_buckets(texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """Buckets of all character 3-grams, text by text, and how many each text has."""
    codes = np.frombuffer("".join([f"#{t}#" if t else "##\0" for t in texts]).encode("utf-32-le", "replace"), np.uint32).astype(np.int64)
    sizes = np.array([max(3, len(t) + 2) for t in texts])
    ends = np.cumsum(sizes)
    codes[ends[[not t for t in texts]] - 1] = _NONE
    starts = np.ones(len(codes), bool)
    starts[ends - 1] = starts[ends - 2] = False
    at = np.flatnonzero(starts)
    keys, back = np.unique(codes[at] | codes[at + 1] << 21 | codes[at + 2] << 42, return_inverse=True)
    terms = ("".join(chr(c) for c in (k & _NONE, k >> 21 & _NONE, k >> 42) if c != _NONE) for k in keys.tolist())
    return np.array([_bucket(t.encode("utf-8", "replace")) for t in terms], np.int64)[back], sizes - 2


def _word_buckets(words: list[list[str]]) -> tuple[np.ndarray, np.ndarray]:
    return np.array([_bucket(w.encode("utf-8", "replace")) for ws in words for w in ws], np.int64), np.array([len(ws) for ws in words])


def _shape(texts: list[str], words: list[list[str]], kinds: list[int]) -> np.ndarray:
    out = np.zeros((len(texts), 2 + len(valuetypes.BROAD)))
    out[:, 0], out[:, 1] = np.log1p([len(t) for t in texts]), np.log1p([len(w) for w in words])
    out[np.arange(len(texts)), np.array(kinds, int) + 1] = 1
    return out


def _softmax(z: np.ndarray) -> np.ndarray:
    e = np.exp(z - z.max(1, keepdims=True))
    return e / e.sum(1, keepdims=True)


def _summed(terms: tuple[np.ndarray, np.ndarray], weights: np.ndarray, most: int = 1 << 16) -> np.ndarray:
    """Sums of the weights of each row's terms; about ``most`` terms are held at once."""
    buckets, n = terms
    out, ends, full = np.zeros((len(n), weights.shape[1])), np.cumsum(n), np.flatnonzero(n)
    if len(full):
        cuts = np.flatnonzero(np.diff(ends[full] // most)) + 1
        for rows in np.split(full, cuts):
            first = ends[rows] - n[rows]
            out[rows] = np.add.reduceat(weights[buckets[first[0] : ends[rows[-1]]]], first - first[0])
    return out


def _bayes(terms, y: np.ndarray, classes: int) -> tuple[np.ndarray, np.ndarray]:
    """Multinomial naive Bayes with one added: log-likelihoods by bucket and class, log-priors."""
    buckets, n = terms
    seen = np.bincount(buckets * classes + np.repeat(y, n), minlength=BUCKETS * classes).reshape(BUCKETS, classes) + 1.0
    return np.log(seen / seen.sum(0)), np.log((np.bincount(y, minlength=classes) + 1.0) / (len(y) + classes))


def _logistic(x: np.ndarray, y: np.ndarray, classes: int, penalty: float = 0.01) -> tuple[np.ndarray, np.ndarray]:
    """Weights and offsets of a logistic model; the penalty is on the weights of columns scaled to unit deviation. Newton steps."""
    sd = x.std(0, ddof=1) if len(x) > 1 else np.zeros(x.shape[1])
    scale = np.where(sd > 0, 1 / np.where(sd > 0, sd, 1), 0)
    mean = x.mean(0)
    z = np.hstack([(x - mean) * scale, np.ones((len(x), 1))])
    d, w, hit = z.shape[1], np.zeros((z.shape[1], classes)), np.eye(classes)[y]
    ridge = np.full((d, classes), penalty)
    ridge[-1] = 0

    def loss(w):
        m = z @ w
        top = m.max(1)
        return np.mean(top + np.log(np.exp(m - top[:, None]).sum(1)) - (m * hit).sum(1)) + 0.5 * (ridge * w * w).sum()

    now = loss(w)
    for _ in range(100):
        p = _softmax(z @ w)
        slope = z.T @ (p - hit) / len(z) + ridge * w
        curve = np.zeros((d, classes, d, classes))
        for i in range(classes):
            for j in range(classes):
                curve[:, i, :, j] = (z * (p[:, i] * ((i == j) - p[:, j]))[:, None]).T @ z / len(z)
        step = np.linalg.lstsq(curve.reshape(d * classes, -1) + np.diag(ridge.ravel() + 1e-10), slope.ravel(), rcond=None)[0].reshape(d, classes)
        size = 1.0
        while size > 1e-6 and loss(w - size * step) > now:
            size /= 2
        before, w = now, w - size * step if size > 1e-6 else w
        now = loss(w)
        if before - now < 1e-13:
            break
    weights = w[:-1] * scale[:, None]
    return weights, w[-1] - mean @ weights


def _fitted(terms, shape: np.ndarray, y: np.ndarray, classes: int) -> tuple:
    # two classes: one vector of weights bears the penalty, which is half of what two opposite ones would
    return *(_bayes(t, y, classes) for t in terms), _logistic(shape, y, classes, 0.02 if classes == 2 else 0.01)


def _base(model: tuple, terms, shape: np.ndarray) -> np.ndarray:
    """Probabilities of the three base learners, beside each other."""
    (g, pg), (w, pw), (s, ps) = model
    return np.hstack([_softmax(_summed(terms[0], g) + pg), _softmax(_summed(terms[1], w) + pw), _softmax(shape @ s + ps)])


def _picked(terms, rows: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    buckets, n = terms
    return buckets[np.repeat(rows, n)], n[rows]


def _stacked(attrs: list[str], texts, words, kinds, of: list[str], place: list[int]) -> bytes:
    """The pickled model of one reference from its values, their attributes and their places among those."""
    y, fold, classes = np.searchsorted(attrs, of), np.array(place) % FOLDS, len(attrs)
    terms, shape = (_gram_buckets(texts), _word_buckets(words)), _shape(texts, words, kinds)
    x, held = np.zeros((len(y), 3 * classes)), np.zeros(len(y), bool)
    for k in range(FOLDS):
        rest = fold == k
        if rest.any() and len(np.unique(y[~rest])) == classes:
            part = _fitted([_picked(t, ~rest) for t in terms], shape[~rest], y[~rest], classes)
            x[rest] = _base(part, [_picked(t, rest) for t in terms], shape[rest])
            held |= rest
    base = _fitted(terms, shape, y, classes)
    if not held.any():
        x, held = _base(base, terms, shape), ~held
    return pickle.dumps((base, _logistic(x[held], y[held], classes)))


def _scored(models: list[tuple], texts, words, kinds) -> np.ndarray:
    """Probabilities of the classes of all references, beside each other; terms are summed for all at once."""
    grams, tokens, shape, out = _gram_buckets(texts), _word_buckets(words), _shape(texts, words, kinds), []
    ends = np.cumsum([len(base[0][1]) for base, _ in models])[:-1]
    by_gram, by_word = (np.split(_summed(t, np.hstack([base[k][0] for base, _ in models])), ends, axis=1) for k, t in enumerate((grams, tokens)))
    for (base, (weights, offset)), g, w in zip(models, by_gram, by_word):
        x = np.hstack([_softmax(g + base[0][1]), _softmax(w + base[1][1]), _softmax(shape @ base[2][0] + base[2][1])])
        out.append(_softmax(x @ weights + offset))
    return np.hstack(out)


class Matcher:
    """Models of references: their names, attributes and pickled weights."""

    def __init__(self, models: list[tuple[str, list[str], bytes]]):
        self.models = models

    def match(self, freq: DataFrame, dataset: str | None = None) -> DataFrame:
        """(ref_dataset, ref_attr, cand_dataset, cand_attr, probability) of proposed matches over the lake's columns, for one
        reference or all of them."""
        models = [m for m in self.models if dataset is None or m[0] == dataset]
        spark = freq.sparkSession
        ship(spark)
        sent = spark.sparkContext.broadcast([m[2] for m in models])

        def sums(batches):
            loaded, found = [pickle.loads(m) for m in sent.value], {}

            def rows():
                yield pa.RecordBatch.from_pylist([{"dataset": d, "attr": a, "n": n, "sums": x.tolist()} for (d, a), (n, x) in found.items()], schema=schema)

            for batch in batches:
                for at in range(0, batch.num_rows, 1_000):
                    part = batch.slice(at, 1_000).to_pydict()
                    p, whose = _scored(loaded, part["n"], part["words"], part["kind"]), {}
                    for i, key in enumerate(zip(part["dataset"], part["attr"])):
                        whose.setdefault(key, []).append(i)
                    for key, of in whose.items():
                        n, x = found.get(key, (0, 0.0))
                        found[key] = n + len(of), x + p[of].sum(0)
                if len(found) > 4_096:
                    yield from rows()
                    found.clear()
            yield from rows()

        schema = pa.schema([("dataset", pa.string()), ("attr", pa.string()), ("n", pa.int64()), ("sums", pa.list_(pa.float64()))])
        values = _featured(freq.where((F.lit(dataset).isNull() | (F.col("dataset") != F.lit(dataset))) & F.col("value").isNotNull()).select("dataset", "attr", "value"))
        parts = values.select("dataset", "attr", "n", "words", "kind").mapInArrow(sums, "dataset string, attr string, n bigint, sums array<double>")
        means = parts.select("dataset", "attr", "n", F.posexplode("sums").alias("place", "p")).groupBy("dataset", "attr", "place").agg((F.sum("p") / F.sum("n")).alias("p"))
        classes = [(i, ref, attr, len(attrs)) for i, (ref, attr, attrs) in enumerate((m[0], attr, m[1]) for m in models for attr in m[1])]
        named = means.join(F.broadcast(spark.createDataFrame(classes, "place int, ref_dataset string, ref_attr string, classes int")), "place").where("dataset <> ref_dataset")
        best = named.groupBy("ref_dataset", "dataset", "attr").agg(F.max(F.struct("p", -F.col("place"), "ref_attr", "classes")).alias("best"))
        return best.where("best.p > 1D / best.classes").select("ref_dataset", F.col("best.ref_attr").alias("ref_attr"), F.col("dataset").alias("cand_dataset"), F.col("attr").alias("cand_attr"), F.col("best.p").alias("probability"))


def references(freq: DataFrame) -> list[str]:
    """Datasets that have something to tell apart: two attributes or more."""
    found = freq.where(F.col("value").isNotNull()).groupBy("dataset").agg(F.count_distinct("attr").alias("n")).where("n > 1")
    return sorted(r["dataset"] for r in found.select("dataset").collect())


def fit_all(freq: DataFrame) -> Matcher | None:
    """Trained on the distinct values of the attributes of each reference; None if there is none."""
    ship(freq.sparkSession)
    order = Window.partitionBy("dataset", "attr").orderBy(F.md5("value"))
    values = freq.where(F.col("value").isNotNull()).select("dataset", "attr", "value").withColumn("i", F.row_number().over(order)).where(F.col("i") <= VALUES)
    several = values.groupBy("dataset").agg(F.count_distinct("attr").alias("n")).where("n > 1").select("dataset")
    rows = stored(_featured(values.join(several, "dataset", "left_semi")).select("dataset", "attr", "n", "words", "kind", "i"))
    schema = pa.schema([("dataset", pa.string()), ("attrs", pa.list_(pa.string())), ("model", pa.binary())])

    def one(part: pa.Table) -> pa.Table:
        v = part.sort_by([("attr", "ascending"), ("i", "ascending")]).to_pydict()
        attrs = sorted(set(v["attr"]))
        return pa.Table.from_pylist([{"dataset": v["dataset"][0], "attrs": attrs, "model": _stacked(attrs, v["n"], v["words"], v["kind"], v["attr"], v["i"])}], schema=schema)

    found = rows.groupBy("dataset").applyInArrow(one, "dataset string, attrs array<string>, model binary").collect()  # a row a reference
    return Matcher(sorted((r["dataset"], list(r["attrs"]), bytes(r["model"])) for r in found)) if found else None


def fit(freq: DataFrame, dataset: str) -> Matcher | None:
    """Trained on one reference alone; None if it has fewer than two attributes."""
    return fit_all(freq.where(F.col("dataset") == dataset))
