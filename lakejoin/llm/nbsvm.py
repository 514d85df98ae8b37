"""Quality classifier: a linear hinge-loss model over n-gram indicators scaled by class log-count ratios.

Every text becomes the set of its hashed indicators: word 1- and 2-grams, 1- to 3-grams of word *shapes*
(letter case, digits and symbols, runs collapsed), of "same word as before" flags, and the density level of each
shape, of repeated words and of repeated lines. An indicator's value is the log ratio of its smoothed shares in
the two classes; rows are scaled to unit length; the separating plane is found by dual coordinate descent, and a
logistic curve fitted on rows the plane hasn't seen turns margins into scores.

Empty, blank and null texts have no indicator and get the score of the intercept. Ties and repeated rows score
alike, since the score depends on the text alone.
"""

from __future__ import annotations

import re
import zlib

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import Cache, crc_mod, documents, filtered, labelled, labels, map_rows, released

BUCKETS = 1 << 18
#: Most labelled rows a fit uses.
TRAIN_ROWS = 8_000
_RUNS = re.compile(r"(.)\1+")
_P, _Q, _R = np.uint64(0x9E3779B97F4A7C15), np.uint64(0xC2B2AE3D27D4EB4F), np.uint64(0x165667B19E3779F9)


def _shape(word: str) -> str:
    return _RUNS.sub(r"\1", "".join("X" if c.isupper() else "x" if c.isalpha() else "9" if c.isdigit() else c for c in word[:64]))


def _codes(word: bytes) -> int:
    """Hash of the lower-cased word and, in the low 16 bits, of its shape."""
    text = word.decode("utf-8", "replace")
    return (zlib.crc32(text.lower().encode()) << 16) | (zlib.crc32(_shape(text).encode()) & 0xFFFF)


_cache = Cache(_codes)


def _mix(x: np.ndarray, kind: int) -> np.ndarray:
    x = (x + np.uint64(kind)) * _P
    x ^= x >> np.uint64(29)
    x *= _Q
    return ((x ^ (x >> np.uint64(32))) & np.uint64(BUCKETS - 1)).astype(np.int32)


def _levels(share: np.ndarray) -> np.ndarray:
    """0 for under 1 in 128, then one level a doubling."""
    return np.floor(np.log2(np.maximum(share, 1 / 256) * 256)).astype(np.uint64)


def indicators(text: str | None) -> np.ndarray:
    """Sorted distinct indicator numbers of a text (int32)."""
    raw = (text or "").encode("utf-8", "replace")
    words = raw.split()
    if not words:
        return np.zeros(0, np.int32)
    code = np.array([_cache[w] for w in words], dtype=np.uint64)
    word, shape = code >> np.uint64(16), code & np.uint64(0xFFFF)
    same = np.zeros(len(words), np.uint64)
    same[1:] = code[1:] == code[:-1]
    out = [_mix(word, 1), _mix(word[:-1] * _R + word[1:], 2)]
    kinds, counts = np.unique(shape, return_counts=True)
    out += [_mix(kinds, 3), _mix(kinds * _R + _levels(counts / len(words)), 4)]
    out += [_mix(np.unique(shape[:-1] * _R + shape[1:]), 5), _mix(np.unique((shape[:-2] * _R + shape[1:-1]) * _R + shape[2:]), 6)]
    out.append(_mix(np.unique(same[:-2] * np.uint64(4) + same[1:-1] * np.uint64(2) + same[2:]), 7))
    distinct = len(set(words)) / len(words)
    lines = [x for x in raw.split(b"\n") if x.strip()]
    again = 1 - len(set(lines)) / max(1, len(lines))
    out.append(_mix(_levels(np.array([same.mean(), distinct, again])) + np.array([0, 100, 200], np.uint64), 8))
    return np.unique(np.concatenate(out))


def dual_coordinate_descent(rows: list[np.ndarray], values: list[np.ndarray], y: np.ndarray, n: int, c: np.ndarray, epochs: int = 12, seed: int = 7) -> np.ndarray:
    """Weights of the L2-regularised hinge loss; ``values[i]`` at columns ``rows[i]``; ``c`` bounds each row's dual."""
    w, alpha = np.zeros(n), np.zeros(len(rows))
    norm = np.array([float(v @ v) for v in values])
    order, rng = np.arange(len(rows)), np.random.default_rng(seed)
    for _ in range(epochs):
        rng.shuffle(order)
        moved = 0.0
        for i in order:
            if norm[i] == 0:
                continue
            at, v = rows[i], values[i]
            gradient = y[i] * float(w[at] @ v) - 1
            new = min(max(alpha[i] - gradient / norm[i], 0.0), c[i])
            step = new - alpha[i]
            if step:
                w[at] += step * y[i] * v
                alpha[i] = new
                moved = max(moved, abs(step))
        if moved < 1e-4:
            break
    return w


def _logistic(margin: np.ndarray, y: np.ndarray) -> tuple[float, float]:
    """Slope and intercept by Newton steps, with smoothed targets so that separable data stay finite."""
    pos, neg = max(1, int(y.sum())), max(1, int((1 - y).sum()))
    target = np.where(y > 0, (pos + 1) / (pos + 2), 1 / (neg + 2))
    a, b = 2.0, 0.0
    for _ in range(50):
        p = 1 / (1 + np.exp(-np.clip(a * margin + b, -30, 30)))
        d, s = p - target, np.maximum(p * (1 - p), 1e-6)
        g = np.array([d @ margin + 1e-3 * a, d.sum()])
        h = np.array([[(s * margin) @ margin + 1e-3, s @ margin], [s @ margin, s.sum() + 1e-9]])
        step = np.linalg.solve(h, g)
        a, b = a - step[0], b - step[1]
        if abs(step).max() < 1e-8:
            break
    return max(a, 1e-3), b


class Model:
    """Ratios, plane and curve; two float32 tables of ``BUCKETS`` entries, whatever the corpus."""

    def __init__(self, ratio: np.ndarray, plane: np.ndarray, bias: float, slope: float, offset: float):
        self.ratio, self.plane, self.bias, self.slope, self.offset = ratio.astype(np.float32), plane.astype(np.float32), bias, slope, offset

    def margin(self, ids: np.ndarray) -> float:
        if not len(ids):
            return self.bias
        r = self.ratio[ids]
        return float(r @ self.plane[ids]) / max(float(np.sqrt(r @ r)), 1e-9) + self.bias

    def score(self, ids: np.ndarray) -> float:
        return float(1 / (1 + np.exp(-np.clip(self.slope * self.margin(ids) + self.offset, -30, 30))))


def fit_rows(sets: list[np.ndarray], y: np.ndarray, c: float = 1.0) -> Model:
    """Fit on rows in the given order: every fifth is kept for the curve."""
    y = np.asarray(y, int)
    if len(y) == 0 or y.min() == y.max():
        p = (y.sum() + 1) / (len(y) + 2)
        return Model(np.zeros(BUCKETS), np.zeros(BUCKETS), 0.0, 1.0, float(np.log(p / (1 - p))))
    held = np.arange(len(y)) % 5 == 4 if len(y) >= 50 else np.zeros(len(y), bool)
    use = np.flatnonzero(~held)
    counts = [np.ones(BUCKETS), np.ones(BUCKETS)]
    for i in use:
        counts[y[i]][sets[i]] += 1
    ratio = np.log(counts[1] / counts[1].sum()) - np.log(counts[0] / counts[0].sum())
    rows = [np.append(sets[i], BUCKETS) for i in use]
    values = []
    for i in use:
        r = ratio[sets[i]]
        values.append(np.append(r / max(np.sqrt(r @ r), 1e-9), 1.0))
    sign = np.where(y[use] > 0, 1.0, -1.0)
    share = np.array([(y[use] == k).mean() for k in (0, 1)])
    w = dual_coordinate_descent(rows, values, sign, BUCKETS + 1, np.array([c * 0.5 / max(share[k], 1e-6) for k in y[use]]))
    model = Model(ratio, w[:BUCKETS], float(w[BUCKETS]), 1.0, 0.0)
    judge = np.flatnonzero(held) if held.any() and y[held].min() != y[held].max() else use
    model.slope, model.offset = _logistic(np.array([model.margin(sets[i]) for i in judge]), y[judge])
    return model


def fit(sample: DataFrame) -> Model:
    """Fit on (doc_id, text, y): indicator sets are made on the executors; the bounded sets come to the driver, which gives their
    memory back before it goes on."""
    model = fit_rows(*_gathered(sample))
    released()
    return model


def _gathered(sample: DataFrame) -> tuple[list[np.ndarray], np.ndarray]:
    """Indicator sets and labels in the order of the fit."""

    def rows(part: dict) -> dict:
        return {"doc_id": part["doc_id"], "y": part["y"], "ids": [indicators(x).tobytes() for x in part["text"]]}

    got = map_rows(sample.select("doc_id", "y", "text"), rows, "doc_id bigint, y int, ids binary").toArrow().to_pydict()
    order = sorted(range(len(got["y"])), key=lambda i: (zlib.crc32(str(got["doc_id"][i]).encode()), got["doc_id"][i], got["ids"][i]))
    return [np.frombuffer(got["ids"][i], np.int32) for i in order], np.array([got["y"][i] for i in order])


def score(docs: DataFrame, model: Model) -> DataFrame:
    """(doc_id, score) of every whole text."""
    return map_rows(docs.select("doc_id", "text"), lambda part: {"doc_id": part["doc_id"], "score": [model.score(indicators(x)) for x in part["text"]]}, "doc_id bigint, score double")


def held_out():
    return crc_mod(F.col("doc_id"), 3) == 1


def train(docs: DataFrame, marks: DataFrame, limit: int = TRAIN_ROWS) -> Model:
    return fit(labelled(docs, marks, "quality", ~held_out(), limit))


def op10_nbsvm_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir)
    scored = score(docs, train(docs, labels(spark, sf_dir)))
    return scored.select("doc_id", held_out().alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))


def stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keep the documents predicted good; all columns pass through, whatever they are called."""
    model = train(docs, labels(spark, sf_dir))
    return filtered(docs, "text", lambda texts: [model.score(indicators(x)) >= 0.5 for x in texts])
