"""Toxicity: boosted trees over dense features, with isotonic calibration.

Features of a text: density, count, variety and peak of lexicon hits (as written, and after undoing character
tricks), second-person words and hits near them, capitals, punctuation, exclamation and question marks, digits,
obfuscated words, length. The lexicon is learned from labelled rows: words, and word beginnings of 4 to 6 letters
(which catch inflected forms), with their log odds by document counts. One half of the labelled rows gives the
lexicon and the other half the trees, so that the trees see hits as they come in new texts. Calibration is fitted
on out-of-fold margins.

Null, empty and blank texts have the zero vector and get its score. Equal texts score alike.
"""

from __future__ import annotations

import re
import zlib
from collections import Counter

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import boosting
from .common import Cache, crc_mod, documents, labelled, labels, map_rows

#: Most labelled rows a fit uses; most lexicon entries.
TRAIN_ROWS, LEXICON = 20_000, 600
NEAR = 5
#: Second-person words of English, German, French and Spanish.
SECOND_PERSON = frozenset(
    "you your yours yourself yourselves ya u du dich dir dein deine deinen deinem deiner euch euer eure ihr ihnen sie tu toi te ton ta tes vous votre vos tú usted ustedes ti tus vosotros os vuestro vuestra".split()
)
_UNDO = str.maketrans("0134578@$!|+", "oieastbasiit")
_ODD = re.compile(rb"[A-Za-z][@$*0-9!|+_.-]+[A-Za-z]")
_ENDS = ".,;:!?\"'()[]{}<>*#%&-_|"


def _plain(word: str) -> str:
    return word.strip(_ENDS).casefold()


def _undone(word: str) -> str:
    return re.sub(r"[\W\d_]", "", word.casefold().translate(_UNDO))


def _keys(word: str) -> list[str]:
    return [word] + [f"{word[:k]}~" for k in (4, 5, 6) if len(word) > k] if len(word) > 2 else []


def tokens(text: str | None) -> set[str]:
    out: set[str] = set()
    for w in set((text or "").encode("utf-8", "replace").lower().split()):
        out.update(_keys(_plain(w.decode("utf-8"))))
    return out


class Features:
    """Vector of a text under a lexicon (entry to weight)."""

    SIZE = 18

    def __init__(self, lexicon: dict[str, float]):
        self.lexicon = lexicon
        self.cache = Cache(self._weigh, 300_000)

    def __reduce__(self):
        return Features, (self.lexicon,)

    def _weigh(self, raw: bytes) -> float:
        """Weight of the best entry; plus 100 if found only after undoing tricks; 1000 for a second-person word."""
        word = raw.decode("utf-8", "replace")
        plain = _plain(word)
        if plain in SECOND_PERSON:
            return 1000.0
        best = max((self.lexicon.get(k, 0.0) for k in _keys(plain)), default=0.0)
        if best == 0.0 and not plain.isalpha() and (undone := _undone(word)) != plain:
            best = max((self.lexicon.get(k, 0.0) for k in _keys(undone)), default=0.0)
            return best + 100.0 if best else 0.0
        return best

    def __call__(self, text: str | None) -> np.ndarray:
        raw = (text or "").encode("utf-8", "replace")
        words = raw.lower().split()
        out = np.zeros(self.SIZE)
        if not words:
            return out
        n, size = len(words), len(raw)
        w = np.array([self.cache[x] for x in words])
        second, hit = w >= 1000, (w > 0) & (w < 1000)
        tricked = hit & (w >= 100)
        weight = np.where(hit, w - 100.0 * tricked, 0.0)
        at, you = np.flatnonzero(hit), np.flatnonzero(second)
        near = 0
        if len(at) and len(you):
            k = np.searchsorted(you, at)
            gap = np.minimum(np.abs(at - you[np.minimum(k, len(you) - 1)]), np.abs(at - you[np.maximum(k - 1, 0)]))
            near = int((gap <= NEAR).sum())
        c = np.bincount(np.frombuffer(raw, np.uint8), minlength=256)
        letters = max(1, int(c[65:91].sum() + c[97:123].sum() + c[192:].sum()))
        strong = weight >= 3.0
        out[:] = (
            weight.sum() / n, np.log1p(hit.sum()), weight.max(), np.log1p(len({words[i] for i in at})), hit.sum() / n,
            np.log1p(strong.sum()), strong.sum() / n, second.sum() / n, near / n, np.log1p(near),
            c[65:91].sum() / letters, c[33] / size, c[63] / size, (c[33:48].sum() + c[58:65].sum() + c[91:97].sum() + c[123:127].sum()) / size,
            c[48:58].sum() / size, (len(_ODD.findall(raw)) + tricked.sum()) / n, np.log1p(n), size / n,
        )
        return out


class Model:
    def __init__(self, features: Features, trees: boosting.Trees, knots):
        self.features, self.trees, self.knots = features, trees, knots

    def scores(self, texts: list[str | None]) -> np.ndarray:
        x = np.stack([self.features(t) for t in texts]) if texts else np.zeros((0, Features.SIZE))
        return np.clip(boosting.calibrated(self.trees.margin(x), self.knots), 0.0, 1.0)


def learn_lexicon(sample: DataFrame, most: int = LEXICON) -> dict[str, float]:
    """Entries whose smoothed log odds are 2 or more, the ``most`` of greatest evidence (odds times toxic documents).

    Tasks count document frequencies for themselves before the shuffle.
    """
    import pyarrow as pa

    def count(batches):
        counts: tuple[Counter, Counter] = (Counter(), Counter())
        for batch in batches:
            for y, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                counts[y].update(tokens(text))
            if len(counts[0]) > 500_000:
                yield pa.RecordBatch.from_pydict(_rows(counts))
                counts = (Counter(), Counter())
        yield pa.RecordBatch.from_pydict(_rows(counts))

    def _rows(counts):
        keys = list(counts[0].keys() | counts[1].keys())
        return {"k": pa.array(keys, pa.string()), "n0": pa.array([counts[0][k] for k in keys], pa.int64()), "n1": pa.array([counts[1][k] for k in keys], pa.int64())}

    size = {r["y"]: r["count"] for r in sample.groupBy("y").count().collect()}
    if not size.get(1) or not size.get(0):
        return {}
    odds = F.log((F.col("n1") + 0.5) / (size[1] + 1.0)) - F.log((F.col("n0") + 0.5) / (size[0] + 1.0))
    least = 3 if size[1] < 400 else 5
    table = sample.select("y", "text").mapInArrow(count, "k string, n0 bigint, n1 bigint").groupBy("k").agg(F.sum("n0").alias("n0"), F.sum("n1").alias("n1"))
    top = table.where(F.col("n1") >= least).withColumn("w", odds).where("w >= 2").orderBy((F.col("w") * F.col("n1")).desc(), "k").limit(most)
    return {r["k"]: r["w"] for r in top.select("k", "w").collect()}


def fit_rows(features: Features, x: np.ndarray, y: np.ndarray, folds: int = 5) -> Model:
    margin, fold = np.zeros(len(y)), np.arange(len(y)) % folds
    for k in range(folds):
        use = fold != k
        margin[~use] = boosting.fit(x[use], y[use]).margin(x[~use]) if use.any() else 0.0
    knots = boosting.isotonic(margin, y) if len(y) else (np.zeros(0), np.zeros(0))
    return Model(features, boosting.fit(x, y), knots)


def fit(sample: DataFrame) -> Model:
    """Fit on (doc_id, text, y); only dense vectors of the bounded sample come to the driver."""
    half = F.pmod(F.xxhash64(F.coalesce("text", F.lit(""))), F.lit(2))
    features = Features(learn_lexicon(sample.where(half == 0)))

    def rows(part: dict) -> dict:
        return {"doc_id": part["doc_id"], "y": part["y"], "x": [features(t).tolist() for t in part["text"]]}

    got = map_rows(sample.where(half == 1).select("doc_id", "y", "text"), rows, "doc_id bigint, y int, x array<double>").toArrow().to_pydict()
    order = sorted(range(len(got["y"])), key=lambda i: (zlib.crc32(str(got["doc_id"][i]).encode()), got["doc_id"][i], got["x"][i]))
    x = np.array([got["x"][i] for i in order]).reshape(-1, Features.SIZE)
    return fit_rows(features, x, np.array([got["y"][i] for i in order], float))


def score(docs: DataFrame, model: Model) -> DataFrame:
    return map_rows(docs.select("doc_id", "text"), lambda part: {"doc_id": part["doc_id"], "score": model.scores(part["text"]).tolist()}, "doc_id bigint, score double")


def held_out():
    return crc_mod(F.col("doc_id"), 5) == 0


def op4_toxicity_boosted(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir)
    model = fit(labelled(docs, labels(spark, sf_dir), "toxic", ~held_out(), TRAIN_ROWS))
    return score(docs, model).select("doc_id", held_out().alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))
