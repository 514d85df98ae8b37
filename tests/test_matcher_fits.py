import numpy as np
from pyspark.ml.classification import LogisticRegression, NaiveBayes
from pyspark.ml.feature import HashingTF
from pyspark.ml.linalg import Vectors
from pyspark.sql import functions as F

from lakejoin.operators import matcher

FREQ = "dataset string, attr string, value string, n bigint"
TEXTS = ["", "a", "ab", "Ärger im Haus", "漢字 and \U0001f600 more", "x" * 300, "12-34-56"]


def test_terms_fall_in_the_buckets_of_spark(spark):
    rows = matcher._featured(spark.createDataFrame([("d", "a", t) for t in TEXTS], "dataset string, attr string, value string"))
    found = rows
    for c in ("grams", "words"):
        found = HashingTF(numFeatures=matcher.BUCKETS, inputCol=c, outputCol=f"x_{c}").transform(found)
    got = found.select("n", "words", "x_grams", "x_words").collect()
    for (buckets, n), c in ((matcher._gram_buckets([r.n for r in got]), "x_grams"), (matcher._word_buckets([r.words for r in got]), "x_words")):
        for r, part in zip(got, np.split(buckets, np.cumsum(n)[:-1])):
            assert dict(zip(*(x.tolist() for x in np.unique(part, return_counts=True)))) == dict(zip(r[c].indices.tolist(), r[c].values))


def test_learners_are_those_of_spark(spark):
    rng = np.random.default_rng(4)
    for classes, family, penalty in ((2, "binomial", 0.02), (3, "multinomial", 0.01), (2, "multinomial", 0.01)):
        y = rng.integers(0, classes, 300)
        x = rng.poisson(1 + np.arange(4) * y[:, None], (300, 4)).astype(float)
        rows = spark.createDataFrame([(float(k), Vectors.dense(v)) for k, v in zip(y, x)], ["label", "features"]).coalesce(1)
        for model in (LogisticRegression(maxIter=200, tol=1e-12, regParam=0.01, family=family).fit(rows), NaiveBayes().fit(rows)):
            want = np.array([r.probability.toArray() for r in model.transform(rows).select("probability").collect()])
            if isinstance(model.getOrDefault("smoothing") if model.hasParam("smoothing") else None, float):
                theta, prior = np.array(model.theta.toArray()), np.array(model.pi.toArray())
                terms = np.repeat(np.tile(np.arange(4), 300), x.astype(int).ravel()), x.sum(1).astype(int)
                got, pi = matcher._bayes(terms, y, classes)
                seen = np.exp(theta)  # over four terms there, over all buckets here
                raw = np.array([x[y == k].sum(0) for k in range(classes)])
                assert np.allclose(seen, (raw + 1) / (raw.sum(1, keepdims=True) + 4)) and np.allclose(np.exp(got[:4].T), (raw + 1) / (raw.sum(1, keepdims=True) + matcher.BUCKETS)) and np.allclose(pi, prior)
            else:
                w, b = matcher._logistic(x, y, classes, penalty)
                assert np.allclose(matcher._softmax(x @ w + b), want, atol=1e-4)


def test_all_references_in_a_few_jobs(spark):
    """Fits and matches take a bounded number of jobs, however many references there are; and each is as if it were alone."""
    rows = [(f"r{k}", a, f"{a}{k} {i * 7 % 31}" if a == "w" else str(i * (k + 3)), 1) for k in range(6) for a in ("w", "k") for i in range(25)]
    freq = spark.createDataFrame(rows, FREQ).cache()
    sc = spark.sparkContext
    sc.setJobGroup("all references", "")
    every = matcher.fit_all(freq).match(freq).collect()
    jobs = len(sc.statusTracker().getJobIdsForGroup("all references"))
    sc.setLocalProperty("spark.jobGroup.id", None)
    assert jobs <= 25
    one = matcher.fit(freq, "r3").match(freq, "r3").collect()
    key = lambda r: (r.ref_dataset, r.ref_attr, r.cand_dataset, r.cand_attr, round(r.probability, 9))
    assert one and {key(r) for r in one} == {key(r) for r in every if r.ref_dataset == "r3"}
    assert {r.ref_dataset for r in every} == {f"r{k}" for k in range(6)} and all(r.ref_dataset != r.cand_dataset for r in every)
