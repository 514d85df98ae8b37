"""The experiments on cost: pre and query time, scaling by rows, columns and format, profile sizes, reduced tuning.

    python bench/experiments.py [--sf DIR] [--out DIR] [NAME ...]

Prints one JSON line an experiment. Data made for scaling goes to ``--out`` (a temporary folder by default).
"""

from __future__ import annotations

import argparse
import json
import os
import sys
import tempfile
import time

sys.path.insert(0, os.path.dirname(os.path.dirname(os.path.abspath(__file__))))

from functools import reduce  # noqa: E402

from pyspark.sql import DataFrame, SparkSession  # noqa: E402
from pyspark.sql import functions as F  # noqa: E402

from lakejoin.operators import chain, costs, discover, matcher, metrics, pairs, profile, quality, scaling, size_lsh, training  # noqa: E402
from lakejoin.plans.context import context  # noqa: E402
from lakejoin.session import stored  # noqa: E402
from lakejoin.sources import derived, lake, store  # noqa: E402


def _fit(spark, points: list[tuple[float, float]]) -> dict:
    row = costs.linear_fit(spark.createDataFrame(points, "x double, y double")).first()
    return {"slope": row.slope, "intercept": row.intercept, "r2": row.r2}


def _base(spark, sf_dir):
    return lake.derived_dataset(spark, sf_dir, "shipments")


def _formats(df, out: str, name: str) -> dict[str, str]:
    paths = {f: f"{out}/{name}.{f}" for f in ("csv", "parquet")}
    df.write.mode("overwrite").csv(paths["csv"], header=True)
    df.write.mode("overwrite").parquet(paths["parquet"])
    return paths


def _profile_seconds(spark, paths: dict[str, str]) -> dict[str, float]:
    readers = {"csv": lambda p: spark.read.csv(p, header=True), "parquet": spark.read.parquet}
    return {f: costs.timed(f, lambda f=f: profile.profile_dataset(readers[f](paths[f]), "shipments"))["seconds"] for f in paths}


def rows_scaling(spark, sf_dir, out, steps=6):
    """Profiling time against rows: the base replicated 1..steps times, one column made distinct by replica."""
    base, found = _base(spark, sf_dir), {"csv": [], "parquet": []}
    for k in range(1, steps + 1):
        copies = base.crossJoin(F.broadcast(spark.range(k))).withColumn("item", F.concat("item", F.lit("-"), "id")).drop("id")
        for f, s in _profile_seconds(spark, _formats(copies, out, f"rows{k}")).items():
            found[f].append((float(k), s))
    return {f: {"seconds": [s for _, s in p], **_fit(spark, p)} for f, p in found.items()}


def columns_scaling(spark, sf_dir, out, steps=6):
    """Profiling time against columns: one more copied column each time."""
    base, found = _base(spark, sf_dir), {"csv": [], "parquet": []}
    for k in range(1, steps + 1):
        wide = base.select("*", *[F.col("item").alias(f"copy{i}") for i in range(k)])
        for f, s in _profile_seconds(spark, _formats(wide, out, f"columns{k}")).items():
            found[f].append((float(k), s))
    return {f: {"seconds": [s for _, s in p], **_fit(spark, p)} for f, p in found.items()}


def pre_time(spark, sf_dir, out):
    """Seconds before the first query: profiles, hash index, matcher."""
    melted = lambda: lake.derived_melted(spark, sf_dir)
    freq = context(spark, sf_dir).string_freq
    timed = [costs.timed("profiles", lambda: profile.profiles(profile.frequencies(melted()))), costs.timed("hash index", lambda: size_lsh.index(size_lsh.partitions(size_lsh.signatures(freq))))]
    began = time.time()
    matcher.fit(freq, "orders_1996")
    return {t["what"]: t["seconds"] for t in timed} | {"matcher": round(time.time() - began, 3)}


def query_time(spark, sf_dir, out):
    """Seconds of a discovery, by attribute and by dataset, and against the number of attributes compared."""
    c = context(spark, sf_dir)
    ref, rest = c.strings.where("dataset = 'orders_1996'"), c.strings.where("dataset <> 'orders_1996'")
    sig, model = c.signatures, c.model
    out_ = {
        "by attribute": costs.timed("", lambda: discover.by_attribute(ref, "buyer", rest, model))["seconds"],
        "by dataset": costs.timed("", lambda: discover.by_dataset(ref, rest, model))["seconds"],
        "hash by attribute": costs.timed("", lambda: size_lsh.query(sig, size_lsh.index(sig), "orders_1996", "buyer"))["seconds"],
    }
    points = []
    for k in (1, 2, 4, 8):
        more = rest.crossJoin(F.broadcast(spark.range(k))).withColumn("dataset", F.concat("dataset", F.lit("-"), "id")).drop("id")
        points.append((float(k), costs.timed("", lambda: discover.by_attribute(ref, "buyer", more, model))["seconds"]))  # noqa: B023
    return out_ | {"attributes": _fit(spark, points)}


def query_rows(spark, sf_dir, out):
    """Seconds of a discovery by attribute over lakes of the same attributes and ever more rows: profiles alone are read."""
    root, points, model = os.path.dirname(sf_dir.rstrip("/")), {}, None
    for sf in ("sf0.001", "sf0.01", "sf0.1"):
        c = context(spark, f"{root}/{sf}")
        ref, rest = c.strings.where("dataset = 'orders_1996'"), c.strings.where("dataset <> 'orders_1996'")
        model = model or chain.fit_chain(c.train)
        costs.timed("", lambda: discover.by_attribute(ref, "buyer", rest, model))  # noqa: B023  warm
        cells = c.freq.agg(F.sum("cnt")).first()[0]
        points[sf] = {"cells": cells, "attributes": c.strings.count(), "seconds": costs.timed("", lambda: discover.by_attribute(ref, "buyer", rest, model))["seconds"]}  # noqa: B023
    return points


def baseline_query_time(spark, sf_dir, out):
    """Seconds of the baselines' discoveries: hash by attribute and by dataset, matcher by dataset (models are built for each query)."""
    c = context(spark, sf_dir)
    sig = c.signatures
    indexed = size_lsh.index(sig)
    attrs = [r["attr"] for r in c.strings.where("dataset = 'orders_1996'").select("attr").collect()]
    by_dataset = lambda: reduce(DataFrame.unionByName, [size_lsh.query(sig, indexed, "orders_1996", a) for a in attrs])
    return {
        "hash by attribute": costs.timed("", lambda: size_lsh.query(sig, indexed, "orders_1996", "buyer"))["seconds"],
        "hash by dataset": costs.timed("", by_dataset)["seconds"],
        "matcher by dataset": costs.timed("", lambda: matcher.fit(c.string_freq, "orders_1996").match(c.string_freq, "orders_1996"))["seconds"],
    }


def ablations(spark, sf_dir, out):
    """Binary accuracy on the test lake, one thing changed at a time; small forests."""
    c = context(spark, sf_dir)

    def part(which, signed=False, minmax=False, use_ratio=True):
        own = c.strings.where(F.expr(derived.split_sql("dataset")) == which)
        scaled = scaling.apply_minmax(own, scaling.fit_minmax(own)) if minmax else scaling.apply_zscore(own, scaling.fit_zscore(own))
        truth = c.truth if use_ratio else quality.truth(c.string_freq, use_ratio=False)
        return stored(training.labelled_pairs(pairs.distances(pairs.candidates(scaled, scaled), signed), truth))

    def judged(test, model, **rules):
        found = discover.predict(test, model, **rules).join(test.select(*pairs.ID, "label"), list(pairs.ID))
        row = metrics.binary(metrics.confusion(found)).first()
        return {k: round(row[k], 4) for k in ("precision", "recall", "f1")}

    train, test = c.train, c.test
    base = chain.fit_chain(train)
    out_ = {"as it is": judged(test, base), "rules off": judged(test, base, rule1=False, rule2=False)}
    out_["chain off"] = judged(test, chain.fit_chain(train, chained=False))
    out_["out-of-fold chain"] = judged(test, chain.fit_chain(train, out_of_fold=True))
    out_["no balancing"] = judged(test, chain.fit_chain(train, balance=False))
    for name, how in {"signed distances": {"signed": True}, "min-max scaling": {"minmax": True}, "truth without the ratio": {"use_ratio": False}}.items():
        out_[name] = judged(part("test", **how), chain.fit_chain(part("train", **how)))
    return out_


def profile_size(spark, sf_dir, out):
    """Mean bytes of a stored profile."""
    store.write(context(spark, sf_dir).profiles, f"{out}/profiles")
    return {"mean_bytes": costs.profile_size(spark, f"{out}/profiles").agg(F.avg("bytes")).first()[0]}


def tuning(spark, sf_dir, out):
    """The search on a reduced grid; ``chain.GRID`` is the whole one."""
    return {str(k): v for k, v in chain.tune(context(spark, sf_dir).train, {"maxBins": (32, 40), "maxDepth": (5, 8), "numTrees": (8, 16)}, folds=3).items()}


EXPERIMENTS = {f.__name__: f for f in (rows_scaling, columns_scaling, pre_time, query_time, query_rows, baseline_query_time, profile_size, tuning, ablations)}


def main() -> None:
    args = argparse.ArgumentParser()
    args.add_argument("--sf", default=os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1"))
    args.add_argument("--out", default=None)
    args.add_argument("names", nargs="*", default=list(EXPERIMENTS))
    given = args.parse_args()
    cpus = os.environ.get("BENCH_CPUS", "8")
    spark = SparkSession.builder.master(f"local[{cpus}]").config("spark.driver.memory", "8g").config("spark.sql.shuffle.partitions", cpus).config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    out = given.out or tempfile.mkdtemp(prefix="lakejoin-bench-")
    for name in given.names:
        print(json.dumps({"experiment": name, "cpus": cpus, "sf": os.path.basename(given.sf.rstrip("/")), **EXPERIMENTS[name](spark, given.sf, out)}), flush=True)
    spark.stop()


if __name__ == "__main__":
    main()
