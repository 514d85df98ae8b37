"""Hash baseline: MinHash containment search over attributes partitioned by size.

Signatures hold ``M`` minima of permuted value hashes. Attributes are dealt to partitions of equal count by
cardinality; within one, a containment threshold becomes a Jaccard threshold through the partition's largest size and
the query's, and the banding (b bands of r minima) with the least expected error for it is used. A hit in any band of
any partition makes a candidate. Signatures are a few KB an attribute; only hashes are shuffled.
"""

from __future__ import annotations

import random
from functools import lru_cache

import numpy as np
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..session import stored

M, PARTS, PRIME = 128, 32, (1 << 31) - 1
WIDTHS = (1, 2, 4, 8, 16, 32)
_random = random.Random(20_240_501)
#: Multipliers and offsets of the permutations.
PERMUTATIONS = tuple((_random.randrange(1, PRIME), _random.randrange(0, PRIME)) for _ in range(M))


def value_hash(v: Column) -> Column:
    return F.conv(F.substring(F.md5(v), 1, 15), 16, 10).cast("bigint") % PRIME


def signatures(freq: DataFrame, m: int = M, scheme: str = "classic") -> DataFrame:
    """(id, dataset, attr, card, sig array<bigint>); id is the struct of the two names. ``one`` permutation: a minimum for each of m residues, empty ones filled
    from the next full one."""
    hashed = freq.where(F.col("value").isNotNull()).select("dataset", "attr", value_hash(F.col("value")).alias("h"))
    card = F.count(F.lit(1)).alias("card")
    if scheme == "classic":
        minima = F.array(*[F.min((F.lit(a) * F.col("h") + F.lit(b)) % PRIME) for a, b in PERMUTATIONS[:m]])
        sig = hashed.groupBy("dataset", "attr").agg(card, minima.alias("sig"))
    else:
        low = hashed.groupBy("dataset", "attr", (F.col("h") % m).alias("slot")).agg(F.min("h").alias("lo"), F.count(F.lit(1)).alias("n"))
        slots = low.groupBy("dataset", "attr").agg(F.sum("n").alias("card"), F.map_from_entries(F.collect_list(F.struct("slot", "lo"))).alias("by"))  # m entries at most
        keys = F.array_sort(F.map_keys("by"))
        at = lambda i: F.coalesce(F.get(F.filter(keys, lambda k: k >= i), F.lit(0)), F.get(keys, F.lit(0)))
        sig = slots.withColumn("sig", F.transform(F.sequence(F.lit(0), F.lit(m - 1)), lambda i: F.element_at("by", at(i)) * m + F.pmod(at(i) - i, F.lit(m)))).drop("by")
    return sig.withColumn("id", F.struct("dataset", "attr"))


def jaccard_estimate(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: F.when(x == y, 1.0).otherwise(0.0)), F.lit(0.0), lambda s, x: s + x) / F.size(a)


def partitions(sig: DataFrame, parts: int = PARTS) -> DataFrame:
    """Adds ``part`` (by cardinality, then names; parts differ by one attribute at most) and ``upper``, the largest cardinality of
    the part. Names and sizes alone are ranked, range by range; the signatures stay where they are."""
    keys = sig.select("dataset", "attr", "card")
    ranged = stored(keys.repartitionByRange("card", "dataset", "attr").withColumn("_range", F.spark_partition_id()))
    sizes = ranged.groupBy("_range").agg(F.count(F.lit(1)).alias("_n"))  # one row a partition
    starts = sizes.select("_range", (F.sum("_n").over(Window.orderBy("_range")) - F.col("_n")).alias("_start"), F.sum("_n").over(Window.partitionBy()).alias("_all"))
    place = F.row_number().over(Window.partitionBy("_range").orderBy("card", "dataset", "attr")) - 1
    ranked = ranged.withColumn("_place", place).join(F.broadcast(starts), "_range").withColumn("_place", F.col("_place") + F.col("_start"))
    # the first parts hold one more where the count doesn't divide
    least, more = F.floor(F.col("_all") / parts), F.col("_all") % parts
    long = more * (least + 1)
    part = F.when(F.col("_place") < long, F.floor(F.col("_place") / (least + 1))).otherwise(more + F.floor((F.col("_place") - long) / F.greatest(least, F.lit(1)))) + 1
    dealt = ranked.select("dataset", "attr", "card", part.cast("int").alias("part"))
    uppers = dealt.groupBy("part").agg(F.max("card").alias("upper"))  # PARTS rows
    return sig.join(dealt.join(F.broadcast(uppers), "part").drop("card"), ["dataset", "attr"])


def jaccard_threshold(t: float, upper: float, query: float) -> float:
    """Jaccard that containment ``t`` of a query of that size implies at least, against sets up to ``upper``."""
    return t / (upper / query + 1 - t)


@lru_cache(maxsize=100_000)
def banding(s: float, m: int = M) -> tuple[int, int]:
    """(b, r) with b * r <= m of least false positives below s plus false negatives above it; trapezoid rule."""
    best, grid = (float("inf"), 1, 1), np.linspace(0.0, 1.0, 201)
    low, high = grid * s, s + grid * (1.0 - s)
    for r in WIDTHS:
        for b in sorted({m // r, *(x for x in (1, 2, 4, 8, 16, 32, 64, 128) if x * r <= m)}):
            miss = lambda x: (1 - x**r) ** b  # noqa: B023, E731
            error = s - np.trapezoid(miss(low), low) + np.trapezoid(miss(high), high)
            best = min(best, (float(error), b, r))
    return best[1], best[2]


def banding_steps(m: int = M, grid: int = 400) -> list[tuple[float, int, int]]:
    """(s, b, r): the banding from each threshold s on, in ascending order; edges are bisected between grid points."""
    out, left = [(0.0, *banding(0.0, m))], 0.0
    for i in range(1, grid + 1):
        right = i / grid
        while banding(right, m) != out[-1][1:]:
            lo, hi = left, right
            while hi - lo > 1e-13:
                mid = (lo + hi) / 2
                lo, hi = (mid, hi) if banding(mid, m) == out[-1][1:] else (lo, mid)
            out.append((hi, *banding(hi, m)))
            left = hi
        left = right
    return out


def _bands(df: DataFrame, b: int, r: int, width: Column) -> DataFrame:
    keys = F.transform(F.sequence(F.lit(0), F.lit(b - 1)), lambda i: F.struct(i.alias("band"), F.md5(F.array_join(F.transform(F.slice("sig", i * r + 1, r), lambda x: x.cast("string")), "-")).alias("key")))
    return df.select("*", width.alias("r"), F.explode(keys).alias("x")).select("*", "x.band", "x.key").drop("x")


def index(sig: DataFrame, m: int = M) -> DataFrame:
    """(part, r, band, key, id): every band of every width, for ``bucketBy(part, r, band, key)`` or a join as it is."""
    out = None
    for r in WIDTHS:
        rows = _bands(sig, m // r, r, F.lit(r)).select("part", "r", "band", "key", "id", "dataset", "attr")
        out = rows if out is None else out.unionByName(rows)
    return out


def query(sig: DataFrame, indexed: DataFrame, dataset: str, attr: str, t: float = 0.5, m: int = M, verify: bool = False) -> DataFrame:
    """(cand_dataset, cand_attr): candidates of other datasets. Partition sizes (``PARTS`` numbers) set the banding."""
    mine = sig.where((F.col("dataset") == dataset) & (F.col("attr") == attr))
    row = mine.select("card").first()
    uppers = sig.groupBy("part").agg(F.first("upper").alias("upper")).collect()
    if row is None:
        return indexed.select(F.col("dataset").alias("cand_dataset"), F.col("attr").alias("cand_attr")).limit(0)
    chosen = [(u["part"], *banding(min(1.0, jaccard_threshold(t, u["upper"], row["card"])), m)) for u in uppers]
    widths = sorted({r for _, _, r in chosen})
    probe = None
    for r in widths:
        rows = _bands(mine.select("sig"), m // r, r, F.lit(r)).select("r", "band", "key")
        probe = rows if probe is None else probe.unionByName(rows)
    plan = sig.sparkSession.createDataFrame(chosen, "part int, b int, r int")
    wanted = F.broadcast(probe.join(F.broadcast(plan), "r").where("band < b"))  # at most PARTS times m rows
    hits = indexed.where(F.col("dataset") != dataset).join(wanted, ["part", "r", "band", "key"]).select("id", "dataset", "attr").distinct()
    if verify:
        other = sig.select("id", F.col("sig").alias("other"), F.col("card").alias("other_card"))
        j = jaccard_estimate(F.col("sig"), F.col("other"))
        both = hits.join(other, "id").crossJoin(F.broadcast(mine.select("sig", "card")))
        hits = both.withColumn("j", j).where(F.col("j") / (1 + F.col("j")) * (F.col("card") + F.col("other_card")) / F.col("card") >= t)
    return hits.select(F.col("dataset").alias("cand_dataset"), F.col("attr").alias("cand_attr"))


def all_hits(sig: DataFrame, t: float, m: int = M) -> DataFrame:
    """(ref_dataset, ref_attr, cand_dataset, cand_attr): every attribute as a query, banding by part and query size class.

    Query sizes are rounded up to powers of two for the choice of bands, so the plan has a bounded number of settings.
    """
    sizes = sig.select(F.ceil(F.log2(F.greatest("card", F.lit(1)))).cast("int").alias("e")).distinct().collect()
    uppers = sig.groupBy("part").agg(F.first("upper").alias("upper")).collect()
    rows = [(s["e"], u["part"], *banding(min(1.0, jaccard_threshold(t, u["upper"], float(2 ** s["e"]))), m)) for s in sizes for u in uppers]
    plan = sig.sparkSession.createDataFrame(rows, "e int, part int, b int, r int")
    probe = None
    for r in sorted({x[3] for x in rows}):
        some = _bands(sig.withColumn("e", F.ceil(F.log2(F.greatest("card", F.lit(1)))).cast("int")).select("dataset", "attr", "e", "sig"), m // r, r, F.lit(r)).select("dataset", "attr", "e", "r", "band", "key")
        probe = some if probe is None else probe.unionByName(some)
    probe = probe.join(plan, ["e", "r"]).where("band < b").select("part", "r", "band", "key", F.col("dataset").alias("ref_dataset"), F.col("attr").alias("ref_attr"))
    found = index(sig, m).join(probe, ["part", "r", "band", "key"]).where(F.col("dataset") != F.col("ref_dataset"))
    return found.select("ref_dataset", "ref_attr", F.col("dataset").alias("cand_dataset"), F.col("attr").alias("cand_attr")).distinct()


def classify(sig: DataFrame, thresholds: tuple[float, ...] = (0.75, 0.5, 0.25, 0.1)) -> DataFrame:
    """Five classes from four searches: the class of the highest threshold that hits; pairs without a hit are absent (0)."""
    out = None
    for cls, t in zip((4, 3, 2, 1), thresholds):
        hits = all_hits(sig, t).withColumn("pred_class", F.lit(cls))
        out = hits if out is None else out.unionByName(hits)
    return out.groupBy("ref_dataset", "ref_attr", "cand_dataset", "cand_attr").agg(F.max("pred_class").alias("pred_class"))
