"""Near-duplicate links of the pipeline: documents whose sets of five-word shingles have a Jaccard similarity of 0.8.

The search loses no pair. Shingles have one fixed order; two sets of similarity 0.8 must share one of the first
``n - ceil(0.8 n) + 1`` of each, so only these meet. Common shingles come last in the order (each is counted by itself in a
sample of the documents; any order is right, a good one makes small groups), so a line that many documents hold is no
meeting place unless it is most of them.

A pair also has to pass the bound that sizes and places in the order set, and is then verified on the whole sets.
Those who share a shingle meet one member, and another one each round; once the links found are known, only members that aren't
connected yet are compared, and no pair twice. Only connectivity is asked for. Before whole sets are sent about, parity bitmaps of a size in
proportion to the sets bound the difference of a pair from below: a bit that differs stands for at least one shingle that only
one of them has. Few pairs but similar ones pass that.

Documents with equal sets are one; empty, blank and null texts have the empty set. A text of fewer than five words is
one shingle.
"""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import dropped, map_rows, run_codes, stored
from .components import components

WORDS = 5
#: Similarity of at least PART / WHOLE.
PART, WHOLE = 4, 5
#: Common shingles that the order knows at most, and one in so many documents counted for them; least bits of a parity bitmap, which
#: has the least power of two that is twice the size of the set.
COMMON, SAMPLE, BITS = 1 << 18, 16, 512


#: Rounds in which each shared shingle has one member as its hub.
HUBS = 2


def shingles(text: str | None) -> np.ndarray:
    """Distinct codes of the five-word runs of a text, ascending; ASCII letters lower-cased."""
    words = (text or "").encode("utf-8", "replace").lower().split()
    return np.unique(run_codes(words, min(WORDS, len(words)))) if words else np.zeros(0, np.uint64)


def commonness(docs: DataFrame) -> tuple[np.ndarray, np.ndarray]:
    """The most frequent shingles of the sample, ascending, and in how many of its documents each is: all that as many or more have
    as the rarest of them, from two on."""

    def codes(part: dict) -> dict:
        return {"h": np.concatenate([np.zeros(0, np.int64), *[shingles(t).view(np.int64) for t in part["text"]]])}

    some = docs.where(F.pmod(F.xxhash64("doc_id"), F.lit(SAMPLE)) == 0).select("text")
    counts = stored(map_rows(some, codes, "h bigint").groupBy("h").agg(F.count(F.lit(1)).alias("n")).where("n > 1"))
    least, left = 2, COMMON
    for n, many in sorted((tuple(r) for r in counts.groupBy("n").count().collect()), reverse=True):  # a row for each count there is
        left -= many
        if left < 0:
            least = n + 1
            break
    found = counts.where(F.col("n") >= least).toArrow()
    dropped(counts)
    h, n = (found.column(k).to_numpy() for k in range(2))
    order = np.argsort(h.view(np.uint64))
    return h.view(np.uint64)[order], n[order].astype(np.int32)


def ordered(codes: np.ndarray, common: tuple[np.ndarray, np.ndarray]) -> np.ndarray:
    """Ascending codes in the order of the search: those that aren't common first, then by frequency."""
    known, n = common
    if not len(known):
        return codes
    at = np.minimum(np.searchsorted(known, codes), len(known) - 1)
    return codes[np.argsort(np.where(known[at] == codes, n[at], 0), kind="stable")]


def sets(docs: DataFrame, fingerprint: Callable[[str | None], int]) -> DataFrame:
    """(doc_id, print, fp, n, prefix, bits): fingerprint of the text, code and size of the set, the shingles by which it is found, in
    order, its bitmap."""
    often = docs.sparkSession.sparkContext.broadcast(commonness(docs))

    def rows(part: dict) -> dict:
        out: dict = {"doc_id": part["doc_id"], "print": [fingerprint(t) for t in part["text"]], "fp": [], "n": [], "prefix": [], "bits": []}
        for t in part["text"]:
            codes = shingles(t)
            n = len(codes)
            out["fp"].append(set_code(codes))
            out["n"].append(n)
            out["bits"].append(parity(codes))
            out["prefix"].append(ordered(codes, often.value)[: n - -(-PART * n // WHOLE) + 1].view(np.int64))
        return out

    return map_rows(docs.select("doc_id", "text"), rows, "doc_id bigint, print bigint, fp bigint, n int, prefix array<bigint>, bits array<bigint>")


def parity(codes: np.ndarray) -> np.ndarray:
    """Bitmap of the places that an odd number of codes have; its two halves folded are the bitmap of half the size."""
    size = max(BITS, 1 << (2 * len(codes) - 1).bit_length() if len(codes) else 0)
    odd = np.bincount((codes >> np.uint64(24)).astype(np.int64) % size, minlength=size) & 1
    return np.packbits(odd.astype(np.uint8)).view(np.int64)


def apart(a, b):
    """Bits that differ between two bitmaps of at most twice each other's size: the longer one is folded. At least as many codes are
    in one of the sets alone."""
    half = lambda x: F.zip_with(F.slice(x, F.lit(1), (F.size(x) / 2).cast("int")), F.slice(x, (F.size(x) / 2 + 1).cast("int"), (F.size(x) / 2).cast("int")), lambda p, q: p.bitwiseXOR(q))
    x, y = F.when(F.size(a) > F.size(b), half(a)).otherwise(a), F.when(F.size(b) > F.size(a), half(b)).otherwise(b)
    return F.aggregate(F.zip_with(x, y, lambda p, q: F.bit_count(p.bitwiseXOR(q))), F.lit(0), lambda s, n: s + n)


def set_code(codes: np.ndarray) -> int:
    return int(np.array(xxhash.xxh3_64_intdigest(codes.tobytes()), np.uint64).view(np.int64))


def bodies(docs: DataFrame, found: DataFrame, wanted: DataFrame) -> DataFrame:
    """(fp, codes): the whole sets of the wanted fp, each from the document of smallest id that has it."""

    def rows(part: dict) -> dict:
        codes = [shingles(t) for t in part["text"]]
        return {"fp": [set_code(c) for c in codes], "codes": [c.view(np.int64) for c in codes]}

    ids = stored(found.select("fp", "doc_id").join(wanted, "fp", "left_semi").groupBy("fp").agg(F.min("doc_id").alias("doc_id")))
    texts = docs.select("doc_id", "text").join(ids.select("doc_id").distinct(), "doc_id", "left_semi").select("text")
    whole = stored(map_rows(texts, rows, "fp bigint, codes array<bigint>").join(ids, "fp", "left_semi").dropDuplicates(["fp"]))
    dropped(ids)
    return whole


def verified(docs: DataFrame, found: DataFrame, each: DataFrame, pairs: DataFrame) -> DataFrame:
    """Those of the distinct pairs (a, b) that are similar enough."""
    p, q = (each.select(F.col("fp").alias(n), F.col("n").alias(f"{n}_n"), F.col("bits").alias(f"{n}_bits")) for n in "ab")
    differ = apart(F.col("a_bits"), F.col("b_bits"))
    pairs = stored(pairs.join(p, "a").join(q, "b").where((PART + WHOLE) * differ <= (WHOLE - PART) * (F.col("a_n") + F.col("b_n"))).select("a", "b"))
    whole = bodies(docs, found, pairs.select(F.explode(F.array("a", "b")).alias("fp")).distinct())
    x, y = (whole.select(F.col("fp").alias(n), F.col("codes").alias(f"{n}_codes")) for n in "ab")
    enough = (PART + WHOLE) * F.size(F.array_intersect("a_codes", "b_codes")) >= PART * (F.size("a_codes") + F.size("b_codes"))
    out = stored(pairs.join(x, "a").join(y, "b").where(enough).select("a", "b"))
    dropped(pairs, whole)
    return out


def _may(left: str, right: str):
    """Whether sizes and places let two sets be similar, if this is the first shingle they share."""
    c = lambda side, name: F.col(f"{side}.{name}")
    shared = 1 + F.least(c(left, "n") - c(left, "i"), c(right, "n") - c(right, "i")) - 1
    fits = WHOLE * F.least(c(left, "n"), c(right, "n")) >= PART * F.greatest(c(left, "n"), c(right, "n"))
    return fits & ((PART + WHOLE) * shared >= PART * (c(left, "n") + c(right, "n"))) & (c(left, "fp") != c(right, "fp"))


def _grown(label: DataFrame | None, new: DataFrame) -> DataFrame:
    """(fp, root) of all linked sets after the links (a, b) of ``new``: components are sought among the roots alone, once a pair."""
    if label is None:
        roots = components(new)
        out = stored(roots.select(F.col("node").alias("fp"), "root"))
        dropped(roots)
        return out
    of = lambda side: label.select(F.col("fp").alias(side), F.col("root").alias(f"r{side}"))
    apart = new.join(of("a"), "a", "left").join(of("b"), "b", "left").select(F.coalesce("ra", "a").alias("a"), F.coalesce("rb", "b").alias("b")).where("a <> b").distinct()
    roots = components(apart)
    joined = roots.select("node", F.col("root").alias("now"))
    moved = label.join(joined, F.col("root") == F.col("node"), "left").select("fp", F.coalesce("now", "root").alias("root"))
    fresh = joined.join(label.select(F.col("fp").alias("node")), "node", "left_anti").select(F.col("node").alias("fp"), F.col("now").alias("root"))
    out = stored(moved.union(fresh))
    dropped(label, roots)
    return out


def links(docs: DataFrame, found: DataFrame, known: DataFrame) -> DataFrame:
    """(a, b) of the fp of sets, as stars: their connectivity is that of all pairs that are similar enough and of the links ``known``,
    whose ends are not compared any more.

    Hashes alone are counted first, and only those that two sets share travel on with what names the set. Then ``HUBS`` rounds
    take one member of each shingle as its hub, another one each time, and compare each member with the hub it shares most
    shingles with: one pair a member, so that a group of many like ones is connected by few. A round compares one member of each
    component of a shingle. What is still apart after that, and may be similar, is compared pair by pair.
    """
    each = stored(found.groupBy("fp").agg(F.first("n").alias("n"), F.first("prefix").alias("prefix"), F.first("bits").alias("bits")))
    met = stored(each.select(F.explode("prefix").alias("h")).groupBy("h").agg(F.count(F.lit(1)).alias("count")).where("count > 1").select("h"))
    held = stored(each.select("fp", "n", F.posexplode("prefix").alias("i", "h")).join(met, "h", "left_semi"))
    dropped(met)
    pair = [F.col("x.fp").alias("a"), F.col("y.fp").alias("b")]
    label, tried = _grown(None, known), None
    for turn in range(HUBS + 2):
        named = stored(held.join(label, "fp", "left").withColumn("root", F.coalesce("root", "fp")))
        mixed = named.groupBy("h").agg(F.min("root").alias("low"), F.max("root").alias("high")).where("low <> high")
        split = stored(named.join(mixed.select("h"), "h", "left_semi"))
        dropped(named)
        if split.isEmpty():
            dropped(split)
            break
        left = other = split
        if turn < HUBS:
            lead = F.struct("n", "fp") if turn == 0 else F.struct(F.xxhash64("fp", F.lit(turn)), F.col("fp"))
            other = split.groupBy("h").agg(F.min_by(F.struct("n", "fp", "i", "root"), lead).alias("one")).select("h", "one.*")
        elif turn == HUBS:
            left = other = stored(split.groupBy("h", "root").agg(F.min(F.struct("n", "fp", "i")).alias("one")).select("h", "root", "one.*"))
        more = left.alias("x").join(other.alias("y"), "h").where(F.col("x.root") != F.col("y.root")).where(_may("x", "y")).select(*pair)
        if turn < HUBS:  # of its hubs a member takes the one that it shares most with: one pair each
            shared = more.groupBy("a", "b").agg(F.count(F.lit(1)).alias("n"))
            more = shared.groupBy("a").agg(F.max(F.struct("n", "b")).alias("best")).select("a", F.col("best.b").alias("b"))
        more = more.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct()
        more = stored(more if tried is None else more.join(tried, ["a", "b"], "left_anti"))
        new = verified(docs, found, each, more)
        label = _grown(label, new)
        dropped(*{id(t): t for t in (split, left, new)}.values())
        tried = more if tried is None else tried.union(more)
    dropped(held, each)
    return label.where("fp <> root").select(F.col("fp").alias("a"), F.col("root").alias("b"))
