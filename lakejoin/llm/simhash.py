"""SimHash near-duplicates through the segment-popcount embedding.

A 64-bit fingerprint becomes a point: the bit counts of its 16 segments of 4 bits. The Manhattan distance of two
points never exceeds the Hamming distance of the fingerprints, so a range join under that distance with radius 2
finds every link. The join runs on the integer grid: each point announces itself in the cells within 1 of its own
(at most 33); two points within 2 meet in some cell. A cell that two fingerprints share gives one pair, which an
exact bit comparison verifies. A cell shared by more is never paired off: its fingerprints are compared exactly
by announcing themselves at the 65 bit patterns within one bit of each, so that two within 2 bits meet at a pattern, where
at most 65 can meet; each pattern links its members in a star. Thus rows stay linear in the number of distinct
fingerprints, whatever the size of a group, and no link is lost: only connectivity is asked for.

Null, empty and blank texts have the fingerprint zero and link like any other. Repeated rows and ties share a
fingerprint, hence a component. A component is named by its smallest ``doc_id``.
"""

from __future__ import annotations

import numpy as np
import xxhash
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import nearcopies
from .common import documents, dropped, fresh, map_rows, stored
from .components import components

SEGMENTS, WIDTH, RADIUS, SEED = 16, 4, 2, 42


def fingerprint(text: str | None, words_each: int = 3) -> int:
    """Majority bits of the XXH64 of each run of three words, ASCII letters lower-cased; signed 64 bits."""
    words = (text or "").encode("utf-8", "replace").lower().split()
    if not words:
        return 0
    if len(words) < words_each:
        runs = [b" ".join(words)]
    else:
        runs = map(b" ".join, zip(*(words[i:] for i in range(words_each))))
    h = np.array([xxhash.xxh64_intdigest(x, SEED) for x in runs], dtype="<u8")
    ones = np.unpackbits(h.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    return int(np.packbits(2 * ones > len(h), bitorder="little").view("<i8")[0])


def fingerprints(docs: DataFrame) -> DataFrame:
    """(doc_id, fp) of every whole text."""
    return map_rows(docs.select("doc_id", "text"), lambda part: {"doc_id": part["doc_id"], "fp": [fingerprint(x) for x in part["text"]]}, "doc_id bigint, fp bigint")


def _segment(k: int):
    return F.bit_count(F.shiftrightunsigned("fp", WIDTH * k).bitwiseAND(F.lit((1 << WIDTH) - 1))).cast("bigint")


def cells(distinct: DataFrame) -> DataFrame:
    """(fp, cell): the grid cells within Manhattan distance 1 of the fingerprint's point, three bits a segment."""
    counts = distinct.select("fp", *[_segment(k).alias(f"s{k}") for k in range(SEGMENTS)])
    home = sum((F.shiftleft(F.col(f"s{k}"), 3 * k) for k in range(1, SEGMENTS)), F.col("s0"))
    near = [F.when(F.col(f"s{k}") < WIDTH, home + F.lit(1 << 3 * k)) for k in range(SEGMENTS)]
    near += [F.when(F.col(f"s{k}") > 0, home - F.lit(1 << 3 * k)) for k in range(SEGMENTS)]
    return counts.select("fp", F.explode(F.array(home, *near)).alias("cell")).where(F.col("cell").isNotNull())


def links(distinct: DataFrame) -> DataFrame:
    """(a, b) fingerprints at most two bits apart; their connectivity is that of all such pairs."""
    spread = cells(distinct)
    met = stored(spread.groupBy("cell").agg(F.count(F.lit(1)).alias("n"), F.min("fp").alias("a"), F.max("fp").alias("b")).where("n > 1"))
    pairs = met.where("n = 2").select("a", "b").distinct().where(F.bit_count(F.col("a").bitwiseXOR(F.col("b"))) <= RADIUS)
    many = spread.join(met.where("n > 2").select("cell"), "cell", "left_semi").select("fp").distinct()
    masks = [0] + [(1 << i) - (1 << 64 if i == 63 else 0) for i in range(64)]
    hubs = many.select("fp", F.explode(F.array(*[F.col("fp").bitwiseXOR(F.lit(m)) for m in masks])).alias("hub"))
    stars = hubs.groupBy("hub").agg(F.min("fp").alias("b"), F.collect_set("fp").alias("near")).where(F.size("near") > 1)
    return pairs.union(stars.select(F.explode("near").alias("a"), "b").where("a <> b"))


def assign(prints: DataFrame) -> DataFrame:
    """(doc_id, fp, component_id) from (doc_id, fp), and what other columns there are: near fingerprints are linked."""
    return joined(prints, links(prints.select("fp").distinct()))


def joined(prints: DataFrame, edges: DataFrame) -> DataFrame:
    """``prints`` (doc_id, fp, ...) with ``component_id``, under links (a, b) of fp."""
    distinct = prints.groupBy("fp").agg(F.min("doc_id").alias("first"))
    roots = components(edges)
    grouped = stored(distinct.join(roots.select(F.col("node").alias("fp"), "root"), "fp"))
    named = grouped.groupBy("root").agg(F.min("first").alias("component_id"))
    linked = grouped.select("fp", "root").join(named, "root").select("fp", F.col("component_id").alias("linked"))
    by_print = stored(distinct.join(linked, "fp", "left").select("fp", F.coalesce("linked", "first").alias("component_id")))
    dropped(roots, grouped)
    # both sides come from files, so a fingerprint with very many copies can be split over tasks
    return prints.join(by_print, "fp").select(*prints.columns, "component_id")


def op2_simhash_components(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = assign(stored(fingerprints(documents(spark, sf_dir))))
    return found.select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


def stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keep the document with the smallest id of each component; all columns pass through.

    Fingerprints link documents first, as in op2. Two bits miss most copies with a few words changed; so documents that are still
    apart are linked where their five-word shingles have a similarity of 0.8 too (see ``nearcopies``). Rows that share a doc_id are copies or versions of one document: one row stays. Rows without an id stay.
    """
    named = docs.where("doc_id is not null")
    found = stored(nearcopies.sets(named, fingerprint))
    near = stored(assign(found.select("doc_id", F.col("print").alias("fp"), F.col("fp").alias("set"))).select("component_id", "set").distinct())
    hubs = near.groupBy("component_id").agg(F.min("set").alias("b"), F.max("set").alias("last")).where("b <> last")
    known = near.join(hubs, "component_id").select(F.col("set").alias("a"), "b")
    edges = nearcopies.links(named, found, known)
    dropped(near)
    ids = stored(joined(found.select("doc_id", "fp"), edges).select("doc_id", "component_id"))
    dropped(found)
    gone = stored(ids.where("doc_id <> component_id").select("doc_id").distinct())
    twice = stored(ids.where("doc_id = component_id").groupBy("doc_id").count().where("count > 1").select("doc_id"))
    dropped(ids)
    names = [F.col(f"`{c}`") for c in docs.columns]
    kept = docs.join(gone, "doc_id", "left_anti").select(*names)
    if twice.isEmpty():
        return kept
    n = fresh(docs, "nth")
    order = Window.partitionBy("doc_id").orderBy(F.md5(F.coalesce(F.col("text"), F.lit(""))), *[F.col(f"`{c}`").cast("string") for c in docs.columns if c not in ("doc_id", "text")])
    one = kept.join(twice, "doc_id", "left_semi").withColumn(n, F.row_number().over(order)).where(F.col(n) == 1).drop(n)
    return kept.join(twice, "doc_id", "left_anti").select(*names).unionByName(one.select(*names))
