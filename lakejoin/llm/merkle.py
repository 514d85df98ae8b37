"""Merkle fingerprints of documents; DataFrame functions alone.

A text splits at blank lines into sections, at line ends into paragraphs, and each paragraph into leaves of at most
``PIECE`` characters, a sentence end closing a leaf. A paragraph's hash is the SHA-256 of its text, a section's that of
its paragraphs' hashes, the root that of its sections' hashes. Equal texts have equal roots, and different texts different
ones; below differing roots only differing branches need a look (``edits``).

A fingerprint is the root followed by a sketch of the leaves: the ``SKETCH`` least of their distinct hashes. From two
fingerprints alone, ``likeness`` is the share of leaves that both hold among all leaves of both: exact while no more leaves
than ``SKETCH`` are there, else estimated from the least hashes of the union (standard error at most 0.5 / sqrt(SKETCH)).

The next document of each is found without a global sort: ids meet in ranges of ``2**SHIFT`` ids, which bounds every
window; the end of a range looks up the first document of the next range that holds any, by the same step on range
numbers, level by level. Texts of documents with an id of their own are shuffled once.

Null texts are empty. Rows without an id come last, together as one document; rows that share an id are versions of one
document: the least text of them stands for it before others, and each is followed by the next id's document. The last
document is followed by the first, a lone one by itself. An empty table gives no row. A very long text makes a very
long list of leaves in its row, never a longer fingerprint.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import documents, stored

SHIFT, PIECE, LAST = 10, 16, 2**63 - 1
#: Leaf hashes in a fingerprint, and the hex digits of each; the root has 64.
SKETCH, DIGITS, ROOT = 64, 10, 64
PATTERN = rf"[^.!?\n]{{1,{PIECE}}}[.!?\n]*|[.!?\n]+"


def _node(children: Column) -> Column:
    return F.sha2(F.array_join(children, ","), 256)


def sections(text: Column) -> Column:
    """array<array<string>>: the hashes of the paragraphs of each section."""
    return F.transform(F.split(text, "\n\n", -1), lambda s: F.transform(F.split(s, "\n", -1), lambda p: F.sha2(p, 256)))


def root(text: Column) -> Column:
    return _node(F.transform(sections(text), _node))


def _let(value: Column, use) -> Column:
    """``use(value)`` with ``value`` computed once."""
    return F.element_at(F.transform(F.array(value), use), 1)


def tree(text: Column) -> Column:
    """struct(root, sections: array<struct(hash, paragraphs)>)"""
    inner = F.transform(sections(text), lambda ps: F.struct(_node(ps).alias("hash"), ps.alias("paragraphs")))
    return _let(inner, lambda s: F.struct(_node(F.transform(s, lambda x: x["hash"])).alias("root"), s.alias("sections")))


def edits(left: Column, right: Column) -> Column:
    """array<struct(section, paragraph)> of two trees: where branches differ, numbers from 0; empty for equal roots."""
    n = F.greatest(F.size(left["sections"]), F.size(right["sections"]))
    none = F.array().cast("array<string>")

    def of(k: Column) -> Column:
        a, b = (F.coalesce(F.get(x["sections"], k)["paragraphs"], none) for x in (left, right))
        m = F.greatest(F.size(a), F.size(b), F.lit(1))
        differ = F.filter(F.sequence(F.lit(0), m - 1), lambda j: ~F.get(a, j).eqNullSafe(F.get(b, j)))
        found = F.transform(differ, lambda j: F.struct(k.alias("section"), j.alias("paragraph")))
        same = F.get(left["sections"], k)["hash"].eqNullSafe(F.get(right["sections"], k)["hash"])
        return F.when(same, F.slice(found, 1, 0)).otherwise(found)

    walk = F.flatten(F.transform(F.sequence(F.lit(0), n - 1), of))
    return F.when(left["root"] == right["root"], F.slice(walk, 1, 0)).otherwise(walk)


def sketch(text: Column) -> Column:
    """The least distinct hashes of the leaves, ascending, in one string."""
    leaves = F.transform(F.regexp_extract_all(text, F.lit(PATTERN), F.lit(0)), lambda p: F.substring(F.md5(p), 1, DIGITS))
    return F.array_join(F.slice(F.array_sort(F.array_distinct(leaves)), 1, SKETCH), "")


def fingerprint(root: Column, text: Column) -> Column:
    return F.concat(root, sketch(text))


def likeness(a: Column, b: Column) -> Column:
    """Of two fingerprints; 1 where neither has a leaf."""

    def leaves(x: Column) -> Column:
        n = ((F.length(x) - ROOT) / DIGITS).cast("int")
        every = F.transform(F.sequence(F.lit(0), F.greatest(n - 1, F.lit(0))), lambda i: F.substring(x, i * DIGITS + ROOT + 1, F.lit(DIGITS)))
        return F.when(n > 0, every).otherwise(F.slice(every, 1, 0))

    def share(s: Column) -> Column:
        least = F.slice(F.array_sort(F.array_union(s["a"], s["b"])), 1, SKETCH)
        return F.when(F.size(least) == 0, F.lit(1.0)).otherwise(F.size(F.array_intersect(F.array_intersect(least, s["a"]), s["b"])) / F.size(least))

    return _let(F.struct(leaves(a).alias("a"), leaves(b).alias("b")), share)


def successors(keys: DataFrame, low: int, high: int) -> DataFrame:
    """(k, next) of distinct bigint keys (k) between ``low`` and ``high``, both present; the last is followed by the first."""
    near = high - low < 1 << SHIFT
    up = F.lit(0).cast("bigint") if near else F.shiftright("k", SHIFT)
    order = Window.partitionBy("up").orderBy("k")
    inner = keys.withColumn("up", up).withColumn("lead", F.lead("k").over(order))
    if near:
        return inner.select("k", F.coalesce("lead", F.lit(low)).alias("next"))
    firsts = stored(keys.groupBy(up.alias("k")).agg(F.min("k").alias("first")))
    above = successors(firsts.select("k"), low >> SHIFT, high >> SHIFT)
    heads = above.join(firsts.select(F.col("k").alias("next"), "first"), "next").select(F.col("k").alias("up"), "first")
    return inner.join(heads, "up").select("k", F.coalesce("lead", "first").alias("next"))


def with_next(docs: DataFrame) -> DataFrame:
    """(doc_id, text, fingerprint, next, next_fingerprint): every text with that of the next document."""
    rows = docs.select("doc_id", F.coalesce("doc_id", F.lit(LAST)).alias("id"), F.coalesce("text", F.lit("")).alias("text"))
    shared = stored(rows.groupBy("id").count().where("count > 1").select("id"))
    versions = rows.join(shared, "id", "left_semi")
    heads = stored(versions.groupBy("id").agg(F.min("text").alias("text")))
    ups = lambda df: df.withColumn("up", F.shiftright("id", SHIFT))
    firsts = stored(ups(rows.select("id")).groupBy("up").agg(F.min("id").alias("first")))
    ends = firsts.agg(F.min("up"), F.max("up")).first()
    after = successors(firsts.select(F.col("up").alias("k")), ends[0], ends[1]) if ends[0] is not None else firsts.select(F.col("up").alias("k"), F.col("up").alias("next"))
    head_id = stored(after.join(firsts.select(F.col("up").alias("next"), "first"), "next").select(F.col("k").alias("after"), F.col("first").alias("id")))

    def marked(df: DataFrame) -> DataFrame:
        return df.withColumn("fingerprint", fingerprint(root(F.col("text")), F.col("text")))

    each = rows.join(shared, "id", "left_anti").select("doc_id", "id", "text", F.lit(False).alias("many")).union(heads.select(F.lit(None).cast("bigint"), "id", "text", F.lit(True)))
    follow = F.struct(F.col("text").alias("next"), F.col("fingerprint").alias("next_fingerprint"))
    begins = each.select("id", "text").join(head_id, "id").groupBy("after").agg(F.first("text").alias("text"))
    begins = stored(marked(begins).select("after", follow.alias("head")))
    led = ups(marked(each)).withColumn("lead", F.lead(follow).over(Window.partitionBy("up").orderBy("id")))
    led = led.join(begins, F.col("up") == F.col("after")).withColumn("follow", F.coalesce("lead", "head"))
    own = led.where("not many").select("doc_id", "text", "fingerprint", "follow.*")
    if shared.isEmpty():
        return own
    followed = stored(led.where("many").select("id", "follow.*"))
    again = marked(versions).join(followed, "id").select("doc_id", "text", "fingerprint", "next", "next_fingerprint")
    return own.union(again)


def compared(docs: DataFrame) -> DataFrame:
    n = F.length("text")
    part = F.floor(n / 4).cast("int")
    pairs = with_next(docs).withColumn("edited", F.concat(F.substring("text", F.lit(1), n - part), F.substring("next", F.lit(1), part)))
    shaped = pairs.select("doc_id", n.cast("bigint").alias("n_chars"), "edited", tree(F.col("text")).alias("tree"), tree(F.col("edited")).alias("other"), "fingerprint", "next_fingerprint")
    ended = shaped.select("*", fingerprint(F.col("other")["root"], F.col("edited")).alias("edited_fingerprint"), F.get(edits(F.col("tree"), F.col("other")), F.lit(0)).alias("first"))
    near = lambda other: likeness(F.col("fingerprint"), F.col(other))
    return ended.select(
        "doc_id", "n_chars", F.sha2("edited", 256).alias("edited_sha256"), "fingerprint", "edited_fingerprint",
        near("edited_fingerprint").alias("near_edited"), near("next_fingerprint").alias("near_next"),
        F.col("first")["section"].cast("bigint").alias("edit_section"), F.col("first")["paragraph"].cast("bigint").alias("edit_paragraph"),
    )


def op9_merkle_fingerprints(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Fingerprints, likenesses, and the first section and paragraph (from 0) where the edited text's tree differs."""
    return compared(documents(spark, sf_dir))


_root = "sha256(list_aggregate(list_transform(string_split({0}, chr(10) || chr(10)), lambda s: sha256(list_aggregate(list_transform(string_split(s, chr(10)), lambda p: sha256(p)), 'string_agg', ','))), 'string_agg', ','))"
_leaves = f"list_slice(list_sort(list_distinct(list_transform(regexp_extract_all({{0}}, '{PATTERN.replace('{', '{{').replace('}', '}}')}'), lambda x: substr(md5(x), 1, {DIGITS})))), 1, {SKETCH})"
_least = f"list_slice(list_sort(list_distinct(list_concat({{0}}, {{1}}))), 1, {SKETCH})"
_near = f"CASE WHEN len({{0}}) + len({{1}}) = 0 THEN 1.0 ELSE CAST(len(list_intersect(list_intersect({_least}, {{0}}), {{1}})) AS DOUBLE) / len({_least}) END"
_differs = "list_position(list_transform(range(greatest(len({0}), len({1}))), lambda i: {0}[i + 1] IS DISTINCT FROM {1}[i + 1]), true) - 1"
ORACLE = f"""
WITH d AS (SELECT doc_id, coalesce(doc_id, {LAST}) AS id, coalesce(text, '') AS text FROM documents),
h AS (SELECT id, min(text) AS text FROM d GROUP BY id),
g AS (SELECT id, coalesce(lead(text) OVER (ORDER BY id), first_value(text) OVER (ORDER BY id)) AS nxt FROM h),
e AS (SELECT d.*, nxt, substr(text, 1, length(text) - length(text) // 4) || substr(nxt, 1, length(text) // 4) AS edited FROM d JOIN g USING (id)),
p AS (SELECT *, {_leaves.format('text')} AS a, {_leaves.format('edited')} AS b, {_leaves.format('nxt')} AS c,
      string_split(text, chr(10) || chr(10)) AS s, string_split(edited, chr(10) || chr(10)) AS t FROM e),
q AS (SELECT *, {_differs.format('s', 't')} AS k FROM p),
r AS (SELECT *, string_split(coalesce(s[k + 1], ''), chr(10)) AS sp, string_split(coalesce(t[k + 1], ''), chr(10)) AS tp FROM q)
SELECT doc_id, CAST(length(text) AS BIGINT) AS n_chars, sha256(edited) AS edited_sha256, {_root.format('text')} || coalesce(array_to_string(a, ''), '') AS fingerprint,
  {_root.format('edited')} || coalesce(array_to_string(b, ''), '') AS edited_fingerprint, {_near.format('a', 'b')} AS near_edited, {_near.format('a', 'c')} AS near_next,
  CAST(CASE WHEN text = edited THEN NULL ELSE k END AS BIGINT) AS edit_section,
  CAST(CASE WHEN text = edited THEN NULL WHEN len(s) <= k OR len(t) <= k THEN 0 ELSE {_differs.format('sp', 'tp')} END AS BIGINT) AS edit_paragraph FROM r
"""
