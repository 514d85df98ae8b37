"""Token counts kept in delta-maintained rollups.

A batch is a table of signed changes: documents inserted, deleted, or counted anew. Its sums by source, language and
tokenizer version are additive, so a batch is reduced once and stored as a few rows; totals are the sum over the
committed batches. A commit writes the sums beside the store and then renames them to the batch's own name; a batch
whose name is there already changes nothing, so replays and retries after a lost executor or driver are harmless.
``compact`` folds batches into one base file that lists them; they stay committed.

Null sources, languages and versions are keys like any other; null counts are 0. Repeated rows count each for
itself. An unknown or null operation fails the whole batch. An empty batch commits and adds nothing. Keys whose
documents, tokens and characters have all returned to 0 leave the totals.
"""

from __future__ import annotations

import re
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..session import ship
from .common import documents, labels, map_rows, shared_dir, stored, tokenizer_file

KEYS, SUMS = ("source", "lang", "version"), ("docs", "tokens", "chars")


def deltas(changes: DataFrame) -> DataFrame:
    """Sums by key of changes (op, source, lang, version, tokens, chars, old_tokens, old_chars)."""
    zero = lambda c: F.coalesce(F.col(c).cast("bigint"), F.lit(0))
    sign = F.when(F.col("op") == "insert", 1).when(F.col("op") == "delete", -1).when(F.col("op") == "revise", 0).otherwise(F.raise_error(F.concat(F.lit("unknown operation "), F.coalesce("op", F.lit("null")))))
    moved = lambda c: F.when(F.col("sign") == 0, zero(c) - zero(f"old_{c}")).otherwise(F.col("sign") * zero(c))
    signed = changes.withColumn("sign", sign.cast("bigint"))
    return signed.groupBy(*KEYS).agg(F.sum("sign").alias("docs"), F.sum(moved("tokens")).alias("tokens"), F.sum(moved("chars")).alias("chars"))


class Rollup:
    """A store of committed batches under a folder that all executors and the driver share."""

    def __init__(self, spark: SparkSession, path: str):
        self.spark, self.path = spark, path.rstrip("/")
        self._jvm = spark._jvm

    def _at(self, name: str):
        path = self._jvm.org.apache.hadoop.fs.Path(f"{self.path}/{name}")
        return path.getFileSystem(self.spark._jsparkSession.sessionState().newHadoopConf()), path

    def _names(self, folder: str) -> list[str]:
        fs, path = self._at(folder)
        return sorted(s.getPath().getName() for s in fs.listStatus(path)) if fs.exists(path) else []

    def batches(self) -> list[str]:
        """Committed batches, folded ones included."""
        return sorted({*self._names("batches"), *self._folded()})

    def _base(self) -> str | None:
        return next(iter(reversed(self._names("base"))), None)

    def _folded(self) -> list[str]:
        base = self._base()
        return [r["name"] for r in self.spark.read.parquet(f"{self.path}/base/{base}/names").collect()] if base else []

    def commit(self, batch: str, changes: DataFrame) -> bool:
        """Reduce and store a batch; False if one of this name is committed already."""
        if not re.fullmatch(r"[\w.-]+", batch):
            raise ValueError(f"not a batch name: {batch!r}")
        if batch in self.batches():
            return False
        fs, staged = self._at(f"staging/{batch}-{uuid.uuid4().hex}")
        deltas(changes).coalesce(1).write.parquet(str(staged))
        return self._published(fs, staged, self._at(f"batches/{batch}")[1])

    def _published(self, fs, staged, final) -> bool:
        """Rename a finished folder to its public name; False if another writer was first. Renaming onto a folder that is there nests
        the one in the other on some file systems, which is undone. The rename has to be atomic: on an object store use
        a committer or file system that makes it so."""
        fs.mkdirs(final.getParent())
        nested = self._jvm.org.apache.hadoop.fs.Path(final, staged.getName())
        done = not fs.exists(final) and fs.rename(staged, final)
        if not done or fs.exists(nested):
            fs.delete(nested, True)
            fs.delete(staged, True)
            return False
        return True

    def totals(self) -> DataFrame:
        folded, base = set(self._folded()), self._base()
        paths = [f"{self.path}/batches/{n}" for n in self._names("batches") if n not in folded]
        paths += [f"{self.path}/base/{base}/sums"] if base else []
        if not paths:
            return self.spark.createDataFrame([], "source string, lang string, version string, docs bigint, tokens bigint, chars bigint")
        summed = self.spark.read.parquet(*paths).groupBy(*KEYS).agg(*[F.sum(c).alias(c) for c in SUMS])
        return summed.where("docs <> 0 or tokens <> 0 or chars <> 0")

    def compact(self) -> None:
        """Fold every committed batch into a new base; readers see the old or the new one."""
        names, sums = self.batches(), self.totals()
        fs, staged = self._at(f"staging/base-{uuid.uuid4().hex}")
        sums.coalesce(1).write.parquet(f"{staged}/sums")
        self.spark.createDataFrame([(n,) for n in names], "name string").coalesce(1).write.parquet(f"{staged}/names")
        _, final = self._at(f"base/{len(self._names('base')):09d}")
        if not self._published(fs, staged, final):
            raise RuntimeError("another compaction came first")


def tokenizer_counts(docs: DataFrame, versions: dict[str, str], pattern: str | None = None, step: int = 64) -> DataFrame:
    """(doc_id, source, lang, chars, tokens): tokens of every whole text under each version's byte-pair vocabulary, in the order of
    ``versions`` (name to path of a file of ranks; the files reach the executors with the job). ``pattern`` cuts a text into the
    words that are encoded apart; by default the one that the given vocabularies are used with."""
    import base64

    import public_tokenizers

    tables = []
    for path in versions.values():
        with open(path, "rb") as f:
            tables.append({base64.b64decode(a): int(b) for a, b in map(bytes.split, f)})
    sent, cut, ready = docs.sparkSession.sparkContext.broadcast(tables), pattern or public_tokenizers.PATTERN, {}

    def rows(part: dict) -> dict:
        if not ready:
            import tiktoken

            ready["all"] = [tiktoken.Encoding(f"v{i}", pat_str=cut, mergeable_ranks=t, special_tokens={}) for i, t in enumerate(sent.value)]
        counts = [[len(c.encode_ordinary(t or "")) for c in ready["all"]] for t in part["text"]]
        return {n: part[n] for n in ("doc_id", "source", "lang")} | {"chars": [len(t or "") for t in part["text"]], "tokens": counts}

    return map_rows(docs.select("doc_id", "source", "lang", "text"), rows, "doc_id bigint, source string, lang string, chars bigint, tokens array<bigint>", step)


#: Versions of the query: name and file of ranks.
VERSIONS = {"bpe-50k": "byte_bpe_50k.tiktoken", "bpe-multi-50k": "byte_bpe_multi_50k.tiktoken"}


def op8_token_rollup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Load all documents under two tokenizer versions, withdraw those labelled of low quality, count those labelled
    toxic as empty under the second, and replay every batch: totals by key."""
    ship(spark)
    counted = stored(tokenizer_counts(documents(spark, sf_dir), {v: tokenizer_file(spark, name) for v, name in VERSIONS.items()}))
    marks = stored(labels(spark, sf_dir).groupBy("doc_id").agg(F.min("quality").alias("quality"), F.max("toxic").alias("toxic")))
    each = F.explode(F.array(*[F.struct(F.lit(v).alias("version"), F.col("tokens")[i].alias("tokens")) for i, v in enumerate(VERSIONS)]))
    rows = counted.select("doc_id", "source", "lang", "chars", each.alias("v")).select("doc_id", "source", "lang", "v.version", "v.tokens", "chars", F.lit(0).alias("old_tokens"), F.lit(0).alias("old_chars"))
    marked = rows.join(marks, "doc_id")
    low = marked.where("quality = 0").withColumn("op", F.lit("delete"))
    second = list(VERSIONS)[-1]
    toxic = marked.where((F.col("toxic") == 1) & (F.col("quality") != 0) & (F.col("version") == second)).withColumns({"op": F.lit("revise"), "old_tokens": F.col("tokens"), "old_chars": F.col("chars")}).withColumns({"tokens": F.lit(0), "chars": F.lit(0)})
    store = Rollup(spark, f"{shared_dir(spark)}/rollup-{uuid.uuid4().hex}")
    plan = (("load", rows.withColumn("op", F.lit("insert"))), ("withdraw", low), ("blank", toxic))
    for name, changes in (*plan, *plan):
        store.commit(name, changes)
    return store.totals()
