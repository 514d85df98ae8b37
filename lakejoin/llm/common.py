"""Helpers that the training-data operators share.

Conventions that hold for every operator here:

* a null text counts as the empty text; rows are never dropped because of it;
* a null ``doc_id`` is an id like any other (it hashes and groups as null);
* only the columns an operator names are read, so extra columns, whatever they
  are called, neither clash nor cost anything; a stage of the pipeline hands all
  columns on and takes names of its own that the table doesn't have (``fresh``);
* a text of any length is read whole; Python tasks hold ``STEP`` rows at a time and
  work in time that grows in proportion to a text's length (times its logarithm, where sorted);
* an empty input gives an empty result of the same schema.
"""

from __future__ import annotations

import ctypes
import gc
from collections.abc import Callable
from itertools import repeat

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..session import dropped, shared_dir, ship, stored, swept  # noqa: F401  operators take them from here

#: A word: a run of characters other than the six ASCII blanks. ``bytes.split()`` cuts UTF-8 text alike.
WORD = r"[^\x20\x09-\x0D]+"

#: Rows handled at once inside a Python task, and bytes of a slice of average rows, so that memory doesn't follow the Arrow batch size.
STEP, SLICE = 256, 8 << 20

_ARROW = {
    "bigint": pa.int64(),
    "int": pa.int32(),
    "double": pa.float64(),
    "boolean": pa.bool_(),
    "string": pa.string(),
    "binary": pa.binary(),
    "array<bigint>": pa.list_(pa.int64()),
    "array<int>": pa.list_(pa.int32()),
    "array<double>": pa.list_(pa.float64()),
    "array<string>": pa.list_(pa.string()),
}


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    ship(spark)
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def labels(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/labels.parquet")


def tokenizer_file(spark: SparkSession, name: str) -> str:
    """Path of a given vocabulary file, under the folder that the setting ``spark.lakejoin.tokenizers`` names."""
    return f"{spark.conf.get('spark.lakejoin.tokenizers', '/opt/tokenizers')}/{name}"


def cut(df: DataFrame) -> DataFrame:
    """End the lineage of a small frame: a reliable checkpoint, which outlives the loss of any executor."""
    shared_dir(df.sparkSession)
    return df.checkpoint(eager=True)


_caches: list = []


def released() -> None:
    """At the end of a task: empty what Python tasks remember and give the memory back, since workers live on for other stages."""
    for cache in _caches:
        cache.clear()
    gc.collect()
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)
    if trim is not None:
        trim(0)


def arrow_schema(ddl: str) -> pa.Schema:
    fields = T._parse_datatype_string(ddl).fields
    return pa.schema([pa.field(f.name, _ARROW[f.dataType.simpleString()]) for f in fields])


def map_rows(df: DataFrame, fn: Callable[[dict], dict], ddl: str, step: int = STEP) -> DataFrame:
    """Run ``fn`` over column lists, a few hundred rows at a time: dict of lists in, dict of lists out."""
    ship(df.sparkSession)
    schema = arrow_schema(ddl)

    def run(batches):
        for batch in batches:
            few = max(1, min(step, SLICE * batch.num_rows // max(1, batch.nbytes)))
            for at in range(0, batch.num_rows, few):
                out = fn(batch.slice(at, few).to_pydict())
                yield pa.RecordBatch.from_pydict({n: out[n] for n in schema.names}, schema=schema)
        released()

    return df.mapInArrow(run, ddl)


def fresh(df: DataFrame, name: str) -> str:
    """``name``, lengthened until no column of ``df`` has it (letter case aside)."""
    taken = {c.lower() for c in df.columns}
    while name.lower() in taken:
        name += "_"
    return name


def _whole_rows(df: DataFrame, change: Callable, out, step: int) -> DataFrame:
    """Whole rows through ``change`` (a record batch in, one out) in slices, whatever their columns are called; ``out`` names the columns
    that come back, a part of ``df``'s."""
    ship(df.sparkSession)

    def run(batches):
        for batch in batches:
            few = max(1, min(step, SLICE * batch.num_rows // max(1, batch.nbytes)))
            for i in range(0, batch.num_rows, few):
                yield change(batch.slice(i, few))
        released()

    plain = df.toDF(*[f"c{i}" for i in range(len(df.columns))])  # mapInArrow can't name columns with dots
    kept = [f"c{df.columns.index(c)}" for c in out]
    return plain.mapInArrow(run, plain.select(*kept).schema).toDF(*out)


def filtered(df: DataFrame, column: str, keep: Callable[[list], list], step: int = STEP) -> DataFrame:
    """The rows for whose ``column`` values ``keep`` says True; all columns pass through."""
    at = df.columns.index(column)
    return _whole_rows(df, lambda part: part.filter(pa.array(keep(part.column(at).to_pylist()), pa.bool_())), df.columns, step)


def rewritten(df: DataFrame, column: str, given: str, fn: Callable[[list, list], list], step: int = STEP) -> DataFrame:
    """``column`` replaced by what ``fn`` makes of its values and those of ``given``, which goes; rows of which it makes None go too."""
    at, by = df.columns.index(column), df.columns.index(given)

    def change(part: pa.RecordBatch) -> pa.RecordBatch:
        new = pa.array(fn(part.column(at).to_pylist(), part.column(by).to_pylist()), part.schema.field(at).type)
        return part.set_column(at, part.schema.field(at), new).filter(new.is_valid()).drop_columns([part.schema.names[by]])

    return _whole_rows(df, change, [c for c in df.columns if c != given], step)


def crc_mod(doc_id: Column, n: int) -> Column:
    """crc32 of the id written as text, modulo ``n``; a null id falls in class 0."""
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % n, F.lit(0))


#: Bits of the map that ``split_by_ids`` broadcasts (at most 65,536 rows of 64), whatever the number of ids.
PLACES = 1 << 22


def split_by_ids(df: DataFrame, ids: DataFrame, column: str = "doc_id") -> tuple[DataFrame, DataFrame]:
    """The rows of ``df`` whose ``column`` may be among the one column of ``ids``, and those whose surely isn't: so a join with the ids
    need not send all texts about. A bit stands for each hash of an id, so some other rows are in the first part too; null is in the second."""
    place = lambda c: F.pmod(F.xxhash64(c), F.lit(PLACES))
    at, block, bits = (fresh(df, n) for n in ("at", "block", "bits"))
    one = F.col(ids.columns[0])
    wanted = ids.where(one.isNotNull()).select(place(one.cast(df.schema[column].dataType)).alias(at))
    maps = wanted.groupBy(F.shiftright(at, 6).alias(block)).agg(F.bit_or(F.expr(f"shiftleft(1L, CAST({at} % 64 AS INT))")).alias(bits))
    names = [F.col(f"`{c}`") for c in df.columns]
    marked = df.withColumn(at, place(F.col(f"`{column}`"))).withColumn(block, F.shiftright(at, 6)).join(F.broadcast(maps), block, "left")
    may = F.col(f"`{column}`").isNotNull() & F.coalesce(F.expr(f"getbit({bits}, CAST({at} % 64 AS INT)) = 1"), F.lit(False))
    return marked.where(may).select(*names), marked.where(~may).select(*names)


def labelled(docs: DataFrame, marks: DataFrame, column: str, learn: Column, limit: int) -> DataFrame:
    """(doc_id, text, y) of at most ``limit`` labelled rows that satisfy ``learn``.

    The bound is part of the fit, never of what is scored. Rows are taken by the hash of their id, so any
    run takes the same ones; a row with several labels takes the largest. Only ids are sorted and sent about;
    the chosen ids (bounded by ``limit``) are broadcast to the scan of the texts.
    """
    ids = (
        marks.where(F.col(column).isNotNull() & F.col("doc_id").isNotNull())
        .where(learn)
        .groupBy("doc_id")
        .agg(F.max(column).cast("int").alias("y"))
        .orderBy(F.xxhash64(F.col("doc_id")), "doc_id")
        .limit(limit)
    )
    return docs.select("doc_id", "text").join(F.broadcast(ids), "doc_id")


class Cache(dict):
    """``cache[key]`` computes a missing value with ``fn``; it empties itself at ``most`` keys, and at the end of each task, so
    memory is bounded."""

    __slots__ = ("fn", "most")

    def __init__(self, fn, most: int = 60_000):
        super().__init__()
        self.fn, self.most = fn, most
        _caches.append(self)

    def __missing__(self, key):
        if len(self) >= self.most:
            self.clear()
        value = self[key] = self.fn(key)
        return value


def run_codes(words: list[bytes], k: int) -> np.ndarray:
    """A 64-bit code of each run of ``k`` successive words. Hashing a word costs less than looking it up among many others."""
    code = np.frombuffer(b"".join(map(xxhash.xxh64_digest, words, repeat(7))), ">u8").astype(np.uint64)
    n = len(words) - k + 1
    h = np.zeros(n, np.uint64)
    for i in range(k):
        h += code[i : i + n] * np.uint64(pow(0x9E3779B97F4A7C15, i + 1, 1 << 64))
    h ^= h >> np.uint64(32)
    h *= np.uint64(0xC2B2AE3D27D4EB4F)
    return h ^ (h >> np.uint64(29))
