"""A lake: named datasets of any connector, their catalog, and the melted form all methods start from."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from . import derived

#: Upper limits of the size classes of datasets, in bytes; beyond the last is L.
TESTBEDS = (("XS", 1 << 20), ("S", 100 << 20), ("M", 1 << 30))
FORMATS = ("parquet", "csv", "json", "xml", "orc", "text", "avro")


def string_columns(df: DataFrame) -> list[str]:
    """Declared strings: the first gate, by which column pruning reaches the scan."""
    return [f.name for f in df.schema.fields if isinstance(f.dataType, T.StringType)]


def melt(df: DataFrame, dataset: str | None = None, columns: list[str] | None = None) -> DataFrame:
    """(dataset, attr, value) of the string columns; ``dataset`` None takes the frame's own column of that name."""
    cols = columns or [c for c in string_columns(df) if dataset is not None or c != "dataset"]
    if not cols:
        return df.sparkSession.createDataFrame([], "dataset string, attr string, value string")
    ids = [F.col("dataset")] if dataset is None else []
    long = df.select(*ids, *[F.col(f"`{c}`") for c in cols]).unpivot(ids, [F.col(f"`{c}`") for c in cols], "attr", "value")
    return long.select((F.col("dataset") if dataset is None else F.lit(dataset)).alias("dataset"), "attr", "value")


def testbed_of(n_bytes, limits: tuple[tuple[str, int], ...] = TESTBEDS) -> F.Column:
    out = F.lit("L")
    for name, limit in reversed(limits):
        out = F.when(n_bytes <= limit, name).otherwise(out)
    return out


class Lake:
    """Ordered datasets by name. Attribute ids are (dataset, attr), so equal names in two datasets don't clash."""

    def __init__(self, spark: SparkSession):
        self.spark, self.frames, self.bytes = spark, {}, {}

    def add(self, name: str, df: DataFrame, n_bytes: int | None = None) -> "Lake":
        if name in self.frames:
            raise ValueError(f"dataset {name} is in the lake already")
        self.frames[name], self.bytes[name] = df, n_bytes
        return self

    def add_table(self, name: str, table: str | None = None) -> "Lake":
        return self.add(name, self.spark.table(table or name))

    def add_file(self, name: str, path: str, fmt: str, n_bytes: int | None = None, **options) -> "Lake":
        """CSV is read as strings (types are found from the values); Avro needs Spark's external module."""
        if fmt not in FORMATS:
            raise ValueError(f"unknown format {fmt}; one of {', '.join(FORMATS)}")
        options = ({"header": "true", "inferSchema": "false"} if fmt == "csv" else {"rowTag": "row"} if fmt == "xml" else {}) | options
        return self.add(name, self.spark.read.format(fmt).options(**options).load(path), n_bytes)

    @classmethod
    def from_dir(cls, spark: SparkSession, path: str, tables: tuple[str, ...]) -> "Lake":
        lake = cls(spark)
        for t in tables:
            lake.add(t, spark.read.parquet(f"{path}/{t}.parquet"))
        return lake

    @classmethod
    def crawl(cls, spark: SparkSession, root: str) -> "Lake":
        """Every file under ``root`` whose extension names a format, with its size; the listing is Spark's own."""
        lake = cls(spark)
        listed = spark.read.format("binaryFile").option("recursiveFileLookup", "true").load(root).select("path", "length")
        for path, size in sorted(map(tuple, listed.collect())):  # one row a file
            stem, _, ext = path.rpartition("/")[2].rpartition(".")
            if ext in FORMATS and stem:
                lake.add_file(stem, path, ext, size)
        return lake

    def catalog(self) -> DataFrame:
        """(dataset, attr, ordinal, declared_type, n_bytes)"""
        rows = [(n, f.name, i, f.dataType.simpleString(), self.bytes[n]) for n, df in self.frames.items() for i, f in enumerate(df.schema.fields)]
        return self.spark.createDataFrame(rows, "dataset string, attr string, ordinal int, declared_type string, n_bytes bigint")

    def melted(self) -> DataFrame:
        """All string cells in one plan: many small datasets make one job, not one each."""
        parts = [melt(df, name) for name, df in self.frames.items() if string_columns(df)]
        return reduce(DataFrame.unionByName, parts) if parts else melt(self.spark.createDataFrame([], "x int"), "")

    def profile(self, mode: str = "exact") -> DataFrame:
        """Profiles of all string columns; ``sketch`` shuffles no value."""
        from ..operators import profile

        return profile.approximate(self.melted()) if mode == "sketch" else profile.profiles(profile.frequencies(self.melted()))

    def discover(self, dataset: str, model, attr: str | None = None, min_class: int = 1, top: int | None = None, profiles: DataFrame | None = None) -> DataFrame:
        """Ranking of the lake's other datasets for one attribute, or for all of a dataset; stored ``profiles`` save the scan."""
        from ..operators import discover

        known = self.profile() if profiles is None else profiles
        ref, rest = known.where(F.col("dataset") == dataset), known.where(F.col("dataset") != dataset)
        if attr is None:
            return discover.by_dataset(ref, rest, model, min_class, top)
        return discover.by_attribute(ref, attr, rest, model, min_class, top)

    def register_views(self, prefix: str = "") -> None:
        for name, df in self.frames.items():
            df.createOrReplaceTempView(f"{prefix}{name}")


#: Bytes of a table's files from which its rows are dealt out over all cores.
DEALT = 1 << 20


def dealt(spark: SparkSession, path: str) -> int:
    """Over how many tasks to deal the rows of a table, 0 to leave them as they are read. A file of one row group is one task, however
    many cores wait for it, and each row becomes many cells; a table of a scan's task and more a core is left."""
    size = int(spark.read.parquet(path)._jdf.queryExecution().optimizedPlan().stats().sizeInBytes())
    tasks = 2 * spark.sparkContext.defaultParallelism
    most = spark._jsparkSession.sessionState().conf().filesMaxPartitionBytes()
    return tasks if DEALT <= size < tasks * most else 0


def group_frame(spark: SparkSession, sf_dir: str, group: derived.Group, tasks: dict[str, int] | None = None) -> DataFrame:
    """A group of the derived lake; its tables are read by path, so no view of the session is touched. ``tasks`` names the tables whose
    rows are dealt out."""
    text = group.sql("spark")
    for t in sorted(derived.TABLES, key=len, reverse=True):
        for word in ("FROM", "JOIN"):
            source = f"parquet.`{sf_dir}/{t}.parquet` AS {t}"
            if word == "FROM" and tasks and tasks.get(t):
                source = f"(SELECT /*+ REPARTITION({tasks[t]}) */ * FROM parquet.`{sf_dir}/{t}.parquet`) AS {t}"
            text = text.replace(f"{word} {t} ", f"{word} {source} ").replace(f"{word} {t})", f"{word} {source})")
            if text.endswith(f"{word} {t}"):
                text = text[: -len(t)] + source
    return spark.sql(text)


def derived_melted(spark: SparkSession, sf_dir: str, families: tuple[str, ...] | None = None) -> DataFrame:
    groups = derived.chosen(families)
    read = [t for t in derived.TABLES if any(f"FROM {t}{end}" in f"{g.select} " for g in groups for end in " )")]
    tasks = {t: dealt(spark, f"{sf_dir}/{t}.parquet") for t in read}
    return reduce(DataFrame.unionByName, [melt(group_frame(spark, sf_dir, g, tasks)) for g in groups])


def derived_dataset(spark: SparkSession, sf_dir: str, dataset: str) -> DataFrame:
    """One dataset of the derived lake as a table of its own."""
    for g in derived.GROUPS:
        if dataset == g.name or dataset.startswith(g.name.partition("_")[0]):
            df = group_frame(spark, sf_dir, g).where(F.col("dataset") == dataset).drop("dataset")
            if g.name == dataset or not df.isEmpty():
                return df
    raise ValueError(f"no dataset {dataset}")
