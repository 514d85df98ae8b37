"""Pairs of columns that mean the same but share no value until one of them is transformed, with the chain switched off.

Each column is given raw, in one style of writing, and again after its transformation (cleaning, dictionary lookup or
unwinding of lists). The pairs are those of one domain, of different datasets, without a raw value in common; their true
class is that of the transformed columns, and the prediction looks at the raw profiles alone.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import normalize
from ..operators import discover, metrics, pairs, profile, quality, transforms
from ..session import stored
from .context import context
from .pairing import _CLASS
from .registry import query


@dataclass(frozen=True)
class Column:
    """One raw column: SQL for Spark and DuckDB alike, its domain, and how it is transformed ("clean", "lookup" or "unwind")."""

    dataset: str
    domain: str
    table: str
    value: str
    kept: str = "true"
    recipe: str = "clean"


_STYLES = {
    "plain": "{0}",
    "dashed": "upper(replace(replace({0}, '#', '-'), '_', '-'))",
    "spaced": "concat('  ', lower(replace(replace({0}, '#', ' '), '_', ' ')), ' .')",
}
_WORDS = {"F": "fulfilled", "O": "open", "P": "pending"}


def _columns() -> list[Column]:
    out = []
    for style, form in _STYLES.items():
        out += [Column(f"customers{m}_{style}", "customer", "customer", form.format("c_name"), f"c_custkey % {m} = 0") for m in (1, 2, 4, 8, 10, 12, 16)]
        out += [Column(f"nations{n}_{style}", "nation", "nation", form.format("n_name"), f"n_nationkey < {n}") for n in (25, 15, 5)]
        out += [Column(f"vendors{m}_{style}", "supplier", "supplier", form.format("s_name"), f"s_suppkey % {m} = 0") for m in (1, 3)]
    out += [Column("region_codes", "region", "region", "concat('R', r_regionkey, 'x')", recipe="lookup"), Column("region_names", "region", "region", "r_name")]
    out += [Column("status_letters", "status", "orders", "o_orderstatus", recipe="lookup")]
    out += [Column("status_words", "status", "orders", f"CASE o_orderstatus {' '.join(f"WHEN '{k}' THEN '{v}'" for k, v in _WORDS.items())} END")]
    out += [Column("brand_lists", "brand", "part", "p_brand", recipe="unwind"), Column("brands", "brand", "part", "p_brand"), Column("brands_small", "brand", "part", "p_brand", "p_size <= 2")]
    return out


COLUMNS = _columns()


def raw_frame(spark: SparkSession, sf_dir: str, c: Column) -> DataFrame:
    """(value): a list column holds the brands of each type in one string."""
    rows = spark.read.parquet(f"{sf_dir}/{c.table}.parquet").where(F.expr(c.kept))
    if c.recipe == "unwind":
        return rows.groupBy("p_type").agg(F.array_join(F.array_sort(F.collect_set("p_brand")), "; ").alias("value")).select("value")
    return rows.select(F.expr(c.value).alias("value"))


def changed_frame(spark: SparkSession, sf_dir: str, c: Column) -> DataFrame:
    """The raw column after its transformation, then cleaned."""
    df = raw_frame(spark, sf_dir, c)
    if c.recipe == "unwind":
        df = transforms.unwind(df, "value", ";")
    if c.recipe == "lookup" and c.domain == "status":
        df = transforms.lookup(df, "value", spark.createDataFrame(list(_WORDS.items()), "key string, mapped string"))
    if c.recipe == "lookup" and c.domain == "region":
        names = spark.read.parquet(f"{sf_dir}/region.parquet").select(F.concat(F.lit("R"), "r_regionkey", F.lit("x")).alias("key"), F.col("r_name").alias("mapped"))
        df = transforms.lookup(df, "value", names)
    return df.select(transforms.clean(F.col("value")).alias("value"))


def _melted(spark: SparkSession, sf_dir: str, frame) -> DataFrame:
    out = None
    for c in COLUMNS:
        rows = frame(spark, sf_dir, c).select(F.lit(c.dataset).alias("dataset"), F.lit(c.domain).alias("attr"), "value")
        out = rows if out is None else out.unionByName(rows)
    return out


def pair_set(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    """Raw frequencies, and (ids, label) of the pairs; the attribute is named by its domain."""
    raw = stored(profile.frequencies(_melted(spark, sf_dir, raw_frame)))
    after = quality.truth(profile.frequencies(_melted(spark, sf_dir, changed_frame))).select(*pairs.ID, "quality")
    met = quality.truth(raw).select(*pairs.ID)
    names = raw.select("dataset", "attr").distinct()
    a, b = (names.select(F.col("dataset").alias(f"{p}_dataset"), F.col("attr").alias(f"{p}_attr")) for p in ("ref", "cand"))
    same = a.join(b, F.col("ref_attr") == F.col("cand_attr")).where("ref_dataset <> cand_dataset")
    return raw, same.join(met, list(pairs.ID), "left_anti").join(after, list(pairs.ID), "left").select(*pairs.ID, F.coalesce("quality", F.lit(0)).alias("label"))


def _sql() -> str:
    clean = lambda v: f"trim(regexp_replace({normalize.sql_lowered(v)}, '{normalize.NOT_WORD}', ' ', 'g'))"
    raw, after = [], []
    for c in COLUMNS:
        head = f"SELECT '{c.dataset}' AS dataset, '{c.domain}' AS attr"
        if c.recipe == "unwind":
            raw.append(f"{head}, string_agg(DISTINCT p_brand, '; ' ORDER BY p_brand) AS value FROM part GROUP BY p_type")
            after.append(f"{head}, {clean('p_brand')} AS value FROM part")
            continue
        raw.append(f"{head}, {c.value} AS value FROM {c.table} WHERE {c.kept}")
        mapped = c.value if c.recipe == "clean" else "r_name" if c.domain == "region" else f"CASE o_orderstatus {' '.join(f"WHEN '{k}' THEN '{v}'" for k, v in _WORDS.items())} ELSE o_orderstatus END"
        after.append(f"{head}, {clean(mapped)} AS value FROM {c.table} WHERE {c.kept}")
    met = lambda t: f"SELECT a.dataset AS ref_dataset, b.dataset AS cand_dataset, count(*) AS n FROM {t} a JOIN {t} b ON a.value = b.value AND a.attr = b.attr AND a.dataset <> b.dataset GROUP BY ALL"
    return f"""WITH raw AS (SELECT DISTINCT * FROM ({' UNION ALL '.join(raw)}) x WHERE value IS NOT NULL), after AS (SELECT DISTINCT * FROM ({' UNION ALL '.join(after)}) y WHERE value IS NOT NULL),
names AS (SELECT DISTINCT dataset, attr FROM raw), card AS (SELECT dataset, count(*) AS card FROM after GROUP BY ALL), rm AS ({met('raw')}), am AS ({met('after')}),
same AS (SELECT a.dataset AS ref_dataset, a.attr AS ref_attr, b.dataset AS cand_dataset, b.attr AS cand_attr FROM names a JOIN names b ON a.attr = b.attr AND a.dataset <> b.dataset),
lone AS (SELECT s.* FROM same s LEFT JOIN rm USING (ref_dataset, cand_dataset) WHERE rm.n IS NULL),
lab AS (SELECT l.*, CAST(coalesce({_CLASS.format(c='CAST(am.n AS DOUBLE) / x.card', k='(CAST(x.card AS DOUBLE) / y.card)')}, 0) AS INT) AS label FROM lone l LEFT JOIN am USING (ref_dataset, cand_dataset) LEFT JOIN card x ON x.dataset = ref_dataset LEFT JOIN card y ON y.dataset = cand_dataset)"""


@query("nonsyntactic_pairs", lambda: f"{_sql()} SELECT * FROM lab")
def nonsyntactic(spark, sf_dir):
    """Pairs that join only after a transformation, with their true class."""
    return pair_set(spark, sf_dir)[1]


@query("nonsyntactic_classes", lambda: f"{_sql()} SELECT label, CAST(count(*) AS BIGINT) AS n FROM lab GROUP BY ALL")
def nonsyntactic_classes(spark, sf_dir):
    return nonsyntactic(spark, sf_dir).groupBy("label").agg(F.count(F.lit(1)).alias("n"))


def predicted(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The pairs with label and the class that independent forests give their raw profiles."""
    c = context(spark, sf_dir)
    raw, labelled = pair_set(spark, sf_dir)
    profiles = stored(profile.string_attributes(profile.profiles(raw)))
    # names that say nothing stand for the domains, which would give the answer away
    unnamed = profiles.withColumn("attr", F.concat(F.lit("c"), F.substring(F.md5("dataset"), 1, 6)))
    found = discover.predict(discover.vectors(unnamed, unnamed, small_ref=False), c.unchained).select("ref_dataset", "cand_dataset", "pred_class")
    return labelled.join(found, ["ref_dataset", "cand_dataset"])


@query("nonsyntactic_confusion")
def nonsyntactic_confusion(spark, sf_dir):
    return metrics.confusion(predicted(spark, sf_dir))


@query("nonsyntactic_share")
def nonsyntactic_share(spark, sf_dir):
    """Share predicted in classes 1 to 3, over all pairs and over those truly joinable after the transformation."""
    cm = stored(nonsyntactic_confusion(spark, sf_dir))
    over = lambda name, **kw: metrics.share_predicted(cm, **kw).select(F.lit(name).alias("over"), "*")
    return over("all").unionByName(over("joinable", truth=(1, 2, 3, 4)))
