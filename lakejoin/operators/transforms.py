"""Transformations after which semantically related columns can be joined by value."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions import normalize
from . import quality


def clean(c: Column) -> Column:
    """Lower case, no accents, symbols to single blanks."""
    return normalize.clean_text(c)


def lookup(df: DataFrame, col: str, mapping: DataFrame) -> DataFrame:
    """Replace values by a dictionary (key, mapped); values it doesn't hold stay. Spark broadcasts it if it is small."""
    return df.join(mapping.select(F.col("key").alias(col), "mapped"), col, "left").withColumn(col, F.coalesce("mapped", col)).drop("mapped")


def unwind(df: DataFrame, col: str, sep: str | None = None) -> DataFrame:
    """One row an element of an array, of a map's keys, or of a string split at ``sep`` (taken literally)."""
    kind = df.schema[col].dataType
    items = F.map_keys(col) if isinstance(kind, T.MapType) else F.col(col) if isinstance(kind, T.ArrayType) else F.transform(F.split(col, r"\Q" + (sep or ";") + r"\E"), lambda x: F.trim(x))
    return df.withColumn(col, F.explode(items))


def approx_truth(freq: DataFrame, recipe: Column) -> DataFrame:
    """Quality of all pairs after ``recipe`` has been applied to every value."""
    changed = freq.withColumn("value", recipe).groupBy("dataset", "attr", "value").agg(F.sum("cnt").alias("cnt"))
    return quality.truth(changed)
