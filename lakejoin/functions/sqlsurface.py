"""SQL functions that Catalyst inlines, pandas cross-checks, a grouped aggregate and table functions."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from ..session import ship
from . import normalize, valuetypes


def _lit(p: str) -> str:
    return "r'" + p + "'"


def register(spark: SparkSession) -> list[str]:
    """Create ``join_quality``, ``name_distance``, ``clean_text``, ``broad_type`` and ``specific_type`` for SQL."""
    n = f"trim(translate(lower(s), '{normalize.ACCENTED}', '{normalize.PLAIN}'))"
    like = lambda p: f"regexp_like({n}, {_lit(p)})"
    bodies = {
        "join_quality(c DOUBLE, k DOUBLE) RETURNS INT": "CASE WHEN c >= 0.75D AND k >= 1/4D THEN 4 WHEN c >= 0.5D AND k >= 1/8D THEN 3 WHEN c >= 0.25D AND k >= 1/12D THEN 2 WHEN c >= 0.1D THEN 1 ELSE 0 END",
        "name_distance(a STRING, b STRING) RETURNS DOUBLE": "CASE WHEN greatest(length(a), length(b)) = 0 THEN 0D ELSE levenshtein(a, b) / greatest(length(a), length(b)) END",
        "clean_text(s STRING) RETURNS STRING": f"trim(regexp_replace({n}, {_lit(normalize.NOT_WORD)}, ' '))",
        "broad_type(s STRING) RETURNS STRING": f"CASE WHEN {like(valuetypes.DATETIME)} THEN 'datetime' WHEN {like(valuetypes.NUMERIC)} THEN 'numeric' WHEN {like(valuetypes.ALPHABETIC)} THEN 'alphabetic' WHEN {like(valuetypes.ALPHANUMERIC)} THEN 'alphanumeric' ELSE 'nonalphanumeric' END",
        "specific_type(s STRING) RETURNS STRING": f"CASE WHEN {like(valuetypes.EMAIL)} THEN 'email' WHEN {like(valuetypes.URL)} THEN 'url' WHEN {like(valuetypes.IP)} THEN 'ip' "
        f"WHEN {like(valuetypes.PHONE)} AND length(regexp_replace({n}, '[^0-9]', '')) BETWEEN 7 AND 15 AND NOT {like(valuetypes.DATETIME)} THEN 'phone' WHEN length({n}) < {valuetypes.SHORT} THEN 'username' ELSE 'phrases' END",
    }
    for head, body in bodies.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {head} RETURN {body}")
    return [h.partition("(")[0] for h in bodies]


def levenshtein(a: str, b: str) -> int:
    row = list(range(len(b) + 1))
    for i, x in enumerate(a, 1):
        last, row[0] = row[0], i
        for j, y in enumerate(b, 1):
            last, row[j] = row[j], min(row[j] + 1, row[j - 1] + 1, last + (x != y))
    return row[-1]


def name_distance_pandas(spark: SparkSession):
    """Vectorised Python form of ``name_distance``; it exists to cross-check the built-in one."""
    ship(spark)

    @F.pandas_udf("double")
    def distance(a: pd.Series, b: pd.Series) -> pd.Series:
        return pd.Series([levenshtein(x, y) / max(len(x), len(y)) if x or y else 0.0 for x, y in zip(a, b)], dtype="float64")

    return distance


def bands_udtf():
    """Table function: rows (band, key) of a signature cut into ``b`` bands of ``r`` minima."""
    from pyspark.sql.functions import udtf

    @udtf(returnType="band: int, key: string")
    class Bands:
        def eval(self, signature: list, b: int, r: int):
            for i in range(b):
                yield i, "-".join(map(str, signature[i * r : (i + 1) * r]))

    return Bands


def minhash_udaf(spark: SparkSession, m: int = 8):
    """Grouped aggregate: the first ``m`` minima of the permuted hashes of a group's values; it cross-checks the built-in form."""
    from hashlib import md5

    from ..operators.size_lsh import PERMUTATIONS, PRIME

    ship(spark)
    chosen = PERMUTATIONS[:m]

    @F.pandas_udf("array<bigint>")
    def minima(values: pd.Series) -> list:
        h = [int(md5(v.encode()).hexdigest()[:15], 16) % PRIME for v in values.dropna().unique()]
        return [min((a * x + b) % PRIME for x in h) for a, b in chosen] if h else []

    return minima


def register_discovery(spark: SparkSession, predicted, name: str = "discover_joins") -> str:
    """SQL table function ``discover_joins(dataset, attr)`` over predictions of all pairs: best class first. The predictions may be a
    lazy frame; the two names are pushed down to its reference side."""
    view = f"{name}_pairs"
    predicted.createOrReplaceTempView(view)
    spark.sql(
        f"CREATE OR REPLACE TEMPORARY FUNCTION {name}(d STRING, a STRING) RETURNS TABLE (cand_dataset STRING, cand_attr STRING, pred_class INT, score DOUBLE) "
        f"RETURN SELECT cand_dataset, cand_attr, pred_class, score FROM {view} WHERE ref_dataset = d AND ref_attr = a AND pred_class >= 1"
    )
    return name
