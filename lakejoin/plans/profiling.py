"""Queries on profiles. Doubles are rounded to six places on both sides."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..functions import normalize, valuetypes
from ..operators import profile, scaling
from ..sources import derived, lake
from .context import context
from .registry import query

_P = valuetypes.SPECIFIC
_SHARE = lambda col, t, side: f"CAST(sum(CASE WHEN {col} = '{t}' THEN cnt ELSE 0 END) AS BIGINT) AS {side}_{t}"


def _dominant(side: str, names: tuple[str, ...]) -> str:
    top = f"greatest({', '.join(f'{side}_{t}' for t in names)})"
    return f"CASE {' '.join(f"WHEN {side}_{t} = {top} THEN '{t}'" for t in names)} END"


#: CTEs melted, freq, vals and prof: the same profile, written for DuckDB.
PROFILE_SQL = f"""{derived.duckdb_melted()},
low AS (SELECT *, {normalize.sql_lowered('value')} AS n FROM freq),
vals AS (SELECT dataset, attr, value, cnt, {valuetypes.sql_broad('n')} AS broad, {valuetypes.sql_specific('n')} AS specific,
  length(regexp_replace(n, '{normalize.NOT_TEXT}', '', 'g')) AS chars,
  len(list_filter(string_split(regexp_replace(n, '{normalize.NOT_WORD}', ' ', 'g'), ' '), lambda w: w <> '')) AS n_words FROM low),
agg AS (SELECT dataset, attr, CAST(sum(cnt) AS BIGINT) AS n_rows, CAST(coalesce(sum(cnt) FILTER (value IS NOT NULL), 0) AS BIGINT) AS n_nonnull FROM vals GROUP BY ALL),
seen AS (SELECT dataset, attr, count(*) AS cardinality, sum(cnt * log2(cnt)) AS clogc, avg(cnt) AS freq_avg, min(cnt) AS freq_min, max(cnt) AS freq_max, stddev_pop(cnt) AS freq_sd,
  quantile_cont(cnt, [0.125, 0.25, 0.375, 0.5, 0.625, 0.75, 0.875]) AS oct, max(chars) AS len_max, min(chars) AS len_min, sum(chars * cnt) AS chars,
  CAST(sum(n_words * cnt) AS BIGINT) AS words_total, min(n_words) AS words_min, max(n_words) AS words_max, CAST(sum(n_words * n_words * cnt) AS DOUBLE) AS words2,
  {', '.join(_SHARE('broad', t, 'b') for t in valuetypes.BROAD)}, {', '.join(_SHARE('specific', t, 's') for t in valuetypes.SPECIFIC)}
  FROM vals WHERE value IS NOT NULL GROUP BY ALL),
prof AS (SELECT a.dataset, a.attr, n_rows, n_nonnull, coalesce(cardinality, 0) AS cardinality, cardinality / n_nonnull AS uniqueness, (n_rows - n_nonnull) / n_rows AS incompleteness,
  log2(n_nonnull) - clogc / n_nonnull AS entropy, freq_avg, freq_min, freq_max, freq_sd, list_transform(oct, lambda q: q / n_nonnull) AS octiles,
  freq_min / n_nonnull AS pct_min, freq_max / n_nonnull AS pct_max, freq_sd / n_nonnull AS pct_sd, freq_max / n_rows AS constancy,
  {_dominant('b', valuetypes.BROAD)} AS data_type, {_dominant('s', valuetypes.SPECIFIC)} AS specific_type,
  {', '.join(f'b_{t} / n_nonnull AS share_{t}' for t in valuetypes.BROAD)}, {', '.join(f's_{t} / n_nonnull AS share_{t}' for t in valuetypes.SPECIFIC)},
  len_max, len_min, chars / n_nonnull AS len_avg, words_total, words_total / n_nonnull AS words_avg, words_min, words_max,
  sqrt(greatest(words2 / n_nonnull - (words_total / n_nonnull) * (words_total / n_nonnull), 0.0)) AS words_sd
  FROM agg a LEFT JOIN seen s ON a.dataset = s.dataset AND a.attr = s.attr),
strs AS (SELECT * FROM prof WHERE data_type IS NOT NULL AND data_type NOT IN ('numeric', 'datetime') AND specific_type <> 'phone')"""

_DOUBLES = {"uniqueness", "incompleteness", "entropy", "freq_avg", "freq_sd", "pct_min", "pct_max", "pct_sd", "constancy", "len_avg", "words_avg", "words_sd", *(f"share_{t}" for t in (*valuetypes.BROAD, *valuetypes.SPECIFIC))}


def _columns(name: str, cols: list[str]) -> None:
    """Register a query of some profile columns."""

    def run(spark, sf_dir):
        return context(spark, sf_dir).profiles.select("dataset", "attr", *[F.round(c, 6).alias(c) if c in _DOUBLES else F.col(c).cast("bigint").alias(c) if c not in ("data_type", "specific_type") else F.col(c) for c in cols])

    picked = ", ".join(f"round({c}, 6) AS {c}" if c in _DOUBLES else f"CAST({c} AS BIGINT) AS {c}" if c not in ("data_type", "specific_type") else c for c in cols)
    query(name, f"{PROFILE_SQL} SELECT dataset, attr, {picked} FROM prof")(run)


_columns("profile_cardinality", ["n_rows", "n_nonnull", "cardinality", "uniqueness", "incompleteness"])
_columns("profile_entropy", ["entropy"])
_columns("profile_frequency", ["freq_avg", "freq_min", "freq_max", "freq_sd", "pct_min", "pct_max", "pct_sd"])
_columns("profile_constancy", ["constancy"])
_columns("profile_lengths", ["len_max", "len_min", "len_avg"])
_columns("profile_words", ["words_total", "words_avg", "words_min", "words_max", "words_sd"])
_columns("profile_broad_types", ["data_type", *(f"share_{t}" for t in valuetypes.BROAD)])
_columns("profile_specific_types", ["specific_type", *(f"share_{t}" for t in valuetypes.SPECIFIC)])
_columns("profile_full", ["n_rows", "n_nonnull", "cardinality", *sorted(_DOUBLES), "freq_min", "freq_max", "len_max", "len_min", "words_total", "words_min", "words_max", "data_type", "specific_type"])


@query("profile_octiles", f"{PROFILE_SQL} SELECT dataset, attr, CAST(k AS INT) AS k, round(octiles[k], 6) AS octile FROM prof, range(1, 8) r(k) WHERE octiles IS NOT NULL")
def octiles(spark, sf_dir):
    return context(spark, sf_dir).profiles.where("octiles is not null").select("dataset", "attr", F.posexplode("octiles").alias("k", "octile")).select("dataset", "attr", (F.col("k") + 1).alias("k"), F.round("octile", 6).alias("octile"))


@query(
    "profile_top_words",
    f"""{derived.duckdb_melted()}, w AS (SELECT dataset, attr, cnt, unnest(list_filter(string_split(regexp_replace({normalize.sql_lowered('value')}, '{normalize.NOT_WORD}', ' ', 'g'), ' '), lambda w: w <> '')) AS word FROM freq WHERE value IS NOT NULL),
s AS (SELECT dataset, attr, word, CAST(sum(cnt) AS BIGINT) AS weight FROM w GROUP BY ALL), r AS (SELECT *, CAST(row_number() OVER (PARTITION BY dataset, attr ORDER BY weight DESC, word) AS INT) AS place FROM s) SELECT * FROM r WHERE place <= 10""",
)
def top_words(spark, sf_dir):
    return profile.top_words(context(spark, sf_dir).freq)


@query("profile_top_values", f"{derived.duckdb_melted()}, r AS (SELECT dataset, attr, value AS word, cnt AS weight, CAST(row_number() OVER (PARTITION BY dataset, attr ORDER BY cnt DESC, value) AS INT) AS place FROM freq WHERE value IS NOT NULL) SELECT * FROM r WHERE place <= 10")
def top_values(spark, sf_dir):
    return profile.top_words(context(spark, sf_dir).freq, unit="value")


def soundex_sql(w: str) -> str:
    """Phonetic code of a lower-case word: the first letter, then three digits of the letters after it; h and w are passed over, letters of
    one digit in a row count once, and anything but a letter parts them. A word that begins otherwise is its own code."""
    letters, digits = "abcdefgijklmnopqrstuvxyz", "012301202245501262301202"  # fixed values: consonant groups; vowels are 0
    lone = f"CASE WHEN substr({w}, 1, 1) IN ('h', 'w') THEN '7' ELSE translate(substr({w}, 1, 1), '{letters}', '{digits}') END"
    rest = f"translate(regexp_replace(regexp_replace(substr({w}, 2), '[hw]', '', 'g'), '[^a-z]', '0', 'g'), '{letters}', '{digits}')"
    run = f"({lone} || {rest})"
    for d in "123456":
        run = f"regexp_replace({run}, '{d}+', '{d}', 'g')"
    return f"CASE WHEN regexp_matches({w}, '^[a-z]') THEN upper(substr({w}, 1, 1)) || rpad(substr(replace(substr({run}, 2), '0', ''), 1, 3), 3, '0') ELSE {w} END"


@query(
    "profile_soundex",
    f"""{derived.duckdb_melted()}, w AS (SELECT dataset, attr, cnt, unnest(list_filter(string_split(regexp_replace({normalize.sql_lowered('value')}, '{normalize.NOT_WORD}', ' ', 'g'), ' '), lambda w: w <> '')) AS word FROM freq WHERE value IS NOT NULL),
s AS (SELECT dataset, attr, word, sum(cnt) AS weight FROM w GROUP BY ALL), r AS (SELECT *, row_number() OVER (PARTITION BY dataset, attr ORDER BY weight DESC, word) AS place FROM s),
x AS (SELECT dataset, attr, {soundex_sql('word')} AS sound, min(place) AS place FROM r WHERE place <= 10 GROUP BY ALL)
SELECT dataset, attr, CAST(row_number() OVER (PARTITION BY dataset, attr ORDER BY place) - 1 AS INT) AS place, sound FROM x""",
)
def soundex(spark, sf_dir):
    return context(spark, sf_dir).profiles.select("dataset", "attr", F.posexplode("top_soundex").alias("place", "sound"))


@query("profile_simpson", f"{derived.duckdb_melted()}, t AS (SELECT dataset, attr, sum(cnt) AS n FROM freq WHERE value IS NOT NULL GROUP BY ALL) SELECT f.dataset, f.attr, round(1 - CAST(sum(cnt * cnt) AS DOUBLE) / (any_value(n) * any_value(n)), 6) AS simpson FROM freq f JOIN t ON f.dataset = t.dataset AND f.attr = t.attr WHERE value IS NOT NULL GROUP BY ALL")
def simpson(spark, sf_dir):
    values = profile.value_table(context(spark, sf_dir).freq)
    return profile.statistics(values, entropy_kind="simpson").where("n_nonnull > 0").select("dataset", "attr", F.round("entropy", 6).alias("simpson"))


@query("string_gate", f"{PROFILE_SQL} SELECT dataset, attr, data_type, specific_type FROM strs")
def gate(spark, sf_dir):
    return context(spark, sf_dir).strings.select("dataset", "attr", "data_type", "specific_type")


_EXACT = ("n_rows", "n_nonnull", "len_max", "len_min", "words_total", "words_min", "words_max", "data_type", "specific_type")


@query("profile_sketch", f"{PROFILE_SQL} SELECT dataset, attr, {', '.join(c if c.endswith('_type') else f'CAST({c} AS BIGINT) AS {c}' for c in _EXACT)}, true AS near FROM prof")
def sketch(spark, sf_dir):
    """Approximate profiles: what is exact in them, and whether cardinality (within 8 %) and, where all values were counted, entropy and
    the largest count agree with the exact profile."""
    c = context(spark, sf_dir)
    about = profile.approximate(lake.derived_melted(spark, sf_dir))
    true = c.profiles.select("dataset", "attr", *[F.col(x).alias(f"_{x}") for x in ("cardinality", "entropy", "freq_max")])
    both = about.join(true, ["dataset", "attr"])
    within = lambda x, part: F.coalesce(F.abs(F.col(x) - F.col(f"_{x}")) <= part * F.abs(F.col(f"_{x}")) + 1e-6, F.lit(True))
    whole = F.col("cardinality") <= profile.SAMPLED
    near = within("cardinality", 0.08) & (~whole | within("entropy", 1e-6)) & (~whole | within("freq_max", 0.0))
    return both.select("dataset", "attr", *[F.col(x) if x.endswith("_type") else F.col(x).cast("bigint").alias(x) for x in _EXACT], near.alias("near"))


_UNPIVOT = lambda body: " UNION ALL ".join(f"SELECT dataset, attr, '{c}' AS feature, {body.format(c=c)} AS z FROM strs" for c in scaling.SCALED)


def _long(df):
    return df.select("dataset", "attr", F.explode(F.array(*[F.struct(F.lit(c).alias("feature"), F.round(f"z_{c}", 6).alias("z")) for c in scaling.SCALED])).alias("s")).select("dataset", "attr", "s.feature", "s.z")


@query("zscore", PROFILE_SQL + " " + _UNPIVOT("round(CASE WHEN stddev_pop({c}) OVER () > 0 THEN ({c} - avg({c}) OVER ()) / stddev_pop({c}) OVER () ELSE 0 END, 6)"))
def zscore(spark, sf_dir):
    return _long(context(spark, sf_dir).scaled)


@query("minmax", PROFILE_SQL + " " + _UNPIVOT("round(CASE WHEN max({c}) OVER () > min({c}) OVER () THEN ({c} - min({c}) OVER ()) / CAST(max({c}) OVER () - min({c}) OVER () AS DOUBLE) ELSE 0 END, 6)"))
def minmax(spark, sf_dir):
    strings = context(spark, sf_dir).strings
    return _long(scaling.apply_minmax(strings, scaling.fit_minmax(strings)))
