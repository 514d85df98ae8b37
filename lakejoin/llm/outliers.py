"""Quality rules: robust multivariate outliers by minimum covariance determinants.

Base counts decide first (``base_failed``). The other texts become vectors of transformed statistics: logarithm of
the mean word length, square roots of the rates of capitals, of symbols and of other punctuation, and half the
shares of repeated lines and of words in repeated runs (a line or two that frame a text are no fault). For each
language and source a minimum-covariance-determinant estimate is found over all its rows: two deterministic starts
(coordinate-wise distances; correlation of hyperbolic tangents), then concentration steps, each keeping the share
``SUBSET`` of least Mahalanobis distance, until the determinants settle; the start with the lesser determinant wins and
is estimated once more from all rows within its own 97.5 % bound. Distances are scaled so that their median is that of the
chi-square law, and a vector beyond the ``LEVEL`` normal quantile of that law is rejected.

Groups of every size go by one rule: an estimate is made for all rows, one for each language, and one for each language and
source, and each counts ``PRIOR`` rows of the estimate above it beside its own (medians, spreads, moments and the scale
alike). So a group of a few rows leans on its language, a large one on itself, and every row is judged. Every
coordinate's variance is at least ``FLOOR`` squared, so a constant statistic doesn't make trifles into outliers.

Rows stay distributed: a step is one pass over a table of six numbers a document. Quantiles come from counts in fixed bins
(``FINE`` to the unit, ``COARSE`` to the factor e for distances), which add up in any order, so a source of any size spreads
over all tasks, no task holds more of a group than its bins, and reruns agree.

Null, empty and short texts fail the base rule. Null languages and sources are groups of their own. Repeated rows
and ties count each for itself and fare alike. A table without a row that passes the base rule needs no estimate.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import documents, map_rows, stored

MIN_WORDS, MOST_REPEATED = 50, 0.5
P, SUBSET, FLOOR = 6, 0.75, 0.06
#: Rows of the estimate above that each estimate counts beside its own; most concentration steps, and the change of a log determinant at which they end.
PRIOR, STEPS, SETTLED = 50.0, 8, 1e-3
#: Bins to the unit of a statistic and to the factor e of a distance.
FINE, COARSE = 1024, 128
#: One-sided level of the cut, in standard deviations of a normal variable.
LEVEL = 3.0
_SYMBOLS = np.frombuffer(b"#*$%&|<>", np.uint8)
_OTHER = np.array([c for c in range(33, 127) if not chr(c).isalnum() and c not in _SYMBOLS.tolist()])


def chi_square(level: float, p: int = P) -> float:
    """Wilson and Hilferty's quantile at a normal quantile."""
    return p * (1 - 2 / (9 * p) + level * (2 / (9 * p)) ** 0.5) ** 3


def statistics(text: str | None) -> tuple:
    """n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words and the vector."""
    text = text or ""
    raw = text.encode("utf-8", "replace")
    words = raw.split()
    n = len(words)
    count = np.bincount(np.frombuffer(raw, np.uint8), minlength=256)
    chars = len(text) - int(count[9:14].sum() + count[32])
    symbols = int(count[_SYMBOLS].sum())
    lines = [x for x in raw.split(b"\n") if x.strip(b" \t\r\x0b\x0c")]
    again = len(lines) - len(set(lines))
    repeated = 0
    if n > 3:
        runs = list(zip(words, words[1:], words[2:]))
        if len(set(runs)) < len(runs):
            seen: dict = {}
            for i, r in enumerate(runs):
                seen.setdefault(r, []).append(i)
            hit = np.zeros(n, bool)
            for at in seen.values():
                if len(at) > 1:
                    for i in at:
                        hit[i : i + 3] = True
            repeated = int(hit.sum())
    each = max(1, chars)
    vector = [
        float(np.log(each / max(1, n))),
        float(np.sqrt(count[65:91].sum() / each)),
        float(np.sqrt(symbols / each)),
        float(np.sqrt(count[_OTHER].sum() / each)),
        0.5 * again / max(1, len(lines)),
        0.5 * repeated / max(1, n),
    ]
    return n, chars, symbols, again, repeated, vector


_COUNTS = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")


def measured(docs: DataFrame) -> DataFrame:
    """(doc_id, lang, source, counts, x0..x5, base_failed)"""

    def rows(part: dict) -> dict:
        got = [statistics(t) for t in part["text"]]
        out = {n: part[n] for n in ("doc_id", "lang", "source")} | {n: [g[i] for g in got] for i, n in enumerate(_COUNTS)}
        return out | {f"x{j}": [g[5][j] for g in got] for j in range(P)}

    ddl = "doc_id bigint, lang string, source string, " + ", ".join(f"{n} bigint" for n in _COUNTS) + ", " + ", ".join(f"x{j} double" for j in range(P))
    table = map_rows(docs.select("doc_id", "lang", "source", "text"), rows, ddl)
    return table.withColumn("base_failed", (F.col("n_words") < MIN_WORDS) | (100 * F.col("n_repeat_words") > int(100 * MOST_REPEATED) * F.col("n_words")))


def _groups(rows: DataFrame) -> DataFrame:
    """Adds ``own`` (language and source) and ``wide`` (language), the names of the groups of a row."""
    tag = lambda c: F.coalesce(F.concat(F.lit("="), F.col(c)), F.lit("0"))
    return rows.withColumn("own", F.concat_ws("\x1f", F.lit("s"), tag("lang"), tag("source"))).withColumn("wide", F.concat_ws("\x1f", F.lit("l"), tag("lang")))


def _leant(found: DataFrame, tree: DataFrame) -> DataFrame:
    """(g, n, v) from sums (g, s) of a group's rows, the first being their weight: means that lean on the group above."""
    mean = lambda up: F.coalesce(F.transform(F.col("s"), lambda x, i: (x + PRIOR * F.get(up, i)) / (F.get("s", F.lit(0)) + PRIOR)), up)
    placed = tree.join(found, "g", "left")
    top = placed.where("level = 0").select("g", "n", F.transform("s", lambda x: x / F.greatest(F.get("s", F.lit(0)), F.lit(1e-9))).alias("v"))
    mid = placed.where("level = 1").join(top.select(F.col("g").alias("above"), F.col("v").alias("up")), "above").select("g", "n", mean(F.col("up")).alias("v"))
    low = placed.where("level = 2").join(mid.select(F.col("g").alias("above"), F.col("v").alias("up")), "above").select("g", "n", mean(F.col("up")).alias("v"))
    return stored(top.union(mid).union(low))


def _quantiles(binned: DataFrame, share: float) -> DataFrame:
    """(g, j, bin): the least bin up to which at least ``share`` of the rows (g, j, bin) of each g and j lie."""
    counts = binned.groupBy("g", "j", "bin").agg(F.count(F.lit(1)).alias("c"))
    by = Window.partitionBy("g", "j")
    ranked = counts.withColumn("upto", F.sum("c").over(by.orderBy("bin"))).withColumn("all", F.sum("c").over(by))
    return ranked.where(F.col("upto") >= share * F.col("all")).groupBy("g", "j").agg(F.min("bin").alias("bin"))


def _medians(values: DataFrame, tree: DataFrame) -> DataFrame:
    """(g, v): medians, leant, of columns y0.. of (g, y0, ..)."""
    each = F.explode(F.array(*[F.struct(F.lit(j).alias("j"), F.floor(F.col(f"y{j}") * FINE).cast("int").alias("bin")) for j in range(P)]))
    mid = _quantiles(values.select("g", each.alias("b")).select("g", "b.j", "b.bin"), 0.5)
    row = mid.groupBy("g").agg(*[F.max(F.when(F.col("j") == j, (F.col("bin") + 0.5) / FINE)).alias(f"q{j}") for j in range(P)])
    weighed = row.join(tree.select("g", "n"), "g").select("g", F.array(F.col("n").cast("double"), *[F.col("n") * F.col(f"q{j}") for j in range(P)]).alias("s"))
    return _leant(weighed, tree).select("g", F.slice("v", 2, P).alias("v"))


def _bin(d: F.Column) -> F.Column:
    return F.floor(F.log(d + 1e-4) * COARSE).cast("int")


def _square(names: list[str], state: str) -> F.Column:
    """Mahalanobis distance of columns under the centre and inverse in ``state`` (arrays)."""
    total, d = F.lit(0.0), [F.col(n) - F.col(f"{state}_m")[i] for i, n in enumerate(names)]
    for i in range(P):
        for j in range(i, P):
            total = total + (1 if i == j else 2) * d[i] * d[j] * F.col(f"{state}_v")[i * P + j]
    return total


def _solve(means: pd.Series) -> pd.DataFrame:
    """Centre, inverse and log determinant from the means of each group (1, P means, upper triangle of products)."""
    out = []
    for s in means:
        m, cov = np.array(s[1 : P + 1]), np.zeros((P, P))
        cov[np.triu_indices(P)] = np.array(s[P + 1 :])
        cov = cov + np.triu(cov, 1).T - np.outer(m, m)
        cov[np.diag_indices(P)] += FLOOR**2
        out.append({"m": m.tolist(), "v": np.linalg.inv(cov).ravel().tolist(), "det": float(np.linalg.slogdet(cov)[1])})
    return pd.DataFrame(out, columns=["m", "v", "det"])


def _sums(names: list[str], use: F.Column) -> F.Column:
    kept = lambda c: F.coalesce(F.sum(F.when(use, c)), F.lit(0.0))
    xs = [F.col(n) for n in names]
    return F.array(kept(F.lit(1.0)), *[kept(x) for x in xs], *[kept(xs[i] * xs[j]) for i in range(P) for j in range(i, P)])


NAMES = [f"x{j}" for j in range(P)]


def _starts(rows: DataFrame, tree: DataFrame) -> DataFrame:
    """(g, a_m, a_v, a_det, b_m, b_v, b_det): both starts of each group."""
    centre = _medians(rows.select("g", *[F.col(n).alias(f"y{j}") for j, n in enumerate(NAMES)]), tree)
    off = rows.join(centre, "g").select("g", *[F.abs(F.col(n) - F.col("v")[j]).alias(f"y{j}") for j, n in enumerate(NAMES)])
    spread = _medians(off, tree).select("g", F.transform("v", lambda x: F.sqrt((1.4826 * x) ** 2 + FLOOR**2)).alias("s"))
    scale = stored(centre.join(spread, "g"))
    bent = [F.tanh((F.col(n) - F.col("v")[j]) / F.col("s")[j]) for j, n in enumerate(NAMES)]
    sums = rows.join(scale, "g").groupBy("g").agg(F.array(F.count(F.lit(1)).cast("double"), *[F.sum(bent[i] * bent[j]) for i in range(P) for j in range(i, P)]).alias("s"))
    products = _leant(sums, tree).select("g", F.slice("v", 2, P * (P + 1) // 2).alias("c"))

    @F.pandas_udf("a_v array<double>, b_v array<double>")
    def inverses(c: pd.Series, s: pd.Series) -> pd.DataFrame:
        out = []
        for cs, ss in zip(c, s):
            cor = np.zeros((P, P))
            cor[np.triu_indices(P)] = cs
            cor = cor + np.triu(cor, 1).T
            d = np.sqrt(np.maximum(np.diag(cor), 1e-6))
            cor = 0.95 * cor / np.outer(d, d) + 0.05 * np.eye(P)
            ss = np.array(ss)
            out.append({"a_v": np.diag(1 / ss**2).ravel().tolist(), "b_v": np.linalg.inv(cor * np.outer(ss, ss)).ravel().tolist()})
        return pd.DataFrame(out, columns=["a_v", "b_v"])

    both = products.join(scale, "g").select("g", "v", inverses("c", "s").alias("i"))
    none = F.lit(0.0)
    return stored(both.select("g", F.col("v").alias("a_m"), F.col("i.a_v").alias("a_v"), none.alias("a_det"), F.col("v").alias("b_m"), F.col("i.b_v").alias("b_v"), none.alias("b_det")))


def _scaled(rows: DataFrame, state: DataFrame, tree: DataFrame) -> DataFrame:
    """(g, e_m, e_v, scale): the factor that brings the median distance to that of the chi-square law."""
    half = _quantiles(rows.join(state, "g").select("g", F.lit(0).alias("j"), _bin(_square(NAMES, "e")).alias("bin")), 0.5)
    weighed = half.join(tree.select("g", "n"), "g").select("g", F.array(F.col("n").cast("double"), F.col("n") * F.exp((F.col("bin") + 0.5) / COARSE)).alias("s"))
    middle = _leant(weighed, tree).select("g", F.col("v")[1].alias("half"))
    return stored(state.join(middle, "g").select("g", "e_m", "e_v", (chi_square(0.0) / F.greatest(F.col("half"), F.lit(chi_square(0.0)))).alias("scale")))


def estimates(measured_rows: DataFrame) -> DataFrame:
    """(g, e_m, e_v, scale): centre, inverse covariance and factor of distances, from rows (own, wide, x0..x5)."""
    sizes = stored(measured_rows.groupBy("own", "wide").agg(F.count(F.lit(1)).alias("n")))
    tree = stored(
        sizes.select(F.col("own").alias("g"), F.col("wide").alias("above"), F.lit(2).alias("level"), "n")
        .union(sizes.groupBy("wide").agg(F.sum("n").alias("n")).select("wide", F.lit("all"), F.lit(1), "n"))
        .union(sizes.agg(F.sum("n").alias("n")).where("n is not null").select(F.lit("all"), F.lit(""), F.lit(0), "n"))
    )
    rows = stored(measured_rows.select(F.explode(F.array("own", "wide", F.lit("all"))).alias("g"), *NAMES))
    state, solved = _starts(rows, tree), F.pandas_udf(_solve, "m array<double>, v array<double>, det double")
    dets = None
    for _ in range(STEPS):
        far = rows.join(state, "g").select("g", *NAMES, _square(NAMES, "a").alias("da"), _square(NAMES, "b").alias("db"))
        each = F.explode(F.array(*[F.struct(F.lit(j).alias("j"), _bin(F.col(d)).alias("bin")) for j, d in enumerate(("da", "db"))]))
        edges = _quantiles(far.select("g", each.alias("b")).select("g", "b.j", "b.bin"), SUBSET)
        cut = stored(edges.groupBy("g").agg(*[F.max(F.when(F.col("j") == j, F.col("bin"))).alias(f"q{d}") for j, d in enumerate(("da", "db"))]))
        near = stored(far.join(cut, "g").groupBy("g").agg(*[_sums(NAMES, _bin(F.col(d)) <= F.col(f"q{d}")).alias(f"s{d}") for d in ("da", "db")]))
        a, b = (_leant(near.select("g", F.col(f"s{d}").alias("s")), tree).select("g", F.col("v").alias(d)) for d in ("da", "db"))
        both = a.join(b, "g").select("g", solved("da").alias("a"), solved("db").alias("b"))
        state = stored(both.select("g", *[F.col(f"{k}.{f}").alias(f"{k}_{f}") for k in "ab" for f in ("m", "v", "det")]))
        now = state.agg(F.sum("a_det"), F.sum("b_det"), F.count(F.lit(1))).first()
        if dets is not None and now[2] and max(abs(now[0] - dets[0]), abs(now[1] - dets[1])) <= SETTLED * now[2]:
            break
        dets = now
    better = F.col("a_det") <= F.col("b_det")
    first = stored(state.select("g", F.when(better, F.col("a_m")).otherwise(F.col("b_m")).alias("e_m"), F.when(better, F.col("a_v")).otherwise(F.col("b_v")).alias("e_v")))
    inside = rows.join(_scaled(rows, first, tree), "g").where(_square(NAMES, "e") * F.col("scale") <= chi_square(1.96)).groupBy("g").agg(_sums(NAMES, F.lit(True)).alias("s"))
    again = _leant(inside, tree).select("g", solved("v").alias("e")).select("g", F.col("e.m").alias("e_m"), F.col("e.v").alias("e_v"))
    return _scaled(rows, stored(again), tree)


def judged(docs: DataFrame) -> DataFrame:
    """Counts, ``distance`` (squared; null where the base rule failed), ``base_failed`` and ``kept`` of every document."""
    rows = stored(_groups(measured(docs)))
    found = estimates(rows.where("not base_failed").select("own", "wide", *NAMES)).withColumnRenamed("g", "own")
    far = rows.join(found, "own", "left").withColumn("distance", F.when(~F.col("base_failed"), _square(NAMES, "e") * F.col("scale")))
    return far.withColumn("kept", ~F.col("base_failed") & (F.coalesce("distance", F.lit(0.0)) <= chi_square(LEVEL)))


def op1_robust_outliers(spark: SparkSession, sf_dir: str) -> DataFrame:
    return judged(documents(spark, sf_dir)).select("doc_id", *_COUNTS, "base_failed", "kept", "distance")
