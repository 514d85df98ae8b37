"""Cleaning of values before syntax is looked at; built-in expressions only."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

#: Accented Latin letters and what they become.
ACCENTED, PLAIN = "àáâãäåçèéêëìíîïñòóôõöùúûüýÿ", "aaaaaaceeeeiiiinooooouuuuyy"
NOT_WORD, NOT_TEXT = r"[^\p{L}\p{N}]+", r"[^\p{L}\p{N}\s]+"


def lowered(v: Column) -> Column:
    """Lower case, accents off, outer blanks off."""
    return F.trim(F.translate(F.lower(v), ACCENTED, PLAIN))


def clean_text(v: Column, strip_symbols: bool = True) -> Column:
    n = lowered(v)
    return F.trim(F.regexp_replace(n, NOT_WORD, " ")) if strip_symbols else n


def tokens(n: Column) -> Column:
    """Words of an already lowered value."""
    return F.filter(F.split(F.regexp_replace(n, NOT_WORD, " "), " "), lambda w: w != "")


def char_length(n: Column) -> Column:
    """Characters of a lowered value without its symbols."""
    return F.length(F.regexp_replace(n, NOT_TEXT, ""))


def sql_lowered(v: str) -> str:
    return f"trim(translate(lower({v}), '{ACCENTED}', '{PLAIN}'))"
