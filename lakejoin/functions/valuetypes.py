"""Data types of single values: five broad ones and six specific ones; the first that fits wins."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

#: Fixed patterns, on lowered values; the syntax is common to Java and RE2.
DATETIME = (
    r"^\d{4}-\d{1,2}-\d{1,2}([ t]\d{1,2}:\d{2}(:\d{2}([.]\d+)?)?(z|[+-]\d{2}:?\d{2})?)?$"
    r"|^\d{1,2}[/.-]\d{1,2}[/.-]\d{2,4}$"
    r"|^\d{1,2}:\d{2}(:\d{2})?$"
)
NUMERIC = r"^[+-]?(\d+|\d{1,3}(,\d{3})+)([.]\d+)?(e[+-]?\d+)?%?$"
ALPHABETIC = r"^\p{L}[\p{L}\s]*$"
ALPHANUMERIC = r"^[\p{L}\p{N}\s]+$"
EMAIL = r"^[^\s@]+@[^\s@]+[.][^\s@]+$"
URL = r"^((https?|ftp)://|www[.])\S+$"
IP = r"^(\d{1,3}[.]){3}\d{1,3}$"
PHONE = r"^[+]?[0-9\s().-]+$"

BROAD = ("datetime", "numeric", "alphabetic", "alphanumeric", "nonalphanumeric")
SPECIFIC = ("email", "url", "ip", "phone", "username", "phrases")
SHORT = 6


def broad_type(n: Column) -> Column:
    out = F.lit("nonalphanumeric")
    for name, pattern in (("alphanumeric", ALPHANUMERIC), ("alphabetic", ALPHABETIC), ("numeric", NUMERIC), ("datetime", DATETIME)):
        out = F.when(F.regexp_like(n, F.lit(pattern)), name).otherwise(out)
    return out


def specific_type(n: Column, short_len: int = SHORT) -> Column:
    like = lambda p: F.regexp_like(n, F.lit(p))
    digits = F.length(F.regexp_replace(n, "[^0-9]", ""))
    phone = like(PHONE) & digits.between(7, 15) & ~like(DATETIME)
    short = F.when(F.length(n) < short_len, "username").otherwise("phrases")
    return F.when(like(EMAIL), "email").when(like(URL), "url").when(like(IP), "ip").when(phone, "phone").otherwise(short)


def sql_broad(n: str) -> str:
    like = lambda p: f"regexp_matches({n}, '{p}')"
    return f"CASE WHEN {like(DATETIME)} THEN 'datetime' WHEN {like(NUMERIC)} THEN 'numeric' WHEN {like(ALPHABETIC)} THEN 'alphabetic' WHEN {like(ALPHANUMERIC)} THEN 'alphanumeric' ELSE 'nonalphanumeric' END"


def sql_specific(n: str) -> str:
    like = lambda p: f"regexp_matches({n}, '{p}')"
    digits = f"length(regexp_replace({n}, '[^0-9]', '', 'g'))"
    return (
        f"CASE WHEN {like(EMAIL)} THEN 'email' WHEN {like(URL)} THEN 'url' WHEN {like(IP)} THEN 'ip' "
        f"WHEN {like(PHONE)} AND {digits} BETWEEN 7 AND 15 AND NOT {like(DATETIME)} THEN 'phone' "
        f"WHEN length({n}) < {SHORT} THEN 'username' ELSE 'phrases' END"
    )
