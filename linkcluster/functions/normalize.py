"""Property normalisation as column expressions."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Steps of label normalisation, in order.
DEFAULT = ("lower", "brackets", "blanks", "trim")
# Accent folding of Latin letters.
ACCENTS_FROM = "àáâãäåçèéêëìíîïñòóôõöùúûüýÿ"
ACCENTS_TO = "aaaaaaceeeeiiiinooooouuuuyy"


def label(c: Column, steps=DEFAULT) -> Column:
    rules = {
        "lower": F.lower,
        "brackets": lambda x: F.regexp_replace(x, r"[\(\[\{][^\)\]\}]*[\)\]\}]", " "),
        "blanks": lambda x: F.regexp_replace(x, r"\s+", " "),
        "trim": F.trim,
        "accents": lambda x: F.translate(F.lower(x), ACCENTS_FROM, ACCENTS_TO),
    }
    for s in steps:
        c = rules[s](c)
    return c


def labels(v: DataFrame, col: str = "label", steps=DEFAULT) -> DataFrame:
    return v.withColumn(col, label(F.col(col), steps))


def year(c: Column, pivot: int = 30) -> Column:
    """Four-digit year of ``'06``, ``06`` or ``2006``; two digits from ``pivot`` on belong to the 1900s."""
    four, two = F.regexp_extract(c, r"(\d{4})", 1), F.regexp_extract(c, r"(\d{2})", 1)
    short = two.try_cast("int")
    return F.when(four != "", four.try_cast("int")).when(two != "", F.when(short >= pivot, short + 1900).otherwise(short + 2000))


def length_seconds(c: Column) -> Column:
    """Seconds of ``2m 4sec``, ``02:04``, milliseconds (whole numbers over 10000) or decimal minutes."""
    c = F.trim(c)
    number = c.try_cast("double")
    part = lambda p, i: F.coalesce(F.regexp_extract(c, p, i).try_cast("int"), F.lit(0))
    words, clock = r"(?:(\d+)\s*m[a-z]*)?\s*(?:(\d+)\s*s[a-z]*)?", r"^(\d+):(\d+)$"
    return (
        F.when(c.rlike(clock), part(clock, 1) * 60 + part(clock, 2))
        .when(number.isNotNull() & c.rlike(r"^\d+$") & (number >= 10000), F.floor(number / 1000 + 0.5))
        .when(number.isNotNull(), F.floor(number * 60 + 0.5))
        .when(c.rlike(r"\d+\s*[ms]"), part(words, 1) * 60 + part(words, 2))
        .cast("bigint")
    )


def grid(x: Column) -> Column:
    """A similarity on a grid of 1e-9 as BIGINT; order and ties are taken on it, so engines agree."""
    return F.floor(x * 1e9 + 0.5).cast("bigint")


def rounded(x: Column, digits: int = 6) -> Column:
    return F.floor(x * float(10**digits) + 0.5) / float(10**digits)
