"""Columns over texts: lines, tokens, words, numbers drawn by hash."""

from __future__ import annotations

import sys
import unicodedata
from functools import lru_cache

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

LETTERS = r"\p{L}+"
WORD = r"[\p{L}\p{N}]+"
VISIBLE = r"\S+"


@lru_cache(maxsize=1)
def letter_class() -> str:
    """All letters (Unicode category L) as a character class of Python's regular expressions, which have no ``\\p{L}``."""
    is_letter = [unicodedata.category(chr(c))[0] == "L" for c in range(sys.maxunicode + 1)]
    starts = [c for c in range(len(is_letter)) if is_letter[c] and not (c and is_letter[c - 1])]
    ends = [c for c in range(len(is_letter)) if is_letter[c] and not (c + 1 < len(is_letter) and is_letter[c + 1])]
    return "[" + "".join(f"{chr(a)}-{chr(b)}" if a < b else chr(a) for a, b in zip(starts, ends, strict=True)) + "]"


def col(c: Column | str) -> Column:
    return F.col(c) if isinstance(c, str) else c


def bound(value: Column, use) -> Column:
    """``use(value)``, with the value computed once however often it is used, also inside lambdas."""
    return F.transform(F.array(value), use)[0]


def lines(text: Column | str) -> Column:
    """Trimmed lines without blanks."""
    return F.filter(F.transform(F.split(col(text), "\n"), lambda x: F.trim(x)), lambda x: x != "")


def tokens(line: Column | str) -> Column:
    """Pieces between white space."""
    return F.filter(F.split(col(line), r"\s+"), lambda x: x != "")


def words(text: Column | str, pattern: str = WORD) -> Column:
    """Lower-cased runs that a pattern matches."""
    return F.regexp_extract_all(F.lower(col(text)), F.lit(pattern), 0)


def share(part: Column, whole: Column) -> Column:
    """A ratio, 0 of nothing."""
    return F.when(whole > 0, part / whole).otherwise(F.lit(0.0))


def exploded_lines(docs: DataFrame, text: str = "text") -> DataFrame:
    """A row for each non-blank line: the other columns, ``pos`` (from 0, blanks counted) and ``line``."""
    other = [c for c in docs.columns if c != text]
    rows = docs.select(*other, F.posexplode(F.split(text, "\n")).alias("pos", "line"))
    return rows.withColumn("line", F.trim("line")).filter("line <> ''")


def drawn(*parts: Column | str | int) -> Column:
    """A number of 32 bits that depends on the parts alone: the same on every retry, layout and engine."""
    texts = [p.cast("string") if isinstance(p, Column) else F.lit(str(p)) for p in parts]
    return F.conv(F.substring(F.md5(F.concat_ws(":", *texts)), 1, 8), 16, 10).cast("long")


def bucket_of(text: Column, buckets: int) -> Column:
    """A hash bucket by the first 32 bits of MD5."""
    return F.conv(F.substring(F.md5(text), 1, 8), 16, 10).cast("long") % buckets
