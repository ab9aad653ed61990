"""Character n-grams and the hashing of them into a fixed range."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

from corpusforge.functions.text import bucket_of, col

NMIN, NMAX, BUCKETS = 2, 5, 2_000_000


def ngrams_of_word(word: Column | str, nmin: int = NMIN, nmax: int = NMAX, pad: bool = True) -> Column:
    """All substrings of nmin to nmax characters of a word, padded by one space on either side."""
    w = F.concat(F.lit(" "), col(word), F.lit(" ")) if pad else col(word)
    none = F.expr("cast(array() as array<string>)")
    one_size = lambda n: F.when(F.length(w) >= n, F.transform(F.sequence(F.lit(1), F.length(w) - n + 1), lambda i: F.substring(w, i, n))).otherwise(none)
    return F.flatten(F.array(*[one_size(F.lit(n)) for n in range(nmin, nmax + 1)]))


def char_ngrams(text: Column | str, nmin: int = NMIN, nmax: int = NMAX, scope: str = "word", pad: bool = True) -> Column:
    """n-grams of a text: inside words, or over the whole line with letters kept and the rest as one space."""
    if scope == "line":
        return ngrams_of_word(F.trim(F.regexp_replace(F.lower(col(text)), r"[^\p{L}]+", " ")), nmin, nmax, pad)
    found = F.regexp_extract_all(F.lower(col(text)), F.lit(r"\p{L}+"), 0)
    return F.flatten(F.transform(found, lambda w: ngrams_of_word(w, nmin, nmax, pad)))


def fnv1a(text: Column | str) -> Column:
    """FNV-1a of 32 bits over UTF-8 bytes."""
    digits = F.regexp_extract_all(F.hex(F.encode(col(text), "UTF-8")), F.lit("(..)"), 1)
    step = lambda h, b: (h.bitwiseXOR(F.conv(b, 16, 10).cast("long")) * 16777619).bitwiseAND(4294967295)
    return F.aggregate(digits, F.lit(2166136261).cast("long"), step)


def bucket(text: Column | str, buckets: int = BUCKETS, algo: str = "md5") -> Column:
    """The id of an n-gram in a fixed range; collisions share an id."""
    if algo == "fnv1a":
        return fnv1a(text) % buckets
    if algo == "xxhash64":
        return F.pmod(F.xxhash64(col(text)), F.lit(buckets))
    return bucket_of(col(text), buckets)
