"""Scripts of a text."""

from __future__ import annotations

import bisect

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from corpusforge.engine import arrow_map
from corpusforge.functions.text import col, share

#: ISO 15924 code and name in regular expressions of the scripts that are counted by patterns.
PATTERNS = {"Latn": "Latin", "Cyrl": "Cyrillic", "Arab": "Arabic", "Hani": "Han", "Grek": "Greek", "Deva": "Devanagari", "Hira": "Hiragana", "Kana": "Katakana", "Hang": "Hangul", "Thai": "Thai", "Hebr": "Hebrew"}
#: First and last code point of blocks, for the one-pass count of many scripts.
RANGES = (
    (0x41, 0x5A, "Latn"), (0x61, 0x7A, "Latn"), (0xC0, 0x24F, "Latn"), (0x370, 0x3FF, "Grek"), (0x400, 0x52F, "Cyrl"), (0x531, 0x58F, "Armn"), (0x5D0, 0x5EA, "Hebr"),
    (0x600, 0x6FF, "Arab"), (0x700, 0x74F, "Syrc"), (0x780, 0x7BF, "Thaa"), (0x7C0, 0x7FF, "Nkoo"), (0x900, 0x97F, "Deva"), (0x980, 0x9FF, "Beng"), (0xA00, 0xA7F, "Guru"),
    (0xA80, 0xAFF, "Gujr"), (0xB00, 0xB7F, "Orya"), (0xB80, 0xBFF, "Taml"), (0xC00, 0xC7F, "Telu"), (0xC80, 0xCFF, "Knda"), (0xD00, 0xD7F, "Mlym"), (0xD80, 0xDFF, "Sinh"),
    (0xE00, 0xE7F, "Thai"), (0xE80, 0xEFF, "Laoo"), (0xF00, 0xFFF, "Tibt"), (0x1000, 0x109F, "Mymr"), (0x10A0, 0x10FF, "Geor"), (0x1200, 0x139F, "Ethi"), (0x13A0, 0x13FF, "Cher"),
    (0x1780, 0x17FF, "Khmr"), (0x1800, 0x18AF, "Mong"), (0x1980, 0x19DF, "Talu"), (0x3041, 0x309F, "Hira"), (0x30A0, 0x30FF, "Kana"), (0x3400, 0x4DBF, "Hani"), (0x4E00, 0x9FFF, "Hani"),
    (0xA800, 0xA82F, "Sylo"), (0xAC00, 0xD7AF, "Hang"), (0x11300, 0x1137F, "Gran"), (0x11400, 0x1147F, "Newa"),
)


def letters_in(text: Column | str, script: str) -> Column:
    return F.regexp_count(col(text), F.lit(rf"[\p{{L}}&&\p{{Is{PATTERNS[script]}}}]"))


def script_shares(text: Column | str, scripts: tuple[str, ...] = tuple(PATTERNS)) -> Column:
    """Map from script to its share of the letters, scripts that occur only."""
    n = F.regexp_count(col(text), F.lit(r"\p{L}"))
    pairs = F.map_from_arrays(F.array(*[F.lit(s) for s in scripts]), F.array(*[share(letters_in(text, s), n) for s in scripts]))
    return F.map_filter(pairs, lambda k, v: v > 0)


def main_script(text: Column | str, scripts: tuple[str, ...] = tuple(PATTERNS)) -> Column:
    """The script of most letters, the first by name of equals; null without letters of a known script."""
    shares = script_shares(text, scripts)
    entries = F.transform(F.map_entries(shares), lambda e: F.struct((-e["value"]).alias("v"), e["key"].alias("k")))
    return F.array_min(entries)["k"]


def count_letters(df: DataFrame, text: str = "text", name: str = "letters") -> DataFrame:
    """Rows with an array column: all letters of the text, then those of each script of ``PATTERNS``; one Arrow pass."""
    at = df.columns.index(text)

    def run(batches):
        from corpusforge.functions.marks import code_classes, letters

        for rows in batches:
            found = [letters(code_classes(t)) if t is not None else None for t in rows.column(at).to_pylist()]
            yield pa.RecordBatch.from_arrays([*rows.columns, pa.array(found, pa.list_(pa.int64()))], names=[*rows.schema.names, name])

    return arrow_map(df, run, T.StructType([*df.schema.fields, T.StructField(name, T.ArrayType(T.LongType()))]))


def main_of_counts(letters: Column, scripts: tuple[str, ...] = tuple(PATTERNS)) -> Column:
    """The script of most letters, the first by name of equals, from counted letters."""
    places = list(PATTERNS)
    entries = F.array(*[F.struct((-letters[places.index(s) + 1]).alias("v"), F.lit(s).alias("k")) for s in scripts])
    least = F.array_min(entries)
    return F.when(least["v"] < 0, least["k"])


#: Stands for all scripts that are not counted apart.
OTHER = "other"


def main_or_other(letters: Column) -> Column:
    """As :func:`main_of_counts` over all counted scripts, or ``OTHER`` if the letters of no counted script are more."""
    known = F.array_max(F.slice(letters, 2, len(PATTERNS)))
    rest = letters[0] - F.aggregate(F.slice(letters, 2, len(PATTERNS)), F.lit(0).cast("long"), lambda a, x: a + x)
    return F.when(rest > known, F.lit(OTHER)).otherwise(main_of_counts(letters))


def scripts_in_one_pass(df: DataFrame, ids: list[str], text: str = "text") -> DataFrame:
    """(ids, script, n) for every script of ``RANGES``: one pass over the text, whatever the number of scripts."""
    starts, ends, names = zip(*sorted(RANGES), strict=True)

    def run(batches):
        for rows in batches:
            out: list[list] = [[] for _ in range(len(ids) + 2)]
            for i, value in enumerate(rows.column(len(ids)).to_pylist()):
                found: dict[str, int] = {}
                for ch, n in _counted(value or "").items():
                    at = bisect.bisect_right(starts, ord(ch)) - 1
                    if at >= 0 and ord(ch) <= ends[at] and ch.isalpha():
                        found[names[at]] = found.get(names[at], 0) + n
                for script, n in found.items():
                    for c in range(len(ids)):
                        out[c].append(rows.column(c)[i])
                    out[-2].append(script)
                    out[-1].append(n)
            yield pa.RecordBatch.from_arrays([*[pa.array([x.as_py() for x in out[c]], rows.schema.field(c).type) for c in range(len(ids))], pa.array(out[-2], pa.string()), pa.array(out[-1], pa.int64())], names=[*ids, "script", "n"])

    kinds = ", ".join(f"`{c}` {df.schema[c].dataType.simpleString()}" for c in ids)
    return arrow_map(df.select(*ids, text), run, f"{kinds}, script string, n long")


def _counted(text: str) -> dict[str, int]:
    return {ch: text.count(ch) for ch in set(text)}
