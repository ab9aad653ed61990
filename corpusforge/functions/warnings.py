"""Quality warnings of documents and lines. Warnings annotate; :mod:`corpusforge.operators.filters` decides what they cost."""

from __future__ import annotations

from dataclasses import dataclass
from functools import reduce

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from corpusforge.engine import arrow_map
from corpusforge.functions import labels as lab
from corpusforge.functions.scripts import PATTERNS, letters_in
from corpusforge.functions.text import bound, col, lines, share, tokens

#: Phrases of boilerplate, the filler phrase, and patterns of broken markup.
POLICY = ("terms of use", "privacy policy", "cookie policy", "uses cookies", "use of cookies", "use cookies")
FILLER = "lorem ipsum"
CURSED = (r"&&&", r"%%%", r"\$\$\$", r"###")
#: Mild words that stand in for an adult lexicon on the given tables.
LEXICON = ("idiot", "loser", "clown", "stupid", "moron", "fool", "dumb", "jerk")


@dataclass(frozen=True)
class Config:
    """Thresholds. Shares fire at or above their value, except those of repetition, which fire above."""

    min_lines: int = 3
    short_chars: int = 100
    short_share: float = 0.5
    edge: float = 0.2
    inconsistent: float = 0.6
    script: float = 0.1
    case: float = 0.5
    uncased_length: int = 4
    technical: float = 0.2
    repeat_words: int = 20
    repeat_share: float = 0.5
    repeat_bigrams: float = 0.2
    repeat_mode: str = "excess"
    long_word: int = 100
    cursed: tuple[str, ...] = CURSED
    lexicon: tuple[str, ...] = LEXICON


DEFAULT = Config()


def tiny(ls: Column, c: Config = DEFAULT) -> Column:
    return F.size(ls) < c.min_lines


def _short(ls: Column, c: Config) -> Column:
    return F.size(F.filter(ls, lambda x: F.length(x) < c.short_chars))


def short_sentences(ls: Column, c: Config = DEFAULT) -> Column:
    return (F.size(ls) > 0) & (share(_short(ls, c), F.size(ls)) >= c.short_share)


def _edge(ls: Column, c: Config) -> Column:
    return F.greatest(F.ceil(F.size(ls) * c.edge), F.lit(1)).cast("int")


def header(ls: Column, c: Config = DEFAULT) -> Column:
    first = F.slice(ls, F.lit(1), _edge(ls, c))
    return (F.size(ls) > 0) & (share(_short(first, c), F.size(first)) >= c.short_share)


def footer(ls: Column, c: Config = DEFAULT) -> Column:
    last = F.when(F.size(ls) > 0, F.slice(ls, -_edge(ls, c), _edge(ls, c))).otherwise(ls)
    return (F.size(ls) > 0) & (share(_short(last, c), F.size(last)) >= c.short_share)


def lid_inconsistent(line_labels: Column, label: Column, c: Config = DEFAULT) -> Column:
    """Lines (an array of labels) that disagree with the document; a line without a label counts as disagreeing."""
    other = F.size(F.filter(line_labels, lambda x: ~x.eqNullSafe(label)))
    return (F.size(line_labels) > 0) & (share(other, F.size(line_labels)) >= c.inconsistent)


def _good_letters(of_script, other: Column, label: Column) -> Column:
    """Letters that a label's language is written in; a language without known scripts is written in its label's own."""
    iso, script = lab.parse(label)["iso"], lab.parse(label)["script"]
    listed, good = iso.isin(*lab.ADMISSIBLE), F.lit(0).cast("long")
    for s in PATTERNS:
        able = [k for k, scripts in lab.ADMISSIBLE.items() if s in scripts]
        named = [s, *[k for k, parts in lab.COMPOSITE.items() if s in parts]]
        fits = F.when(listed, iso.isin(*able) if able else F.lit(False)).otherwise(script.isin(*named))
        good = good + F.when(fits, of_script(s)).otherwise(0)
    return good + F.when(~listed & ~script.isin(*PATTERNS, *lab.COMPOSITE), other).otherwise(0)


def script_inconsistent_counts(letters: Column, label: Column, is_technical: Column, c: Config = DEFAULT) -> Column:
    """Letters of scripts in which the label's language is not written; a technical text counts as inconsistent too.

    ``letters`` is an array of all letters and those of each script of ``PATTERNS``, as ``marks.letters`` gives it.
    """
    places = {s: i + 1 for i, s in enumerate(PATTERNS)}
    other = letters[0] - sum((letters[i] for i in places.values()), F.lit(0).cast("long"))
    good = _good_letters(lambda s: letters[places[s]], other, label)
    return F.coalesce((letters[0] > 0) & (F.round(1 - good / letters[0], 9) >= c.script), F.lit(False)) | F.coalesce(is_technical, F.lit(False))


def script_inconsistent(text: Column, label: Column, c: Config = DEFAULT) -> Column:
    """The same on a text column, by patterns."""
    counts = F.array(F.regexp_count(text, F.lit(r"\p{L}")).cast("long"), *[letters_in(text, s).cast("long") for s in PATTERNS])
    return bound(counts, lambda x: script_inconsistent_counts(x, label, technical(text, c), c))


def list_case_line(line: Column, c: Config = DEFAULT) -> Column:
    upper = lambda words: F.size(F.filter(words, lambda w: w.rlike(r"^\p{Lu}")))
    return bound(tokens(line), lambda words: (F.size(words) > 0) & (share(upper(words), F.size(words)) >= c.case))


def list_case(ls: Column, c: Config = DEFAULT, rule: str = "share") -> Column:
    """Half of the lines are lists by case; with ``rule='any'`` one is enough."""
    hits = F.size(F.filter(ls, lambda x: list_case_line(x, c)))
    return hits > 0 if rule == "any" else (F.size(ls) > 0) & (share(hits, F.size(ls)) >= c.case)


def list_case_uncased_line(line: Column, c: Config = DEFAULT) -> Column:
    """In scripts without case and spaces: short pieces between spaces."""
    short = lambda words: F.size(F.filter(words, lambda w: F.length(w) <= c.uncased_length))
    many = lambda: bound(tokens(line), lambda words: (F.size(words) > 1) & (share(short(words), F.size(words)) >= c.case))
    return line.rlike(r"[\p{IsHan}\p{IsHiragana}\p{IsKatakana}\p{IsThai}]") & many()


def list_case_uncased(ls: Column, c: Config = DEFAULT) -> Column:
    return (F.size(ls) > 0) & (share(F.size(F.filter(ls, lambda x: list_case_uncased_line(x, c))), F.size(ls)) >= c.case)


def technical(text: Column | str, c: Config = DEFAULT, ignore_space: bool = False) -> Column:
    t = F.regexp_replace(col(text), r"\s", "") if ignore_space else col(text)
    return (F.length(t) > 0) & (share(F.regexp_count(t, F.lit(r"[\p{N}\p{P}\p{S}]")), F.length(t)) >= c.technical)


def cursed(text: Column | str, patterns: tuple[str, ...] = CURSED) -> Column:
    return col(text).rlike("|".join(patterns))


def _repeated(items: Column, mode: str) -> Column:
    """Share of items beyond the first of their kind (excess), or of items whose kind occurs again (occurrence)."""
    if mode == "excess":
        return share(F.size(items) - F.size(F.array_distinct(items)), F.size(items))
    again = F.filter(items, lambda x: F.size(F.filter(items, lambda y: y == x)) > 1)
    return share(F.size(again), F.size(items))


def bigrams(words: Column) -> Column:
    """Neighbours side by side; the array is cut twice, not once a pair, which would copy it every time."""
    none = F.expr("cast(array() as array<string>)")
    n = F.size(words) - 1
    return F.when(n > 0, F.zip_with(F.slice(words, F.lit(1), n), F.slice(words, F.lit(2), n), lambda a, b: F.concat_ws(" ", a, b))).otherwise(none)


def repetition_line(line: Column, c: Config = DEFAULT) -> Column:
    pairs = lambda words: bound(bigrams(words), lambda b: _repeated(b, c.repeat_mode) > c.repeat_bigrams)
    return bound(tokens(line), lambda words: (F.size(words) > c.repeat_words) & ((_repeated(words, c.repeat_mode) > c.repeat_share) | pairs(words)))


def repetition(ls: Column, c: Config = DEFAULT) -> Column:
    return F.exists(ls, lambda x: repetition_line(x, c))


def long_word(text: Column | str, c: Config = DEFAULT) -> Column:
    return col(text).rlike(rf"\S{{{c.long_word + 1},}}")


def filler(text: Column | str) -> Column:
    return F.contains(F.lower(col(text)), F.lit(FILLER))


def policy(text: Column | str, phrases: tuple[str, ...] = POLICY) -> Column:
    return F.lower(col(text)).rlike("|".join(phrases))


def js(text: Column | str) -> Column:
    return col(text).rlike("Java[Ss]cript")


def curly(text: Column | str) -> Column:
    return col(text).rlike("[{}]")


def adult(text: Column | str, lexicon: tuple[str, ...] = LEXICON) -> Column:
    return F.lower(col(text)).rlike(r"\b(" + "|".join(lexicon) + r")\b")


def mine_lexicon(vocabulary: DataFrame, seeds: tuple[str, ...] = LEXICON, min_len: int = 4) -> DataFrame:
    """Vocabulary pieces worth a human look for the lexicon: longer than three characters and holding a known word."""
    bare = F.regexp_replace(F.lower("piece"), r"[^\p{L}]", "")
    return vocabulary.select(bare.alias("piece")).filter((F.length("piece") >= min_len) & F.col("piece").rlike("|".join(seeds))).distinct()


#: Warnings that a single line decides.
LINE_LEVEL = ("list_case", "repetition", "long_word", "technical", "curly", "js", "policy", "filler", "cursed", "adult")
NAMES = ("tiny", "short_sentences", "header", "footer", "list_case", "list_case_uncased", "technical", "cursed", "repetition", "long_word", "filler", "policy", "js", "curly", "adult")


def document_flags(text: Column | str = "text", c: Config = DEFAULT, ls: Column | None = None) -> dict[str, Column]:
    """All warnings that need no language identification, by name; ``ls`` are the text's lines, where they are at hand."""
    t, ls = col(text), lines(text) if ls is None else ls
    return {
        "tiny": tiny(ls, c), "short_sentences": short_sentences(ls, c), "header": header(ls, c), "footer": footer(ls, c), "list_case": list_case(ls, c),
        "list_case_uncased": list_case_uncased(ls, c), "technical": technical(t, c), "cursed": cursed(t, c.cursed), "repetition": repetition(ls, c), "long_word": long_word(t, c),
        "filler": filler(t), "policy": policy(t), "js": js(t), "curly": curly(t), "adult": adult(t, c.lexicon),
    }


def line_flags(line: Column, c: Config = DEFAULT) -> dict[str, Column]:
    return {
        "list_case": list_case_line(line, c), "repetition": repetition_line(line, c), "long_word": long_word(line, c), "technical": technical(line, c), "curly": curly(line),
        "js": js(line), "policy": policy(line), "filler": filler(line), "cursed": cursed(line, c.cursed), "adult": adult(line, c.lexicon),
    }


def named(flags: dict[str, Column]) -> Column:
    """Names of the flags that hold, as an array."""
    return F.array_compact(F.array(*[F.when(flag, F.lit(name)) for name, flag in flags.items()]))


def annotate(docs: DataFrame, c: Config = DEFAULT, text: str = "text") -> DataFrame:
    """Documents with their array of ``warnings``: one Arrow pass, ten times as fast as :func:`annotate_columns`."""
    at = docs.columns.index(text)

    def run(batches):
        from corpusforge.functions.marks import Marker

        marker = Marker(c)
        for rows in batches:
            found = pa.array([marker.of(t) for t in rows.column(at).to_pylist()], pa.list_(pa.string()))
            yield pa.RecordBatch.from_arrays([*rows.columns, found], names=[*rows.schema.names, "warnings"])

    return arrow_map(docs, run, T.StructType([*docs.schema.fields, T.StructField("warnings", T.ArrayType(T.StringType()))]))


def annotate_columns(docs: DataFrame, c: Config = DEFAULT, text: str = "text") -> DataFrame:
    """The same in one projection of DataFrame functions."""
    return docs.withColumn("warnings", bound(lines(text), lambda ls: named(document_flags(text, c, ls))))


def lexicon_of(table: DataFrame, column: str = "word", most: int = 100_000) -> tuple[str, ...]:
    """A lexicon or a list of patterns for :class:`Config` from a table; raises beyond ``most`` rows, as it is sent to every task."""
    rows = table.select(column).distinct().orderBy(column).limit(most + 1).collect()
    if len(rows) > most:
        raise ValueError(f"more than {most} entries")
    return tuple(r[0] for r in rows)


def any_of(flags: dict[str, Column]) -> Column:
    return reduce(lambda a, b: a | b, flags.values())
