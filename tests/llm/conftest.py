"""Documents with nulls, empties, repeats, long texts and clashing columns."""

from __future__ import annotations

import pytest

LONG = "the quick brown fox jumps over the lazy dog. " * 4000
TEXTS = [
    (1, "Hello world, this is a plain text.\nWith a second line.", "en"),
    (2, "Hello world, this is a plain text.\nWith a second line.", "en"),
    (2, "Hello world, this is a plain text.\nWith a second line.", "en"),
    (3, None, "en"),
    (4, "", None),
    (5, "   \n\t ", "fr"),
    (None, "no id here, but words enough to count.", "en"),
    (6, LONG, "en"),
    (7, "日本語のテキスト 😀 with émojis and àccents", "und"),
    (8, "it's <|endoftext|> don't   stop\n\n\nnow 123 4.5", "en"),
    (9, "x" * 3000, None),
]
#: Columns whose names the operators use themselves.
CLASHES = "n_tokens long, part long, start long, ids string, print long, component_id long, score double, at string, key long, base string, spans string"


@pytest.fixture(scope="session")
def odd_docs(spark):
    names = [c.split()[0] for c in CLASHES.split(", ")]
    rows = [(i, t, lang, "s", len(t or ""), *[None] * len(names)) for i, t, lang in TEXTS]
    return spark.createDataFrame(rows, f"doc_id long, text string, lang string, source string, n_chars long, {CLASHES}").repartition(3)


@pytest.fixture(scope="session")
def no_docs(odd_docs):
    return odd_docs.limit(0)
