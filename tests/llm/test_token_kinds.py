"""Every mixed token is tested for randomness, whatever its case and separators."""

from __future__ import annotations

import random

import pytest
from pyspark.sql import functions as F

from corpusforge.llm import secrets

UPPER = "0123456789ABCDEFGHIJKLMNOPQRSTUVWXYZ"


def cut(key: str, mark: str, *sizes: int) -> str:
    places = [sum(sizes[:k]) for k in range(len(sizes) + 1)]
    return mark.join(key[a:b] for a, b in zip(places, places[1:], strict=False))


@pytest.fixture(scope="module")
def keys():
    rng = random.Random(11)
    draw = lambda letters, n: "1" + "".join(rng.choices(letters, k=n - 2)) + letters[-1]
    made = {"plain": [], "upper hex": [], "upper": [], "uuid": [], "lower": []}
    for _ in range(60):
        made["upper hex"].append(draw("0123456789ABCDEF", 40))
        made["upper"].append(draw(UPPER, 40))
        made["uuid"].append(cut(draw("0123456789abcdef", 32), "-", 8, 4, 4, 4, 12))
        made["lower"].append(cut(draw(UPPER.lower(), 43), rng.choice("-_/+"), 11, 20, 12))
        made["plain"].append(rng.choice("-_/+").join(["the", "chapter", "of", "the", "letters", "on", "the", "tree", "3"]))
    made["upper hex"].append("9233A8ECF7C5B09FE5949719B6B82BC439E9329B")
    return [(kind, key) for kind, found in made.items() for key in found]


def test_tokens_of_one_case_and_with_separators_are_found(spark, keys):
    df = spark.createDataFrame([(i, f"see {key} there") for i, (_, key) in enumerate(keys)], "doc_id long, text string")
    assert df.select(secrets.candidates(F.col("text")).alias("c")).filter(F.size("c") == 0).count() == 0
    found = {r.doc_id for r in secrets.scan(df).filter(F.size("random") > 0).collect()}
    share = lambda kind: sum(i in found for i, (k, _) in enumerate(keys) if k == kind) / sum(k == kind for k, _ in keys)
    assert all(share(kind) >= 0.9 for kind in ("upper hex", "upper", "uuid", "lower"))
    assert share("plain") == 0
    clean = {r.doc_id: r.text for r in secrets.redact(df).collect()}
    assert {i for i, t in clean.items() if t == "see [SECRET] there"} == found
