"""Noise generators work on whole texts."""

from __future__ import annotations

import hashlib
import re

from corpusforge import queries
from corpusforge.engine import read
from corpusforge.operators import noise


def lines_of(spark, small, name):
    return {r.doc_id: r.line for r in queries.QUERIES[name](spark, small).collect()}


def test_noise_covers_the_whole_text(spark, small):
    texts = {r.doc_id: (r.text, r.lang) for r in read(spark, small, "documents", "doc_id", "text", "lang").collect()}
    assert max(len(t) for t, _ in texts.values()) > 80
    drawn = lambda *parts: int(hashlib.md5(":".join(map(str, parts)).encode()).hexdigest()[:8], 16)
    replaced = {i: "".join("\ufffd" if drawn("train", "fffd", i, k) % 1000 < 300 else c for k, c in enumerate(t)) for i, (t, _) in texts.items()}
    assert lines_of(spark, small, "noise_replacement") == replaced
    assert lines_of(spark, small, "noise_spaced") == {i: " ".join(re.sub(r"[ \t\n\v\f\r]+", "", t)) for i, (t, _) in texts.items()}
    foreign = {i: t for i, (t, lang) in texts.items() if lang is not None and lang != "en"}
    assert lines_of(spark, small, "noise_mojibake_latin") == {i: t.encode().decode("latin-1") for i, t in foreign.items()}
    table = {ord(a): b for a, b in reversed(list(zip(*noise.ARABIC_MOJIBAKE, strict=False)))} | {ord(a): None for a in noise.ARABIC_MOJIBAKE[0][len(noise.ARABIC_MOJIBAKE[1]) :]}
    assert lines_of(spark, small, "noise_mojibake_arabic") == {i: t.translate(table) for i, t in foreign.items()}


def test_every_document_has_its_drawn_noise(spark, small):
    texts = {r.doc_id: r.text for r in read(spark, small, "documents", "doc_id", "text").collect()}
    for name, letters in (("noise_pdf", set(noise.STROKES)), ("noise_binary", None)):
        lines = lines_of(spark, small, name)
        assert set(lines) == set(texts)
        of = {t: {lines[i] for i in texts if texts[i] == t} for t in texts.values()}
        assert all(len(x) == 1 for x in of.values()) and len(set(lines.values())) == len(of)  # copies alike, others not
        assert letters is None or all(set(x) <= letters | {" "} for x in lines.values())
    rows = queries.QUERIES["und_samples"](spark, small).collect()
    assert sorted((r.label, r.doc_id) for r in rows) == sorted((f"und_{s}", i) for s in ("Mong", "Newa", "Gran") for i in texts)
    assert all(set(r.line) <= set(noise.alphabet(r.label[4:])) | {" "} for r in rows)
