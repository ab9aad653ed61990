"""The Arrow pass of warnings and letters against the column definitions and against joins."""

from __future__ import annotations

import pytest
from pyspark.sql import functions as F

from corpusforge.engine import read
from corpusforge.functions import scripts
from corpusforge.functions import warnings as W
from corpusforge.operators import lid, traindata
from corpusforge.plans import annotate

ODD = [
    (1, "One Two Three\nFour Five\nsix seven eight"), (2, "日本 語の テキスト です\n短い 文 と 文"), (3, "lorem ipsum " * 30), (4, "{a} 1234 &&& 5678"), (5, None), (6, ""), (7, "  \n \n"),
    (8, "x" * 150 + "\nJavascript\nUses Cookies here"), (9, "É à Ü ǅ Ⅳ ß x y"), (10, "abc где é عربي 漢字 ไทย ελλ\nжук"), (11, "you idiot, idiotic\nfoolé fool"), (12, "\n".join(["long line " * 20] * 5) + "\nshort"),
]


@pytest.fixture(scope="module")
def texts(spark, small):
    odd = spark.createDataFrame(ODD, "doc_id long, text string")
    return odd.union(read(spark, small, "documents", "doc_id", "text").withColumn("doc_id", F.col("doc_id") + 100))


@pytest.mark.parametrize("config", [W.DEFAULT, W.Config(repeat_mode="occurrence", min_lines=5, case=0.2)])
def test_pass_equals_columns(texts, config):
    a = {r.doc_id: r.warnings for r in W.annotate(texts, config).collect()}
    b = {r.doc_id: r.warnings for r in W.annotate_columns(texts, config).filter("text is not null").collect()}
    assert {k: v for k, v in a.items() if k in b} == b and a[5] == []


def test_letters_equal_patterns(texts):
    columns = [F.regexp_count("text", F.lit(r"\p{L}")).cast("long"), *[scripts.letters_in("text", s).cast("long") for s in scripts.PATTERNS]]
    for r in scripts.count_letters(texts.withColumn("want", F.array(*columns))).collect():
        assert r.text is None or r.letters == r.want
    main = scripts.count_letters(texts).select("text", scripts.main_of_counts(F.col("letters")).alias("a"), scripts.main_script("text").alias("b")).collect()
    assert all(r.a == r.b for r in main)


def test_script_inconsistency_by_counts_and_by_patterns(texts):
    for label in ("eng_Latn", "rus_Cyrl", "jpn_Jpan", "amh_Ethi", "und_Mong"):
        t = scripts.count_letters(texts.filter("text is not null").withColumn("label", F.lit(label)))
        both = t.select(W.script_inconsistent_counts(F.col("letters"), F.col("label"), W.technical("text")).alias("a"), W.script_inconsistent(F.col("text"), F.col("label")).alias("b"))
        assert all(r.a == r.b for r in both.collect())


@pytest.mark.parametrize("restrict", [False, True])
def test_restricted_and_free_identification_by_pass_and_by_join(spark, small, texts, monkeypatch, restrict):
    rows = traindata.labelled_lines(read(spark, small, "documents")).select("label", "line")
    rows = rows.union(rows.filter("label = 'deu_Latn'").select(F.lit("rus_Cyrl"), F.translate("line", "abcdefghijklmnop", "абцдефгхийклмноп")))
    model = lid.fit_counts(rows)
    by = annotate.Pass(restrict=restrict, letters=True, warnings=W.DEFAULT)
    show = lambda: sorted((r.doc_id, r.pred, round(r.prob or 0, 6), [(x.pos, x.pred, round(x.prob or 0, 6)) for x in r.lines], r.letters, r.named) for r in annotate.identify_rows(texts, model, by=by).collect())
    fused = show()
    monkeypatch.setattr(annotate, "BROADCAST_PAIRS", 10)
    joined = show()
    plain = lambda rows: [(i, p, q, ls, named) for i, p, q, ls, _, named in rows]
    assert plain(fused) == plain(joined)
    assert len(fused) == len(ODD) + 200


def test_words_of_many_labels_and_small_steps(spark, small, monkeypatch):
    rows = traindata.labelled_lines(read(spark, small, "documents")).select(F.concat("label", F.lit("_"), F.col("pos") % 7).alias("label"), "line")
    model, docs = lid.fit_counts(rows), read(spark, small, "documents", "doc_id", "text").filter("doc_id < 30")
    arrays = annotate.Model(model)
    texts = [r.text for r in docs.collect()]
    whole = annotate._batch(annotate.Scorer(arrays, model.pattern), texts, annotate.Pass(), None)
    monkeypatch.setattr(annotate, "STEP", 1)
    monkeypatch.setattr(annotate, "MEMO_BYTES", 1)
    monkeypatch.setattr(annotate, "MEMO_GRAMS", 50)
    monkeypatch.setattr(annotate, "LONGEST", 5)
    small_steps = annotate._batch(annotate.Scorer(arrays, model.pattern), texts, annotate.Pass(), None)
    assert whole[0].to_pylist() == small_steps[0].to_pylist()
    assert [x["pred"] for d in whole[2].to_pylist() for x in d] == [x["pred"] for d in small_steps[2].to_pylist() for x in d]
