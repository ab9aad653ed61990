"""Boundaries of warnings, worked arithmetic, replacement of personal data, digests, labels, features."""

from __future__ import annotations

import pytest
from pyspark.sql import functions as F

from corpusforge.functions import cost, features, html, labels, lsh, pii, scripts
from corpusforge.functions import warnings as W
from corpusforge.operators import compare, coverage


def flags(spark, text: str) -> set[str]:
    row = W.annotate(spark.createDataFrame([(text,)], "text string")).first()
    return set(row.warnings)


def test_published_arithmetic():
    assert round(cost.wall_hours(3.16e9, 48, 20, 1379, 245), 1) == 339.9
    assert compare.extrapolate(260, 0.01, 100) == 2_600_000


def test_cumulated_languages(spark):
    sizes = [10**7] * 12 + [10**6] * 22 + [10**5] * 29 + [10**4] * 52 + [10**3] * 89 + [10**2] * 145 + [10] * 360
    counted = spark.createDataFrame([(i, n) for i, n in enumerate(sizes)], "label int, n_docs long")
    t = counted.groupBy(coverage.size_bucket().alias("bucket")).agg(F.count(F.lit(1)).alias("n")).collect()
    by = {r.bucket: r.n for r in t}
    assert sum(n for b, n in by.items() if b >= 2) == 349 and sum(n for b, n in by.items() if b >= 1) == 709


@pytest.mark.parametrize(
    ("text", "name", "expected"),
    [
        ("a\nb", "tiny", True), ("a\nb\nc", "tiny", False), ("a\n \nb\n\n", "tiny", True),
        ("x" * 99 + "\n" + "y" * 100, "short_sentences", True), ("x" * 99 + "\n" + "y" * 100 + "\n" + "z" * 100, "short_sentences", False),
        ("short\n" + ("y" * 120 + "\n") * 4, "header", True), (("y" * 120 + "\n") * 4 + "short", "header", False), (("y" * 120 + "\n") * 4 + "short", "footer", True),
        ("Aa bb", "list_case", True), ("Aa bb cc", "list_case", False),
        ("ab1.efghij", "technical", True), ("ab1.efghijk", "technical", False),
        ("w" * 101, "long_word", True), ("w" * 100, "long_word", False),
        ("JavaScript", "js", True), ("Javascript", "js", True), ("javascript", "js", False),
        ("a } b", "curly", True), ("LOREM IPSUM", "filler", True), ("see our Cookie Policy", "policy", True), ("cookies", "policy", False),
        (" ".join(["same"] * 21), "repetition", True), (" ".join(["same"] * 20), "repetition", False), (" ".join(f"w{i}" for i in range(25)), "repetition", False),
        (" ".join([f"w{i}" for i in range(11)] * 2), "repetition", True), ("", "tiny", True), ("", "technical", False),
        ("what an idiot", "adult", True), ("idiotic", "adult", False),
    ],
)
def test_warning_thresholds(spark, text, name, expected):
    assert (name in flags(spark, text)) is expected


def test_repetition_counts_excess_or_occurrence(spark):
    line = " ".join([f"a{i}" for i in range(12)] + [f"a{i}" for i in range(12)])
    df = spark.createDataFrame([(line,)], "line string")
    share = lambda mode: df.select(W._repeated(W.tokens("line"), mode)).first()[0]
    assert share("excess") == 0.5 and share("occurrence") == 1.0


def test_inconsistency_edges(spark):
    df = spark.createDataFrame([(["eng_Latn"] * 4 + ["fra_Latn"] * 6, "eng_Latn"), (["eng_Latn"] * 41 + [None] * 59, "eng_Latn"), ([], "eng_Latn")], "ls array<string>, label string")
    assert [r[0] for r in df.select(W.lid_inconsistent(F.col("ls"), F.col("label"))).collect()] == [True, False, False]
    texts = spark.createDataFrame([("a" * 90 + "б" * 10, "eng_Latn"), ("a" * 91 + "б" * 9, "eng_Latn"), ("б" * 50, "rus_Cyrl"), ("", "eng_Latn")], "text string, label string")
    assert [r[0] for r in texts.select(W.script_inconsistent(F.col("text"), F.col("label"))).collect()] == [True, False, False, False]


def test_lists_in_scripts_without_case(spark):
    assert "list_case_uncased" in flags(spark, "一二 三四 五六七") and "list_case_uncased" not in flags(spark, "一二三四五六七八 三四五六七八九十")


def test_personal_data(spark):
    t = "mail joe.doe+x@mail.example.co or 8.8.8.8, 10.0.0.1, 172.31.0.1, 172.32.0.1, 233.1.1.1, 999.1.1.1, 1.2.3.4.5; phone +1 555 0100"
    df = spark.createDataFrame([(t,), (None,), ("",)], "text string")
    once = df.select(pii.apply("text").alias("text"))
    got = [r.text for r in once.collect()]
    assert [r.text for r in once.select(pii.apply("text").alias("text")).collect()] == got
    assert "joe.doe" not in got[0] and "8.8.8.8," not in got[0] and "172.32.0.1" not in got[0]
    assert all(x in got[0] for x in ("10.0.0.1", "172.31.0.1", "233.1.1.1", "999.1.1.1", "+1 555 0100"))
    assert got[1:] == [None, ""]
    c = df.select(pii.counts("text").alias("c")).first().c
    assert (c.email, c.private_ip) == (1, 3)


def test_digest_of_close_texts_is_close():
    base = " ".join(f"word{i * 7919 % 1000}" for i in range(400))
    d = lsh.digest(base)
    assert d == lsh.digest(base) and len(d) == 138 and lsh.distance(d, d) == 0
    near, far = lsh.digest(base + " one more word"), lsh.digest(" ".join(f"other{i * 31 % 977}" for i in range(300)))
    assert lsh.distance(d, near) == lsh.distance(near, d) < lsh.distance(d, far)
    assert lsh.digest("short") is None and lsh.digest("a" * 500) is None and lsh.digest(None) is None


def test_features_and_hashes(spark):
    df = spark.createDataFrame([("Ab, c",)], "t string")
    assert df.select(features.char_ngrams("t", 2, 3)).first()[0] == [" a", "ab", "b ", " ab", "ab ", " c", "c ", " c "]
    assert df.select(features.char_ngrams("t", 4, 5, scope="line")).first()[0] == [" ab ", "ab c", "b c ", " ab c", "ab c "]
    assert spark.range(1).select(features.fnv1a(F.lit("abc"))).first()[0] == 440920331


def test_labels_and_scripts(spark):
    df = spark.createDataFrame([("rus-Cyrl",), ("und_Mong",), ("zxx_Latn",)], "label string")
    assert [tuple(r[0]) for r in df.select(labels.parse("label")).collect()] == [("rus", "Cyrl", "lang"), ("und", "Mong", "und"), ("zxx", "Latn", "zxx")]
    texts = spark.createDataFrame([(1, "abc где é"), (2, "𑌅𑌆 x"), (3, None)], "id long, text string")
    got = {(r.id, r.script): r.n for r in scripts.scripts_in_one_pass(texts, ["id"]).collect()}
    assert got == {(1, "Latn"): 4, (1, "Cyrl"): 3, (2, "Gran"): 2, (2, "Latn"): 1}


def test_html_traps(spark):
    page = '<html lang="de"><head><title>t</title></head><body><script>var a = "</p><b>x";</script><nav>menu</nav><p>Eins &amp; zwei<br>drei<p>vier <b>f&uuml;nf</body></html>'
    r = spark.createDataFrame([(page,)], "h string").select(html.strip_tags("h").alias("t"), html.html_lang("h").alias("l")).first()
    assert r.t == "Eins & zwei\ndrei\nvier fünf" and r.l == "de"
