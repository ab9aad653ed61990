"""The audit: samples, in-language scores, languages outside the model, clues, and repeated ends of lines."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from corpusforge.functions.html import html_lang, url_lang


def sample(docs: DataFrame, label: str, n_labels: int, per_label: int = 20, salt: str = "audit") -> DataFrame:
    """(label, doc_id, rank): some labels by hash, some documents of each by hash."""
    names = docs.select(F.col(label).alias("label")).distinct().orderBy(F.md5(F.concat_ws(":", F.lit(salt), "label")), "label").limit(n_labels)
    rows = docs.select(F.col(label).alias("label"), "doc_id").join(F.broadcast(names), "label")
    rank = F.row_number().over(Window.partitionBy("label").orderBy(F.md5(F.concat_ws(":", F.lit(salt), "doc_id")), "doc_id"))
    return rows.withColumn("rank", rank).filter(F.col("rank") <= per_label)


def score(judged: DataFrame) -> DataFrame:
    """(n_labels, macro_avg, median) of the in-language share by label; rows without a verdict don't count."""
    per = judged.filter("verdict is not null").groupBy("label").agg(F.avg(F.col("verdict").cast("double")).alias("share"))
    return per.agg(F.count(F.lit(1)).alias("n_labels"), F.round(F.avg("share"), 6).alias("macro_avg"), F.round(F.median("share"), 6).alias("median"))


def out_of_model(truth: DataFrame, model_labels: DataFrame) -> DataFrame:
    """(label, n): languages met in the audit that the model doesn't have."""
    return truth.join(F.broadcast(model_labels.select("label").distinct()), "label", "left_anti").groupBy("label").agg(F.count(F.lit(1)).alias("n"))


def clues(pages: DataFrame) -> DataFrame:
    """(page_id, url_code, html_code, agree)."""
    t = pages.select("page_id", url_lang("url").alias("url_code"), html_lang("html").alias("html_code"))
    return t.withColumn("agree", F.col("url_code") == F.col("html_code"))


def affix_repetition(docs: DataFrame, n: int = 2, min_lines: int = 3) -> DataFrame:
    """(doc_id, kind, affix, lines): first or last words that several lines of a document share."""
    from corpusforge.functions.text import exploded_lines, tokens

    rows = exploded_lines(docs.select("doc_id", "text")).withColumn("w", tokens("line")).filter(F.size("w") > n)
    both = rows.select("doc_id", F.explode(F.array(F.struct(F.lit("prefix").alias("kind"), F.concat_ws(" ", F.slice("w", 1, n)).alias("affix")), F.struct(F.lit("suffix").alias("kind"), F.concat_ws(" ", F.slice("w", -n, n)).alias("affix")))).alias("x"))
    return both.groupBy("doc_id", "x.kind", "x.affix").agg(F.count(F.lit(1)).alias("lines")).filter(F.col("lines") >= min_lines)


def recleanse(kept: DataFrame, rules: DataFrame) -> DataFrame:
    """A cleaner release: documents of the labels that the audit gave up go."""
    return kept.join(F.broadcast(rules.select("label")), "label", "left_anti")
