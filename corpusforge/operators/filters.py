"""Filters by warnings, their exceptions, calibration and measured precision."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from corpusforge.functions import labels as lab
from corpusforge.functions import warnings as W

#: Warnings that never cost a document, and those that don't where words are not separated.
IGNORED = ("short_sentences", "header", "footer")
WORD_BASED = ("long_word", "repetition")


def strings(*names: str) -> Column:
    return F.array(*[F.lit(n) for n in names])


def costly(warnings: Column, label: Column | None = None) -> Column:
    """The warnings that count against a row."""
    left = F.array_except(warnings, strings(*IGNORED))
    if label is None:
        return left
    return F.when(lab.word_based(label), left).otherwise(F.array_except(left, strings(*WORD_BASED)))


def keep_documents(docs: DataFrame, label: str | None = None) -> DataFrame:
    """Documents without a warning that counts; their other warnings stay as metadata."""
    return docs.filter(F.size(costly(F.col("warnings"), F.col(label) if label else None)) == 0)


def drop_documents(docs: DataFrame, label: str | None = None) -> DataFrame:
    return docs.filter(F.size(costly(F.col("warnings"), F.col(label) if label else None)) > 0)


def keep_lines(lines: DataFrame, c: W.Config = W.DEFAULT) -> DataFrame:
    """Lines without a warning of their own."""
    return lines.filter(~W.any_of(W.line_flags(F.col("line"), c)))


def calibration_sample(lines: DataFrame, label: str, script: str = "script", per_label: int = 20) -> DataFrame:
    """(script, stratum, label, doc_id, pos): a large, a middle and a small language of each script, some lines of each.

    Languages are ranked by lines; the first tenth is the head, up to a quarter the middle, the rest the tail. One language
    of each stratum and its lines are chosen by hash.
    """
    sizes = lines.groupBy(script, label).agg(F.count(F.lit(1)).alias("n"))
    order = Window.partitionBy(script).orderBy(F.desc("n"), label)
    at = F.row_number().over(order) / F.count(F.lit(1)).over(Window.partitionBy(script))
    strata = sizes.withColumn("stratum", F.when(at <= 0.10, "top").when(at <= 0.25, "middle").otherwise("bottom"))
    pick = F.row_number().over(Window.partitionBy(script, "stratum").orderBy(F.md5(F.col(label)), label))
    chosen = strata.withColumn("pick", pick).filter("pick = 1").select(script, "stratum", label)
    rank = F.row_number().over(Window.partitionBy(label).orderBy(F.md5(F.concat_ws(":", "doc_id", "pos")), "doc_id", "pos"))
    return lines.join(F.broadcast(chosen), [script, label]).withColumn("rank", rank).filter(F.col("rank") <= per_label).select(script, "stratum", label, "doc_id", "pos")


def warning_precision(docs: DataFrame, verdicts: DataFrame) -> DataFrame:
    """(warning, n, bad, precision, lift): how often a warning meets content that people called bad."""
    judged = docs.select("doc_id", "warnings").join(verdicts.select("doc_id", "quality"), "doc_id")
    base = judged.agg(F.avg((F.col("quality") == 0).cast("double")).alias("base"))
    each = judged.select("quality", F.explode("warnings").alias("warning")).groupBy("warning").agg(F.count(F.lit(1)).alias("n"), F.sum(F.when(F.col("quality") == 0, 1).otherwise(0)).alias("bad"))
    return each.join(F.broadcast(base)).select("warning", "n", "bad", F.round(F.col("bad") / F.col("n"), 6).alias("precision"), F.round(F.col("bad") / F.col("n") / F.col("base"), 4).alias("lift"))  # base: one row
