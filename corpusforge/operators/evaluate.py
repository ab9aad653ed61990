"""Measures over predictions: rows with ``gold`` and ``pred`` (null: a miss)."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def confusion(pred: DataFrame) -> DataFrame:
    """(gold, pred, n): everything below runs on these few rows."""
    return pred.groupBy("gold", F.coalesce("pred", F.lit("none")).alias("pred")).agg(F.count(F.lit(1)).alias("n"))


def prf(pred: DataFrame) -> DataFrame:
    """(label, tp, fp, fn, tn, precision, recall, f1, fpr) of every gold label."""
    cells = confusion(pred)
    golds = cells.groupBy(F.col("gold").alias("label")).agg(F.sum("n").alias("of_gold"), F.sum(F.when(F.col("gold") == F.col("pred"), F.col("n")).otherwise(0)).alias("tp"))
    preds = cells.groupBy(F.col("pred").alias("label")).agg(F.sum("n").alias("of_pred"))
    total = Window.partitionBy()  # over one row a label
    t = golds.join(preds, "label", "left").withColumn("of_pred", F.coalesce("of_pred", F.lit(0))).withColumn("all", F.sum("of_gold").over(total))
    t = t.select("label", "tp", (F.col("of_pred") - F.col("tp")).alias("fp"), (F.col("of_gold") - F.col("tp")).alias("fn"), (F.col("all") - F.col("of_gold") - F.col("of_pred") + F.col("tp")).alias("tn"))
    ratio = lambda a, b: F.round(F.when(b > 0, a / b).otherwise(F.lit(0.0)), 6)
    tp, fp, fn, tn = (F.col(c) for c in ("tp", "fp", "fn", "tn"))
    return t.select("label", "tp", "fp", "fn", "tn", ratio(tp, tp + fp).alias("precision"), ratio(tp, tp + fn).alias("recall"), ratio(2 * tp, 2 * tp + fp + fn).alias("f1"), ratio(fp, fp + tn).alias("fpr"))


def f1(pred: DataFrame) -> DataFrame:
    return prf(pred).select("label", "tp", "fp", "fn", "precision", "recall", "f1")


def fpr(pred: DataFrame) -> DataFrame:
    return prf(pred).select("label", "fp", "tn", "fpr")


def macro(per_label: DataFrame, measure: str) -> DataFrame:
    return per_label.agg(F.lit(f"{measure}_macro").alias("metric"), F.round(F.avg(measure), 6).alias("value"), F.count(F.lit(1)).alias("n_labels"))


def micro_f1(pred: DataFrame) -> DataFrame:
    """With one label a row, micro F1 is accuracy over rows that have a prediction or not."""
    right = F.sum(F.when(F.col("gold").eqNullSafe(F.col("pred")), 1).otherwise(0))
    return pred.agg(F.lit("f1_micro").alias("metric"), F.round(2 * right / (F.count(F.lit(1)) + F.count("pred")), 6).alias("value"), F.countDistinct("gold").alias("n_labels"))


def worst(per_label: DataFrame, k: int = 3) -> DataFrame:
    return per_label.orderBy("f1", "label").limit(k).select("label", "f1")


def delta(a: DataFrame, b: DataFrame) -> DataFrame:
    """Difference in F1 of two models, label by label."""
    both = a.select("label", F.col("f1").alias("f1_a")).join(b.select("label", F.col("f1").alias("f1_b")), "label", "full")
    return both.withColumn("delta", F.round(F.coalesce("f1_b", F.lit(0.0)) - F.coalesce("f1_a", F.lit(0.0)), 6))


def calibration(pred: DataFrame, bins: int = 10) -> DataFrame:
    """(bin, n, conf, acc): mean probability against accuracy."""
    p = pred.filter("pred is not null").withColumn("bin", F.least(F.floor(F.round(F.col("prob"), 9) * bins), F.lit(bins - 1)).cast("int"))
    return p.groupBy("bin").agg(F.count(F.lit(1)).alias("n"), F.round(F.avg("prob"), 4).alias("conf"), F.round(F.avg((F.col("gold") == F.col("pred")).cast("double")), 6).alias("acc"))


def expected_calibration_error(bins: DataFrame) -> DataFrame:
    return bins.agg(F.round(F.sum(F.col("n") * F.abs(F.col("conf") - F.col("acc"))) / F.sum("n"), 6).alias("ece"))


def rejection(pred: DataFrame, rejected) -> DataFrame:
    """(is_noise, n, rejected, rate): of noise the share that is turned away, and of true text the share that is lost."""
    r = pred.groupBy("is_noise").agg(F.count(F.lit(1)).alias("n"), F.sum(F.when(rejected, 1).otherwise(0)).alias("rejected"))
    return r.withColumn("rate", F.round(F.col("rejected") / F.col("n"), 6))


def cousins(pred: DataFrame, absent: list[str]) -> DataFrame:
    """(gold, pred, n, mean_prob): which labels take the texts of languages that a model doesn't know."""
    return pred.filter(F.col("gold").isin(*absent) & F.col("pred").isNotNull()).groupBy("gold", "pred").agg(F.count(F.lit(1)).alias("n"), F.round(F.avg("prob"), 4).alias("mean_prob"))


def domain_gap(inside: DataFrame, outside: DataFrame) -> DataFrame:
    both = inside.select("label", F.col("f1").alias("f1_in")).join(outside.select("label", F.col("f1").alias("f1_out")), "label", "full")
    return both.withColumn("gap", F.round(F.coalesce("f1_in", F.lit(0.0)) - F.coalesce("f1_out", F.lit(0.0)), 6))


def label_overlap(bench: DataFrame, model: DataFrame) -> DataFrame:
    """Labels of a benchmark, and how many a model covers."""
    known = model.select("label").distinct().withColumn("known", F.lit(True))
    return bench.select("label").distinct().join(known, "label", "left").agg(F.count(F.lit(1)).alias("n_bench"), F.count("known").alias("n_covered"))


def indomain_sample(rows: DataFrame, cap: int = 1000, salt: str = "in-domain") -> DataFrame:
    """min(cap, n) rows of each label, by hash."""
    order = F.md5(F.concat_ws(":", F.lit(salt), "doc_id", "pos"))
    ranked = rows.withColumn("rank", F.row_number().over(Window.partitionBy("label").orderBy(order, "doc_id", "pos")))
    return ranked.filter(F.col("rank") <= cap)
