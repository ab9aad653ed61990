"""Two identifiers over the same pages: where they disagree on rare labels, who is right, and what that means at scale."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def joined(a: DataFrame, b: DataFrame, key: str = "doc_id") -> DataFrame:
    """(key, label_a, label_b): a page that one run lacks or rejects is its miss; pages that both miss don't count."""
    left, right = a.select(key, F.col("pred").alias("label_a")), b.select(key, F.col("pred").alias("label_b"))
    return left.join(right, key, "full").filter("label_a is not null or label_b is not null")


def rare(pairs: DataFrame, max_n: int = 10, key: str = "doc_id") -> DataFrame:
    """Disagreements where a label given by either has at most ``max_n`` pages among the calls of both."""
    calls = pairs.select(key, F.explode(F.array("label_a", "label_b")).alias("label")).filter("label is not null").distinct()
    few = calls.groupBy("label").agg(F.count(F.lit(1)).alias("n")).filter(F.col("n") <= max_n).select("label")
    ids = calls.join(few, "label").select(key).distinct()
    return pairs.join(ids, key, "left_semi").filter(~F.col("label_a").eqNullSafe(F.col("label_b")))


def chosen(pairs: DataFrame, n: int = 20, salt: str = "compare", key: str = "doc_id") -> DataFrame:
    return pairs.orderBy(F.md5(F.concat_ws(":", F.lit(salt), key)), key).limit(n)


def state(label: str, truth: str = "truth"):
    return F.when(F.col(label).isNull(), "miss").when(F.col(label) == F.col(truth), "correct").otherwise("wrong")


def outcomes(pairs: DataFrame) -> DataFrame:
    """(state_a, correct, wrong, miss): columns are the states of the second identifier."""
    t = pairs.select(state("label_a").alias("state_a"), state("label_b").alias("state_b"))
    return t.groupBy("state_a").pivot("state_b", ["correct", "wrong", "miss"]).agg(F.count(F.lit(1))).na.fill(0)


def extrapolate(n, fraction: float, snapshots: int):
    """Pages of all snapshots, from those of a part of one."""
    return n / fraction * snapshots


def call_rate(pred: DataFrame, name: str) -> DataFrame:
    return pred.agg(F.lit(name).alias("lid"), F.count(F.lit(1)).alias("n"), F.count("pred").alias("calls"), F.round(F.count("pred") / F.count(F.lit(1)), 6).alias("rate"))
