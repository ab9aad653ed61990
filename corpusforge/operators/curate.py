"""Curation of labels: confusions, weak labels, rules for macro-languages."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

RULES = "op string, from_label string, to_label string"


def confused_pairs(cells: DataFrame) -> DataFrame:
    """(a, b, n_ab, n_ba, n) of labels that are taken for each other, from (gold, pred, n)."""
    wrong = cells.filter((F.col("gold") != F.col("pred")) & (F.col("pred") != "none"))
    a, b = F.least("gold", "pred"), F.greatest("gold", "pred")
    forward = F.sum(F.when(F.col("gold") < F.col("pred"), F.col("n")).otherwise(0))
    return wrong.groupBy(a.alias("a"), b.alias("b")).agg(forward.alias("n_ab"), (F.sum("n") - forward).alias("n_ba"), F.sum("n").alias("n"))


def annotate_pairs(pairs: DataFrame, languages: DataFrame) -> DataFrame:
    """Confused pairs with whether both belong to one macro-language."""
    macro = F.broadcast(languages.select("label", "macro_label"))
    left = pairs.join(macro.withColumnsRenamed({"label": "a", "macro_label": "macro_a"}), "a", "left")
    return left.join(macro.withColumnsRenamed({"label": "b", "macro_label": "macro_b"}), "b", "left").withColumn("one_macro", F.coalesce(F.col("macro_a") == F.col("macro_b"), F.lit(False)))


def mixture(pred: DataFrame, min_share: float = 0.01) -> DataFrame:
    """(gold, pred, n, share): labels whose texts another label takes in some number."""
    cells = pred.filter("pred is not null").groupBy("gold", "pred").agg(F.count(F.lit(1)).alias("n"))
    total = cells.groupBy("gold").agg(F.sum("n").alias("total"))
    return cells.join(total, "gold").select("gold", "pred", "n", F.round(F.col("n") / F.col("total"), 6).alias("share")).filter((F.col("gold") != F.col("pred")) & (F.col("share") >= min_share))


def low_labels(f1: DataFrame, floor: float = 0.7) -> DataFrame:
    return f1.filter(F.col("f1") < floor).select("label", "f1")


def drop_labels(rows: DataFrame, labels: DataFrame) -> DataFrame:
    return rows.join(F.broadcast(labels.select("label")), "label", "left_anti")


def apply_rules(rows: DataFrame, rules: DataFrame) -> DataFrame:
    """Relabel, merge and rename give a new label, delete drops the rows, keep leaves them; ``rules`` has one row a label."""
    r = F.broadcast(rules.select(F.col("from_label").alias("label"), "op", "to_label"))
    out = rows.join(r, "label", "left").filter(~F.col("op").eqNullSafe("delete"))
    return out.withColumn("label", F.when(F.col("op").isin("relabel", "merge", "rename"), F.col("to_label")).otherwise(F.col("label"))).drop("op", "to_label")


def split_mass(scored: DataFrame, pairs: DataFrame, keys: list[str]) -> DataFrame:
    """(a, b, n, top, both): over texts won by either of a pair, the winner's mean probability and that of the two together."""
    p = scored.select(*keys, "label", "prob")
    top = p.groupBy(*keys).agg(F.max("prob").alias("top"), F.max_by("label", "prob").alias("won"))
    sides = p.join(F.broadcast(pairs), (F.col("label") == F.col("a")) | (F.col("label") == F.col("b"))).groupBy(*keys, "a", "b").agg(F.sum("prob").alias("both"))
    rows = sides.join(top, keys).filter((F.col("won") == F.col("a")) | (F.col("won") == F.col("b")))
    return rows.groupBy("a", "b").agg(F.count(F.lit(1)).alias("n"), F.round(F.avg("top"), 4).alias("top"), F.round(F.avg("both"), 4).alias("both"))


def check_exclusive(labels: DataFrame, languages: DataFrame) -> DataFrame:
    """Macro-languages that stand beside one of their members in a label set."""
    own = labels.select("label").distinct()
    member = own.join(F.broadcast(languages.filter("macro_label is not null").select("label", "macro_label")), "label")
    iso = own.select(F.substring_index("label", "_", 1).alias("macro_label"), F.col("label").alias("macro"))
    return member.join(iso, "macro_label").select("macro", "label")
