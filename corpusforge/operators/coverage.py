"""Coverage: how many languages have how many documents, against another corpus, by area, class and share kept."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def by_label(docs: DataFrame, label: str) -> DataFrame:
    return docs.groupBy(F.col(label).alias("label")).agg(F.count(F.lit(1)).alias("n_docs"))


def size_bucket(n: str = "n_docs"):
    """Power of ten at or below a number, by digits, so that no logarithm rounds."""
    return (F.length(F.col(n).cast("string")) - 1).cast("int")


def size_buckets(docs: DataFrame, label: str) -> DataFrame:
    """(bucket, n_labels, n_docs, cumulative): labels by size, and labels of this size or larger."""
    t = by_label(docs, label).groupBy(size_bucket().alias("bucket")).agg(F.count(F.lit(1)).alias("n_labels"), F.sum("n_docs").alias("n_docs"))
    return t.withColumn("cumulative", F.sum("n_labels").over(Window.orderBy(F.desc("bucket")).rowsBetween(Window.unboundedPreceding, 0)))  # a row a power of ten


def compare(a: DataFrame, b: DataFrame, label: str) -> DataFrame:
    """(label, docs_a, docs_b, ratio)."""
    left, right = by_label(a, label).withColumnRenamed("n_docs", "docs_a"), by_label(b, label).withColumnRenamed("n_docs", "docs_b")
    both = left.join(right, "label", "full").na.fill(0, ["docs_a", "docs_b"])
    return both.withColumn("ratio", F.when(F.col("docs_b") > 0, F.round(F.col("docs_a") / F.col("docs_b"), 6)))


def by_area(docs: DataFrame, label: str, languages: DataFrame) -> DataFrame:
    """(area, bucket, n_labels, n_docs) with totals; constructed languages are an area of their own."""
    area = F.when(F.col("constructed"), "constructed").otherwise(F.coalesce("macroarea", F.lit("unknown")))
    t = by_label(docs, label).join(F.broadcast(languages), "label", "left").select(area.alias("area"), size_bucket().alias("bucket"), "n_docs")
    return t.cube("area", "bucket").agg(F.count(F.lit(1)).alias("n_labels"), F.sum("n_docs").alias("n_docs"))


def class_share(docs: DataFrame, label: str, classes: str = "classes") -> DataFrame:
    """(bucket, class, share): in each size of languages the share of documents with a class."""
    sized = by_label(docs, label).select(F.col("label").alias(label), size_bucket().alias("bucket"))
    rows = docs.join(F.broadcast(sized), label)
    total = rows.groupBy("bucket").agg(F.count(F.lit(1)).alias("total"))
    per = rows.select("bucket", F.explode(classes).alias("class")).groupBy("bucket", "class").agg(F.count(F.lit(1)).alias("n"))
    return per.join(total, "bucket").select("bucket", "class", "n", F.round(F.col("n") / F.col("total"), 6).alias("share"))


def contamination(pred: DataFrame, large: list[str]) -> DataFrame:
    """(gold, n, lost, share): documents of smaller languages that a large language's label took."""
    small = pred.filter(~F.col("gold").isin(*large))
    t = small.groupBy("gold").agg(F.count(F.lit(1)).alias("n"), F.sum(F.when(F.col("pred").isin(*large), 1).otherwise(0)).alias("lost"))
    return t.withColumn("share", F.round(F.col("lost") / F.col("n"), 6))


def retention(before: DataFrame, after: DataFrame, label: str) -> DataFrame:
    """(label, bucket, n_in, n_kept, share)."""
    a, b = by_label(before, label), by_label(after, label).withColumnRenamed("n_docs", "n_kept")
    t = a.join(b, "label", "left").na.fill(0, ["n_kept"])
    return t.select("label", size_bucket().alias("bucket"), F.col("n_docs").alias("n_in"), "n_kept", F.round(F.col("n_kept") / F.col("n_docs"), 6).alias("share"))
