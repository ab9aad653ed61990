"""The corpus sink: one table, partitioned by snapshot and label group, sorted by label within files."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Label groups; thousands of labels share them, so that rare labels don't make tiny files.
GROUPS = 64


def label_group(label: str = "label", groups: int = GROUPS):
    return F.pmod(F.xxhash64(label), F.lit(groups)).cast("int")


def write_corpus(docs: DataFrame, path: str, snapshot: str = "snapshot", label: str = "label", salts: int = 8, max_records: int = 1_000_000) -> None:
    """Write or replace snapshots. A large label is dealt to ``salts`` tasks; writing a snapshot again replaces it."""
    rows = docs.withColumn("label_group", label_group(label)).withColumn("_salt", F.pmod(F.xxhash64("doc_id"), F.lit(salts)))
    dealt = rows.repartition("label_group", "_salt").drop("_salt").sortWithinPartitions(snapshot, "label_group", label)
    writer = dealt.write.mode("overwrite").option("partitionOverwriteMode", "dynamic").option("maxRecordsPerFile", max_records)
    writer.partitionBy(snapshot, "label_group").parquet(path)


def read_label(spark: SparkSession, path: str, label: str) -> DataFrame:
    """One label's subcorpus: its group's folders, then row groups by their statistics."""
    group = spark.range(1).select(F.pmod(F.xxhash64(F.lit(label)), F.lit(GROUPS)).cast("int")).first()[0]
    return spark.read.parquet(path).filter((F.col("label_group") == group) & (F.col("label") == label))
