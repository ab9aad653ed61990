"""Continuous ingestion: the same annotation as in batch, counts and windows over events, deduplication and monitoring."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from corpusforge.engine import scratch_path
from corpusforge.functions import labels as lab
from corpusforge.functions import warnings as W


def source(spark: SparkSession, directory: str, name: str, max_files: int = 64) -> DataFrame:
    """A given table as a stream of files."""
    schema = spark.read.parquet(f"{directory}/{name}.parquet").schema
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", max_files).option("pathGlobFilter", f"{name}*.parquet" if not _is_folder(spark, directory, name) else "*.parquet").parquet(_place(spark, directory, name))


def _is_folder(spark: SparkSession, directory: str, name: str) -> bool:
    from corpusforge.engine import hadoop_path

    fs, p = hadoop_path(spark, f"{directory}/{name}.parquet")
    return fs.getFileStatus(p).isDirectory()


def _place(spark: SparkSession, directory: str, name: str) -> str:
    return f"{directory}/{name}.parquet" if _is_folder(spark, directory, name) else directory


def annotate(src: DataFrame) -> DataFrame:
    """Stateless: the batch annotation on rows as they come."""
    return W.annotate(src)


def label_counts(src: DataFrame, label: str = "lang") -> DataFrame:
    return src.groupBy(F.col(label).alias("label")).agg(F.count(F.lit(1)).alias("n"))


def _timed(src: DataFrame, lateness: str) -> DataFrame:
    return src.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", lateness)


def _windows(src: DataFrame, window, *keys: str) -> DataFrame:
    t = src.groupBy(window.alias("w"), *keys).agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("value"), 2).alias("value"))
    return t.select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), *keys, "n", "value")


def tumbling(src: DataFrame, size: str = "1 hour", lateness: str = "2 hours") -> DataFrame:
    return _windows(_timed(src, lateness), F.window("ts", size), "event_type")


def sliding(src: DataFrame, size: str = "1 hour", step: str = "15 minutes", lateness: str = "2 hours") -> DataFrame:
    return _windows(_timed(src, lateness), F.window("ts", size, step), "event_type")


def session(src: DataFrame, gap: str = "30 minutes", lateness: str = "2 hours") -> DataFrame:
    return _windows(_timed(src, lateness), F.session_window("ts", gap), "user_id")


def dedup(src: DataFrame, key: str, lateness: str | None = None) -> DataFrame:
    """The first row of each key: within the watermark if the rows have event time, else for good."""
    return _timed(src, lateness).dropDuplicatesWithinWatermark([key]) if lateness else src.dropDuplicates([key])


def enrich(src: DataFrame, dim: DataFrame, key: str) -> DataFrame:
    return src.join(dim, key, "left")


def interval_join(purchases: DataFrame, errors: DataFrame, within: str = "10 minutes", lateness: str = "1 hour") -> DataFrame:
    """Errors of a user in the time after a purchase; both sides forget what is too old to match."""
    p = _timed(purchases, lateness).select(F.col("user_id"), F.col("ts").alias("bought"), F.col("event_id").alias("purchase_id"))
    e = _timed(errors, lateness).select(F.col("user_id").alias("error_user"), F.col("ts").alias("failed"), F.col("event_id").alias("error_id"))
    return p.join(e, F.expr(f"user_id = error_user and failed >= bought and failed <= bought + interval {within}")).select("purchase_id", "error_id")


def drift(src: DataFrame, key: str, flag: str, threshold: float = 0.5, least: int = 10) -> DataFrame:
    """(key, n, flagged, share, alert) after each batch: a running share by key, with a flag beyond the threshold."""
    import pandas as pd

    def update(k, batches, state):
        n, bad = state.get if state.exists else (0, 0)
        for pdf in batches:
            n, bad = n + len(pdf), bad + int(pdf[flag].sum())
        state.update((n, bad))
        yield pd.DataFrame({key: [k[0]], "n": [n], "flagged": [bad], "share": [bad / n], "alert": [n >= least and bad / n >= threshold]})

    kind = src.schema[key].dataType.simpleString()
    return src.select(key, flag).groupBy(key).applyInPandasWithState(update, f"`{key}` {kind}, n long, flagged long, share double, alert boolean", "n long, bad long", "update", "NoTimeout")


def finish(stream: DataFrame, name: str, mode: str = "complete", write: Callable | None = None) -> DataFrame:
    """Run a stream over what is there now and read its result from the shared folder.

    In complete mode every batch holds the whole result, so a batch that is run again gives the same table.
    """
    spark = stream.sparkSession
    path, checkpoint = scratch_path(spark, f"stream-{name}"), scratch_path(spark, f"checkpoint-{name}")

    def put(df: DataFrame, batch: int) -> None:
        df.write.mode("overwrite").parquet(path if mode == "complete" else f"{path}/batch={batch}")

    stream.writeStream.outputMode(mode).option("checkpointLocation", checkpoint).trigger(availableNow=True).foreachBatch(write or put).start().awaitTermination()
    return spark.read.schema(stream.schema).parquet(path).select(*stream.columns)


def to_coverage(src: DataFrame, path: str, label: str = "lang") -> DataFrame:
    """Counts by label as an upserted table: each batch replaces its own part, so a repeated batch changes nothing."""
    spark = src.sparkSession

    def put(df: DataFrame, batch: int) -> None:
        label_counts(df, label).write.mode("overwrite").parquet(f"{path}/batch={batch}")

    src.writeStream.option("checkpointLocation", scratch_path(spark, "checkpoint-coverage")).trigger(availableNow=True).foreachBatch(put).start().awaitTermination()
    return spark.read.parquet(path).groupBy("label").agg(F.sum("n").alias("n"))


def _utc(df: DataFrame) -> DataFrame:
    return df.select(*[F.date_format(c, "yyyy-MM-dd HH:mm:ss").alias(c) if c in ("start", "end") else F.col(c) for c in df.columns])


def _events(spark: SparkSession, sf: str) -> DataFrame:
    return source(spark, sf, "events")


def _enriched(spark: SparkSession, sf: str) -> DataFrame:
    """Documents with what is known of their language; the table of languages is read again for each batch."""
    rows = source(spark, sf, "documents").select("doc_id", lab.label_of("lang").alias("label"))
    return finish(enrich(rows, F.broadcast(lab.languages(spark).select("label", "macroarea")), "label"), "enrich", "append").select("doc_id", "label", "macroarea")


def _failures(spark: SparkSession, sf: str) -> DataFrame:
    buys, errors = (_events(spark, sf).filter(F.col("event_type") == kind) for kind in ("purchase", "error"))
    return finish(interval_join(buys, errors, "10 hours"), "interval", "append")


def _drifted(spark: SparkSession, sf: str) -> DataFrame:
    """What the last batch said of each source: its share of documents under 1,000 characters, with a flag from 0.3 on."""
    short = source(spark, sf, "documents").select("source", (F.coalesce(F.length("text"), F.lit(0)) < 1000).alias("short"))
    told = finish(drift(short, "source", "short", threshold=0.3), "drift", "update")
    last = told.groupBy("source").agg(F.max(F.struct("n", "flagged", "share", "alert")).alias("x"))
    return last.select("source", "x.n", "x.flagged", F.round("x.share", 6).alias("share"), "x.alert")


QUERIES = {
    "stream_tumbling": lambda spark, sf: _utc(finish(tumbling(_events(spark, sf)), "tumbling")),
    "stream_sliding": lambda spark, sf: _utc(finish(sliding(_events(spark, sf)), "sliding")),
    "stream_session": lambda spark, sf: finish(session(_events(spark, sf)), "session").groupBy("user_id").agg(F.count(F.lit(1)).alias("sessions"), F.sum("n").alias("n")),
    "stream_dedup": lambda spark, sf: finish(dedup(source(spark, sf, "documents").select(F.md5("text").alias("h")), "h"), "dedup", "append"),
    "stream_label_counts": lambda spark, sf: finish(label_counts(source(spark, sf, "documents")), "labels"),
    "stream_enrich": _enriched,
    "stream_interval_join": _failures,
    "stream_drift": _drifted,
    "stream_upsert": lambda spark, sf: to_coverage(source(spark, sf, "documents"), scratch_path(spark, "coverage")),
    "stream_annotate": lambda spark, sf: finish(annotate(source(spark, sf, "documents").select("doc_id", "text")).select("doc_id", F.array_join("warnings", ",").alias("warnings")), "annotate", "append"),
}

_WINDOW = "select strftime(s, '%Y-%m-%d %H:%M:%S') as start, strftime(s + interval 1 hour, '%Y-%m-%d %H:%M:%S') as \"end\", event_type, count(*) as n, round(sum(value), 2) as value from ({rows}) group by all"
SQL = {
    "stream_tumbling": _WINDOW.format(rows="select time_bucket(interval 1 hour, ts) as s, event_type, value from events"),
    "stream_sliding": _WINDOW.format(rows="select time_bucket(interval 15 minutes, ts) - k * interval 15 minutes as s, event_type, value from events, range(4) r(k)"),
    "stream_session": "with g as (select user_id, case when ts - lag(ts) over (partition by user_id order by ts) < interval 30 minutes then 0 else 1 end as new from events) select user_id, cast(sum(new) as bigint) as sessions, count(*) as n from g group by all",
    "stream_dedup": "select distinct md5(text) as h from documents",
    "stream_label_counts": "select lang as label, count(*) as n from documents group by all",
    "stream_interval_join": "select p.event_id as purchase_id, e.event_id as error_id from events p join events e using (user_id) where p.event_type = 'purchase' and e.event_type = 'error' and e.ts between p.ts and p.ts + interval 10 hours",
    "stream_drift": "select source, n, flagged, round(flagged / n, 6) as share, n >= 10 and flagged / n >= 0.3 as alert from (select source, count(*) as n, count(*) filter (coalesce(length(text), 0) < 1000) as flagged from documents group by all)",
    "stream_upsert": "select lang as label, cast(count(*) as bigint) as n from documents group by all",
}
