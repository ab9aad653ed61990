"""Pipelines, identification, sources, sinks and streams."""

from __future__ import annotations

import gzip
import hashlib
import importlib.util
import re

import numpy as np
import pytest
from pyspark.sql import functions as F

from corpusforge import engine, queries
from corpusforge.engine import read, scratch_path
from corpusforge.functions import warnings as W
from corpusforge.operators import evaluate, lid, noise, softmax
from corpusforge.plans import annotate, pipeline, sqlapi
from corpusforge.sources import corpus, crawl
from corpusforge.streaming import stream


def plan(df) -> str:
    return df._jdf.queryExecution().explainString(df._sc._jvm.org.apache.spark.sql.execution.ExplainMode.fromString("formatted"))


def test_scans_are_pruned_and_filters_pushed(spark, small):
    text = plan(read(spark, small, "documents", "doc_id", "lang").filter("doc_id > 100"))
    assert "PushedFilters: [IsNotNull(doc_id), GreaterThan(doc_id,100)]" in text and "ReadSchema: struct<doc_id:bigint,lang:string>" in text
    assert "BroadcastHashJoin" in plan(queries.QUERIES["join_broadcast"](spark, small)) and "SortMergeJoin" in plan(queries.QUERIES["join_smj"](spark, small))


def test_annotation_needs_no_shuffle_and_no_python(spark, small):
    text = plan(W.annotate_columns(read(spark, small, "documents")))
    assert "Exchange" not in text and "Python" not in text and "Arrow" not in text
    assert "Exchange" not in plan(queries.QUERIES["warn_all"](spark, small))
    assert "Exchange" not in plan(pipeline.run(read(spark, small, "documents"), pipeline.Config(model=queries.model(spark, small))).kept)


@pytest.fixture(scope="module")
def model(spark, small):
    m = queries.model(spark, small)
    return lid.LidModel(m.counts.cache(), m.totals.cache(), m.buckets, m.alpha, m.pattern)


def test_documents_are_identified(spark, model):
    sf = "/root/testdata/sf0.01"
    gold = read(spark, sf, "documents", "doc_id", "lang").select("doc_id", queries.lab.label_of("lang").alias("gold"))
    p = gold.join(annotate.identify(read(spark, sf, "documents"), model), "doc_id").cache()
    assert evaluate.macro(evaluate.f1(p), "f1").first().value >= 0.97
    lines = p.select("gold", F.explode("lines.pred").alias("pred"))
    assert evaluate.macro(evaluate.f1(lines), "f1").first().value >= 0.90


def test_reject_labels_turn_noise_away(spark, small):
    r = {(x["method"], x["is_noise"]): x["rate"] for x in queries.QUERIES["lid_rejection_vs_threshold"](spark, small).collect()}
    assert r["labels", True] >= 0.95 and r["labels", False] <= 0.01 and r["labels", True] > r["threshold", True]


def test_softmax_equals_plain_descent(spark):
    """One partition, one round: the same parameters as plain numpy gives."""
    rows = [("a", "aba caba"), ("b", "xyz zyx"), ("a", "abba"), ("b", "zzz yx"), ("a", None), ("b", "12")] * 3
    m = softmax.fit_softmax(spark.createDataFrame(rows, "label string, line string"), buckets=500, dim=4, rounds=1, partitions=1, seed=5)
    rng = np.random.default_rng(5)
    embed, weight = rng.uniform(-0.25, 0.25, (500, 4)).astype(np.float32), np.zeros((4, 2))
    h = lambda t: int(hashlib.md5(t.encode()).hexdigest()[:8], 16)
    known = sorted((r for r in rows if r[1] is not None), key=lambda r: (h("5:" + hashlib.md5(r[1].encode()).hexdigest()), r[1]))
    for label, line in known:
        grams = [w[i : i + n] for w in (f" {x} " for x in line.split() if x.isalpha()) for n in range(2, 6) for i in range(len(w) - n + 1)]
        if not grams:
            continue
        ids = [h(g) % 500 for g in grams]
        hidden = embed[ids].mean(axis=0)
        p = np.exp(hidden @ weight - (hidden @ weight).max())
        error = p / p.sum() - np.array([label == "a", label == "b"])
        step = weight @ error
        weight = weight - 0.5 * np.outer(hidden, error)
        for i in ids:
            embed[i] -= 0.5 * step / len(ids)
    assert np.allclose(m.embed, embed, atol=1e-4) and np.allclose(m.weight, weight, atol=1e-4) and np.abs(m.weight).max() > 0.01


def test_softmax_reads_its_rows_twice_whatever_the_rounds(spark):
    """Once to count labels, once to deal rows out to the rounds."""
    read = spark.sparkContext.accumulator(0)

    def counted(batches):
        for rows in batches:
            read.add(rows.num_rows)
            yield rows

    made = [("a", "aba caba"), ("b", "xyz zyx"), ("a", "abba"), ("b", "zzz yx")] * 5
    rows = spark.createDataFrame(made, "label string, line string").mapInArrow(counted, "label string, line string")
    softmax.fit_softmax(rows, buckets=5000, dim=4, rounds=6)
    assert read.value == 2 * len(made)


def test_features_are_those_of_all_letters(spark):
    f = softmax.Features(1000)
    for line in ("", "12 34", "the the Cat's", "É\u0301té 1²Ⅷ ʰ", "\U00010400\U00010428 x", "ы漢字ß"):
        words = re.findall(f"{softmax.letter_class()}+", line.lower())
        want = sorted(int(hashlib.md5(p[i : i + n].encode()).hexdigest()[:8], 16) % 1000 for w in words for p in [f" {w} "] for n in range(2, 6) for i in range(len(p) - n + 1))
        ids, counts = f.counted(line)
        assert np.repeat(ids, counts.astype(int)).tolist() == want


def test_softmax_tells_languages_apart_with_two_million_buckets(spark):
    sf = "/root/testdata/sf0.01"
    m = softmax.fit_softmax(queries.train_lines(spark, sf))
    assert m.embed.shape == (2_000_000, 16)
    test = queries.test_docs(spark, sf)
    p = test.select("doc_id", "gold").join(softmax.predict_softmax(test, m, "doc_id"), "doc_id")
    assert evaluate.macro(evaluate.f1(p), "f1").first().value >= 0.9


def test_binary_files_become_lines(spark, small):
    got = noise.binary_files(spark, f"{small}/nation.parquet").collect()
    assert got and got[0].line.startswith("PAR1") and all(r.line.isprintable() or "\xad" in r.line for r in got)
    with pytest.raises(Exception, match="file too large"):
        noise.binary_files(spark, f"{small}/nation.parquet", most=10).collect()


def test_model_round_trip(spark, model, small):
    path = scratch_path(spark, "model")
    model.save(path)
    again = lid.LidModel.load(spark, path)
    test = queries.test_docs(spark, small)
    rows = lambda m: sorted(map(tuple, lid.predict(test, m, ["doc_id"], "text").select("doc_id", "pred", F.round("prob", 6)).collect()))
    assert rows(again) == rows(model)


def test_pipeline_keeps_or_drops_every_document(spark, small, model):
    docs = read(spark, small, "documents")
    out = pipeline.run(docs, pipeline.Config(lid=lambda d: annotate.identify(d, model), digest=True))
    kept, dropped = ({r.doc_id for r in df.select("doc_id").collect()} for df in (out.kept, out.dropped))
    assert kept | dropped == {r.doc_id for r in docs.collect()} and not kept & dropped
    assert out.kept.filter("lsh_digest is not null").count() > 0
    everything = pipeline.run(docs, pipeline.Config(filter=False)).kept
    assert everything.count() == docs.count()


def test_corpus_sink_replaces_snapshots(spark, small):
    docs = read(spark, small, "documents", "doc_id", "text", "lang").withColumnRenamed("lang", "label")
    path = scratch_path(spark, "corpus")
    corpus.write_corpus(docs.withColumn("snapshot", F.lit("a")), path)
    corpus.write_corpus(docs.limit(50).withColumn("snapshot", F.lit("b")), path)
    corpus.write_corpus(docs.limit(20).withColumn("snapshot", F.lit("b")), path)
    assert {r.snapshot: r.n for r in spark.read.parquet(path).groupBy("snapshot").agg(F.count(F.lit(1)).alias("n")).collect()} == {"a": docs.count(), "b": 20}
    assert corpus.read_label(spark, path, "de").filter("snapshot = 'a'").count() == docs.filter("label = 'de'").count()


def test_crawl_archives(spark, tmp_path):
    record = lambda url, body: f"WARC/1.0\r\nWARC-Type: conversion\r\nWARC-Target-URI: {url}\r\nContent-Length: {len(body.encode())}\r\n\r\n".encode() + body.encode() + b"\r\n\r\n"
    (tmp_path / "a.wet").write_bytes(record("http://x/1", "one\nline é") + record("http://x/2", ""))
    with gzip.open(tmp_path / "b.wet.gz", "wb") as f:
        f.write(record("http://x/3", "three") + b"WARC/1.0\r\nContent-Length: 99\r\n\r\ncut off")
    crawl.register(spark)
    got = {r.url: r.body for r in spark.read.format("crawltext").load(str(tmp_path)).collect()}
    assert got == {"http://x/1": "one\nline é", "http://x/2": "", "http://x/3": "three", None: "cut off"}
    again = crawl.read_archives(spark, f"{tmp_path}/*.wet*").collect()
    assert {r.url: r.body for r in again} == got and [r.record_type for r in again if r.url is None] == ["truncated"]
    streamed = stream.finish(crawl.stream_archives(spark, str(tmp_path)), "archives", "append")
    assert {r.url: r.body for r in streamed.collect()} == got


def test_sql_functions(spark, small):
    sqlapi.register(spark)
    read(spark, small, "documents").createOrReplaceTempView("docs_for_sql")
    n = spark.sql("select count(*) n from docs_for_sql where warn_tiny(text)").first().n
    assert n == queries.QUERIES["warn_tiny"](spark, small).count()
    assert spark.sql("select line from docs_for_sql, lateral line_table(text) where doc_id = 1").count() > 0
    assert spark.sql("select gram from ngram_table('ab', 2, 3)").count() == 5
    assert [r.s for r in spark.sql("select script_of(x) s from values ('abc где'), ('где тут a'), ('12'), (null) t(x)").collect()] == ["Cyrl" if "где" in x and len(x) > 8 else y for x, y in (("abc где", "Cyrl"), ("где тут a", "Cyrl"), ("12", None), ("", None))]
    assert spark.sql("select host_suffixes('a.b.example.org') h").first().h == ["a.b.example.org", "b.example.org", "example.org"]
    pair = spark.sql("select lsh_distance(lsh_digest(text), lsh_digest(text)) same, lsh_distance(lsh_digest(text), lsh_digest(concat(text, ' and more words'))) near from docs_for_sql where length(text) > 2000").first()
    assert pair.same == 0 and 0 <= pair.near < 200
    sqlapi.register_model(spark, queries.model(spark, small))
    said = spark.sql("select lang, lid_label(text) label from docs_for_sql where length(text) > 500").collect()
    assert sum(queries.lab.LABELS[r.lang] == r.label for r in said) >= 0.97 * len(said)
    assert spark.sql("select lsh_digest(text) d from docs_for_sql where length(text) > 500").filter("d is not null").count() > 0


def test_stream_equals_batch(spark, small):
    rows = lambda df: sorted(map(tuple, df.collect()))
    batch = W.annotate(read(spark, small, "documents", "doc_id", "text")).select("doc_id", F.array_join("warnings", ","))
    assert rows(stream.QUERIES["stream_annotate"](spark, small)) == rows(batch)
    path = scratch_path(spark, "coverage")
    cov = stream.to_coverage(stream.source(spark, small, "documents"), path)
    assert rows(cov) == rows(read(spark, small, "documents").groupBy("lang").agg(F.count(F.lit(1))))


def test_streams_with_state(spark, small):
    events = stream.source(spark, small, "events")
    buys, errors = (events.filter(F.col("event_type") == k) for k in ("purchase", "error"))
    got = stream.finish(stream.interval_join(buys, errors, "10 hours"), "interval", "append").count()
    e = read(spark, small, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    p, x = e.filter("event_type = 'purchase'").alias("p"), e.filter("event_type = 'error'").alias("x")
    assert got == p.join(x, F.expr("p.user_id = x.user_id and x.ts >= p.ts and x.ts <= p.ts + interval 10 hours")).count()
    drift = stream.drift(stream.source(spark, small, "documents").withColumn("flag", F.length("text") < 500), "lang", "flag")
    rows = stream.finish(drift, "drift", "update").collect()
    assert sum(r.n for r in rows) == 200 and all(0 <= r.share <= 1 for r in rows)
    once = stream.finish(stream.dedup(events, "user_id", "60 days"), "once", "append")
    assert once.count() == read(spark, small, "events").select("user_id").distinct().count()
    dim = spark.createDataFrame([("en", "English")], "lang string, name string")
    assert stream.finish(stream.enrich(stream.source(spark, small, "documents").select("doc_id", "lang"), dim, "lang"), "enrich", "append").filter("name is not null").count() > 0


def test_library_stands_without_the_training_data_operators():
    import ast
    from pathlib import Path

    root = Path(engine.__file__).parent
    for f in root.rglob("*.py"):
        if "llm" not in f.parts:
            names = [n.module or "" for n in ast.walk(ast.parse(f.read_text())) if isinstance(n, ast.ImportFrom)]
            assert not any(".llm" in n for n in names), f
    assert importlib.util.find_spec("corpusforge.queries") is not None
