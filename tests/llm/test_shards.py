"""The shard store: round trips, tiers, atomic versions."""

from __future__ import annotations

import duckdb
import pytest
from pyspark.sql import functions as F

from corpusforge.engine import read, scratch_path
from corpusforge.llm.queries import ORACLES, QUERIES
from corpusforge.llm import shards
from corpusforge.llm.shards import ShardStore


def rows_of(df):
    return sorted(map(str, (tuple(r) for r in df.collect())))


def test_arrivals_are_merged_and_nothing_is_lost(spark, small):
    docs = read(spark, small, "documents")
    store = ShardStore(spark, scratch_path(spark, "test-shards"), target=60_000, arrival_rows=20)
    for k in range(3):
        assert store.append(docs.filter(F.pmod("doc_id", F.lit(3)) == k)) == k + 1
    before = store.manifest().agg(F.sum("shards")).first()[0]
    assert store.compact(docs.schema) == 4
    after = store.manifest().collect()
    assert sum(r["shards"] for r in after) < before and sum(r["rows"] for r in after) == docs.count()
    sizes = store.read(docs.schema).select("_metadata.file_path", "_metadata.file_size").distinct().collect()
    assert len(sizes) == sum(r["shards"] for r in after) > 1 and all(s["file_size"] < 2 * 60_000 for s in sizes)
    assert rows_of(store.read(docs.schema)) == rows_of(docs)
    assert rows_of(store.read(docs.schema, version=3)) == rows_of(docs)  # older versions stay readable
    while store.compact(docs.schema) is not None:
        pass
    assert store.plan().isEmpty()
    assert store.vacuum() > 0 and rows_of(store.read(docs.schema)) == rows_of(docs) and len(store.versions()) == 1
    store.append(docs.limit(5))
    assert store.read(docs.schema).count() == docs.count() + 5


def test_compaction_shuffles_no_rows_and_fills_files(spark, tmp_path):
    store = ShardStore(spark, f"file://{tmp_path}/s", target=200_000, arrival_rows=500)
    rows = spark.range(0, 40_000, numPartitions=16).withColumn("x", F.sha2(F.col("id").cast("string"), 256))
    for k in range(4):
        store.append(rows.filter(F.col("id") % 4 == k))
    before = store.manifest().agg(F.sum("shards")).first()[0]
    store.compact(rows.schema)
    run = store.manifest().collect()
    assert len(run) == 1 and before > 50 and run[0]["shards"] <= 2 * -(-run[0]["bytes"] // 200_000)
    assert store.plan().isEmpty() and rows_of(store.read(rows.schema)) == rows_of(rows)


def test_snapshots_and_versions_agree(spark, monkeypatch):
    monkeypatch.setattr(shards, "SNAPSHOT", 3)
    store = ShardStore(spark, scratch_path(spark, "test-shards"), fewest=3)
    rows, want = spark.range(1), {}
    for v in range(1, 9):
        if v % 4 == 0:
            assert store.compact(rows.schema) == v
        else:
            assert store.append(spark.range(v, v + 1)) == v
        want[v] = rows_of(store.read(rows.schema))
    assert all(rows_of(store.read(rows.schema, v)) == want[v] for v in want)
    assert store._numbers("s") == [3, 6] and len(want[8]) == 6
    store.vacuum(keep=2)
    assert store.versions() == [7, 8] and rows_of(store.read(rows.schema, 7)) == want[7] and rows_of(store.read(rows.schema)) == want[8]


def test_of_two_writers_one_fails(spark):
    store = ShardStore(spark, scratch_path(spark, "test-shards"))
    store.append(spark.range(5))
    store.commit(store.changes([]), 2)
    with pytest.raises(Exception, match="(?i)exist"):
        store.commit(store.changes([]), 2)
    assert store.versions() == [1, 2] and store.read(spark.range(1).schema).count() == 5


def test_odd_documents_and_empty_appends(spark, odd_docs, no_docs):
    clash = odd_docs.withColumn("run", F.lit("x")).withColumn("tier", F.lit("y"))
    store = ShardStore(spark, scratch_path(spark, "test-shards"), arrival_rows=1)
    assert store.read(clash.schema).collect() == [] and store.compact(clash.schema) is None
    store.append(clash.limit(0))
    store.append(clash)
    assert store.compact(clash.schema) is not None
    assert rows_of(store.read(clash.schema)) == rows_of(clash)


def test_query_returns_every_document(spark, small):
    con = duckdb.connect()
    con.execute(f"create view documents as select * from '{small}/documents.parquet'")
    assert sorted(map(tuple, QUERIES["op2_sharding"](spark, small).collect())) == sorted(con.execute(ORACLES["op2_sharding"]).fetchall())
