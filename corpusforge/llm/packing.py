"""Packing by concatenate and cut: prefix sums over partition token totals, then fixed windows.

First pass: every input partition writes its documents' ids, each with the ids before it in that partition. The partition
totals (one row a partition) give each partition's place in the whole stream of ids. Second pass: every document is cut
where a window of ``seq_len`` ids ends, so its pieces know their sequence and offset without any shuffle of ids. A document
that crosses a window gives one boundary record on each side.

Defined results: a null text counts as empty (its end id alone is packed); repeated rows are packed as often as they occur;
a null doc_id stays null; an empty table gives no pieces; other columns are ignored.
"""

from __future__ import annotations

import zlib
from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from corpusforge.engine import arrow_map, batch, scratch_path
from corpusforge.llm.encoding import encoder

SEQ_LEN = 2048
#: Rows of an Arrow batch that carries ids.
CHUNK = 512

STREAM = "doc_id long, before long, n_tokens long, ids binary"
PIECES = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long"


def token_stream(path: str, end_id: int) -> Callable:
    """Arrow function: (doc_id, text) to STREAM; ``before`` counts the ids of the partition's earlier documents."""

    def run(batches):
        enc, end, before = encoder(path), np.array([end_id], dtype="<u4").tobytes(), 0
        for rows in batches:
            for at in range(0, rows.num_rows, CHUNK):
                part = rows.slice(at, CHUNK)
                ids = [x + end for x in enc.encode(part.column(1).to_pylist())]
                n = np.fromiter((len(x) // 4 for x in ids), dtype=np.int64, count=len(ids))
                first = before + np.cumsum(n) - n
                before += int(n.sum())
                yield batch(doc_id=part.column(0), before=pa.array(first), n_tokens=pa.array(n), ids=pa.array(ids, pa.binary()))

    return run


def cut(seq_len: int, with_ids: bool) -> Callable:
    """Arrow function: (doc_id, at, n_tokens, ids) to pieces; ``at`` is the document's place in the whole stream."""

    def run(batches):
        for rows in batches:
            docs, places, raws = rows.column(0).to_pylist(), rows.column(1).to_pylist(), rows.column(3)
            out = []
            for i, (doc, at) in enumerate(zip(docs, places, strict=True)):
                raw = raws[i].as_buffer()
                n, start = len(raw) // 4, 0
                while start < n:
                    seq, offset = divmod(at + start, seq_len)
                    length = min(n - start, seq_len - offset)
                    ids = memoryview(raw)[4 * start : 4 * (start + length)]
                    out.append((doc, start, length, zlib.crc32(ids), n, seq, offset, *([bytes(ids)] if with_ids else [])))
                    start += length
            names = ["doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset"]
            cols = [pa.array(c, pa.int64()) for c in list(zip(*out, strict=True))[:7]] if out else [pa.array([], pa.int64())] * 7
            if with_ids:
                names, cols = [*names, "ids"], [*cols, pa.array([r[7] for r in out], pa.binary())]
            yield pa.RecordBatch.from_arrays(cols, names=names)

    return run


def placed(stream: DataFrame) -> DataFrame:
    """STREAM rows with ``part`` (their partition) to rows with ``at``, their place in the whole stream.

    One total a partition is summed up in one task; that table has as many rows as the stream has files.
    """
    totals = stream.groupBy("part").agg(F.sum("n_tokens").alias("total"))
    before = Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    offsets = totals.select("part", F.coalesce(F.sum("total").over(before), F.lit(0)).alias("base"))
    return stream.join(F.broadcast(offsets), "part").withColumn("at", F.col("base") + F.col("before"))


def pack(docs: DataFrame, path: str, end_id: int, seq_len: int = SEQ_LEN, with_ids: bool = False) -> DataFrame:
    """Pieces of all documents (and their ids as little-endian unsigned 32-bit integers, if asked for)."""
    spark = docs.sparkSession
    source = docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string"))
    stream = arrow_map(source, token_stream(path, end_id), STREAM).withColumn("part", F.spark_partition_id())
    where = scratch_path(spark, "stream")
    stream.write.parquet(where)
    stream = spark.read.schema(stream.schema).parquet(where)
    return arrow_map(placed(stream).select("doc_id", "at", "n_tokens", "ids"), cut(seq_len, with_ids), PIECES + ", ids binary" * with_ids)
