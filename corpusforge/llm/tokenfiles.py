"""Token ids in ORC files: runs of integers, row indexes and Bloom filters on document ids.

Documents are dealt out by ranges of doc_id, so the files and their stripes hold ascending, disjoint ranges: statistics of
files, stripes and row groups prune a range of ids, Bloom filters prune single ids, and stripes are read in parallel.

Defined results: a null text is empty (its end id alone is stored); a null doc_id comes first and stays null; repeated rows
are stored as often as they occur, equal ids in order of the text's XXH64, then of the text; an empty table gives no rows;
other columns are ignored.
"""

from __future__ import annotations

import zlib
from collections import Counter
from itertools import accumulate

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from corpusforge.engine import arrow_map, batch, scratch_path
from corpusforge.llm.encoding import encoder

#: Format settings: rows between index entries, bytes of a stripe, share of false hits of a Bloom filter.
OPTIONS = {"compression": "snappy", "orc.row.index.stride": "1000", "orc.stripe.size": str(16 << 20), "orc.bloom.filter.columns": "doc_id", "orc.bloom.filter.fpp": "0.01"}
CHUNK = 256
#: Pieces of texts whose ids a worker remembers, some 230 bytes each.
REMEMBERED = 1_600_000
#: What stands for a null id where ranges are found.
LEAST = -(1 << 63)
SCHEMA = "doc_id long, before long, n_tokens long, ids array<int>"


def _encode(path: str, end_id: int):
    def run(batches):
        enc, end, before = encoder(path, REMEMBERED), np.array([end_id], dtype="<u4").tobytes(), 0
        for rows in batches:
            for at in range(0, rows.num_rows, CHUNK):
                part = rows.slice(at, CHUNK)
                raw = [x + end for x in enc.encode(part.column(1).to_pylist())]
                n = np.fromiter((len(x) // 4 for x in raw), dtype=np.int64, count=len(raw))
                ends = np.cumsum(n)
                ids = pa.ListArray.from_arrays(pa.array(np.concatenate([[0], ends]).astype(np.int32)), pa.array(np.frombuffer(b"".join(raw), dtype="<i4")))
                yield batch(doc_id=part.column(0), before=pa.array(before + ends - n), n_tokens=pa.array(n), ids=ids)
                before += int(ends[-1])

    return run


def dealt_by_id(rows: DataFrame) -> DataFrame:
    """Rows in partitions of ascending, disjoint ranges of doc_id, nulls first; an id of many rows fills several partitions.

    The bounds come from the ids alone; ``repartitionByRange`` would read all texts once more for its sample. A row finds its
    range in two steps, among every ``step``-th bound and then between two of those. A bound that is found c times belongs to
    an id (or to null) that holds as many ranges' worth of rows: its rows are dealt to c ranges by their text's hash, in the
    order in which they are sorted. Only rows equal in id and text must share a range.
    """
    n = int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    key = F.coalesce("doc_id", F.lit(LEAST).cast("long"))
    found = rows.select(F.percentile_approx(key, [k / n for k in range(1, n)], 20 * n).alias("b")).first()["b"] if n > 1 else None
    times = Counter(found or [])  # one number for each partition at most
    if not times:
        return rows.coalesce(1)
    bounds = sorted(times)
    step = int(len(bounds) ** 0.5) + 1
    numbers = lambda x, kind: F.array(*[F.lit(b).cast(kind) for b in x])
    coarse, fine = numbers(bounds[::step], "long"), numbers(bounds, "long")
    last, copies = numbers(accumulate(times[b] for b in bounds), "int"), numbers([times[b] for b in bounds], "int")
    block = F.size(F.filter(coarse, lambda b: b <= key))
    inside = (block - 1) * step + F.size(F.filter(F.slice(fine, (block - 1) * step + 1, F.lit(step)), lambda b: b <= key))
    dealt = rows.withColumn("_at", F.when(block > 0, inside).otherwise(0))
    at = F.col("_at")
    share = F.xxhash64("text").cast("double") / float(1 << 64) + 0.5
    spare = F.get(copies, at - 1) - 1
    # an id that is the least number itself follows the nulls
    spread = (spare > 0) & (F.get(fine, at - 1) == key) & ~F.coalesce(F.col("doc_id") == F.lit(LEAST), F.lit(False))
    back = F.when(spread, spare - F.least(spare, F.floor(share * (spare + 1)).cast("int"))).otherwise(0)
    return dealt.withColumn("_range", F.when(at > 0, F.get(last, at - 1) - back).otherwise(0).cast("int")).repartitionById(sum(times.values()) + 1, F.col("_range")).drop("_range", "_at")


def write_ids(docs: DataFrame, path: str, tokenizer: str, end_id: int) -> None:
    """Encode every document, append ``end_id``, and write the ids in ascending doc_id order."""
    source = docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string"))
    ordered = dealt_by_id(source).sortWithinPartitions(F.col("doc_id").asc_nulls_first(), F.xxhash64("text"), "text")
    arrow_map(ordered, _encode(tokenizer, end_id), SCHEMA).withColumn("part", F.spark_partition_id()).write.options(**OPTIONS).orc(path)


def read_ids(spark: SparkSession, path: str) -> DataFrame:
    """The files' rows with ``start``, the ids of all documents before."""
    files = spark.read.schema(SCHEMA + ", part int").orc(path)
    totals = files.groupBy("part").agg(F.sum("n_tokens").alias("total"))
    before = Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    bases = totals.select("part", F.coalesce(F.sum("total").over(before), F.lit(0)).alias("base"))  # a row for each file
    return files.join(F.broadcast(bases), "part").select("doc_id", (F.col("base") + F.col("before")).alias("start"), "n_tokens", "ids")


def look_up(spark: SparkSession, path: str, doc_ids: list[int]) -> DataFrame:
    """Some documents by id: statistics and Bloom filters keep the reader from the other stripes and row groups."""
    return spark.read.schema(SCHEMA).orc(path).filter(F.col("doc_id").isin(doc_ids)).select("doc_id", "n_tokens", "ids")


def _sums(batches):
    for rows in batches:
        ids = rows.column(3)
        values, at = ids.values.to_numpy(zero_copy_only=False), ids.offsets.to_numpy()
        raw = memoryview(np.ascontiguousarray(values, dtype="<i4")).cast("B")
        sums = [zlib.crc32(raw[4 * a : 4 * b]) for a, b in zip(at[:-1].tolist(), at[1:].tolist(), strict=True)]
        yield batch(doc_id=rows.column(0), start=rows.column(1), n_tokens=pa.array(np.diff(at).astype(np.int64)), ids_crc32=pa.array(sums, pa.int64()))


def digests(ids: DataFrame) -> DataFrame:
    """Rows of :func:`read_ids` to counts and check sums, both taken from the ids that were read."""
    return arrow_map(ids.select("doc_id", "start", "n_tokens", "ids"), _sums, "doc_id long, start long, n_tokens long, ids_crc32 long")


def round_trip(docs: DataFrame, tokenizer: str, end_id: int) -> DataFrame:
    """Write and read back through a new folder of the shared one."""
    spark = docs.sparkSession
    path = scratch_path(spark, "ids")
    write_ids(docs, path, tokenizer, end_id)
    return digests(read_ids(spark, path))
