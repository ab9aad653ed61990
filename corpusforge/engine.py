"""What every operator needs from the session: the shared folder, written tables, and Python code on the executors."""

from __future__ import annotations

import atexit
import os
import tempfile
import uuid
import zipfile
from collections.abc import Callable, Iterator
from pathlib import Path

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import types as T

TEXT_TABLES = ("documents", "embeddings", "pages", "benchmark", "labels", "conversations")
TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", *TEXT_TABLES)


def read(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    """A given table, with only the named columns (all when none is named)."""
    table = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return table.select(*columns) if columns else table


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: ``spark.checkpoint.dir`` of the session.

    Where it is unset, a temporary folder of this process serves a local master (tests, one machine); a cluster is refused.
    """
    named = spark.sparkContext.getConf().get("spark.checkpoint.dir", None) or spark.conf.get("spark.checkpoint.dir", None)
    if named:
        return named.rstrip("/")
    if not spark.sparkContext.master.startswith("local"):
        raise RuntimeError("set spark.checkpoint.dir to a folder that driver and executors share")
    if "own" not in _OWN:
        _OWN["own"] = tempfile.mkdtemp(prefix="corpusforge-")
        atexit.register(_remove_tree, _OWN["own"])
    return "file://" + _OWN["own"]


_OWN: dict[str, str] = {}
#: The folder of this process's tables in the shared one.
_RUN = uuid.uuid4().hex


def _remove_tree(path: str) -> None:
    import shutil

    shutil.rmtree(path, ignore_errors=True)


def scratch_path(spark: SparkSession, name: str) -> str:
    """A new path in the shared folder; what lies there goes with :func:`clean`, at the latest when the process ends."""
    if "clean" not in _OWN:
        _OWN["clean"] = ""
        atexit.register(_clean_at_exit)
    return f"{shared_dir(spark)}/corpusforge/{_RUN}/{name}-{uuid.uuid4().hex}"


def clean(spark: SparkSession) -> None:
    """Remove all tables that this process wrote to the shared folder; no DataFrame that reads them may be used afterwards."""
    remove(spark, f"{shared_dir(spark)}/corpusforge/{_RUN}")


def _clean_at_exit() -> None:
    from pyspark import SparkContext

    session = SparkSession.getActiveSession() if SparkContext._active_spark_context is not None else None
    if session is not None:
        try:
            clean(session)
        except Exception:  # the session's JVM is gone already; the folder is left to the cluster's own retention
            pass


def hadoop_path(spark: SparkSession, path: str):
    """The file system of a path and the path, as Hadoop objects: any store that Spark reaches will do."""
    jvm = spark._jvm
    p = jvm.org.apache.hadoop.fs.Path(path)
    return p.getFileSystem(spark._jsc.hadoopConfiguration()), p


def remove(spark: SparkSession, path: str) -> None:
    fs, p = hadoop_path(spark, path)
    fs.delete(p, True)


def written(df: DataFrame, name: str) -> DataFrame:
    """The rows of ``df`` as a table in the shared folder: its lineage ends there, and lost executors don't matter."""
    spark = df.sparkSession
    path = scratch_path(spark, name)
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


class Rounds:
    """Tables written by an iterative plan, where each round only needs the one before it."""

    def __init__(self, spark: SparkSession, name: str, keep: int = 2):
        self.spark, self.name, self.keep, self.paths = spark, name, keep, []

    def write(self, df: DataFrame) -> DataFrame:
        path = scratch_path(self.spark, self.name)
        df.write.parquet(path)
        self.paths.append(path)
        while len(self.paths) > self.keep:
            remove(self.spark, self.paths.pop(0))
        return self.spark.read.schema(df.schema).parquet(path)


#: Rows of an Arrow batch: rows here are whole texts, and a batch is held several times over on its way.
ARROW_ROWS = 1000


def ship(spark: SparkSession) -> None:
    """Send this package to the executors, once a session, so that their Python can import it anywhere."""
    sc = spark.sparkContext
    if int(spark.conf.get("spark.sql.execution.arrow.maxRecordsPerBatch")) > ARROW_ROWS:
        spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", str(ARROW_ROWS))
    if getattr(sc, "_corpusforge_shipped", False):
        return
    root = Path(__file__).resolve().parent
    folder = tempfile.mkdtemp(prefix="corpusforge-ship-")
    atexit.register(_remove_tree, folder)
    target = os.path.join(folder, "corpusforge_package.zip")
    with zipfile.ZipFile(target, "w", zipfile.ZIP_DEFLATED) as z:
        for f in sorted(root.rglob("*.py")):
            z.write(f, f"{root.name}/{f.relative_to(root)}")
    sc.addPyFile(target)
    sc._corpusforge_shipped = True


_STATE: dict[tuple, object] = {}


def worker_state(key: tuple, make: Callable[[], object]):
    """What a Python worker remembers between tasks, of one kind at a time: the next kind's state takes its place."""
    if key not in _STATE:
        if _STATE:
            _STATE.clear()
            _give_back()
        _STATE[key] = make()
    return _STATE[key]


def _give_back() -> None:
    """Return freed memory to the system, which allocators would rather keep."""
    import ctypes
    import gc

    gc.collect()
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL("libc.so.6").malloc_trim(0)
    except (OSError, AttributeError):  # another C library
        pass


Batches = Iterator[pa.RecordBatch]


def arrow_map(df: DataFrame, fn: Callable[[Batches], Batches], schema: str | T.StructType) -> DataFrame:
    """``mapInArrow`` with this package on the executors."""
    ship(df.sparkSession)
    return df.mapInArrow(fn, schema)


def batch(**columns: pa.Array) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays(list(columns.values()), names=list(columns))
