"""Size-tiered compaction of immutable shards under a versioned manifest, with DataFrame functions only.

An arrival is appended as a run: a folder of small shards, written by narrow tasks. Runs are grouped into tiers by size;
the runs of a tier whose shards are small and together enough are merged into one run of target-sized files, by narrow tasks
again, since rows have no order to keep: partitions are put together, nothing is shuffled. A run of full files is settled
and never rewritten, so each row is rewritten about once a tier.

A version of the manifest holds only what its commit added and removed, one row a run; every ``SNAPSHOT`` versions the whole
state is written beside it, so a commit costs what it changes and a reader opens a bounded number of manifests. A version
takes effect by one rename that fails if the version exists, so readers see whole versions and of two writers one must try
again; this asks for a file system whose rename is atomic and refuses an existing target (HDFS and the like, local disks,
not plain object stores). Shards are never changed; those of replaced runs go with :meth:`vacuum`.

Defined results: all rows and columns come back as they were appended, nulls, repeats and empty texts included; an empty
append adds a run without rows; compaction without enough small shards makes no version.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from corpusforge.engine import hadoop_path, read, remove, scratch_path

#: Bytes of a full shard; factor between tiers; bytes of the lowest tier; small shards that are worth a merge; rows of an arrival's file.
TARGET, FACTOR, LOWEST, FEWEST, ARRIVAL_ROWS = 64 << 20, 4, 1 << 20, 4, 4096
#: Versions between two whole states.
SNAPSHOT = 32
MANIFEST = "run string, bytes long, shards long, rows long, tier int"
CHANGES = "added boolean, " + MANIFEST


class ShardStore:
    """Runs and manifests under one folder."""

    def __init__(self, spark: SparkSession, root: str, target: int = TARGET, fewest: int = FEWEST, arrival_rows: int = ARRIVAL_ROWS):
        self.spark, self.root, self.target, self.fewest, self.arrival_rows = spark, root, target, fewest, arrival_rows

    def _numbers(self, letter: str) -> list[int]:
        fs, folder = hadoop_path(self.spark, f"{self.root}/manifest")
        if not fs.exists(folder):
            return []
        names = [s.getPath().getName() for s in fs.listStatus(folder)]
        return sorted(int(n[1:]) for n in names if n.startswith(letter) and n[1:].isdigit())

    def versions(self) -> list[int]:
        return self._numbers("v")

    def changes(self, versions: list[int]) -> DataFrame:
        paths = [f"{self.root}/manifest/v{v:08d}" for v in versions]
        return self.spark.read.schema(CHANGES).parquet(*paths) if paths else self.spark.createDataFrame([], CHANGES)

    def manifest(self, version: int | None = None) -> DataFrame:
        """The runs of a version, the last if none is named."""
        known = self.versions()
        last = (known[-1] if known else 0) if version is None else version
        base = max((s for s in self._numbers("s") if s <= last), default=0)
        logged = self.changes([v for v in known if base < v <= last])
        state = logged.filter("added").drop("added")
        if base:
            state = self.spark.read.schema(MANIFEST).parquet(f"{self.root}/manifest/s{base:08d}").union(state)
        return state.join(logged.filter("not added").select("run"), "run", "left_anti")

    def _publish(self, rows: DataFrame, name: str) -> None:
        jvm = self.spark._jvm
        temporary = f"{self.root}/manifest/_{uuid.uuid4().hex}"
        rows.write.parquet(temporary)
        source, target = jvm.org.apache.hadoop.fs.Path(temporary), jvm.org.apache.hadoop.fs.Path(f"{self.root}/manifest/{name}")
        context = jvm.org.apache.hadoop.fs.FileContext.getFileContext(source.toUri(), self.spark._jsc.hadoopConfiguration())
        none = self.spark.sparkContext._gateway.new_array(jvm.org.apache.hadoop.fs.Options.Rename, 0)
        try:
            context.rename(source, target, none)
        except Exception:
            remove(self.spark, temporary)
            raise

    def commit(self, changes: DataFrame, version: int) -> None:
        """Make ``changes`` (CHANGES rows, one a run) the version; raises if another writer was first."""
        self._publish(changes.coalesce(1), f"v{version:08d}")
        if version % SNAPSHOT == 0:
            self._publish(self.manifest(version), f"s{version:08d}")

    def _described(self, run: str, schema) -> DataFrame:
        """The manifest row of a written run: its shards, bytes and rows from metadata columns alone, and its tier."""
        files = self.spark.read.schema(schema).parquet(f"{self.root}/data/{run}")
        meta = files.select(F.col("_metadata.file_path").alias("path"), F.col("_metadata.file_size").alias("size"))
        sized = meta.groupBy("path").agg(F.max("size").alias("size"), F.count(F.lit(1)).alias("n"))
        total = sized.agg(F.coalesce(F.sum("size"), F.lit(0)).alias("bytes"), F.count(F.lit(1)).alias("shards"), F.coalesce(F.sum("n"), F.lit(0)).alias("rows"))
        tier = F.greatest(F.floor(F.log(F.greatest("bytes", F.lit(1)) / LOWEST) / F.log(F.lit(float(FACTOR)))) + 1, F.lit(0)).cast("int")
        return total.select(F.lit(True).alias("added"), F.lit(run).alias("run"), "bytes", "shards", "rows", tier.alias("tier"))

    def append(self, rows: DataFrame) -> int:
        """Add rows as a run of small shards, where they lie; returns the new version."""
        run = uuid.uuid4().hex
        rows.write.option("maxRecordsPerFile", self.arrival_rows).option("compression", "zstd").parquet(f"{self.root}/data/{run}")
        version = (self.versions() or [0])[-1] + 1
        self.commit(self._described(run, rows.schema), version)
        return version

    def plan(self) -> DataFrame:
        """Tiers to merge: (tier, runs, bytes, rows, shards) of runs with small shards, where these are enough together."""
        small = self.manifest().filter((F.col("rows") > 0) & (F.col("bytes") < F.col("shards") * (self.target * 3 // 4)))
        tiers = small.groupBy("tier").agg(F.collect_list("run").alias("runs"), F.sum("bytes").alias("bytes"), F.sum("rows").alias("rows"), F.sum("shards").alias("shards"))
        return tiers.filter((F.col("shards") >= self.fewest) & (F.col("shards") > F.ceil(F.col("bytes") / self.target)))

    def compact(self, schema) -> int | None:
        """Merge what :meth:`plan` names, each tier into a run of its own; the new version, or ``None`` where nothing is to be merged.

        The plan has a row a tier with the names of its runs, some dozens between two compactions, not of shards.
        """
        gone, changes = [], None
        for tier in self.plan().collect():
            run, files = uuid.uuid4().hex, max(-(-tier["bytes"] // self.target), 1)
            rows = self.spark.read.schema(schema).parquet(*[f"{self.root}/data/{r}" for r in tier["runs"]])
            fair = -(-tier["rows"] * 5 // (files * 4))  # a file has a quarter more rows than its share at most
            rows.coalesce(files).write.option("compression", "zstd").option("maxRecordsPerFile", fair).parquet(f"{self.root}/data/{run}")
            own = self._described(run, schema)
            changes = own if changes is None else changes.union(own)
            gone += tier["runs"]
        if changes is None:
            return None
        dropped = self.manifest().filter(F.col("run").isin(gone)).select(F.lit(False).alias("added"), "run", "bytes", "shards", "rows", "tier")
        version = self.versions()[-1] + 1
        self.commit(changes.union(dropped), version)
        return version

    def read(self, schema, version: int | None = None) -> DataFrame:
        """All rows of a version, with Spark's hidden ``_metadata`` of their shards; the driver names runs, Spark lists their shards."""
        paths = [f"{self.root}/data/{r['run']}" for r in self.manifest(version).select("run").collect()]
        return self.spark.read.schema(schema).parquet(*paths) if paths else self.spark.createDataFrame([], schema)

    def vacuum(self, keep: int = 1) -> int:
        """Delete runs that none of the last ``keep`` versions has, and older manifests; returns how many runs went."""
        versions = self.versions()
        old, first = versions[:-keep], versions[-keep] if len(versions) >= keep else 0
        if not old:
            return 0
        if first not in self._numbers("s"):
            self._publish(self.manifest(first), f"s{first:08d}")
        replaced = self.changes([v for v in versions if v <= first]).filter("not added").select("run").distinct()
        gone = 0
        for r in replaced.toLocalIterator():
            remove(self.spark, f"{self.root}/data/{r['run']}")
            gone += 1
        for v in old:
            remove(self.spark, f"{self.root}/manifest/v{v:08d}")
        for s in self._numbers("s"):
            if s < first:
                remove(self.spark, f"{self.root}/manifest/s{s:08d}")
        return gone


#: Arrivals of the query.
ARRIVALS = 4


def compacted(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Append the documents in arrivals, compact them, and read the last version back."""
    docs = read(spark, sf_dir, "documents")
    store = ShardStore(spark, scratch_path(spark, "shards"))
    for k in range(ARRIVALS):
        store.append(docs.filter(F.coalesce(F.pmod(F.col("doc_id"), F.lit(ARRIVALS)), F.lit(0)) == k))
    store.compact(docs.schema)
    return store.read(docs.schema).select("doc_id", F.md5("text").alias("text_md5"), "lang", "source", "n_chars")
