"""Near copies by the Jaccard similarity of word shingles: SimHash blocks and MinHash bands find candidates, exact shares decide.

A text is its set of shingles. Texts with equal sets meet once. Candidates come from two places. The fingerprints of
:mod:`corpusforge.llm.simhash` over the same shingles, joined on pigeonhole blocks, link what differs in a few bits. At a
similarity of 0.8 fingerprints differ in some ten bits of 64, far beyond what blocks can join, so MinHash bands add the rest:
of BANDS bands of ROWS minima one agrees for texts of similarity s but for a share (1 - s ** ROWS) ** BANDS of the pairs:
three in a million at 0.8, fewer above. Groups of a band with the same members are met once; a task holds the shingle hashes
of a bounded run of a group and links it by a spanning forest of exact similarities; longer groups are split into blocks, and
each pair of blocks is a run of its own.

Defined results: null and blank texts are copies of each other; a row without doc_id is never dropped and stands for nobody;
rows that repeat a doc_id with another text belong to that text's group.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from corpusforge.engine import arrow_map, batch, worker_state, written
from corpusforge.llm.simhash import fingerprint, keep_first, links, row_hash, sent, shingle_hashes
from corpusforge.operators.components import components

WORDS, SIMILARITY = 5, 0.8
BANDS, ROWS = 24, 4
#: Members of a group that one task compares at once.
RUN = 1024
#: Shingle hashes whose minima are taken at once.
SLICE = 4096
_RNG = np.random.default_rng(20240307)
_TURN = _RNG.integers(0, 1 << 63, (BANDS * ROWS, 1), dtype=np.uint64)
_TIMES = _RNG.integers(0, 1 << 63, (BANDS * ROWS, 1), dtype=np.uint64) * np.uint64(2) + np.uint64(1)


def shingles(text: str | None, words: int = WORDS) -> np.ndarray:
    """Sorted hashes of the distinct word shingles."""
    return np.unique(shingle_hashes(text, words))


def sketch(text: str | None, words: int) -> tuple[np.ndarray, int]:
    """The shingles and the fingerprint of a text."""
    hashes = shingle_hashes(text, words)
    return np.unique(hashes), fingerprint(hashes)


def bands(hashes: np.ndarray) -> list[int]:
    """A key for each band, the band's number included; nothing for a text without words."""
    if not len(hashes):
        return []
    least = np.full(BANDS * ROWS, np.iinfo(np.uint64).max)
    for at in range(0, len(hashes), SLICE):
        least = np.minimum(least, ((hashes[at : at + SLICE] ^ _TURN) * _TIMES).min(axis=1))
    return [xxhash.xxh64_intdigest(row.tobytes(), number) - (1 << 63) for number, row in enumerate(least.reshape(BANDS, ROWS))]


def _sketches(words: int):
    def run(batches):
        worker_state(("shingles",), object)
        for rows in batches:
            sets, prints = zip(*(sketch(t, words) for t in rows.column(1).to_pylist()), strict=True) if rows.num_rows else ((), ())
            whole = pa.array([xxhash.xxh64_intdigest(s.tobytes()) - (1 << 63) for s in sets], pa.int64())
            yield batch(doc_id=rows.column(0), row=rows.column(2), whole=whole, bands=pa.array([bands(s) for s in sets], pa.list_(pa.int64())), print=pa.array(np.array(prints, dtype=np.uint64).view(np.int64)))

    return run


def _sets(words: int):
    def run(batches):
        worker_state(("shingles",), object)
        for rows in batches:
            yield batch(whole=rows.column(0), hashes=pa.array([shingles(t, words).tobytes() for t in rows.column(1).to_pylist()], pa.binary()))

    return run


def forest(sets: list[np.ndarray], similarity: float) -> list[tuple[int, int]]:
    """Links between places that join all sets of at least this similarity: from each one reached to all not yet reached."""
    sizes = np.array(list(map(len, sets)))
    codes = np.unique(np.concatenate(sets), return_inverse=True)[1]
    parts = np.split(codes, np.cumsum(sizes)[:-1])
    inside = np.zeros(int(codes.max()) + 1, dtype=bool)
    left, out = np.arange(len(sets)), []
    while len(left):
        queue, left = [int(left[0])], left[1:]
        while queue and len(left):
            at = queue.pop()
            fit = left[np.minimum(sizes[left], sizes[at]) >= similarity * np.maximum(sizes[left], sizes[at]) - 1e-9]
            inside[parts[at]] = True
            both = np.array([np.count_nonzero(inside[parts[i]]) for i in fit.tolist()], dtype=np.int64)
            inside[parts[at]] = False
            found = fit[both >= similarity * (sizes[fit] + sizes[at] - both) - 1e-9]
            left = np.setdiff1d(left, found, assume_unique=True)
            queue.extend(found.tolist())
            out.extend((at, i) for i in found.tolist())
    return out


def _link_groups(similarity: float):
    """Arrow function over (key, sub, whole, hashes), sorted by key and sub: links (a, b)."""

    def run(batches):
        worker_state(("shingle links",), object)
        at, ids, sets = None, [], []

        def close() -> list[tuple[int, int]]:
            return [(ids[x], ids[y]) for x, y in forest(sets, similarity)] if len(ids) > 1 else []

        for rows in batches:
            found: list[tuple[int, int]] = []
            for key, sub, whole, hashes in zip(*(c.to_pylist() for c in rows.columns), strict=True):
                if (key, sub) != at:
                    found.extend(close())
                    at, ids, sets = (key, sub), [], []
                ids.append(whole)
                sets.append(np.frombuffer(hashes, dtype=np.uint64))
            yield batch(a=pa.array([a for a, _ in found], pa.int64()), b=pa.array([b for _, b in found], pa.int64()))
        found = close()
        yield batch(a=pa.array([a for a, _ in found], pa.int64()), b=pa.array([b for _, b in found], pa.int64()))

    return run


def near_copies(docs: DataFrame, words: int = WORDS, similarity: float = SIMILARITY, run: int = RUN) -> DataFrame:
    """(doc_id, component_id) of every document with a doc_id; the component is the smallest doc_id reachable by links."""
    own, component = _grouped(docs, words, similarity, run)
    return own.select("doc_id", "whole").join(component, "whole").select("doc_id", "component_id")


def _grouped(docs: DataFrame, words: int, similarity: float, run: int) -> tuple[DataFrame, DataFrame]:
    """(doc_id, row, whole) of every document with a doc_id, and (whole, component_id) of its set of shingles.

    The first pass over the texts leaves sketches of some hundred bytes each. Sets of shingles, as long as the texts, are made
    in a second pass and for one row of each text that a group holds beside another.
    """
    source = docs.filter("doc_id is not null").select(F.col("doc_id").cast("long"), F.col("text").cast("string"), row_hash(docs).alias("row"))
    own = written(arrow_map(source, _sketches(words), "doc_id long, row long, whole long, bands array<long>, print long"), "sketches")
    distinct = written(own.groupBy("whole").agg(F.min(F.struct("doc_id", "row")).alias("first"), F.first("bands").alias("bands"), F.first("print").alias("print")), "distinct")
    banded = distinct.select("whole", F.explode("bands").alias("key"))
    groups = banded.groupBy("key").agg(F.count(F.lit(1)).alias("n"), F.bit_xor(F.xxhash64("whole")).alias("x"), F.min("whole").alias("least"), F.max("whole").alias("most")).filter("n > 1")
    groups = groups.groupBy("n", "x", "least", "most").agg(F.min("key").alias("key")).select("key", "n")
    members = written(banded.join(groups, "key").unionByName(_by_fingerprint(distinct)), "members")
    wanted = distinct.join(members.select("whole").distinct(), "whole", "left_semi").select("whole", F.col("first.doc_id").alias("i"), F.col("first.row").alias("r"))
    wanted = sent(written(wanted, "wanted"))
    texts = source.join(wanted, (F.col("doc_id") == F.col("i")) & (F.col("row") == F.col("r"))).select("whole", "text")
    sets = arrow_map(texts, _sets(words), "whole long, hashes binary").groupBy("whole").agg(F.first("hashes").alias("hashes"))
    blocks = members.withColumn("blocks", F.when(F.col("n") > run, F.ceil(F.col("n") * 2 / run)).otherwise(1).cast("long")).withColumn("mine", F.expr("pmod(xxhash64(whole, 7), blocks)"))
    dealt = blocks.select("key", "whole", F.explode(F.expr("transform(sequence(0L, blocks - 1), o -> least(o, mine) * blocks + greatest(o, mine))")).alias("sub"))
    runs = dealt.join(sets, "whole").select("key", "sub", "whole", "hashes").repartition("key", "sub").sortWithinPartitions("key", "sub")
    linked = components(arrow_map(runs, _link_groups(similarity), "a long, b long"))
    reached = distinct.select("whole", F.col("first.doc_id").alias("id")).join(linked.withColumnsRenamed({"id": "whole", "component": "group"}), "whole", "left")
    first = reached.filter("group is not null").groupBy("group").agg(F.min("id").alias("least"))
    return own, reached.join(first, "group", "left").select("whole", F.coalesce("least", "id").alias("component_id"))


def _by_fingerprint(distinct: DataFrame) -> DataFrame:
    """(key, whole, n): groups of two that fingerprints of few differing bits link."""
    prints = distinct.filter(F.size("bands") > 0).groupBy("print").agg(F.min("whole").alias("id"))
    linked = links(prints)
    equal = distinct.select("print", "whole").join(prints.withColumnRenamed("id", "b"), "print").filter("whole <> b").select(F.col("whole").alias("a"), "b")
    pairs = linked.union(equal).select(F.xxhash64(F.least("a", "b"), F.greatest("a", "b"), F.lit("print")).alias("key"), F.explode(F.array("a", "b")).alias("whole"))
    return pairs.distinct().withColumn("n", F.lit(2).cast("long"))


def first_of_each(docs: DataFrame, words: int = WORDS, similarity: float = SIMILARITY, run: int = RUN) -> DataFrame:
    """Rows, with all their columns, that stand for their group: of a group one row of the smallest doc_id; rows without doc_id stay."""
    own, component = _grouped(docs, words, similarity, run)
    return keep_first(docs, own.select("doc_id", "row", "whole").join(component, "whole").select("doc_id", "row", F.col("component_id").alias("group")))
