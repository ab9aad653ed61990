"""SimHash near-duplicates by pigeonhole blocks.

A fingerprint has 64 bits. With at most d differing bits, of d + 2 blocks at least two are equal, so fingerprints are joined
on pairs of blocks (15 keys for d = 4) and then compared bit by bit. Equal fingerprints meet once: the join runs over
distinct fingerprints. Rows of a key come sorted to a task, which links them by a spanning forest (never all pairs) and
hands on what is longer than a bounded run; those runs are split into blocks and each pair of blocks is a task of its own.

Defined results: a null or blank text has fingerprint zero and links like any other; repeated rows share a component; a row
without doc_id gets a fingerprint and no component; an empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

from itertools import combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from corpusforge.engine import arrow_map, batch, worker_state, written
from corpusforge.operators.components import components

WORDS, DISTANCE, SEED = 4, 4, 42
#: Members of a key that one task compares; longer runs are split.
RUN = 4096
#: Shingle hashes whose bits are counted at once.
SLICE = 1 << 16


def shingle_hashes(text: str | None, words: int = WORDS) -> np.ndarray:
    """XXH64 of each word shingle, repeats included; words are split at ASCII white space, A-Z in lower case."""
    parts = (text or "").encode().lower().split()
    if not parts:
        return np.empty(0, dtype=np.uint64)
    joined = b" ".join(parts)
    if len(parts) <= words:
        return np.array([xxhash.xxh64_intdigest(joined, SEED)], dtype=np.uint64)
    ends = np.cumsum(np.fromiter(map(len, parts), dtype=np.int64, count=len(parts)) + 1)
    starts = [0, *ends[:-words].tolist()]
    digest = xxhash.xxh64_intdigest
    return np.array([digest(joined[s:e], SEED) for s, e in zip(starts, (ends[words - 1 :] - 1).tolist(), strict=True)], dtype=np.uint64)


def fingerprint(hashes: np.ndarray) -> int:
    """Bits that are set in more than half of the hashes."""
    ones = np.zeros(64, dtype=np.int64)
    for at in range(0, len(hashes), SLICE):
        ones += np.unpackbits(hashes[at : at + SLICE].view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    return int(np.packbits(2 * ones > len(hashes), bitorder="little").view(np.uint64)[0])


def _fingerprints(words: int):
    def run(batches):
        worker_state(("fingerprints",), object)
        for rows in batches:
            prints = np.array([fingerprint(shingle_hashes(t, words)) for t in rows.column(1).to_pylist()], dtype=np.uint64)
            yield pa.RecordBatch.from_arrays([rows.column(0), pa.array(prints.view(np.int64)), *rows.columns[2:]], names=["doc_id", "print", *rows.schema.names[2:]])

    return run


def fingerprints(docs: DataFrame, words: int = WORDS) -> DataFrame:
    """(doc_id, print): the fingerprint of every whole text as a signed 64-bit integer."""
    return arrow_map(docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")), _fingerprints(words), "doc_id long, print long")


def block_keys(distance: int):
    """One (number, value of two blocks) key for each pair of blocks, as a column of arrays over ``print``."""
    n = distance + 2
    bounds = [64 * i // n for i in range(n + 1)]

    def block(i: int):
        return F.shiftrightunsigned("print", bounds[i]).bitwiseAND((1 << (bounds[i + 1] - bounds[i])) - 1)

    keys = []
    for number, (i, j) in enumerate(combinations(range(n), 2)):
        wide = bounds[i + 1] - bounds[i]
        keys.append(F.shiftleft(block(j), wide).bitwiseOR(block(i)).bitwiseOR(F.lit(number << 48)))
    return F.array(*keys)


def _forest(prints: np.ndarray, ids: np.ndarray, distance: int) -> list[tuple[int, int]]:
    """Links that join the members of each component: from each one reached, to all not yet reached and close to it."""
    left, out = np.arange(len(prints)), []
    while len(left):
        queue, left = [int(left[0])], left[1:]
        while queue and len(left):
            at = queue.pop()
            close = np.bitwise_count(prints[left] ^ prints[at]) <= distance
            if close.any():
                found = left[close]
                left = left[~close]
                queue.extend(found.tolist())
                out.extend((int(ids[at]), int(x)) for x in ids[found])
    return out


def _link_runs(distance: int, longest: int):
    """Arrow function over (key, sub, print, id), sorted by key and sub: links (a, b), or rows of longer runs as they come."""

    def run(batches):
        links: list[tuple[int, int]] = []
        key, sub, prints, ids, over = None, None, [], [], False

        def result(more=()):
            a, b = [x for x, _ in links], [x for _, x in links]
            links.clear()
            nones = [None] * len(a)
            k, s, p, i = (np.concatenate(x).tolist() for x in more) if more else ([], [], [], [])
            pad = [None] * len(k)
            return batch(a=pa.array(a + pad, pa.int64()), b=pa.array(b + pad, pa.int64()), key=pa.array(nones + k, pa.int64()), sub=pa.array(nones + s, pa.int64()), print=pa.array(nones + p, pa.int64()), id=pa.array(nones + i, pa.int64()))

        def close():
            if len(ids) and not over and sum(map(len, ids)) > 1:
                links.extend(_forest(np.concatenate(prints).view(np.uint64), np.concatenate(ids), distance))

        for rows in batches:
            k, s, p, i = (rows.column(c).to_numpy(zero_copy_only=False) for c in range(4))
            if not len(k):
                continue
            cuts = np.flatnonzero((np.diff(k) != 0) | (np.diff(s) != 0)) + 1
            starts, ends = np.concatenate([[0], cuts]), np.concatenate([cuts, [len(k)]])
            # pairs, the most frequent runs, all at once; not the batch's first and last run, which may go on elsewhere
            two = np.flatnonzero(ends - starts == 2)
            two = two[(two > 0) & (two < len(starts) - 1)]
            x, y = starts[two], starts[two] + 1
            near = np.bitwise_count(p[x].view(np.uint64) ^ p[y].view(np.uint64)) <= distance
            links.extend(zip(i[x[near]].tolist(), i[y[near]].tolist(), strict=True))
            rest = np.flatnonzero(ends - starts != 1)
            rest = np.union1d(np.setdiff1d(rest, two), [0, len(starts) - 1])
            more: list[list[np.ndarray]] = [[], [], [], []]
            for a, b in zip(starts[rest].tolist(), ends[rest].tolist(), strict=True):
                if (k[a], s[a]) != (key, sub):
                    close()
                    key, sub, prints, ids, over = k[a], s[a], [], [], False
                prints.append(p[a:b])
                ids.append(i[a:b])
                n = sum(map(len, ids))
                if over or n > longest:
                    over = True
                    for column, values in zip(more, (np.full(n, key), np.full(n, sub), np.concatenate(prints), np.concatenate(ids)), strict=True):
                        column.append(values)
                    prints, ids = [], []
            if links or more[0]:
                yield result(more if more[0] else ())
        close()
        yield result()

    return run


LINKS = "a long, b long, key long, sub long, print long, id long"


def links(prints: DataFrame, distance: int = DISTANCE, run: int = RUN) -> DataFrame:
    """Links (a, b) that connect all fingerprints (columns print, id; distinct prints) at ``distance`` bits or fewer."""
    keyed = prints.select(F.explode(block_keys(distance)).alias("key"), F.lit(0).cast("long").alias("sub"), "print", "id")
    first = written(arrow_map(keyed.repartition("key").sortWithinPartitions("key"), _link_runs(distance, run), LINKS), "runs")
    long = first.filter("key is not null")
    sizes = long.groupBy("key").agg(F.count(F.lit(1)).alias("n"))
    blocks = long.join(sizes, "key").withColumn("blocks", F.ceil(F.col("n") * 2 / run).cast("long")).withColumn("mine", F.expr("pmod(xxhash64(print), blocks)"))
    paired = blocks.select(
        "key", "print", "id", F.explode(F.expr("transform(sequence(0L, blocks - 1), o -> least(o, mine) * blocks + greatest(o, mine))")).alias("sub")
    )
    second = arrow_map(paired.select("key", "sub", "print", "id").repartition("key", "sub").sortWithinPartitions("key", "sub"), _link_runs(distance, 1 << 30), LINKS)
    return first.filter("key is null").select("a", "b").union(second.filter("key is null").select("a", "b"))


def near_duplicates(docs: DataFrame, words: int = WORDS, distance: int = DISTANCE, run: int = RUN) -> DataFrame:
    """(doc_id, print, component_id) of every document; the component is the smallest doc_id reachable by links."""
    prints = written(fingerprints(docs, words), "prints")
    distinct = written(prints.filter("doc_id is not null").groupBy("print").agg(F.min("doc_id").alias("id")), "distinct")
    found = components(links(distinct, distance, run))
    component = distinct.join(found, "id", "left").select(F.col("print").alias("of"), F.coalesce("component", "id").alias("component"))
    joined = prints.join(component, prints.print == component.of, "left")
    return joined.select("doc_id", "print", F.when(F.col("doc_id").isNotNull(), F.col("component")).alias("component_id"))


def first_of_each(docs: DataFrame, words: int = WORDS, distance: int = DISTANCE) -> DataFrame:
    """Rows, with all their columns, that stand for their group: of a group one row of the smallest doc_id; rows without doc_id stay."""
    source = docs.filter("doc_id is not null").select(F.col("doc_id").cast("long"), F.col("text").cast("string"), row_hash(docs).alias("row"))
    prints = written(arrow_map(source, _fingerprints(words), "doc_id long, print long, row long"), "prints")
    distinct = written(prints.groupBy("print").agg(F.min("doc_id").alias("id")), "distinct")
    component = distinct.join(components(links(distinct, distance)), "id", "left").select("print", F.coalesce("component", "id").alias("group"))
    return keep_first(docs, prints.join(component, "print").select("doc_id", "row", "group"))


def row_hash(docs: DataFrame):
    """A number that tells rows of one doc_id apart; equal rows have the same."""
    return F.xxhash64(*[F.col(f"`{c}`") for c in docs.columns])


#: Rows of two numbers that are broadcast at most, some 64 MB; more are joined by shuffle.
SENT = 4_000_000


def sent(rows: DataFrame) -> DataFrame:
    """Narrow rows of a written table, to be broadcast if they are few enough: then the texts they are joined with stay where they lie."""
    return F.broadcast(rows) if rows.limit(SENT + 1).count() <= SENT else rows


def keep_first(docs: DataFrame, members: DataFrame) -> DataFrame:
    """``docs`` without the rows that another row of their group stands for; ``members`` has (doc_id, row, group) of each row with a doc_id.

    Rows are told apart by their doc_id and a hash of all columns, so rows of one doc_id with different texts have each
    their own fate. The smallest doc_id stands for a group, of its rows the one with the smallest hash, of equal rows one.
    Only ids and hashes travel, but for the rows of a repeated one that stays.
    """
    members = written(members, "members")
    first = members.groupBy("group").agg(F.min(F.struct("doc_id", "row")).alias("first")).select(F.col("group").alias("g"), "first.*")
    first = first.select("g", F.col("doc_id").alias("i"), F.col("row").alias("r"))
    counted = members.groupBy("group", "doc_id", "row").agg(F.count(F.lit(1)).alias("n"))
    told = written(counted.join(first, F.col("group") == F.col("g")).select(F.col("doc_id").alias("i"), F.col("row").alias("r"), ((F.col("doc_id") == F.col("i")) & (F.col("row") == F.col("r"))).alias("stays"), "n"), "told")
    of = lambda t: (F.col("doc_id").cast("long") == t.i) & (row_hash(docs) == t.r)
    gone = sent(told.filter("not stays").select("i", "r"))
    kept = docs.join(gone, of(gone), "left_anti")
    again = sent(told.filter("stays and n > 1").select("i", "r"))
    if again.isEmpty():
        return kept
    once = docs.join(again, of(again)).dropDuplicates(["i", "r"]).select(*[docs[f"`{c}`"] for c in docs.columns])
    return kept.join(again, of(again), "left_anti").union(once)


def with_hex(result: DataFrame) -> DataFrame:
    """Fingerprints as 16 lower-case hexadecimal digits."""
    return result.select("doc_id", F.lower(F.lpad(F.hex("print"), 16, "0")).alias("fingerprint"), "component_id")
