"""Opt-in deduplication: exact by hash, near by halves of bands of the digest, compared inside tasks.

A band has sixteen two-bit codes. A changed code costs 1 at least, so below distance 32 some band has one change at most, and
one half of that band none: digests meet on equal halves (32 keys) in cells of similar length. A task compares what
its rows have besides: the other half with each code left out, lengths, the header, then all codes. It hands on a
spanning forest of links, never pairs; long runs of a key are dealt out once more by the other half with a code left out.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from corpusforge.engine import arrow_map, batch, written
from corpusforge.functions import lsh
from corpusforge.operators.components import components

BANDS, HALF = 16, 8
MAX_DISTANCE = 30
#: Lengths that share a cell, and the greatest difference of two lengths up to MAX_DISTANCE; each cell holds as many of the next.
CELL, NEAR = 16, 2
#: Rows of a key that one task compares at first; longer runs are dealt out again.
RUN = 1 << 14
#: Rows whose runs are compared at once, pairs that are compared by their lower bounds, and by all their codes.
ROWS, PAIRS, WHOLE = 1 << 15, 1 << 18, 1 << 12


def exact(docs: DataFrame, text: str = "text") -> DataFrame:
    """(doc_id, copies) of the first document of each text; hashes travel, texts don't."""
    return docs.groupBy(F.sha2(text, 256).alias("h")).agg(F.min("doc_id").alias("doc_id"), F.count(F.lit(1)).alias("copies")).select("doc_id", "copies")


def _halves(raw: np.ndarray) -> np.ndarray:
    """The 32 halves of bands of digests, eight codes in 16 bits each."""
    return np.ascontiguousarray(raw[:, 5:]).view("<u2").astype(np.int64)


def _raw(column: pa.Array) -> np.ndarray:
    return np.frombuffer(b"".join(column.to_pylist()), dtype=np.uint8).reshape(-1, 69)


def _keyed(batches):
    """Arrow function over (digest, id): a row (key, digest, id) for each half of a band and each cell of the length.

    Rows come half by half: those of a digest lie apart, so what is shuffled is the same a digest for any number of partitions.
    """
    for rows in batches:
        if not rows.num_rows:
            continue
        raw = _raw(rows.column(0))
        length = raw[:, 3].astype(np.int64)
        cells, at = [length // CELL, (length // CELL - 1) % (256 // CELL)], [np.arange(len(raw)), np.flatnonzero(length % CELL < NEAR)]
        at, cell = np.concatenate(at), np.concatenate([cells[0], cells[1][at[1]]])
        keys = (np.arange(2 * BANDS) << 21) | (cell[:, None] << 16) | _halves(raw)[at]
        yield rows.take(pa.array(np.tile(at, 2 * BANDS))).add_column(0, "key", pa.array(keys.T.ravel()))


def _again(batches):
    """Arrow function over (key, digest, id) of long runs: a row for each code of the other half that may differ."""
    for rows in batches:
        if not rows.num_rows:
            continue
        key = rows.column(0).to_numpy()
        other = _halves(_raw(rows.column(1)))[np.arange(len(key)), (key >> 21) ^ 1]
        code = np.arange(HALF)
        keys = (key[:, None] << 19) | (code << 16) | (other[:, None] & ~(3 << 2 * code))
        yield rows.take(pa.array(np.repeat(np.arange(len(key)), HALF))).set_column(0, "key", pa.array(keys.ravel()))


class _Forest:
    """Digests of some rows and the trees that link them."""

    def __init__(self, raw: np.ndarray, ids: np.ndarray, most: int):
        self.raw, self.most = raw, most
        self.codes = np.ascontiguousarray(raw[:, 5:]).view(np.uint64)
        self.header = raw[:, 3].astype(np.int16), (raw[:, 4] >> 4).astype(np.int16), (raw[:, 4] & 15).astype(np.int16)
        self.ids, self.node = np.unique(ids, return_inverse=True)
        self.parent = np.arange(len(self.ids))
        self.links: list[tuple[int, int]] = []

    def tree(self, rows: np.ndarray) -> np.ndarray:
        return self.parent[self.node[rows]]

    def try_pairs(self, a: np.ndarray, b: np.ndarray) -> None:
        """Link rows of different trees that are close; cheap lower bounds of the distance first."""
        apart = self.tree(a) != self.tree(b)
        a, b = a[apart], b[apart]
        total = np.zeros(len(a), dtype=np.int64)
        for values, size, free in zip(self.header, (256, 16, 16), (0, 1, 1), strict=True):
            d = np.abs(values[a] - values[b])
            d = np.minimum(d, size - d)
            total += np.where(d <= 1, d, 12 * (d - free))
        ok = total <= self.most
        a, b, total = a[ok], b[ok], total[ok]
        changed = np.zeros(len(a), dtype=np.int64)
        for k in range(self.codes.shape[1]):
            x = self.codes[a, k] ^ self.codes[b, k]
            changed += np.bitwise_count((x | x >> np.uint64(1)) & np.uint64(0x5555555555555555))
        ok = total + changed <= self.most
        for k in range(0, np.count_nonzero(ok), WHOLE):
            x, y, d = a[ok][k : k + WHOLE], b[ok][k : k + WHOLE], total[ok][k : k + WHOLE]
            apart = self.tree(x) != self.tree(y)
            x, y, d = x[apart], y[apart], d[apart]
            d = d + (self.raw[x, :3] != self.raw[y, :3]).any(axis=1) + lsh.BYTE_GAP[self.raw[x, 5:], self.raw[y, 5:]].sum(axis=1)
            self._join(self.node[x[d <= self.most]].tolist(), self.node[y[d <= self.most]].tolist())

    def _join(self, a: list[int], b: list[int]) -> None:
        parent = self.parent
        for x, y in zip(a, b, strict=True):
            p, q = x, y
            while parent[p] != p:
                p = parent[p]
            while parent[q] != q:
                q = parent[q]
            if p != q:
                parent[max(p, q)] = min(p, q)
                self.links.append((int(self.ids[x]), int(self.ids[y])))
        if a:
            while (parent != parent[parent]).any():
                parent[:] = parent[parent]


def _compare(forest: _Forest, run: np.ndarray, length: np.ndarray) -> None:
    """Try all pairs of rows of the same run (a number of 58 bits) whose lengths (under 32) are near.

    Neighbours come first, so runs that they make one tree need no other pairs.
    """
    both = run << 5 | length
    order = np.argsort(both, kind="stable")
    both, run, length = both[order], run[order], length[order]
    for step in (1, 2):
        i = np.flatnonzero((run[step:] == run[:-step]) & (length[step:] - length[:-step] <= NEAR))
        for k in range(0, len(i), PAIRS):
            forest.try_pairs(order[i[k : k + PAIRS]], order[i[k : k + PAIRS] + step])
    starts = np.flatnonzero(np.concatenate([[True], run[1:] != run[:-1]]))
    sizes, trees = np.diff(np.append(starts, len(run))), forest.tree(order)
    done = np.minimum.reduceat(trees, starts) == np.maximum.reduceat(trees, starts)
    left = np.flatnonzero(np.repeat(~done & (sizes > 3), sizes))
    end = np.searchsorted(both, both[left] + NEAR, side="right")
    many = np.maximum(end - left - 3, 0)
    left, many = left[many > 0], many[many > 0]
    before = np.concatenate([[0], np.cumsum(many)])
    at = 0
    while at < len(left):
        to = max(at + 1, int(np.searchsorted(before, before[at] + PAIRS, side="right")) - 1)
        i, n = left[at:to], many[at:to]
        a = np.repeat(i, n)
        b = a + 3 + np.arange(len(a)) - np.repeat(before[at:to] - before[at], n)
        forest.try_pairs(order[a], order[b])
        at = to


def _links_within(key: np.ndarray, raw: np.ndarray, ids: np.ndarray, again: bool, most: int) -> list[tuple[int, int]]:
    """Links of whole runs of keys, sorted by key."""
    forest = _Forest(raw, ids, most)
    first = key >> 19 if again else key
    length = (raw[:, 3] - CELL * (first >> 16 & 31)) % 256
    group = np.cumsum(np.concatenate([[0], np.diff(key) != 0]))
    if again:
        _compare(forest, group, length)
        return forest.links
    other = _halves(raw)[np.arange(len(key)), (key >> 21) ^ 1]
    for code in range(HALF):
        _compare(forest, group << 16 | other & ~(3 << 2 * code), length)
    return forest.links


LINKS = "a long, b long, key long, digest binary, id long"


def _link_runs(longest: int, again: bool, most: int):
    """Arrow function over (key, digest, id), sorted by key: links (a, b), or rows of longer runs as they come."""

    def links(parts: list[pa.RecordBatch]) -> pa.RecordBatch:
        table = pa.Table.from_batches(parts).combine_chunks()
        found = _links_within(table.column(0).to_numpy(), _raw(table.column(1)), table.column(2).to_numpy(), again, most)
        n = len(found)
        return batch(a=pa.array([x for x, _ in found], pa.int64()), b=pa.array([x for _, x in found], pa.int64()), key=pa.nulls(n, pa.int64()), digest=pa.nulls(n, pa.binary()), id=pa.nulls(n, pa.int64()))

    def passed(rows: pa.RecordBatch) -> pa.RecordBatch:
        none = pa.nulls(rows.num_rows, pa.int64())
        return batch(a=none, b=none, key=rows.column(0), digest=rows.column(1), id=rows.column(2))

    def run(batches):
        whole, held = [], 0  # rows of runs that have ended
        last, own, size, over = None, [], 0, False  # rows of the run that may go on
        for rows in batches:
            if not rows.num_rows:
                continue
            key = rows.column(0).to_numpy()
            cuts = [0, *(np.flatnonzero(np.diff(key)) + 1).tolist(), len(key)]
            inner = (cuts[1], cuts[-2]) if len(cuts) > 2 else (0, 0)
            for a, b in ((0, cuts[1]), inner, (cuts[-2], len(key))) if len(cuts) > 2 else ((0, len(key)),):
                if a == b:
                    continue
                part = rows.slice(a, b - a)
                if key[a] != last:
                    if size > 1:
                        whole, held = whole + own, held + size
                    last, own, size, over = key[a], [], 0, False
                own, size = [*own, part], size + b - a
                if (a, b) == inner:  # runs that lie in this batch; a batch is shorter than the longest run
                    whole, held = whole + own, held + size
                    last, own, size = None, [], 0
                elif over or size > longest:
                    yield from map(passed, own)
                    own, size, over = [], 0, True
                if held >= ROWS:
                    yield links(whole)
                    whole, held = [], 0
        if size > 1:
            whole = whole + own
        if whole:
            yield links(whole)

    return run


def digest_links(one: DataFrame, max_distance: int = MAX_DISTANCE, longest: int = RUN) -> DataFrame:
    """Links (a, b) that connect all digests (columns lsh_digest, id; distinct digests) at ``max_distance`` or less."""
    row = "key long, digest binary, id long"
    sorted_by_key = lambda df: df.repartition("key").sortWithinPartitions("key")
    keyed = arrow_map(one.select(F.unhex("lsh_digest").alias("digest"), F.col("id").cast("long")), _keyed, row)
    first = written(arrow_map(sorted_by_key(keyed), _link_runs(longest, False, max_distance), LINKS), "runs")
    long = arrow_map(first.filter("key is not null").select("key", "digest", "id"), _again, row)
    second = arrow_map(sorted_by_key(long), _link_runs(1 << 62, True, max_distance), LINKS)
    return first.filter("key is null").select("a", "b").union(second.select("a", "b"))


def near(docs: DataFrame, max_distance: int = MAX_DISTANCE) -> DataFrame:
    """(doc_id, component_id): documents whose digests are close, with what they lead to.

    Equal digests meet once. A document without digest stands alone.
    """
    if max_distance > MAX_DISTANCE:
        raise ValueError(f"halves of bands and cells of lengths find all pairs only up to distance {MAX_DISTANCE}")
    own = written(lsh.digests(docs, "doc_id"), "digests")
    one = written(own.filter("lsh_digest is not null and doc_id is not null").groupBy("lsh_digest").agg(F.min("doc_id").alias("id")), "distinct")
    links = digest_links(one, max_distance)
    found = one.join(components(links), "id", "left").select(F.col("lsh_digest").alias("of"), F.coalesce("component", "id").alias("c"))
    return own.join(found, own.lsh_digest == found.of, "left").select("doc_id", F.coalesce("c", "doc_id").alias("component_id"))
