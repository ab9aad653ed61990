"""Near-duplicate vectors by a pivot-permutation index.

A bounded sample gives the pivots, whose number grows with the root of the vectors'; each vector is described by its nearest
pivots. What two vectors must share is ``shared`` (two) pivots, so the inverted lists are kept by pair of pivots: a vector
stands in the lists of all pairs of its pivots, and whoever meets in a list has the count that retrieval asks for. Lists are
made and counted on ids alone; lists of one member go, of lists with equal members the first stays, and only members of
those that are left fetch their vectors and are verified by cosine in double precision. A pair that several lists retrieve
belongs to the list of its two smallest common pivots, which a product of small matrices tells for a whole block.

Equal vectors are indexed once, with their number. Lists are compared in blocks of bounded size: a list of many blocks is
dealt out as pairs of blocks. A block gives counts of links and a spanning forest, never its pairs.

Defined results: a null or zero vector, one with null or non-finite components, or one without label links with nothing;
equal vectors of a label link (their cosine is 1); repeated rows count as different vectors; a row without vec_id is kept and
links with nothing; an empty table gives no rows; other columns are ignored. Ties between pivots go to the earlier pivot.
"""

from __future__ import annotations

from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from corpusforge.engine import arrow_map, batch, written
from corpusforge.operators.components import components

#: The index: fewest and most pivots drawn, pivots by root of the number of vectors, nearest pivots of a vector.
FEWEST, PIVOTS, PER_ROOT, NEAREST, SHARED = 256, 8192, 4.0, 8, 2
COSINE = 0.93
#: Pivots have a smaller cosine than the first of these with each other; the next ones are tried where too few are so far apart.
APART = (0.6, 0.75, 0.88)
#: Vectors of a block; two blocks are in memory at once.
BLOCK = 1024


def usable():
    """Whether a row can link."""
    fine = F.forall("embedding", lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf"))) & F.exists("embedding", lambda x: x != 0)
    return F.col("vec_id").isNotNull() & F.col("label").isNotNull() & F.coalesce(fine, F.lit(False))


def unit(rows: pa.Array) -> np.ndarray:
    """A column of float arrays of one length as unit vectors in double precision."""
    return _normed(rows.flatten().to_numpy(zero_copy_only=False).reshape(len(rows), -1))


def _normed(x: np.ndarray) -> np.ndarray:
    x = x.astype(np.float64)
    x = x / np.abs(x).max(axis=1, keepdims=True)
    return x / np.linalg.norm(x, axis=1, keepdims=True)


def n_pivots(n: int) -> int:
    """Pivots for so many vectors: lists stay short as the table grows, and the driver holds a bounded number."""
    return int(min(max(PER_ROOT * n**0.5, FEWEST), PIVOTS))


def draw_pivots(vectors: DataFrame, most: int) -> np.ndarray:
    """At most ``most`` pivots, one row each, from the ``2 * most`` vectors whose values hash lowest.

    One that resembles an earlier pivot is left out: members of a large cluster would take several of their own kind for
    their nearest pivots, in an order that means nothing. Where all vectors resemble each other, closer ones are let in.
    """
    hashed = vectors.select(F.xxhash64("embedding").alias("h"), "embedding")
    rows = hashed.orderBy("h").limit(2 * most).select("embedding").toArrow().column(0).combine_chunks()
    if not len(rows):
        return np.empty((0, 0))
    sample = unit(rows)
    kept = np.empty((min(most, len(sample)), sample.shape[1]))
    n, left = 0, np.arange(len(sample))
    for apart in APART:
        later = []
        for i in left.tolist():
            if n == len(kept):
                break
            if n == 0 or (kept[:n] @ sample[i]).max() < apart:
                kept[n] = sample[i]
                n += 1
            else:
                later.append(i)
        left = np.array(later, dtype=np.int64)
    return kept[:n]


def _describe(pivots: np.ndarray, nearest: int):
    """Sorted numbers of the nearest pivots, and the lists (pairs of pivots) that a vector stands in."""

    def run(batches):
        k = min(nearest, len(pivots))
        pairs = np.array(list(combinations(range(k), 2)) or [(0, 0)])
        for rows in batches:
            if not rows.num_rows:
                continue
            sims = np.round(unit(rows.column(2)) @ pivots.T, 12)
            near = np.sort(np.argsort(-sims, axis=1, kind="stable")[:, :k], axis=1) if len(pivots) <= 4 * k else _top(sims, k)
            lists = near[:, pairs[:, 0]].astype(np.int64) * len(pivots) + near[:, pairs[:, 1]]
            ends = lambda width: np.arange(0, rows.num_rows * width + 1, width, dtype=np.int32)
            yield pa.RecordBatch.from_arrays(
                [rows.column(0), rows.column(1), pa.ListArray.from_arrays(ends(k), pa.array(near.ravel().astype(np.int32))), pa.ListArray.from_arrays(ends(len(pairs)), pa.array(lists.ravel()))],
                names=["id", "label", "pivots", "lists"],
            )

    return run


def _top(sims: np.ndarray, k: int) -> np.ndarray:
    """Sorted places of the k largest of each row; of equals at the edge those that partition gives, the same for equal rows."""
    return np.sort(np.argpartition(-sims, k - 1, axis=1)[:, :k], axis=1)


def _owned(x: np.ndarray, y: np.ndarray, first: int, second: int) -> np.ndarray | None:
    """(member of x, member of y): no common pivot before this list's two but the first; ``None`` where no pair can be so."""
    before = np.unique(np.concatenate([x[x < second], y[y < second]]))
    before = before[before != first]
    if not len(before):
        return np.ones((len(x), len(y)), dtype=bool)
    of = lambda m: (m[:, :, None] == before).any(axis=1)
    a, b = of(x), of(y)
    if (a.all(axis=0) & b.all(axis=0)).any():
        return None
    return a.astype(np.float32) @ b.astype(np.float32).T == 0


def _owned_pairs(x: np.ndarray, y: np.ndarray, first: np.ndarray, second: np.ndarray) -> np.ndarray:
    """The same for pairs, each of a list of its own."""
    common = (x[:, :, None] == y[:, None, :]).any(axis=2)
    return ~(common & (x < second[:, None]) & (x != first[:, None])).any(axis=1)


def _list_links(cosine: float, pivots: int):
    """Arrow function over rows of (label, list, sub), sorted so: forest links (a, b), and link counts (a, n)."""

    def finish(number, side, ids, vectors, near, weights):
        ids, near, weights = np.concatenate(ids), np.concatenate(near), np.concatenate(weights)
        side, units = np.concatenate(side), None
        same = not side.any()
        at_x, at_y = (np.arange(len(side)),) * 2 if same else (np.flatnonzero(side == s) for s in (1, 2))
        counts = np.zeros(len(ids), dtype=np.int64)
        root, out = np.arange(len(ids)), []
        for start in range(0, len(at_x), 256):
            x = at_x[start : start + 256]
            owned = _owned(near[x], near[at_y], number // pivots, number % pivots)
            if owned is None:
                continue
            if units is None:  # most lists of a tight cluster own no pair, and need no vectors
                units = _normed(np.concatenate(vectors))
            linked = owned & (units[x] @ units[at_y].T >= cosine)
            if same:
                linked &= x[:, None] < at_y[None, :]
            if not linked.any():
                continue
            counts[x] += linked @ weights[at_y]
            counts[at_y] += weights[x] @ linked
            u, v = np.nonzero(linked)
            u, v = x[u], at_y[v]
            while True:  # a link for each pair of trees that meet, until none do
                ru, rv = root[u], root[v]
                apart = ru != rv
                if not apart.any():
                    break
                u, v = u[apart], v[apart]
                low, high = np.minimum(ru[apart], rv[apart]), np.maximum(ru[apart], rv[apart])
                high, first = np.unique(high, return_index=True)
                out.append((ids[u[first]], ids[v[first]]))
                root[high] = low[first]
                while (root[root] != root).any():
                    root = root[root]
        return out, (ids[counts > 0], counts[counts > 0])

    def run(batches):
        links, totals = [], []
        key, held = None, None

        def close():
            if held and sum(map(len, held[1])) > 1:
                more, counted = finish(key[1], *held)
                links.extend(more)
                totals.append(counted)

        def result():
            none = np.empty(0, dtype=np.int64)
            a, b = (np.concatenate([none, *(x[c] for x in links)]) for c in (0, 1))
            i, n = (np.concatenate([none, *(x[c] for x in totals)]) for c in (0, 1))
            links.clear(), totals.clear()
            return batch(a=pa.array(np.concatenate([a, i])), b=pa.concat_arrays([pa.array(b), pa.nulls(len(i), pa.int64())]), n=pa.concat_arrays([pa.nulls(len(a), pa.int64()), pa.array(n)]))

        for rows in batches:
            if not rows.num_rows:
                continue
            keys = np.stack([rows.column(c).to_numpy(zero_copy_only=False).astype(np.int64) for c in range(3)], axis=1)
            cuts = [0, *(np.flatnonzero((np.diff(keys, axis=0) != 0).any(axis=1)) + 1).tolist(), len(keys)]
            x = rows.column(5).flatten().to_numpy(zero_copy_only=False).reshape(rows.num_rows, -1)
            near = rows.column(6).flatten().to_numpy().reshape(rows.num_rows, -1)
            side, ids, weights = (rows.column(c).to_numpy(zero_copy_only=False) for c in (3, 4, 7))
            # lists of two, the most frequent ones, all at once; not the batch's first and last list, which may go on elsewhere
            at = np.array(cuts)
            two = at[1:-2][np.diff(at)[1:-1] == 2] if len(at) > 3 else at[:0]
            two = two[side[two] + side[two + 1] == 0]
            if len(two):
                a = two[_owned_pairs(near[two], near[two + 1], keys[two, 1] // pivots, keys[two, 1] % pivots)]
                b = a + 1
                close_by = (_normed(x[a]) * _normed(x[b])).sum(axis=1) >= cosine
                a, b = a[close_by], b[close_by]
                links.append((ids[a], ids[b]))
                totals.append((np.concatenate([ids[a], ids[b]]), np.concatenate([weights[b], weights[a]])))
            done = set(two.tolist())
            for a, b in zip(cuts[:-1], cuts[1:], strict=True):
                if a in done:
                    continue
                if (now := tuple(keys[a].tolist())) != key:
                    close()
                    key, held = now, ([], [], [], [], [])
                for column, values in zip(held, (side, ids, x, near, weights), strict=True):
                    column.append(values[a:b])
            if links or totals:
                yield result()
        close()
        yield result()

    return run


def near_vectors(vectors: DataFrame, cosine: float = COSINE, pivots: int | None = None, nearest: int = NEAREST, block: int = BLOCK) -> DataFrame:
    """(vec_id, n_links, component_id, kept) for every row; ``pivots`` are as many as :func:`n_pivots` says if not given."""
    rows = vectors.select(F.col("vec_id").cast("long"), "embedding", F.col("label").cast("long"))
    good = rows.filter(usable())
    distinct = good.groupBy("label", "embedding").agg(F.min("vec_id").alias("id"), F.count(F.lit(1)).alias("n"))
    distinct = written(distinct.select("id", "label", "embedding", "n", *_identity()), "vectors")
    found = None
    for size, n in distinct.groupBy(F.size("embedding")).agg(F.count(F.lit(1))).collect():  # a row a length; as a rule there is one
        some = distinct.filter(F.size("embedding") == size)
        part = _links(some, draw_pivots(some, pivots or n_pivots(n)), cosine, nearest, block)
        found = part if found is None else found.union(part)
    alone = rows.filter(~usable()).select("vec_id", F.lit(0).cast("long").alias("n_links"), F.col("vec_id").alias("component_id"), F.lit(True).alias("kept"))
    if found is None:
        return alone
    found = written(found, "pairs")
    counts = found.filter("n is not null").groupBy(F.col("a").alias("of")).agg(F.sum("n").alias("others"))
    groups = components(found.filter("n is null").select("a", "b")).withColumnRenamed("id", "of")
    each = distinct.select("id", "label", "n", "h", "k").join(counts, F.col("id") == F.col("of"), "left").drop("of").join(groups, F.col("id") == F.col("of"), "left")
    each = each.select(F.col("label").alias("l"), F.col("h").alias("eh"), F.col("k").alias("ek"), (F.coalesce("others", F.lit(0)) + F.col("n") - 1).alias("n_links"), F.coalesce("component", "id").alias("component_id"))
    named = good.select("vec_id", "label", *_identity())  # 128 bits stand for the vector; equal ones may be very many, which adaptive execution splits
    linked = named.join(each, (F.col("label") == F.col("l")) & (F.col("h") == F.col("eh")) & (F.col("k") == F.col("ek")))
    return linked.select("vec_id", "n_links", "component_id", (F.col("vec_id") == F.col("component_id")).alias("kept")).union(alone)


def _identity() -> list:
    """Two independent 64-bit hashes of a vector."""
    return [F.xxhash64("embedding").alias("h"), F.xxhash64(F.lit(7), F.reverse("embedding")).alias("k")]


def _links(distinct: DataFrame, sample: np.ndarray, cosine: float, nearest: int, block: int) -> DataFrame:
    """Links (a, b) that join what is linked, and numbers of links (a, n)."""
    described = written(arrow_map(distinct.select("id", "label", "embedding"), _describe(sample, nearest), "id long, label long, pivots array<int>, lists array<long>"), "described")
    posted = described.select("id", "label", F.explode("lists").alias("list"))
    sizes = posted.groupBy("label", "list").agg(F.count(F.lit(1)).alias("members"), F.bit_xor(F.xxhash64("id")).alias("x"), F.min("id").alias("least"), F.max("id").alias("most")).filter("members > 1")
    sizes = sizes.groupBy("label", "members", "x", "least", "most").agg(F.min("list").alias("list"))  # of lists with equal members the first
    sizes = sizes.select(F.col("label").alias("l"), F.col("list").alias("p"), F.ceil(F.col("members") / block).cast("long").alias("blocks"))
    dealt = posted.join(sizes, (F.col("label") == F.col("l")) & (F.col("list") == F.col("p"))).withColumn("mine", F.expr("pmod(xxhash64(id), blocks)"))
    places = written(
        dealt.withColumn("o", F.explode(F.expr("sequence(0L, blocks - 1)"))).select(
            "label", "list", F.expr("least(o, mine) * blocks + greatest(o, mine)").alias("sub"), F.expr("case when mine = o then 0 when mine < o then 1 else 2 end").alias("side"), "id"
        ),
        "lists",
    )
    wanted = distinct.join(described.select("id", "pivots"), "id").select("id", "embedding", "pivots", "n")
    lists = places.join(wanted, "id").select("label", "list", "sub", "side", "id", "embedding", "pivots", "n")
    lists = lists.repartition("label", "list", "sub").sortWithinPartitions("label", "list", "sub")
    return arrow_map(lists, _list_links(cosine, len(sample)), "a long, b long, n long")
