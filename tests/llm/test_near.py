"""SimHash and vector near-duplicates against brute force."""

from __future__ import annotations

import re

import duckdb
import numpy as np
import pyarrow as pa
import pytest
import xxhash

from corpusforge.engine import read
from corpusforge.llm import pivots, shingles, simhash
from corpusforge.llm.queries import ORACLES, QUERIES
from corpusforge.operators import components


def plain_fingerprint(text: str | None) -> int:
    words = [w for w in re.split("[\x20\x09-\x0d]+", re.sub("[A-Z]", lambda m: m[0].lower(), text or "")) if w]
    if not words:
        return 0
    shingles = [" ".join(words[i : i + 4]) for i in range(max(1, len(words) - 3))]
    hashes = [xxhash.xxh64_intdigest(s.encode(), 42) for s in shingles]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hashes) > len(hashes))


def groups(ids: list[int], linked: np.ndarray) -> list[int]:
    """Smallest id reachable, for each row; ``linked`` is a symmetric matrix."""
    best = np.array(ids)
    while True:
        new = np.array([min(best[i], best[np.flatnonzero(linked[i])].min(initial=best[i])) for i in range(len(ids))])
        if (new == best).all():
            return best.tolist()
        best = new


def close(prints: list[int], distance: int = 4) -> np.ndarray:
    p = np.array(prints, dtype=np.uint64)
    return np.bitwise_count(p[:, None] ^ p[None, :]) <= distance


def test_components_of_paths_stars_and_loops(spark):
    edges = [(i, i + 1) for i in range(1, 60)] + [(100, i) for i in range(101, 160)] + [(200, 201), (201, 200), (7, 7), (300, 299)]
    got = {r.id: r.component for r in components.components(spark.createDataFrame(edges, "a long, b long")).collect()}
    assert got == {**dict.fromkeys(range(1, 61), 1), **dict.fromkeys(range(100, 160), 100), 200: 200, 201: 200, 299: 299, 300: 299}


def test_no_links_no_components(spark):
    assert components.components(spark.createDataFrame([], "a long, b long")).collect() == []


def test_simhash_equals_brute_force(spark, small):
    docs = sorted((r.doc_id, r.text) for r in read(spark, small, "documents").collect())
    prints = [plain_fingerprint(t) for _, t in docs]
    want = groups([i for i, _ in docs], close(prints))
    got = {r.doc_id: (r.fingerprint, r.component_id) for r in QUERIES["op10_simhash"](spark, small).collect()}
    assert got == {i: (f"{p:016x}", c) for (i, _), p, c in zip(docs, prints, want, strict=True)}


@pytest.mark.parametrize("run", [4, simhash.RUN])
def test_links_keep_components_when_runs_are_split(spark, run):
    rng = np.random.default_rng(1)
    base = rng.integers(0, 1 << 63, 6, dtype=np.uint64)
    prints = {int(b) for b in base}
    for b in base[:3]:  # chains that wander off, and many close to one
        at = int(b)
        for _ in range(40):
            at ^= 1 << int(rng.integers(64)) | 1 << int(rng.integers(64))
            prints.add(at)
            prints.add(int(b) ^ 1 << int(rng.integers(64)))
    prints = sorted(prints)
    rows = [(int(np.uint64(p).view(np.int64)), i) for i, p in enumerate(prints)]
    found = components.components(simhash.links(spark.createDataFrame(rows, "print long, id long"), run=run))
    got = {r.id: r.component for r in found.collect()}
    assert [got.get(i, i) for i in range(len(prints))] == groups(list(range(len(prints))), close(prints))


def test_simhash_of_odd_documents(odd_docs, no_docs):
    got = simhash.near_duplicates(odd_docs).collect()
    assert len(got) == odd_docs.count()
    by = {r.doc_id: r.component_id for r in got}
    assert by[1] == by[2] == 1 and by[3] == by[4] == by[5] == 3 and by[None] is None and by[6] == 6
    assert simhash.near_duplicates(no_docs).collect() == []
    kept = simhash.first_of_each(odd_docs)
    assert kept.columns == odd_docs.columns
    assert sorted((r.doc_id or -1) for r in kept.collect()) == [-1, 1, 3, 6, 7, 8, 9]


def brute_vectors(rows):
    ok = [v is not None and label is not None and i is not None and all(x is not None and np.isfinite(x) for x in v) and any(v) for i, v, label in rows]
    unit = [np.array(v, dtype=float) / np.linalg.norm(np.array(v, dtype=float)) if o else None for (_, v, _), o in zip(rows, ok, strict=True)]
    n = len(rows)
    linked = np.zeros((n, n), dtype=bool)
    for a in range(n):
        for b in range(n):
            linked[a, b] = a != b and ok[a] and ok[b] and rows[a][2] == rows[b][2] and len(unit[a]) == len(unit[b]) and unit[a] @ unit[b] >= 0.93
    return linked


def planted(dim: int, seed: int, clusters: int = 25, most: int = 9):
    """Vectors in clusters around the threshold, null labels, copies, and rows that can't link."""
    rng = np.random.default_rng(seed)
    rows, i = [], 0
    for label in (1, 2, None):
        for _ in range(clusters):
            centre = rng.normal(size=dim)
            for _ in range(int(rng.integers(1, most))):
                rows.append((i, (centre + rng.normal(size=dim) * rng.uniform(0.05, 0.3)).astype(np.float32).tolist(), label))
                i += 1
    rows += [(i, rows[0][1], 1), (i + 1, rows[0][1], 1), (i + 2, None, 1), (i + 3, [0.0] * dim, 1), (i + 4, [float("nan")] * dim, 1), (i + 5, [None] * dim, 1), (i + 6, [1.0] * 8, 1), (i + 7, [2.0] * 8, 1)]
    return rows


@pytest.mark.parametrize(("dim", "seed"), [(16, 2), (64, 3)])
def test_vectors_equal_their_sql_with_blocks(spark, dim, seed):
    rows = planted(dim, seed)
    linked = brute_vectors(rows)
    df = spark.createDataFrame(rows, "vec_id long, embedding array<float>, label int").repartition(3)
    con = duckdb.connect()
    con.register("embeddings", pa.table({"vec_id": [r[0] for r in rows], "embedding": pa.array([r[1] for r in rows], pa.list_(pa.float32())), "label": pa.array([r[2] for r in rows], pa.int32())}))
    want = sorted(con.execute(ORACLES["op6_near_vectors"]).fetchall())
    assert [r[1] for r in want] == linked.sum(axis=1).tolist() and linked.sum() > 300
    assert [r[2] for r in want] == groups([r[0] for r in rows], linked)
    for block in (8, pivots.BLOCK):
        got = sorted(tuple(r) for r in pivots.near_vectors(df, block=block).collect())
        assert got == want


@pytest.mark.parametrize("dim", [8, 64, 200])
def test_recall_on_planted_vectors(spark, dim):
    """Ten thousand vectors: pairs just above the threshold, clusters of many, and one cluster of a third of all rows."""
    rng = np.random.default_rng(dim)
    unit = lambda x: x / np.linalg.norm(x, axis=1, keepdims=True)
    base = unit(rng.normal(size=(3000, dim)))
    off = rng.normal(size=base.shape)
    off = unit(off - (off * base).sum(axis=1, keepdims=True) * base)
    c = rng.uniform(0.932, 0.97, size=(3000, 1))
    hot = unit(unit(rng.normal(size=(1, dim))) + unit(rng.normal(size=(3400, dim))) * 0.2)
    x = np.concatenate([base, c * base + np.sqrt(1 - c * c) * off, hot, np.repeat(base[:100], 6, axis=0)])
    label = np.concatenate([np.arange(3000) % 3, np.arange(3000) % 3, np.zeros(3400, dtype=int), np.repeat(np.arange(100) % 3, 6)])
    linked = np.zeros(len(x), dtype=np.int64)
    for a in range(0, len(x), 1000):
        linked[a : a + 1000] = ((x[a : a + 1000] @ x.T >= 0.93) & (label[a : a + 1000, None] == label[None, :])).sum(axis=1) - 1
    df = spark.createDataFrame(pa.table({"vec_id": np.arange(len(x)), "embedding": pa.array(list(x), pa.list_(pa.float64())), "label": label}))
    got = pivots.near_vectors(df).toPandas().set_index("vec_id").loc[range(len(x))]
    assert (got.n_links.values <= linked).all()
    pairs = slice(0, 6000)  # the cluster's many links must not hide lost pairs
    assert got.n_links.values[pairs].sum() >= 0.95 * linked[pairs].sum() and got.n_links.sum() >= 0.95 * linked.sum()


def test_no_vectors_and_no_usable_vectors(spark):
    empty = spark.createDataFrame([], "vec_id long, embedding array<float>, label int, n long")
    assert pivots.near_vectors(empty).collect() == []
    none = spark.createDataFrame([(1, None, 1, 5), (2, [1.0], None, 5)], "vec_id long, embedding array<float>, label int, n long")
    assert sorted((r.vec_id, r.n_links, r.component_id, r.kept) for r in pivots.near_vectors(none).collect()) == [(1, 0, 1, True), (2, 0, 2, True)]


def test_pivots_grow_with_the_table_within_a_bound():
    assert pivots.n_pivots(10) == 256 and pivots.n_pivots(10_000) == 400 and pivots.n_pivots(10**12) == 8192


def test_rows_of_one_id_with_other_texts_stay(spark):
    t, u, v = ("one two three four five six seven eight nine ten", "all these words are quite different from those others", "nothing here is shared with any text above or below")
    rows = [(3, t, "a"), (7, t, "a"), (7, u, "b"), (7, u, "c"), (9, v, "x"), (9, v, "x"), (None, t, "a"), (None, t, "a")]
    docs = spark.createDataFrame(rows, "doc_id long, text string, source string")
    for first_of_each in (simhash.first_of_each, shingles.first_of_each):
        got = sorted(((r.doc_id or -1), r.text, r.source) for r in first_of_each(docs).collect())
        assert [(i, x) for i, x, _ in got] == [(-1, t), (-1, t), (3, t), (7, u), (9, v)]
        again = sorted(((r.doc_id or -1), r.text, r.source) for r in first_of_each(docs.repartition(5, "source")).collect())
        assert again == got
