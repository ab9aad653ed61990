"""The near-copy stage of the pipeline against exact Jaccard similarities."""

from __future__ import annotations

import numpy as np

import corpus_pipeline
from corpusforge.engine import read
from corpusforge.llm import shingles


def groups(ids: list[int], linked: np.ndarray) -> list[int]:
    """Smallest id reachable, for each row; ``linked`` is a symmetric matrix."""
    best = np.array(ids)
    while True:
        new = np.array([min(best[i], best[np.flatnonzero(linked[i])].min(initial=best[i])) for i in range(len(ids))])
        if (new == best).all():
            return best.tolist()
        best = new


def test_pipeline_stage_finds_all_near_copies(spark):
    sf = "/root/testdata/sf0.01"
    docs = read(spark, sf, "documents")
    rows = [(r.doc_id, {tuple(w[k : k + 5]) for k in range(max(1, len(w) - 4))} if (w := (r.text or "").encode().lower().split()) else set()) for r in docs.collect()]
    rows.sort()
    inverted = {}
    for place, (_, s) in enumerate(rows):
        for x in s:
            inverted.setdefault(x, []).append(place)
    linked = np.eye(len(rows), dtype=bool)
    for place, (_, s) in enumerate(rows):
        shared = np.zeros(len(rows), dtype=np.int64)
        for x in s:
            shared[inverted[x]] += 1
        linked[place] |= np.array([5 * n >= 4 * (len(s) + len(t) - n) for n, (_, t) in zip(shared.tolist(), rows, strict=True)])
    want = groups([i for i, _ in rows], linked)
    got = sorted(r.doc_id for r in corpus_pipeline.near_duplicates(spark, docs, sf).collect())
    assert got == [i for (i, _), w in zip(rows, want, strict=True) if i == w]
    assert {255, 770, 875, 944}.isdisjoint(got)


def test_shingle_groups_split_into_runs(spark):
    rng = np.random.default_rng(3)
    words = [f"w{k}" for k in range(200)]
    rows = []
    for i in range(60):
        own = list(words)
        own[int(rng.integers(200))] = f"x{i}"
        rows.append((i, " ".join(own)))
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    sets = [set(shingles.shingles(t).tolist()) for _, t in rows]
    linked = np.array([[len(a & b) >= 0.8 * len(a | b) for b in sets] for a in sets])
    want = groups([i for i, _ in rows], linked)
    for run in (8, shingles.RUN):
        got = {r.doc_id: r.component_id for r in shingles.near_copies(df, run=run).collect()}
        assert [got[i] for i, _ in rows] == want
