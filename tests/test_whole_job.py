"""Nothing is left out: links of digests, lines on the join path, lines and n-grams of the queries."""

from __future__ import annotations

import hashlib
import re

import numpy as np
from pyspark.sql import functions as F

from corpusforge import queries
from corpusforge.functions import lsh
from corpusforge.operators import dedup
from corpusforge.plans import annotate


def test_digests_whose_changes_touch_every_band_are_linked(spark, monkeypatch):
    rng = np.random.default_rng(4)
    made = []
    for _ in range(12):
        codes = rng.integers(0, 4, 256)
        made.append(codes)
        for changes in (15, 16, 20, 25, 28, 30, 31):
            other = codes.copy()
            for k in range(changes):  # spread over the sixteen bands
                at = k % 16 * 16 + int(rng.integers(8)) * 2 + k // 16
                other[at] += 1 if other[at] < 3 else -1
            made.append(other)
    packed = [(c.reshape(-1, 4) << np.array([0, 2, 4, 6])).sum(axis=1).astype(np.uint8).tobytes().hex() for c in made]
    digests = ["00000010ff" + p for p in packed]
    n = len(digests)
    near = [[lsh.distance(a, b) <= dedup.MAX_DISTANCE for b in digests] for a in digests]
    want = list(range(n))
    for _ in range(n):
        want = [min(want[j] for j in range(n) if near[i][j]) for i in range(n)]
    table = spark.createDataFrame(list(enumerate(digests)), "doc_id long, lsh_digest string")
    monkeypatch.setattr(dedup.lsh, "digests", lambda docs, key: table)
    assert [c for _, c in sorted(map(tuple, dedup.near(table).collect()))] == want


def test_join_path_gives_the_same_lines(spark, small, monkeypatch):
    m = queries.model(spark, small)
    docs = queries.test_docs(spark, small).select("doc_id", "text").union(spark.createDataFrame([(5, None), (5, "12 34\n\n the word"), (None, "une autre ligne")], "doc_id long, text string"))
    line = lambda x: (x.pos, x.pred, x.prob and round(x.prob, 6))
    rows = lambda: sorted(((r.doc_id or -1, str(r.pred), round(r.prob or 0, 6), list(map(line, r.lines))) for r in annotate.identify(docs, m).collect()), key=str)
    want = rows()
    monkeypatch.setattr(annotate, "BROADCAST_PAIRS", 0)
    assert rows() == want


def grams(text: str) -> set[str]:
    return {p[i : i + n] for w in re.findall(r"[^\W\d_]+", text.lower()) for p in [f" {w} "] for n in range(2, 6) for i in range(len(p) - n + 1)}


def test_every_line_is_predicted_and_every_gram_has_its_bucket(spark, small):
    lines = queries.lines(spark, small).filter("part = 9").filter(F.col("line").rlike(r"\p{L}"))
    got = {(r.doc_id, r.pos) for r in queries.QUERIES["lid_predict_lines"](spark, small).collect()}
    assert got == {(r.doc_id, r.pos) for r in lines.select("doc_id", "pos").collect()} and max(p for _, p in got) >= 3
    want = set().union(*(grams(r.line) for r in queries.lines(spark, small).collect()))
    rows = {r.g: (r.b, r.fnv) for r in queries.QUERIES["hash_buckets"](spark, small).collect()}
    assert set(rows) == want and max(map(len, want)) == 5

    def fnv(g: str) -> int:
        h = 2166136261
        for byte in g.encode():
            h = (h ^ byte) * 16777619 & 0xFFFFFFFF
        return h

    assert rows == {g: (int(hashlib.md5(g.encode()).hexdigest()[:8], 16) % queries.BUCKETS, fnv(g)) for g in want}


def test_links_of_digests_equal_those_of_all_pairs_without_rows_for_pairs(spark):
    rng = np.random.default_rng(7)
    made = []
    for group in range(60):  # families of every size, some of many near digests, around lengths that a ring closes
        codes, length = rng.integers(0, 4, 256), int(rng.choice([0, 1, 14, 15, 16, 17, 31, 254, 255]))
        for _ in range(150 if group < 4 else int(rng.integers(1, 7))):
            other = codes.copy()
            at = rng.choice(256, int(rng.integers(0, 22)), replace=False)
            other[at] = np.clip(other[at] + rng.choice([-1, 1], len(at)), 0, 3)
            body = (other.reshape(-1, 4) << np.array([0, 2, 4, 6])).sum(axis=1).astype(np.uint8).tobytes().hex()
            made.append(f"{int(rng.integers(2)):06x}{(length + int(rng.integers(-1, 2))) % 256:02x}{int(rng.integers(6, 9)):x}{int(rng.integers(14, 17)) % 16:x}" + body)
    made = sorted(set(made))
    a, b = zip(*[(i, j) for i in range(len(made)) for j in range(i) if lsh.distance(made[i], made[j]) <= dedup.MAX_DISTANCE], strict=True)
    want = np.arange(len(made))
    a, b, before = np.array(a), np.array(b), None
    while before is None or (before != want).any():
        before, low = want.copy(), np.minimum(want[a], want[b])
        np.minimum.at(want, a, low)
        np.minimum.at(want, b, low)
    table = spark.createDataFrame(list(enumerate(made)), "id long, lsh_digest string")
    for longest in (dedup.RUN, 20):
        links = dedup.digest_links(table, longest=longest).collect()
        assert len(links) < len(a) / 4 and len(set(want.tolist())) < len(made)
        assert all(lsh.distance(made[x], made[y]) <= dedup.MAX_DISTANCE for x, y in links)
        got, before = list(range(len(made))), None
        while before != got:
            before = list(got)
            for x, y in links:
                got[x] = got[y] = min(got[x], got[y])
        assert got == want.tolist()
