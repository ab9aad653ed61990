"""A locality-sensitive digest of texts: 256 buckets in two bits each, a header with check sum, length and spread."""

from __future__ import annotations

import math
import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import types as T

from corpusforge.engine import arrow_map

BUCKETS, LEAST_BYTES, WINDOW = 256, 50, 5
#: Which of the window's bytes (0: the newest) a triplet takes, besides the newest.
TRIPLETS = ((1, 2), (1, 3), (2, 3), (2, 4), (1, 4), (3, 4))
#: A permutation of the byte values from a documented seed, so digests agree with each other only.
TABLE = np.random.default_rng(20240229).permutation(256).astype(np.uint8)


def digest(text: str | None) -> str | None:
    """Hexadecimal digest of 69 bytes; nothing for texts that are too short or too uniform."""
    raw = np.frombuffer((text or "").encode(), dtype=np.uint8)
    if len(raw) < LEAST_BYTES:
        return None
    newest = raw[WINDOW - 1 :]
    n = len(newest)
    counts = np.zeros(BUCKETS, dtype=np.int64)
    for salt, (i, j) in enumerate(TRIPLETS, start=1):
        h = TABLE[TABLE[salt] ^ newest]
        h = TABLE[h ^ raw[WINDOW - 1 - i : WINDOW - 1 - i + n]]
        h = TABLE[h ^ raw[WINDOW - 1 - j : WINDOW - 1 - j + n]]
        counts += np.bincount(h, minlength=BUCKETS)
    if np.count_nonzero(counts) <= BUCKETS // 2:
        return None
    ordered = np.sort(counts)
    q1, q2, q3 = (int(ordered[BUCKETS * k // 4 - 1]) for k in (1, 2, 3))
    codes = ((counts > q1).astype(np.uint8) + (counts > q2) + (counts > q3)).reshape(-1, 4)
    body = (codes[:, 0] | codes[:, 1] << 2 | codes[:, 2] << 4 | codes[:, 3] << 6).astype(np.uint8)
    ratio = lambda q: int(q * 100 / max(q3, 1)) % 16
    head = [*(zlib.crc32(raw) & 0xFFFFFF).to_bytes(3, "big"), int(math.log(len(raw)) / math.log(1.1)) % 256, ratio(q1) << 4 | ratio(q2)]
    return (bytes(head) + body.tobytes()).hex()


_GAP = np.array([[0, 1, 2, 6], [1, 0, 1, 2], [2, 1, 0, 1], [6, 2, 1, 0]])
BYTE_GAP = np.array([[sum(_GAP[a >> s & 3, b >> s & 3] for s in (0, 2, 4, 6)) for b in range(256)] for a in range(256)], dtype=np.int32)


def distance(a: str, b: str) -> int:
    """0 for equal digests; grows with the edits between the texts."""
    x, y = bytes.fromhex(a), bytes.fromhex(b)
    ring = lambda p, q, size: min((p - q) % size, (q - p) % size)
    heavy = lambda d: d if d <= 1 else 12 * (d - 1)
    total = ring(x[3], y[3], 256)
    total = total if total <= 1 else 12 * total
    total += heavy(ring(x[4] >> 4, y[4] >> 4, 16)) + heavy(ring(x[4] & 15, y[4] & 15, 16)) + (x[:3] != y[:3])
    return int(total + BYTE_GAP[np.frombuffer(x[5:], dtype=np.uint8), np.frombuffer(y[5:], dtype=np.uint8)].sum())


def digests(df: DataFrame, key: str, text: str = "text") -> DataFrame:
    """(key, lsh_digest)."""

    def run(batches):
        for rows in batches:
            yield pa.RecordBatch.from_arrays([rows.column(0), pa.array([digest(t) for t in rows.column(1).to_pylist()], pa.string())], names=[key, "lsh_digest"])

    return arrow_map(df.select(key, text), run, f"`{key}` {df.schema[key].dataType.simpleString()}, lsh_digest string")


def with_digests(df: DataFrame, text: str = "text", name: str = "lsh_digest") -> DataFrame:
    """Rows with their digest; nothing is joined."""
    at = df.columns.index(text)

    def run(batches):
        for rows in batches:
            yield pa.RecordBatch.from_arrays([*rows.columns, pa.array([digest(t) for t in rows.column(at).to_pylist()], pa.string())], names=[*rows.schema.names, name])

    return arrow_map(df, run, T.StructType([*df.schema.fields, T.StructField(name, T.StringType())]))


def distances(pairs: DataFrame) -> DataFrame:
    """Pairs (a, b, digest_a, digest_b) with their distance."""

    def run(batches):
        for rows in batches:
            d = [distance(x, y) for x, y in zip(rows.column(2).to_pylist(), rows.column(3).to_pylist(), strict=True)]
            yield pa.RecordBatch.from_arrays([rows.column(0), rows.column(1), pa.array(d, pa.int64())], names=["a", "b", "distance"])

    return arrow_map(pairs.select("a", "b", "digest_a", "digest_b"), run, "a long, b long, distance long")
