"""The linear classifier over averaged n-gram embeddings, trained by averaged rounds of stochastic gradient descent.

Rows are cut into rounds by hash. In a round every partition starts from the same parameters and goes once over its rows;
each gives the rows of the tables that it changed, and these are averaged by row, as a distributed aggregate, over the
partitions that touched it. The driver takes averaged rows alone: ``buckets + labels`` rows of ``dim`` numbers at most,
whatever the input and the number of partitions (128 MB at two million buckets); that bound is also what is sent out.
"""

from __future__ import annotations

import hashlib
import re
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from corpusforge.engine import arrow_map, batch, remove, scratch_path, worker_state
from corpusforge.functions.text import drawn, letter_class

BUCKETS, DIM, RATE, ROUNDS = 2_000_000, 16, 0.5, 4
#: Rows that a partition goes over in a round.
ROWS = 25_000


@dataclass
class SoftmaxModel:
    labels: list[str]
    embed: np.ndarray
    weight: np.ndarray

    def save(self, path: str) -> None:
        np.savez(path, labels=np.array(self.labels), embed=self.embed, weight=self.weight)

    @staticmethod
    def load(path: str) -> SoftmaxModel:
        z = np.load(path)
        return SoftmaxModel(z["labels"].tolist(), z["embed"], z["weight"])


class _Grams(dict):
    """Bucket ids of n-grams, remembered in bounded number."""

    def __init__(self, buckets: int, memo: int):
        self.buckets, self.memo = buckets, memo

    def __missing__(self, gram: str) -> int:
        if len(self) >= self.memo:
            self.clear()
        self[gram] = bucket = int(hashlib.md5(gram.encode()).hexdigest()[:8], 16) % self.buckets
        return bucket


class Features:
    """Bucket ids of the n-grams of a text; words and n-grams are remembered in bounded number."""

    def __init__(self, buckets: int, nmin: int = 2, nmax: int = 5, memo: int = 200_000):
        self.sizes, self.memo = range(nmin, nmax + 1), memo
        self.words = re.compile(f"{letter_class()}+")
        # the same below U+10000, where the expression is a table instead of a list of ranges
        self.plain = re.compile(f"[{''.join(r for r in re.findall('.-.|.', letter_class()[1:-1]) if r[0] < chr(0x10000))}]+")
        self.known: dict[str, np.ndarray] = {}
        self.grams = _Grams(buckets, memo)

    def of(self, text: str | None) -> np.ndarray:
        known, learn, lower = self.known, self._learn, (text or "").lower()
        words = self.plain if lower.isascii() or max(lower) < chr(0x10000) else self.words
        found = [known[w] if w in known else learn(w) for w in words.findall(lower)]
        return np.concatenate(found) if found else np.empty(0, dtype=np.int32)

    def counted(self, text: str | None) -> tuple[np.ndarray, np.ndarray]:
        """Different bucket ids, ascending, and how often each occurs."""
        ids = self.of(text)
        ids.sort()
        last = np.append(np.flatnonzero(ids[1:] != ids[:-1]), len(ids) - 1) if len(ids) else np.empty(0, dtype=np.int64)
        counts = last.astype(np.float32)
        counts[1:] -= counts[:-1].copy()
        counts[:1] += 1
        return ids[last].astype(np.int64), counts

    def _learn(self, word: str) -> np.ndarray:
        if len(self.known) >= self.memo:
            self.known.clear()
        p, grams = f" {word} ", self.grams
        self.known[word] = ids = np.array([grams[p[i : i + n]] for n in self.sizes for i in range(len(p) - n + 1)], dtype=np.int32)
        return ids


def _softmax(z: np.ndarray) -> np.ndarray:
    e = np.exp(z - z.max())
    return e / e.sum()


def epoch(model: SoftmaxModel, rows, rate: float) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """One pass over (label, text) rows: the rows of the embedding that changed, by how much, and the change of the weights."""
    embed, weight, place = model.embed.copy(), model.weight.copy(), {x: i for i, x in enumerate(model.labels)}
    features = worker_state(("features", len(embed)), lambda: Features(len(embed)))
    touched = np.zeros(len(embed), dtype=bool)
    for label, line in rows:
        ids, counts = features.counted(line)
        if not len(ids):
            continue
        of_ids, n = embed.take(ids, axis=0), counts.sum()
        hidden = counts @ of_ids / n
        error = _softmax(hidden @ weight)
        error[place[label]] -= 1
        step = weight @ error
        weight -= rate * hidden[:, None] * error
        of_ids -= counts[:, None] * (rate * step / n).astype(embed.dtype)
        embed[ids] = of_ids
        touched[ids] = True
    own = np.flatnonzero(touched)
    return own, embed[own] - model.embed[own], weight - model.weight


#: Rows of the tables that travel together, as bytes: single rows of numbers would take several times the room.
BLOCK = 1 << 12
BLOCKS = "block long, rows binary, changes binary"


def _round(holder, rate: float):
    """Arrow function over (label, line): changed rows in blocks, those of the weights numbered after the buckets."""

    def run(batches):
        model = holder.value
        pairs = ((x, y) for rows in batches for x, y in zip(rows.column(0).to_pylist(), rows.column(1).to_pylist(), strict=True))
        own, changed, weight = epoch(model, pairs, rate)
        if len(own):
            number = np.concatenate([own, len(model.embed) + np.arange(len(model.labels))])
            values = np.concatenate([changed, weight.T]).astype(np.float32)
            starts = np.flatnonzero(np.concatenate([[True], np.diff(number // BLOCK) != 0]))
            for a, b in zip(starts, [*starts[1:], len(number)], strict=True):
                at = (number[a:b] % BLOCK).astype(np.int16)
                yield batch(block=pa.array([int(number[a]) // BLOCK]), rows=pa.array([at.tobytes()]), changes=pa.array([values[a:b].tobytes()]))

    return run


def _averaged(dim: int):
    """Arrow function over blocks, sorted by number: each block once, with the mean over those that changed a row."""

    def run(batches):
        block, total, count = None, np.zeros((BLOCK, dim)), np.zeros(BLOCK, dtype=np.int64)

        def result():
            at = np.flatnonzero(count)
            mean = (total[at] / count[at, None]).astype(np.float32)
            return batch(block=pa.array([block]), rows=pa.array([at.astype(np.int16).tobytes()]), changes=pa.array([mean.tobytes()]))

        for part in batches:
            for number, rows, changes in zip(*(c.to_pylist() for c in part.columns), strict=True):
                if number != block:
                    if block is not None:
                        yield result()
                    block = number
                    total[:], count[:] = 0, 0
                at = np.frombuffer(rows, dtype=np.int16)
                total[at] += np.frombuffer(changes, dtype=np.float32).reshape(-1, dim)
                count[at] += 1
        if block is not None:
            yield result()

    return run


def fit_softmax(rows: DataFrame, text: str = "line", buckets: int = BUCKETS, dim: int = DIM, rate: float = RATE, rounds: int = ROUNDS, seed: int = 0, partitions: int | None = None) -> SoftmaxModel:
    """One epoch over (label, line) rows; the same result, to rounding, for the same number of partitions and seed.

    ``partitions`` grow with the rows if not given.
    """
    rng = np.random.default_rng(seed)
    sizes = {r["label"]: r["n"] for r in rows.groupBy("label").agg(F.count(F.lit(1)).alias("n")).collect()}  # a row a label
    labels = sorted(x for x in sizes if x is not None)
    partitions = partitions or max(4, -(-sum(sizes.values()) // (rounds * ROWS)))
    model = SoftmaxModel(labels, rng.uniform(-1 / dim, 1 / dim, (buckets, dim)).astype(np.float32), np.zeros((dim, len(labels)), dtype=np.float32))
    spark = rows.sparkSession
    order = drawn(str(seed), F.md5(text))
    rounded = rows.filter("label is not null").select("label", F.col(text).alias("line"), order.alias("order"))
    path = scratch_path(spark, "dealt")
    rounded.withColumn("round", (F.col("order") % rounds).cast("int")).write.partitionBy("round").parquet(path)  # a round reads its own rows
    dealt = spark.read.schema("label string, line string, order long, round int").parquet(path)
    for k in range(rounds):
        part = dealt.filter(F.col("round") == k).withColumn("part", (F.col("order") / rounds).cast("long") % partitions)
        part = part.repartition(partitions, "part").sortWithinPartitions("order", "line").select("label", "line")
        holder = spark.sparkContext.broadcast(model)
        changes = arrow_map(part, _round(holder, rate * (1 - k / rounds)), BLOCKS)
        mean = arrow_map(changes.repartition("block").sortWithinPartitions("block"), _averaged(dim), BLOCKS).toArrow()
        embed, weight = model.embed.copy(), model.weight.copy()
        for number, own, change in zip(*(c.to_pylist() for c in mean.columns), strict=True):
            at = number * BLOCK + np.frombuffer(own, dtype=np.int16).astype(np.int64)
            change = np.frombuffer(change, dtype=np.float32).reshape(-1, dim)
            embed[at[at < buckets]] += change[at < buckets]
            weight[:, at[at >= buckets] - buckets] += change[at >= buckets].T
        model = SoftmaxModel(labels, embed, weight)
        holder.unpersist()
    remove(spark, path)
    return model


def predict_softmax(units: DataFrame, model: SoftmaxModel, key: str, text: str = "text") -> DataFrame:
    """(key, pred, prob); null for texts without a word."""
    holder = units.sparkSession.sparkContext.broadcast(model)

    def run(batches):
        m = holder.value
        features = worker_state(("features", len(m.embed)), lambda: Features(len(m.embed)))
        for rows in batches:
            pred, prob = [], []
            for t in rows.column(1).to_pylist():
                ids = features.of(t)
                p = _softmax(m.embed[ids].mean(axis=0) @ m.weight) if len(ids) else None
                pred.append(None if p is None else m.labels[int(p.argmax())])
                prob.append(None if p is None else float(p.max()))
            yield pa.RecordBatch.from_arrays([rows.column(0), pa.array(pred, pa.string()), pa.array(prob, pa.float64())], names=[key, "pred", "prob"])

    return arrow_map(units.select(key, text), run, f"`{key}` {units.schema[key].dataType.simpleString()}, pred string, prob double")
