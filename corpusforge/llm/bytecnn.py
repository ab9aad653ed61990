"""Language identification by a byte convolutional network, trained in numpy.

Windows of fixed length go through filters of several widths over byte embeddings, max pooling and softmax. In training a
pooled value has one winning position, so the gradient only touches that position's bytes. For prediction, embedding times
filter is tabulated: a filter of width two is one look-up by byte pair, wider ones are sums of two look-ups. Every window of
the whole text is scored; a document's probabilities are the mean over its windows, weighted by their bytes.

The training sample is bounded: at most about ``DOCS`` documents of each label (drawn by hash of doc_id) and ``WINDOWS``
windows of each, whatever the size of the corpus. Documents held out by ``held_out`` are never drawn.

Defined results: a null text or one without a letter gives ``und`` with score 0; without any labelled text every document
is ``und``; repeated rows are predicted alike; a null doc_id is never drawn for training and counts as not held out; an
empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

import re
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from corpusforge.engine import arrow_map, batch, worker_state

#: Network: bytes of a window, widths of filters, filters of each width, size of a byte's embedding.
LENGTH, WIDTHS, FILTERS, EMBED = 256, (2, 3, 4), 16, 12
#: Training: documents of a label and windows of a document at most, updates, windows of an update, rate, seed.
DOCS, WINDOWS, UPDATES, BATCH, RATE, SEED = 800, 6, 700, 64, 0.004, 7
STEP = LENGTH - max(WIDTHS) + 1
#: Windows scored at once.
CHUNK = 512
UNDETERMINED = "und"
LETTER = re.compile(r"[^\W\d_]")


def held_out(doc_id: Column) -> Column:
    return F.coalesce(F.crc32(doc_id.cast("string")) % 4 == 2, F.lit(False))


def has_letter(text: str | None) -> bool:
    return any(m[0].isalpha() for m in LETTER.finditer(text)) if text else False


@dataclass
class Network:
    labels: list[str]
    embed: np.ndarray  # 256 x EMBED
    kernels: list[np.ndarray]  # width x EMBED x FILTERS
    bias: np.ndarray  # filters of all widths
    weight: np.ndarray  # filters of all widths x labels
    offset: np.ndarray  # labels

    def tables(self):
        """Look-up tables: by byte pair, or for width three by pair and single byte."""
        single = [[(self.embed @ k[j]).astype(np.float32) for j in range(len(k))] for k in self.kernels]
        pair = lambda a, b: (a[:, None, :] + b[None, :, :]).reshape(65536, -1)
        return [[pair(*s[j : j + 2]) if j + 1 < len(s) else s[j] for j in range(0, len(s), 2)] for s in single]

    def probabilities(self, windows: np.ndarray, tables) -> np.ndarray:
        bytes_ = windows.astype(np.intp)
        pairs = bytes_[:, :-1] * 256 + bytes_[:, 1:]
        pooled = []
        for width, own in zip(WIDTHS, tables, strict=True):
            n, act = LENGTH - width + 1, None
            for j, table in zip(range(0, width, 2), own, strict=True):
                part = table[(pairs if len(table) > 256 else bytes_)[:, j : j + n]]
                act = part if act is None else np.add(act, part, out=act)
            pooled.append(act.max(axis=1))
        z = np.maximum(np.concatenate(pooled, axis=1) + self.bias, 0) @ self.weight + self.offset
        z = np.exp(z - z.max(axis=1, keepdims=True))
        return z / z.sum(axis=1, keepdims=True)


def windows_of(text: str) -> np.ndarray:
    """All windows of a text, overlapping so that every byte sequence of a filter's width lies in one; zero-padded."""
    raw = np.frombuffer(text.encode(), dtype=np.uint8)
    n = max(1, -(-(len(raw) - (LENGTH - STEP)) // STEP))
    padded = np.zeros((n - 1) * STEP + LENGTH, dtype=np.uint8)
    padded[: len(raw)] = raw
    return np.lib.stride_tricks.as_strided(padded, (n, LENGTH), (STEP, 1))


def fit(windows: np.ndarray, gold: np.ndarray, labels: list[str]) -> Network:
    """Adam on cross-entropy; classes are drawn equally often."""
    rng = np.random.default_rng(SEED)
    net = Network(labels, rng.normal(0, 0.3, (256, EMBED)), [rng.normal(0, (w * EMBED) ** -0.5, (w, EMBED, FILTERS)) for w in WIDTHS], np.zeros(FILTERS * len(WIDTHS)), rng.normal(0, 0.1, (FILTERS * len(WIDTHS), len(labels))), np.zeros(len(labels)))
    params = [net.embed, *net.kernels, net.bias, net.weight, net.offset]
    moment, square = [np.zeros_like(p) for p in params], [np.zeros_like(p) for p in params]
    members = [np.flatnonzero(gold == k) for k in range(len(labels))]
    for step in range(1, UPDATES + 1):
        kinds = rng.integers(0, len(labels), BATCH)
        rows = np.array([members[k][rng.integers(len(members[k]))] for k in kinds])
        x = windows[rows]
        vectors = net.embed[x]
        pooled, where = [], []
        for width, kernel in zip(WIDTHS, net.kernels, strict=True):
            n = LENGTH - width + 1
            act = sum(vectors[:, j : j + n] @ kernel[j] for j in range(width))
            at = act.argmax(axis=1)
            where.append(at)
            pooled.append(np.take_along_axis(act, at[:, None, :], axis=1)[:, 0])
        h = np.concatenate(pooled, axis=1) + net.bias
        hidden = np.maximum(h, 0)
        z = hidden @ net.weight + net.offset
        p = np.exp(z - z.max(axis=1, keepdims=True))
        p /= p.sum(axis=1, keepdims=True)
        p[np.arange(BATCH), kinds] -= 1
        p /= BATCH
        back = (p @ net.weight.T) * (h > 0)
        grads = [np.zeros_like(q) for q in params]
        grads[-1], grads[-2], grads[-3] = p.sum(axis=0), hidden.T @ p, back.sum(axis=0)
        for i, (width, kernel) in enumerate(zip(WIDTHS, net.kernels, strict=True)):
            g, at = back[:, i * FILTERS : (i + 1) * FILTERS], where[i]
            for j in range(width):
                won = np.take_along_axis(x, at + j, axis=1)  # windows x filters: the byte that won
                grads[1 + i][j] = np.einsum("bfe,bf->ef", net.embed[won], g)
                np.add.at(grads[0], won, g[:, :, None] * kernel[j].T[None])
        rate = RATE * (1 - step / (UPDATES + 1))
        for q, grad, m, s in zip(params, grads, moment, square, strict=True):
            m += 0.1 * (grad - m)
            s += 0.001 * (grad * grad - s)
            q -= rate * (m / (1 - 0.9**step)) / (np.sqrt(s / (1 - 0.999**step)) + 1e-8)
    return net


def _draw(batches):
    for rows in batches:
        out = []
        for doc, lang, text in zip(*(c.to_pylist() for c in rows.columns), strict=True):
            if has_letter(text):
                all_ = windows_of(text)
                for at in np.unique(np.linspace(0, len(all_) - 1, WINDOWS).astype(int)):
                    out.append((doc, int(at), lang, all_[at].tobytes()))
        cols = list(zip(*out, strict=True)) or [(), (), (), ()]
        yield batch(doc_id=pa.array(cols[0], pa.int64()), at=pa.array(cols[1], pa.int64()), lang=pa.array(cols[2], pa.string()), window=pa.array(cols[3], pa.binary()))


def train(docs: DataFrame) -> Network | None:
    """Fit on a bounded sample of labelled documents that are not held out; ``None`` where there is none."""
    source = docs.select(F.col("doc_id").cast("long"), F.col("lang").cast("string"), F.col("text").cast("string"))
    allowed = source.filter(F.col("doc_id").isNotNull() & F.col("lang").isNotNull() & ~held_out(F.col("doc_id")))
    sizes = {r["lang"]: r["n"] for r in allowed.groupBy("lang").agg(F.count(F.lit(1)).alias("n")).collect()}  # a row a language
    if not sizes:
        return None
    share = F.element_at(F.create_map(*[F.lit(x) for lang, n in sizes.items() for x in (lang, min(1.0, DOCS / n))]), F.col("lang"))
    drawn = allowed.filter((F.pmod(F.xxhash64("doc_id"), F.lit(1 << 30)) < share * (1 << 30)) & F.col("text").isNotNull())
    sample = arrow_map(drawn.select("doc_id", "lang", "text"), _draw, "doc_id long, at long, lang string, window binary").toArrow().sort_by([("doc_id", "ascending"), ("at", "ascending"), ("window", "ascending")])
    if not sample.num_rows:
        return None
    labels = sorted(set(sample["lang"].to_pylist()))
    gold = np.array([labels.index(x) for x in sample["lang"].to_pylist()])
    return fit(np.frombuffer(b"".join(sample["window"].to_pylist()), dtype=np.uint8).reshape(-1, LENGTH), gold, labels)


def _predict(net: Network | None, column: int = 1, with_text: bool = False):
    def run(batches):
        tables = worker_state(("network", None if net is None else net.embed.tobytes()[:64]), lambda: net and net.tables())
        for rows in batches:
            texts = rows.column(column).to_pylist()
            sums, weights = np.zeros((len(texts), len(net.labels) if net else 1)), np.zeros(len(texts))
            held, owners, shares, n = [], [], [], 0

            def flush():
                nonlocal n
                if held:
                    x, own, share = np.concatenate(held), np.concatenate(owners), np.concatenate(shares)
                    for at in range(0, len(x), CHUNK):
                        p = net.probabilities(x[at : at + CHUNK], tables) * share[at : at + CHUNK, None]
                        np.add.at(sums, own[at : at + CHUNK], p)
                    np.add.at(weights, own, share)
                held.clear(), owners.clear(), shares.clear()
                n = 0

            for i, text in enumerate(texts):
                if net and has_letter(text):
                    w = windows_of(text)
                    share = np.full(len(w), float(LENGTH))
                    share[-1] = max(1, np.count_nonzero(w[-1]))
                    held.append(w), owners.append(np.full(len(w), i)), shares.append(share)
                    n += len(w)
                    if n >= CHUNK:
                        flush()
            flush()
            p = sums / np.maximum(weights, 1e-9)[:, None]
            best = p.argmax(axis=1)
            known = weights > 0
            pred = [net.labels[b] if k else UNDETERMINED for b, k in zip(best.tolist(), known.tolist(), strict=True)]
            score = np.where(known, np.clip(p.max(axis=1), 0, 1), 0.0)
            kept = [c for c in range(rows.num_columns) if with_text or c != column]
            yield pa.RecordBatch.from_arrays([pa.array(pred, pa.string()), pa.array(score), *[rows.column(c) for c in kept]], names=["lang_pred", "score", *[rows.schema.names[c] for c in kept]])

    return run


def predict(docs: DataFrame, net: Network | None) -> DataFrame:
    """(doc_id, held_out, lang_pred, score) for the whole text of every document."""
    source = docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string"))
    out = arrow_map(source, _predict(net), "lang_pred string, score double, doc_id long")
    return out.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "lang_pred", "score")


def keep_identified(docs: DataFrame, net: Network | None, least: float) -> DataFrame:
    """Rows, with all their columns, whose language is known with a score of ``least`` or more; a null ``lang`` is filled."""
    given = docs.select(*[F.col(f"`{c}`").alias(f"_{i}") for i, c in enumerate(docs.columns)])
    schema = T.StructType([T.StructField("lang_pred", T.StringType()), T.StructField("score", T.DoubleType()), *given.schema])
    out = arrow_map(given, _predict(net, docs.columns.index("text"), True), schema).filter((F.col("lang_pred") != UNDETERMINED) & (F.col("score") >= least))
    kept = [F.coalesce(f"_{i}", "lang_pred").alias(c) if c == "lang" else F.col(f"_{i}").alias(c) for i, c in enumerate(docs.columns)]
    return out.select(*kept)


def identify(docs: DataFrame) -> DataFrame:
    return predict(docs, train(docs))
