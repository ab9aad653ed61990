"""Identification of documents and their lines in one Arrow pass over the text.

The counting model becomes sorted buckets with their (label, gain) pairs, sent once to every executor while it is small
enough; n-grams are hashed once and words scored once, and both are remembered within a bound in bytes. A document's n-grams
are its lines' n-grams, so its score is the sum of its lines' scores. Other columns pass through, so nothing is joined; on
request the same pass counts letters by script and raises the warnings, so the text enters Python once.
"""

from __future__ import annotations

import hashlib
import re
from dataclasses import dataclass, replace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from corpusforge.engine import arrow_map, worker_state, written
from corpusforge.functions import warnings as W
from corpusforge.functions.features import NMAX, NMIN
from corpusforge.functions.text import exploded_lines, letter_class
from corpusforge.operators.lid import LidModel, predict

#: (bucket, label) pairs that may be broadcast, 12 bytes each; larger models predict by join.
BROADCAST_PAIRS = 16_000_000
#: Bytes of remembered words' gains in a worker, remembered n-grams, and the longest word that is remembered.
MEMO_BYTES, MEMO_GRAMS, LONGEST = 128 << 20, 1_000_000, 64
#: Numbers that one step holds: words of a step times labels.
STEP = 4_000_000
LINE = pa.list_(pa.struct([("pos", pa.int32()), ("pred", pa.string()), ("prob", pa.float64())]))
LINES = "array<struct<pos:int,pred:string,prob:double>>"


class Model:
    """A model as arrays: sorted buckets, where their pairs begin, labels and gains of the pairs, weight of unseen n-grams by label."""

    def __init__(self, model: LidModel, allowed: list[str] | None = None):
        totals = {r["label"]: r["total"] for r in model.totals.collect()}  # a row a label
        self.labels = sorted(x for x in totals if allowed is None or x in allowed)
        place = {x: i for i, x in enumerate(self.labels)}
        pairs = model.counts.filter(F.col("label").isin(*self.labels)).toArrow() if allowed is not None else model.counts.toArrow()
        b, col = pairs["b"].to_numpy(), np.array([place[x] for x in pairs["label"].to_pylist()], dtype=np.int32)
        order = np.lexsort((col, b))
        self.col, self.gain = col[order], np.log1p(pairs["c"].to_numpy()[order] / model.alpha)
        self.keys, first = np.unique(b[order], return_index=True)
        self.first = np.append(first, len(b))
        self.unseen = np.array([np.log(model.alpha / (totals[x] + model.alpha * model.buckets)) for x in self.labels])
        self.buckets = model.buckets
        self.scripts = [x.replace("-", "_").partition("_")[2] for x in self.labels]


@dataclass(frozen=True)
class Pass:
    """What the pass gives besides the document's label."""

    tau: float = 1.0
    lines: bool = True
    #: Only labels of the text's main script may win (the script-restricted release).
    restrict: bool = False
    letters: bool = False
    warnings: W.Config | None = None


class Scorer:
    def __init__(self, model: Model, pattern: str):
        self.model = model
        self.words = re.compile(pattern.replace(r"\p{L}", letter_class()))
        self.grams: dict[str, int] = {}
        self.known: dict[str, int] = {}
        self.width = len(model.labels) + 1
        self.room = max(MEMO_BYTES // (8 * self.width), 1024)
        self.table = np.zeros((1024, self.width))

    def _rows(self, grams: list[str]) -> np.ndarray:
        """Places of n-grams' buckets among the model's, -1 for those it lacks."""
        found = list(map(self.grams.get, grams))
        if None in found:
            new = {g for g, k in zip(grams, found, strict=True) if k is None}
            if len(self.grams) + len(new) > MEMO_GRAMS:
                self.grams.clear()
                new = set(grams)
            ordered, keys = sorted(new), self.model.keys
            b = np.array([int(hashlib.md5(g.encode("utf-8", "surrogatepass")).hexdigest()[:8], 16) % self.model.buckets for g in ordered], dtype=np.int64)
            at = np.minimum(np.searchsorted(keys, b), max(len(keys) - 1, 0))
            rows = np.where(keys[at] == b, at, -1) if len(keys) else np.full(len(b), -1)
            self.grams.update(zip(ordered, rows.tolist(), strict=True))
            found = list(map(self.grams.get, grams))
        return np.array(found, dtype=np.int64)

    def _score(self, words: list[str]) -> np.ndarray:
        """Gains by label and number of n-grams of each word."""
        m, out = self.model, np.zeros((len(words), self.width))
        grams: list[str] = []
        sizes = np.empty(len(words), dtype=np.int64)
        for i, w in enumerate(words):
            p, before = f" {w} ", len(grams)
            for n in range(NMIN, NMAX + 1):
                grams.extend([p[j : j + n] for j in range(len(p) - n + 1)])
            sizes[i] = len(grams) - before
        out[:, -1] = sizes
        rows, of = self._rows(grams), np.repeat(np.arange(len(words)), sizes)
        seen = rows >= 0
        rows, of = rows[seen], of[seen]
        n = m.first[rows + 1] - m.first[rows]
        for a in range(0, len(rows), max(STEP // self.width, 1)):  # each n-gram has at most one pair a label
            b = a + max(STEP // self.width, 1)
            k = n[a:b]
            pairs = np.repeat(m.first[rows[a:b]] - np.cumsum(k) + k, k) + np.arange(int(k.sum()))
            flat = np.repeat(of[a:b], k) * self.width + m.col[pairs]
            out += np.bincount(flat, weights=m.gain[pairs], minlength=out.size).reshape(out.shape)
        return out

    def vectors(self, words: list[str]) -> np.ndarray:
        """Gains and number of n-grams of each word."""
        found = list(map(self.known.get, words))
        if None not in found:
            return self.table[found]
        new = [w for w in {w for w, k in zip(words, found, strict=True) if k is None} if len(w) <= LONGEST]
        if len(self.known) + len(new) > self.room:
            self.known.clear()
            new = [w for w in set(words) if len(w) <= LONGEST]
        start, end = len(self.known), len(self.known) + len(new)
        if end > len(self.table):
            self.table = np.concatenate([self.table, np.zeros((max(end - len(self.table), len(self.table)), self.width))])
        for a in range(0, len(new), 4096):
            self.table[start + a : start + a + len(new[a : a + 4096])] = self._score(new[a : a + 4096])
        self.known.update(zip(new, range(start, end), strict=True))
        found = list(map(self.known.get, words))
        rare = [i for i, k in enumerate(found) if k is None]
        out = self.table[[0 if k is None else k for k in found]]
        for i in rare:  # very long words, one at a time and not remembered
            out[i] = self._score([words[i]])[0]
        return out

    def best(self, sums: np.ndarray, tau: float, banned: np.ndarray | None = None) -> tuple[pa.Array, pa.Array]:
        """Label and probability for rows of summed gains; null for rows without an n-gram."""
        if not len(sums) or not self.model.labels:
            return pa.nulls(len(sums), pa.string()), pa.nulls(len(sums), pa.float64())
        n = sums[:, -1:]
        z = (sums[:, :-1] + n * self.model.unseen) / (tau * np.sqrt(np.maximum(n, 1)))
        some = n[:, 0] > 0
        if banned is not None:
            z[banned] = -np.inf
            some &= ~banned.all(axis=1)
            z[~some] = 0
        p = np.exp(z - z.max(axis=1, keepdims=True))
        p /= p.sum(axis=1, keepdims=True)
        top = np.round(p, 9).argmax(axis=1)
        pred = pa.DictionaryArray.from_arrays(pa.array(top.astype(np.int32), mask=~some), pa.array(self.model.labels, pa.string())).dictionary_decode()
        return pred, pa.array(p[np.arange(len(p)), top], mask=~some)


def _batch(scorer: Scorer, texts: list[str | None], by: Pass, marker):
    """Columns pred, prob, lines, letters, warnings of a batch."""
    k, step = scorer.width, max(STEP // scorer.width, 64)
    docs = np.zeros((len(texts), k))
    positions: list[int] = []
    sizes = np.zeros(len(texts), dtype=np.int64)
    preds, probs, letters, warned = [], [], [], []
    held: list[str] = []
    owner: list[int] = []
    lengths: list[int] = []

    def flush():
        if not lengths:
            return
        sums = np.zeros((len(lengths), k))
        of = np.repeat(np.arange(len(lengths)), lengths)
        for a in range(0, len(held), step):
            own = of[a : a + step]
            starts = np.flatnonzero(np.diff(own, prepend=-1))
            sums[own[starts]] += np.add.reduceat(scorer.vectors(held[a : a + step]), starts, axis=0)
        o = np.array(owner)
        starts = np.flatnonzero(np.diff(o, prepend=-1))
        docs[o[starts]] += np.add.reduceat(sums, starts, axis=0)
        if by.lines:
            pred, prob = scorer.best(sums, by.tau)
            preds.append(pred)
            probs.append(prob)
        held.clear(), owner.clear(), lengths.clear()

    for i, text in enumerate(texts):
        kept = []
        for pos, line in enumerate((text or "").split("\n")):
            if s := line.strip(" "):
                found = scorer.words.findall(s.lower())
                held.extend(found)
                owner.append(i)
                lengths.append(len(found))
                kept.append(s)
                if by.lines:
                    positions.append(pos)
                if len(held) >= step or len(lengths) >= step:
                    flush()
        sizes[i] = len(kept)
        if marker is not None or by.letters or by.restrict:
            from corpusforge.functions import marks

            counts = marks.code_classes(text or "")
            letters.append(marks.letters(counts))
            if marker is not None:
                warned.append(marker.of(text, kept, counts))
    flush()
    banned = None
    if by.restrict and scorer.model.labels:
        banned = _banned(scorer.model.scripts, np.array(letters, dtype=np.int64).reshape(len(texts), -1))
    out = list(scorer.best(docs, by.tau, banned))
    if by.lines:
        inner = pa.StructArray.from_arrays(
            [pa.array(positions, pa.int32()), pa.concat_arrays([pa.nulls(0, pa.string()), *preds]), pa.concat_arrays([pa.nulls(0, pa.float64()), *probs])], fields=list(LINE.value_type)
        )
        out.append(pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(sizes)]).astype(np.int32)), inner).cast(LINE))
    else:
        out.append(pa.nulls(len(texts), LINE))
    out.append(pa.array(letters, pa.list_(pa.int64())) if by.letters else pa.nulls(len(texts), pa.list_(pa.int64())))
    out.append(pa.array(warned, pa.list_(pa.string())) if marker is not None else pa.nulls(len(texts), pa.list_(pa.string())))
    return out


def _banned(label_scripts: list[str], letters: np.ndarray) -> np.ndarray:
    """(text, label): labels of another script than the text's main one; texts without letters may be anything."""
    from corpusforge.functions.labels import COMPOSITE
    from corpusforge.functions.scripts import PATTERNS

    names = list(PATTERNS)
    by_name = sorted(range(len(names)), key=lambda i: names[i])
    counts = letters[:, 1:][:, by_name]
    rest = letters[:, 0] - counts.sum(axis=1)
    fits = [[x == names[i] or names[i] in COMPOSITE.get(x, ()) for x in label_scripts] for i in by_name]
    fits = np.array([*fits, [x not in PATTERNS and x not in COMPOSITE for x in label_scripts]], dtype=bool)
    main = np.where(rest > counts.max(axis=1), len(names), counts.argmax(axis=1))
    return (letters[:, 0] > 0)[:, None] & ~fits[main]


def _pass(holder, name: str, pattern: str, by: Pass, at: int):
    def run(batches):
        from corpusforge.functions.marks import Marker

        scorer = worker_state((name, pattern), lambda: Scorer(holder.value, pattern))
        marker = Marker(by.warnings) if by.warnings is not None else None
        for rows in batches:
            more = _batch(scorer, rows.column(at).to_pylist(), by, marker)
            yield pa.RecordBatch.from_arrays([*rows.columns, *more], names=[*rows.schema.names, "pred", "prob", "lines", "letters", "named"])

    return run


def _identify_by_join(docs: DataFrame, model: LidModel, text: str, by: Pass) -> DataFrame:
    """Documents and lines predicted by join; rows are numbered once, since keys may be null or repeated."""
    rows = written(docs.withColumn("unit__", F.monotonically_increasing_id()), "units")
    only = rows.select(F.col("unit__").alias("unit"), F.col(text).alias("text"))
    if by.restrict:
        from corpusforge.operators import lid

        found = lid.predict_restricted(only, model, ["unit"], "text", by.tau)
    else:
        found = predict(only, model, ["unit"], "text", by.tau)
    out = rows.join(found.withColumnRenamed("unit", "unit__"), "unit__", "left")
    if by.lines:
        lines = exploded_lines(only)
        per = lines.select("unit", "pos").join(predict(lines, model, ["unit", "pos"], "line", by.tau), ["unit", "pos"], "left")
        gathered = per.groupBy(F.col("unit").alias("unit__")).agg(F.array_sort(F.collect_list(F.struct("pos", "pred", "prob"))).alias("lines"))
        out = out.join(gathered, "unit__", "left").withColumn("lines", F.coalesce(F.col("lines").cast(LINES), F.array().cast(LINES)))
    else:
        out = out.withColumn("lines", F.lit(None).cast(LINES))
    if by.letters or by.warnings is not None:
        from corpusforge.functions.scripts import count_letters

        out = count_letters(out, text)
        if by.warnings is not None:
            out = W.annotate(out, by.warnings, text).withColumnRenamed("warnings", "named")
    return out.drop("unit__")


def identify_rows(docs: DataFrame, model: LidModel, text: str = "text", by: Pass = Pass()) -> DataFrame:
    """The rows of ``docs`` with pred, prob, lines, letters and named (the warnings); by broadcast while the model is small, else by join.

    Both ways give the same result. Columns of those names must not be among the rows' own.
    """
    counts = written(model.counts, "model")  # counted, collected and summed: trained once
    model = replace(model, counts=counts, totals=counts.groupBy("label").agg(F.sum("c").alias("total")))
    if counts.count() > BROADCAST_PAIRS:
        out = _identify_by_join(docs, model, text, by)
    else:
        arrays = Model(model)
        name = hashlib.md5(arrays.gain.tobytes() + arrays.keys.tobytes() + "".join(arrays.labels).encode()).hexdigest()
        holder = docs.sparkSession.sparkContext.broadcast(arrays)
        more = [("pred", "string"), ("prob", "double"), ("lines", LINES), ("letters", "array<bigint>"), ("named", "array<string>")]
        schema = T.StructType([*docs.schema.fields, *T.StructType.fromDDL(", ".join(f"{n} {t}" for n, t in more)).fields])
        out = arrow_map(docs, _pass(holder, name, model.pattern, by, docs.columns.index(text)), schema)
    unused = [c for c, use in (("letters", by.letters), ("named", by.warnings is not None)) if not use]
    return out.drop(*unused)


def identify(docs: DataFrame, model: LidModel, key: str = "doc_id", text: str = "text", tau: float = 1.0, with_lines: bool = True) -> DataFrame:
    """(key, pred, prob, lines) of whole texts."""
    rows = docs.select(F.col(key).cast("long").alias(key), F.col(text).cast("string").alias("text"))
    return identify_rows(rows, model, "text", Pass(tau=tau, lines=with_lines)).select(key, "pred", "prob", "lines")
