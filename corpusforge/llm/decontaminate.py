"""Benchmark decontamination by spaced seeds.

A seed is a fixed mask over neighbouring words: marked positions are hashed, the others may differ. Hashes of all seeds of
the benchmark are joined with those of every document; around each hit both texts are laid over each other on that
diagonal, and the longest stretch with at least ``SIMILARITY`` equal words is measured. A document and an item overlap when
that stretch has ``OVERLAP`` words or more, or when an item of no more words lies whole in the document with that share of
equal words, its first and last word included.

The hashes of the benchmark's seeds are sent out in blocks of a bounded number of words, and each task joins its documents'
hashes with them; there is one pass over the documents for each block. A join by shuffle would move six hashes for every word
of the corpus, some sixteen times the text. A seed that is frequent on both sides is spread over the tasks that hold its
documents, and a task takes its hits in slices of bounded size.

Words are runs of letters and digits in lower case. Items of fewer words than a seed has marks count when they stand whole in
the document. Defined results: a null or empty text overlaps with nothing; items of fewer than ``least`` words are left out
(the report takes all; the filter asks for ``LEAST``, since clean documents hold phrases of a few words); repeated rows are
each reported; null ids stay null; empty tables give no rows; other columns are ignored; of equally long overlaps with an
item the first is reported.
"""

from __future__ import annotations

import re

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from corpusforge.engine import arrow_map, worker_state

#: The masks, each with five positions that count.
MASKS = ("11111", "1101011", "11001011", "101100101", "1100010011", "11010100001")
OVERLAP, SIMILARITY, LEAST = 13, 0.8, 8
#: Words of a benchmark block; words of documents that are hashed at once; hits that are held at once.
BLOCK, CHUNK, SLICE = 500_000, 1 << 16, 1 << 19
#: Words whose hashes a worker remembers, and the longest of them.
MEMO, LONGEST = 400_000, 64
WORD = re.compile(r"[^\W_]+")
WEIGHT = 5
SEEDS = [np.flatnonzero(np.frombuffer(m.encode(), dtype=np.uint8) == ord("1")) for m in (*MASKS, *("1" * n for n in range(1, WEIGHT)))]
FACTORS = np.array([xxhash.xxh64_intdigest(str(j).encode(), 1) | 1 for j in range(WEIGHT)], dtype=np.uint64)


class WordHashes:
    def __init__(self):
        self.known: dict[str, int] = {}

    def of(self, text: str | None) -> np.ndarray:
        words = WORD.findall(text.lower()) if text else []
        found = list(map(self.known.get, words))
        if None in found:
            if len(self.known) > MEMO:
                self.known = {}
            for i, value in enumerate(found):
                if value is None:
                    found[i] = xxhash.xxh64_intdigest(words[i])
                    if len(words[i]) <= LONGEST:
                        self.known[words[i]] = found[i]
        return np.array(found, dtype=np.uint64)


def seed_hashes(words: np.ndarray, seed: int) -> np.ndarray:
    """The hash of a mask at every position where it fits."""
    marked = SEEDS[seed]
    n = len(words) - int(marked[-1])
    if n <= 0:
        return np.empty(0, dtype=np.uint64)
    code = words[:n] * FACTORS[0]
    for j in range(1, len(marked)):
        code = (code ^ (code >> np.uint64(29))) + words[marked[j] : marked[j] + n] * FACTORS[j]
    code ^= code >> np.uint64(31)
    return code * np.uint64(0x9E3779B97F4A7C15)


class Index:
    """The seeds of a block of benchmark items; those of fewer marks hold the items of as many words, whole."""

    def __init__(self, items: list[tuple[int | None, np.ndarray]]):
        self.items = items
        self.tables = []
        sizes = np.array([len(w) for _, w in items], dtype=np.int64)
        for seed, marked in enumerate(SEEDS):
            own = np.flatnonzero(sizes == len(marked) if len(marked) < WEIGHT else sizes >= WEIGHT)
            codes = [seed_hashes(items[i][1], seed) for i in own.tolist()]
            code = np.concatenate([np.empty(0, dtype=np.uint64), *codes])
            item = np.repeat(own, [len(c) for c in codes]).astype(np.int32)
            at = np.concatenate([np.empty(0, dtype=np.int32), *[np.arange(len(c), dtype=np.int32) for c in codes]])
            order = np.argsort(code, kind="stable")
            bits = max(16, int(32 * len(code) + 1).bit_length())
            there = np.zeros(1 << bits, dtype=bool)
            there[code >> np.uint64(64 - bits)] = True
            self.tables.append((code[order], item[order], at[order], there, np.uint64(64 - bits)))

    def hits(self, words: np.ndarray):
        """(seed, word position, item, position in the item) of what both have, at most ``SLICE`` hits at once."""
        for seed, (code, item, at, there, shift) in enumerate(self.tables):
            if not len(code):
                continue
            own = seed_hashes(words, seed)
            maybe = np.flatnonzero(there[own >> shift])
            low, high = (np.searchsorted(code, own[maybe], side) for side in ("left", "right"))
            n = high - low
            maybe, low, n = maybe[n > 0], low[n > 0], n[n > 0]
            before = np.concatenate([[0], np.cumsum(n)])
            for first in range(0, int(before[-1]), SLICE):  # the hits numbered first to first + SLICE, whosever they are
                number = np.arange(first, min(first + SLICE, int(before[-1])))
                place = np.searchsorted(before, number, "right") - 1
                where = low[place] + number - before[place]
                yield seed, maybe[place], item[where], at[where]


def longest(equal: np.ndarray, similarity: float = SIMILARITY) -> tuple[int, int]:
    """The longest stretch, from an equal word to an equal word, whose share of equal words is at least ``similarity``.

    With running sums of what each word gains, the stretch must not lose. Only starts with a smaller sum than all before
    can be best, so a stack of these is met by the ends from the right.
    """
    gain = (np.concatenate([[0.0], np.cumsum(np.where(equal, 1 - similarity, -similarity))]) + 1e-9 * np.arange(len(equal) + 1)).tolist()
    places = np.flatnonzero(equal).tolist()
    starts: list[int] = []
    for i in places:
        if not starts or gain[i] < gain[starts[-1]]:
            starts.append(i)
    start, end = 0, 0
    for last in reversed(places):
        while starts and gain[last + 1] >= gain[starts[-1]]:
            i = starts.pop()
            if last + 1 - i > end - start:
                start, end = i, last + 1
    return start, end


def overlaps(index: Index, words: np.ndarray, ends: np.ndarray):
    """Verified overlaps of several documents, laid end to end: (document, item, its start, start in the document, words, equal).

    What a slice of hits names is verified at once; diagonals that another seed named are known while they are few.
    """
    starts = np.concatenate([[0], ends])
    seen: set[tuple[int, int, int]] = set()
    for seed, at, item, inside in index.hits(words):
        doc = np.searchsorted(ends, at, "right")
        whole = np.searchsorted(ends, at + int(SEEDS[seed][-1]), "right") == doc
        named = np.unique(np.stack([doc[whole], item[whole].astype(np.int64), (at - inside)[whole]]), axis=1)
        new = [x for x in map(tuple, named.T.tolist()) if x not in seen]
        if len(seen) + len(new) > SLICE:
            seen.clear()
        seen.update(new)
        for d, i, diagonal in new:
            own, first, last = index.items[i][1], int(starts[d]), int(ends[d])
            low, high = max(0, first - diagonal), min(len(own), last - diagonal)
            equal = words[diagonal + low : diagonal + high] == own[low:high]
            s, e = longest(equal)
            if len(equal) == len(own) <= OVERLAP and equal.sum() >= SIMILARITY * len(own) - 1e-9:
                s, e = 0, len(own)  # a whole short item, substituted words at its ends included
            if e - s >= min(OVERLAP, len(own)):
                yield d, i, low + s, diagonal + low + s - first, e - s, int(equal[s:e].sum())


def _grouped(hashes: WordHashes, texts: list[str | None]):
    """Documents in groups of about CHUNK words: first document, their words, where each ends."""
    first, held, n = 0, [], 0
    for i, text in enumerate(texts):
        held.append(hashes.of(text))
        n += len(held[-1])
        if n >= CHUNK or i == len(texts) - 1:
            yield first, np.concatenate(held), np.cumsum([len(w) for w in held])
            first, held, n = i + 1, [], 0


def _state(shared, name: str) -> tuple[Index, WordHashes]:
    return worker_state(("benchmark", name), lambda: (Index(shared.value), WordHashes()))


def _report(shared, name: str):
    def run(batches):
        index, hashes = _state(shared, name)
        for rows in batches:
            docs, out = rows.column(0).to_pylist(), []
            for first, words, ends in _grouped(hashes, rows.column(1).to_pylist()):
                best = {}
                for doc, item, start, at, length, equal in overlaps(index, words, ends):
                    key = (-length, -equal, at, start)
                    if (doc, item) not in best or key < best[doc, item]:
                        best[doc, item] = key
                out.extend((docs[first + doc], index.items[item][0], -k[0], -k[1], k[2], k[3]) for (doc, item), k in sorted(best.items()))
            cols = [pa.array(c, pa.int64()) for c in (zip(*out, strict=True) if out else [()] * 6)]
            yield pa.RecordBatch.from_arrays(cols, names=["doc_id", "item_id", "n_words", "n_equal", "doc_start", "item_start"])

    return run


def _clean(shared, name: str, text: int):
    def run(batches):
        index, hashes = _state(shared, name)
        for rows in batches:
            keep = np.ones(rows.num_rows, dtype=bool)
            for first, words, ends in _grouped(hashes, rows.column(text).to_pylist()):
                for overlap in overlaps(index, words, ends):
                    keep[first + overlap[0]] = False
            yield rows.filter(pa.array(keep))

    return run


def benchmark_blocks(benchmark: DataFrame, least: int = 1, block: int = BLOCK):
    """Blocks of items as (item_id, word hashes). Items stream to the driver; a block has ``block`` words or little more."""
    hashes, held, n = WordHashes(), [], 0
    for item, text in benchmark.select(F.col("item_id").cast("long"), F.col("text").cast("string")).toLocalIterator():
        words = hashes.of(text)
        if len(words) >= max(least, 1):
            held.append((item, words))
            n += len(words)
        if n >= block:
            yield held
            held, n = [], 0
    if held:
        yield held


def _sent(docs: DataFrame, block) -> tuple:
    name = xxhash.xxh64_hexdigest(b"".join(str(item).encode() + w.tobytes() for item, w in block))
    return docs.sparkSession.sparkContext.broadcast(block), name


RESULT = "doc_id long, item_id long, n_words long, n_equal long, doc_start long, item_start long"


def contaminated(docs: DataFrame, benchmark: DataFrame, least: int = 1) -> DataFrame:
    """The best overlap of each document with each item that it overlaps with; positions count words."""
    source = docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string"))
    parts = [arrow_map(source, _report(*_sent(docs, b)), RESULT) for b in benchmark_blocks(benchmark, least)]
    out = parts[0] if parts else docs.sparkSession.createDataFrame([], RESULT)
    for more in parts[1:]:
        out = out.union(more)
    return out


def without_contaminated(docs: DataFrame, benchmark: DataFrame, least: int = LEAST) -> DataFrame:
    """Documents, with all their columns, that overlap with no item of ``least`` words or more."""
    out, at = docs, docs.columns.index("text")
    for b in benchmark_blocks(benchmark, least):
        out = arrow_map(out, _clean(*_sent(docs, b), at), docs.schema)
    return out
