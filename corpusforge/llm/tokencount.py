"""Token counts by a count-only Viterbi over a unigram vocabulary.

An Aho-Corasick automaton gives every vocabulary piece that ends at each character; dynamic programming keeps the best score
and the number of pieces of the best path, never the path. Ties are those of the tokenizers library's unigram model: at each
end the piece that starts first wins, a character without a piece of its own costs the smallest score less 10, and such
characters count one piece for each of their bytes. Words (cut before every space, as that library's Metaspace pre-tokenizer
does) are counted once and remembered in two generations of bounded size.

Defined results: a null text counts as empty and has 0 tokens; repeated rows are counted alike; a null doc_id stays null; an
empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from corpusforge.engine import arrow_map, batch, worker_state

SPACE = "▁"
#: Fixed value: what an unknown character costs beyond the smallest score.
PENALTY = 10.0
#: Words that a worker remembers, and the longest of them.
MEMO, LONGEST = 700_000, 64


def unigram_vocabulary(path: str) -> list[tuple[str, float]]:
    """Pieces and scores of a public sentencepiece file, in order of id; they serve as a unigram vocabulary."""
    import sentencepiece

    sp = sentencepiece.SentencePieceProcessor(model_file=path)
    return [(sp.id_to_piece(i), sp.get_score(i)) for i in range(sp.get_piece_size())]


class CountViterbi:
    def __init__(self, vocabulary: list[tuple[str, float]]):
        import ahocorasick

        pieces = dict(vocabulary)
        if any(f"<0x{b:02X}>" not in pieces for b in range(256)):
            raise ValueError("the vocabulary has no piece for some byte")
        self.automaton = ahocorasick.Automaton()
        for piece, score in pieces.items():
            if piece:
                self.automaton.add_word(piece, (len(piece), score))
        self.automaton.make_automaton()
        self.unknown = min(s for _, s in vocabulary) - PENALTY
        self.young: dict[str, int] = {}
        self.old: dict[str, int] = {}

    def best(self, word: str) -> tuple[float, int]:
        """Score and number of pieces of the best path over one word."""
        n, unknown = len(word), self.unknown
        score, count = [0.0] * (n + 1), [0] * (n + 1)
        at, top, pieces, single = 0, None, 0, False  # position at + 1 is open: its best score and pieces so far
        for end, (length, own) in self.automaton.iter(word):
            while end > at:
                if not single and (top is None or score[at] + unknown > top):
                    top, pieces = score[at] + unknown, count[at] + len(word[at].encode())
                at += 1
                score[at], count[at], top, single = top, pieces, None, False
            start = end + 1 - length
            total = score[start] + own
            if top is None or total > top:
                top, pieces = total, count[start] + 1
            if length == 1:
                single = True
        while at < n:
            if not single and (top is None or score[at] + unknown > top):
                top, pieces = score[at] + unknown, count[at] + len(word[at].encode())
            at += 1
            score[at], count[at], top, single = top, pieces, None, False
        return score[n], count[n]

    def count(self, text: str | None) -> int:
        if not text:
            return 0
        words = text.replace(SPACE, " ").split(" ")
        if not words[0]:
            words = words[1:]
        found = list(map(self.young.get, words))
        if None in found:
            for i, known in enumerate(found):
                if known is None:
                    found[i] = self._learn(words[i])
        return sum(found)

    def _learn(self, word: str) -> int:
        n = self.young.get(word)
        if n is None:
            if len(self.young) >= MEMO // 2:
                self.old, self.young = self.young, {}
            n = self.old.get(word)
            if n is None:
                n = self.best(SPACE + word)[1]
            if len(word) <= LONGEST:
                self.young[word] = n
        return n


def counter(path: str) -> CountViterbi:
    return worker_state(("counter", path), lambda: CountViterbi(unigram_vocabulary(path)))


def _count(path: str):
    def run(batches):
        c = counter(path)
        for rows in batches:
            yield batch(doc_id=rows.column(0), n_tokens=pa.array([c.count(t) for t in rows.column(1).to_pylist()], pa.int64()))

    return run


def token_counts(docs: DataFrame, path: str) -> DataFrame:
    """(doc_id, n_tokens) of every whole text; ``path`` is a sentencepiece file."""
    return arrow_map(docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")), _count(path), "doc_id long, n_tokens long")
