"""Warnings and letters of whole texts in plain Python, for passes that hold the texts in Arrow batches anyway.

The definitions are those of :mod:`corpusforge.functions.warnings`; on long texts one pass here costs a tenth of the
interpreted lambdas there. Tests hold the two against each other.
"""

from __future__ import annotations

import re
import unicodedata
from collections import Counter
from functools import lru_cache

import numpy as np

from corpusforge.functions.scripts import PATTERNS
from corpusforge.functions.warnings import DEFAULT, FILLER, POLICY, Config

_TOKEN = re.compile(r"\S+", re.ASCII)
_UNCASED = re.compile("[⺀-⿕々〇〡-〩〸-〻ぁ-ゟァ-ヿㇰ-ㇿ㐀-䶿一-鿿豈-龎ｦ-ﾝก-ฺเ-๛\U0001b000-\U0001b167\U00020000-\U000323af]")
_JS = re.compile("Java[Ss]cript")
_SYMBOL = 0x80


@lru_cache(maxsize=1)
def classes() -> np.ndarray:
    """For each code point: 1 + the place of its script in ``PATTERNS`` for letters, 15 for other letters, 128 for numbers, punctuation and symbols."""
    import regex

    table = np.zeros(0x110000, dtype=np.uint8)
    points = [c for c in range(0x110000) if not 0xD800 <= c < 0xE000]
    everything = "".join(map(chr, points))
    for c, ch in zip(points, everything, strict=True):
        kind = unicodedata.category(ch)[0]
        if kind == "L":
            table[c] = 15
        elif kind in "NPS":
            table[c] = _SYMBOL
    for place, name in enumerate(PATTERNS.values()):
        own = np.array([ord(m) for m in regex.findall(rf"\p{{Script={name}}}", everything)], dtype=np.int64)
        own = own[table[own] == 15]
        table[own] = place + 1
    return table


def code_classes(text: str) -> np.ndarray:
    """How many code points of each class a text has."""
    points = np.frombuffer(text.encode("utf-32-le", "surrogatepass"), dtype=np.uint32)
    return np.bincount(classes()[points], minlength=_SYMBOL + 1)


def letters(counts: np.ndarray) -> list[int]:
    """All letters, then those of each script of ``PATTERNS``."""
    return [int(counts[1:16].sum()), *counts[1 : len(PATTERNS) + 1].tolist()]


def text_lines(text: str) -> list[str]:
    return [s for line in text.split("\n") if (s := line.strip(" "))]


def _share(part: float, whole: float) -> float:
    return part / whole if whole > 0 else 0.0


def _upper(token: str) -> bool:
    c = token[0]
    return "A" <= c <= "Z" or (c > "\x7f" and unicodedata.category(c) == "Lu")


def _repeated(items: list, mode: str) -> float:
    if mode == "excess":
        return _share(len(items) - len(set(items)), len(items))
    n = Counter(items)
    return _share(sum(k for k in n.values() if k > 1), len(items))


class Marker:
    """Names of the warnings that hold for a text, in the order of ``warnings.NAMES``."""

    def __init__(self, c: Config = DEFAULT):
        self.c = c
        self.cursed = re.compile("|".join(c.cursed)) if c.cursed else None
        self.adult = re.compile(r"\b(?:" + "|".join(c.lexicon) + r")\b", re.ASCII) if c.lexicon else None

    def of(self, text: str | None, ls: list[str] | None = None, counts: np.ndarray | None = None) -> list[str]:
        if text is None:
            return []
        c, found = self.c, []
        ls = text_lines(text) if ls is None else ls
        n, lower = len(ls), text.lower()
        short = [len(x) < c.short_chars for x in ls]
        edge = max(int(np.ceil(n * c.edge)), 1)
        words = [_TOKEN.findall(x) for x in ls]
        if n < c.min_lines:
            found.append("tiny")
        for name, part in (("short_sentences", short), ("header", short[:edge]), ("footer", short[-edge:])):
            if n and sum(part) / len(part) >= c.short_share:
                found.append(name)
        if n and sum(bool(w) and sum(map(_upper, w)) / len(w) >= c.case for w in words) / n >= c.case:
            found.append("list_case")
        if n and not text.isascii() and _UNCASED.search(text):
            hits = sum(len(w) > 1 and sum(len(x) <= c.uncased_length for x in w) / len(w) >= c.case and _UNCASED.search(line) is not None for line, w in zip(ls, words, strict=True))
            if hits / n >= c.case:
                found.append("list_case_uncased")
        if self.technical(text, counts):
            found.append("technical")
        if self.cursed is not None and self.cursed.search(text):
            found.append("cursed")
        if any(self._repeats(w) for w in words):
            found.append("repetition")
        if any(len(x) > c.long_word for w in words for x in w):
            found.append("long_word")
        if FILLER in lower:
            found.append("filler")
        if any(p in lower for p in POLICY):
            found.append("policy")
        if _JS.search(text):
            found.append("js")
        if "{" in text or "}" in text:
            found.append("curly")
        if self.adult is not None and self.adult.search(lower):
            found.append("adult")
        return found

    def technical(self, text: str, counts: np.ndarray | None = None) -> bool:
        counts = code_classes(text) if counts is None else counts
        return bool(text) and counts[_SYMBOL] / len(text) >= self.c.technical

    def _repeats(self, words: list[str]) -> bool:
        c = self.c
        if len(words) <= c.repeat_words:
            return False
        return _repeated(words, c.repeat_mode) > c.repeat_share or _repeated(list(zip(words[:-1], words[1:], strict=True)), c.repeat_mode) > c.repeat_bigrams
