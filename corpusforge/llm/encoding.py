"""Exact token ids by the tokenizers library, remembered piece by piece.

A text is cut only where both public pre-tokenizers start a new word whatever stands around: before a single space between
a visible character and a letter, between a letter and a plain punctuation mark or line end, and after a lone line end
before a letter (letters: Latin, Greek, Cyrillic). So the ids of the pieces, one after the other, are the ids of the text.
Every piece is encoded by the library itself; two generations of a dictionary of bounded size remember what it gave (pieces
of more than ``LONGEST`` characters are not remembered, so the bound is one in bytes too).

The strings of special tokens in a text become their ids, as the library does by default; such texts go to it whole.
"""

from __future__ import annotations

import os
import re
from array import array
from itertools import compress, count, repeat
from operator import is_

import numpy as np

from corpusforge.engine import worker_state

_LETTER = "A-Za-zÀ-ÖØ-öø-įı-ɏΑ-ΡΣ-Ωα-ωЀ-ҁ"
#: Text with none of these (apostrophes, runs of white space, other scripts) may be cut around every letter run.
_ODD = re.compile(f"'|\\s\\s|[^\\n -~{_LETTER}]")
_PLAIN = re.compile(f" ?[{_LETTER}]+| ?[^{_LETTER} ]+| ")
_CUT = re.compile(f"(?<=[!-~{_LETTER}])(?= [{_LETTER}])|(?<=[{_LETTER}])(?=[.,;:!?\\n])|(?<=[!-~{_LETTER}]\\n)(?=[{_LETTER}])")
_WORD = re.compile(f" ?[{_LETTER}]+")
#: Characters of the longest piece that is remembered.
LONGEST = 64
#: Words that show how a tokenizer prepares plain words.
_PROBES = (" the", "The", " ÉTÉ", "naïve", " Жук", "ΟΔΟΣ", " ıſ", "ß", " thingwhhe", "nation")


#: Latin-1 bytes of such plain text.
_PLAIN_BYTES = bytes(b for b in range(256) if not _ODD.search(chr(b)))


def is_plain(text: str) -> bool:
    """Whether ``_ODD`` finds nothing; for Latin-1 text without a regular expression."""
    try:
        raw = text.encode("latin-1")
    except UnicodeEncodeError:
        return _ODD.search(text) is None
    return not (raw.translate(None, _PLAIN_BYTES) or b"  " in raw or b"\n\n" in raw or b" \n" in raw or b"\n " in raw)


def pieces_of(text: str) -> list[str]:
    """The pieces of a text; joined, they are the text."""
    return _PLAIN.findall(text) if is_plain(text) else _CUT.split(text)


def _visible_bytes() -> dict[int, str]:
    """The printable stand-ins that byte-level vocabularies use for bytes: printable Latin-1 as it is, the rest from U+0100 on."""
    own = [*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)]
    rest = [b for b in range(256) if b not in own]
    return {b: chr(b) for b in own} | {b: chr(256 + i) for i, b in enumerate(rest)}


class PieceEncoder:
    """Token ids of whole texts as little-endian unsigned 32-bit bytes; about ``capacity`` pieces are remembered.

    A plain word is one pre-token, so it may go to the library's model directly, which takes a quarter of the time of a
    whole call; whether that gives the same ids is tried on some words when the tokenizer is loaded.
    """

    def __init__(self, path: str, capacity: int = 1_000_000, special_as_text: bool = False):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.tokenizer.encode_special_tokens = special_as_text
        added = [] if special_as_text else [t.content for t in self.tokenizer.get_added_tokens_decoder().values()]
        self.hint = re.match(r"[^\w]*", os.path.commonprefix(added))[0]
        self.special = re.compile("|".join(map(re.escape, added)), re.IGNORECASE) if added else None
        self.half = capacity // 2
        self.young: dict[str, bytes] = {}
        self.old: dict[str, bytes] = {}
        normalizer = self.tokenizer.normalizer
        self.lower = normalizer is not None and normalizer.normalize_str("AÉ") == "aé"
        shown = self.tokenizer.pre_tokenizer.pre_tokenize_str(" a") if self.tokenizer.pre_tokenizer else []
        self.spaced = [t for t, _ in shown] == ["Ġa"]
        self.visible = _visible_bytes()
        self.model = self.tokenizer.model
        self.direct = True
        self.direct = all(self._word(w) == self._library([w])[0] for w in _PROBES)

    def _library(self, texts: list[str]) -> list[bytes]:
        return [np.array(e.ids, dtype="<u4").tobytes() for e in self.tokenizer.encode_batch_fast(texts, add_special_tokens=False)]

    def _word(self, word: str) -> bytes:
        """Ids of a plain word by the model itself."""
        if not self.spaced:
            word = word.lstrip(" ")
        if word.isascii():
            word = (word.lower() if self.lower else word).replace(" ", "Ġ")
        else:
            word = "".join([c.lower() for c in word]) if self.lower else word
            word = "".join([self.visible[b] for b in word.encode()])
        return array("I", [t.id for t in self.model.tokenize(word)]).tobytes()

    def _learn(self, pieces: list[str]) -> dict[str, bytes]:
        known, rest = {}, pieces
        if self.direct:
            rest, word = [], self._word
            for p in pieces:
                if (p.isalpha() or (p[0] == " " and p[1:].isalpha())) and _WORD.fullmatch(p):
                    known[p] = word(p)
                else:
                    rest.append(p)
        if rest:
            known.update(zip(rest, self._library(rest), strict=True))
        return known

    def encode(self, texts: list[str | None]) -> list[bytes]:
        """Ids of each text."""
        return [self._encode(t) if t else b"" for t in texts]

    def _encode(self, text: str) -> bytes:
        if self.special is not None and self.hint in text and self.special.search(text):
            return self._library([text])[0]
        pieces = pieces_of(text)
        if len(pieces) > self.half:  # one text with more pieces than a generation holds
            return self._library([text])[0]
        found = list(map(self.young.get, pieces))
        gaps = list(compress(count(), map(is_, found, repeat(None))))
        if gaps:
            learned = self._fill({pieces[i] for i in gaps})
            for i in gaps:
                found[i] = learned[pieces[i]]
        return b"".join(found)

    def _fill(self, missing: set[str]) -> dict[str, bytes]:
        """Ids of pieces that the young generation lacks; they join it. When it is full, it becomes the old one."""
        learned = {p: known for p in missing if (known := self.old.get(p)) is not None}
        learned.update(self._learn([p for p in missing if p not in learned]))
        if len(self.young) + len(learned) > self.half:
            self.old, self.young = self.young, {}
        self.young.update(learned if max(map(len, learned)) <= LONGEST else {p: x for p, x in learned.items() if len(p) <= LONGEST})
        return learned


def encoder(path: str, capacity: int = 1_000_000) -> PieceEncoder:
    """One encoder in a Python worker."""
    return worker_state(("encoder", path, capacity), lambda: PieceEncoder(path, capacity))


def tokenizer_path(name: str) -> str:
    """Where the public tokenizer files of this machine lie; every operator takes such a path as a parameter."""
    import public_tokenizers

    return public_tokenizers.path(name)
