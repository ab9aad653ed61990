"""Token counts, id files and packing against the tokenizers library."""

from __future__ import annotations

import zlib

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from tokenizers import Tokenizer, models, pre_tokenizers

from corpusforge.engine import read, scratch_path
from corpusforge.llm import packing, tokencount, tokenfiles
from corpusforge.llm.encoding import PieceEncoder, tokenizer_path
from corpusforge.llm.queries import QUERIES

BYTES, WORDS, PIECES = (tokenizer_path(n) for n in ("byte_bpe_50k.json", "word_bpe_49k.json", "piece_bpe_32k.model"))


def library(path: str) -> Tokenizer:
    return Tokenizer.from_file(path)  # as it is: strings of special tokens become their ids


def ids_of(t: Tokenizer, text: str | None) -> list[int]:
    return t.encode(text or "", add_special_tokens=False).ids


@settings(max_examples=100, deadline=None)
@given(st.text(alphabet="aeéñßİΣσ 's\n\t.,!1²-日😀́ \u0085tThe", max_size=40))
def test_pieces_encode_as_the_whole(text):
    for path in (BYTES, WORDS):
        assert encoder_of(path).encode([text])[0] == np.array(ids_of(library_of(path), text), dtype="<u4").tobytes()


@settings(max_examples=100, deadline=None)
@given(st.lists(st.sampled_from(["<|endoftext|>", "<|startoftext|>", "<|ENDOFTEXT|>", "<|endoftext", "|>", " ", "\n", "hello", " x", "<", "a"]), max_size=8))
def test_strings_of_special_tokens_encode_as_the_library_does(parts):
    text = "".join(parts)
    for path in (BYTES, WORDS):
        assert encoder_of(path).encode([text])[0] == np.array(ids_of(library_of(path), text), dtype="<u4").tobytes()


def test_special_strings_may_be_text():
    plain = Tokenizer.from_file(BYTES)
    plain.encode_special_tokens = True
    text = "hello <|endoftext|> x"
    assert PieceEncoder(BYTES, special_as_text=True).encode([text])[0] == np.array(ids_of(plain, text), dtype="<u4").tobytes()
    assert PieceEncoder(BYTES).encode([text])[0] == np.array([31373, 220, 50256, 2124], dtype="<u4").tobytes()


def test_very_long_words_are_not_remembered():
    e, text = PieceEncoder(BYTES), "y" * 5000 + " z" * 3
    assert e.encode([text, text])[1] == np.array(ids_of(library_of(BYTES), text), dtype="<u4").tobytes()
    assert max(map(len, e.young), default=0) <= 64


_LIBRARIES: dict[str, Tokenizer] = {}
_ENCODERS: dict[str, PieceEncoder] = {}


def encoder_of(path: str) -> PieceEncoder:
    if path not in _ENCODERS:
        _ENCODERS[path] = PieceEncoder(path)
    return _ENCODERS[path]


def library_of(path: str) -> Tokenizer:
    if path not in _LIBRARIES:
        _LIBRARIES[path] = library(path)
    return _LIBRARIES[path]


def test_generations_forget_and_learn_again():
    small, texts = PieceEncoder(BYTES, capacity=8), ["one two three four", "five six seven", "one two", "a b c d e f g h i j"]
    for _ in range(3):
        assert [len(x) // 4 for x in small.encode(texts)] == [len(ids_of(library_of(BYTES), t)) for t in texts]


@pytest.fixture(scope="module")
def unigram() -> Tokenizer:
    t = Tokenizer(models.Unigram(tokencount.unigram_vocabulary(PIECES), unk_id=0, byte_fallback=True))
    t.pre_tokenizer = pre_tokenizers.Metaspace(replacement="▁", prepend_scheme="always", split=True)
    return t


def test_counts_equal_the_library_on_documents(spark, small, unigram):
    docs = {r.doc_id: r.text for r in read(spark, small, "documents").collect()}
    got = {r.doc_id: r.n_tokens for r in QUERIES["op1_token_counts"](spark, small).collect()}
    assert got == {i: len(unigram.encode(t).ids) for i, t in docs.items()}


def test_counts_of_odd_documents(odd_docs, no_docs, unigram):
    got = sorted((r.doc_id or -1, r.n_tokens) for r in tokencount.token_counts(odd_docs, PIECES).collect())
    assert got == sorted((r.doc_id or -1, len(unigram.encode(r.text).ids) if r.text else 0) for r in odd_docs.collect())
    assert tokencount.token_counts(no_docs, PIECES).collect() == []


def test_ties_keep_the_longest_piece():
    byte_pieces = [(f"<0x{b:02X}>", -50.0) for b in range(256)]
    vocabulary = [("<unk>", 0.0), ("▁", -1.0), ("a", -1.0), ("b", -1.0), ("ab", -2.0), ("▁a", -2.0), ("abb", -3.0), *byte_pieces]
    t = Tokenizer(models.Unigram(vocabulary, unk_id=0, byte_fallback=True))
    c = tokencount.CountViterbi(vocabulary)
    for word in ("▁ab", "▁abb", "▁aabb", "▁bab", "▁aZb", "▁é"):
        assert c.best(word)[1] == len(t.encode(word).ids), word


def expected(texts: list[str | None], path: str, end: int) -> list[list[int]]:
    return [[*ids_of(library_of(path), t), end] for t in texts]


def crc(ids) -> int:
    return zlib.crc32(np.array(ids, dtype="<u4").tobytes())


def test_id_files_hold_what_was_encoded(spark, small):
    docs = sorted((r.doc_id, r.text) for r in read(spark, small, "documents").collect())
    got = {r.doc_id: (r.start, r.n_tokens, r.ids_crc32) for r in QUERIES["op7_token_files"](spark, small).collect()}
    at, want = 0, {}
    for (i, _), ids in zip(docs, expected([t for _, t in docs], BYTES, 0), strict=True):
        want[i] = (at, len(ids), crc(ids))
        at += len(ids)
    assert got == want


def test_id_files_of_odd_documents(spark, odd_docs, no_docs):
    rows = sorted(odd_docs.select("doc_id", "text").collect(), key=lambda r: (r.doc_id is not None, r.doc_id or 0, r.text is not None, r.text or ""))
    got = sorted(tokenfiles.round_trip(odd_docs, BYTES, 0).collect(), key=lambda r: r.start)
    assert [r.doc_id for r in got] == [r.doc_id for r in rows]
    assert [(r.n_tokens, r.ids_crc32) for r in got] == [(len(x), crc(x)) for x in expected([r.text for r in rows], BYTES, 0)]
    assert got[0].start == 0 and all(b.start == a.start + a.n_tokens for a, b in zip(got, got[1:], strict=False))
    assert tokenfiles.round_trip(no_docs, BYTES, 0).collect() == []


@pytest.mark.parametrize("hot", [None, 7, -(1 << 63)])
def test_ids_of_many_rows_fill_several_ranges(spark, hot):
    least = -(1 << 63)
    rows = [(hot, f"copy {k}") for k in range(400)] + [(i, f"text {i}") for i in range(400)] + [(None, None), (None, "x"), (least, "least"), (least, None), (least + 1, "next")]
    path = scratch_path(spark, "ids")
    tokenfiles.write_ids(spark.createDataFrame(rows, "doc_id long, text string").repartition(5), path, BYTES, 0)
    files = spark.read.orc(path)
    held = {r.part: r["count"] for r in files.groupBy("part").count().collect()}
    ranges = int(spark.conf.get("spark.sql.shuffle.partitions"))
    assert len(held) > 1
    if hot != least:
        assert max(held.values()) <= 2 * len(rows) / ranges + 10
    got = sorted(tokenfiles.digests(tokenfiles.read_ids(spark, path)).collect(), key=lambda r: r.start)
    order = lambda i: (i is not None, i or 0)
    assert [r.doc_id for r in got] == sorted((i for i, _ in rows), key=order)
    want = expected([t for _, t in rows], BYTES, 0)
    assert sorted((*order(r.doc_id), r.ids_crc32) for r in got) == sorted((*order(i), crc(x)) for (i, _), x in zip(rows, want, strict=True))
    assert got[0].start == 0 and all(b.start == a.start + a.n_tokens for a, b in zip(got, got[1:], strict=False))
    hashes = {(i, crc(x)): h for (i, _), x, h in zip(rows, want, [r.h for r in spark.createDataFrame(rows, "doc_id long, text string").selectExpr("xxhash64(text) as h").collect()], strict=True)}
    assert [(*order(r.doc_id), hashes[r.doc_id, r.ids_crc32]) for r in got] == sorted((*order(i), h) for (i, _), h in hashes.items())


def test_id_files_are_looked_up_by_id(spark, small):
    path = scratch_path(spark, "ids")
    tokenfiles.write_ids(read(spark, small, "documents"), path, BYTES, 0)
    found = tokenfiles.look_up(spark, path, [3, 77])
    assert sorted(r.doc_id for r in found.collect()) == [3, 77]
    assert "PushedFilters: [In(doc_id, [3,77])]" in found._jdf.queryExecution().explainString(found._sc._jvm.org.apache.spark.sql.execution.ExplainMode.fromString("formatted"))


def packed_ok(rows, docs: list[tuple[int | None, str | None]], seq_len: int):
    whole = {}
    for (i, _), ids in zip(docs, expected([t for _, t in docs], WORDS, 1), strict=True):
        whole.setdefault(i, []).append(ids)
    by_sequence, by_doc = {}, {}
    for r in rows:
        by_sequence.setdefault(r.sequence_id, []).append((r.offset, r.length))
        by_doc.setdefault(r.doc_id, []).append(r)
    for k, pieces in by_sequence.items():
        at = 0
        for offset, length in sorted(pieces):
            assert offset == at and length > 0
            at += length
        assert at == seq_len or k == max(by_sequence)
    assert set(by_doc) == set(whole)
    for i, pieces in by_doc.items():
        if len(whole[i]) == 1:
            ids, at = whole[i][0], 0
            for r in sorted(pieces, key=lambda r: r.start):
                assert r.start == at and r.doc_tokens == len(ids) and r.ids_crc32 == crc(ids[at : at + r.length])
                at += r.length
            assert at == len(ids)
        else:
            assert sum(r.length for r in pieces) == sum(map(len, whole[i]))


def test_packing_fills_sequences(spark, small):
    docs = [(r.doc_id, r.text) for r in read(spark, small, "documents").collect()]
    packed_ok(QUERIES["op9_packing"](spark, small).collect(), docs, 2048)


def test_packing_of_odd_documents(odd_docs, no_docs):
    docs = [(r.doc_id, r.text) for r in odd_docs.collect()]
    packed_ok(packing.pack(odd_docs, WORDS, 1, seq_len=16).collect(), docs, 16)
    with_ids = packing.pack(odd_docs, WORDS, 1, seq_len=64, with_ids=True).collect()
    assert all(len(r.ids) == 4 * r.length and zlib.crc32(r.ids) == r.ids_crc32 for r in with_ids)
    assert packing.pack(no_docs, WORDS, 1).collect() == []
