"""The pipeline's stages, one after the other."""

from __future__ import annotations

import re
import zlib

import corpus_pipeline
import numpy as np
from tokenizers import Tokenizer

from corpusforge.engine import read
from corpusforge.llm import bytecnn, decontaminate, secrets
from corpusforge.llm.encoding import tokenizer_path


def covered(text: str, spans: str) -> str:
    """The text with a placeholder for each stretch that the listed spans cover."""
    out, at = "", 0
    for a, b in sorted(tuple(map(int, s.split(":")[1:])) for s in spans.split(",") if s):
        if a >= at:
            out += text[at:a] + "[SECRET]"
        at = max(at, b)
    return out + text[at:]


def shingle_sets(docs: dict[int, str]) -> dict[int, set]:
    out = {}
    for i, t in docs.items():
        w = [x for x in re.split("[\x20\x09-\x0d]+", re.sub("[A-Z]", lambda m: m[0].lower(), t or "")) if x]
        out[i] = {tuple(w[k : k + 5]) for k in range(len(w) - 4)} if len(w) > 5 else {tuple(w)} if w else set()
    return out


def brute_survivors(docs: dict[int, str]) -> set[int]:
    """Of each group of texts linked by a Jaccard similarity of 0.8 or more over five words the smallest id."""
    sets, group = shingle_sets(docs), {i: i for i in docs}

    def root(i: int) -> int:
        while group[i] != i:
            i = group[i]
        return i

    ids = sorted(docs)
    for k, i in enumerate(ids):
        for j in ids[:k]:
            both = len(sets[i] & sets[j])
            whole = len(sets[i] | sets[j])
            if (not whole) or both >= 0.8 * whole - 1e-9:
                a, b = sorted((root(i), root(j)))
                group[b] = a
    return {i for i in ids if root(i) == i}


def brute_pieces(docs: dict[int, str]) -> dict[int, list[int]]:
    t = Tokenizer.from_file(tokenizer_path("word_bpe_49k.json"))
    return {i: [*t.encode(x or "", add_special_tokens=False).ids, 1] for i, x in docs.items()}


def test_whole_run_equals_brute_force(spark, small):
    """Each stage against a plain version on what its predecessor kept, and the run's pieces against the last of these."""
    docs = read(spark, small, "documents")
    texts = lambda df: {r.doc_id: r.text for r in df.collect()}
    start = texts(docs)
    stages = dict(corpus_pipeline.STAGES)
    docs = stages["language"](spark, docs, small).cache()
    kept = texts(docs)
    gold = {r.doc_id: r.lang for r in read(spark, small, "documents").collect()}
    said = {r.doc_id: r for r in bytecnn.identify(read(spark, small, "documents")).collect()}
    assert set(kept) == {i for i, r in said.items() if r.lang_pred != "und" and r.score >= corpus_pipeline.LEAST_SCORE} and len(kept) >= 0.97 * len(start)
    assert all(r.lang == (gold[r.doc_id] or said[r.doc_id].lang_pred) for r in docs.collect())
    docs = stages["near_duplicates"](spark, docs, small).cache()
    assert set(texts(docs)) == brute_survivors(kept) and len(brute_survivors(kept)) < len(kept)
    before = texts(docs)
    dirty = {r.doc_id for r in decontaminate.contaminated(docs, read(spark, small, "benchmark"), least=decontaminate.LEAST).collect()}
    words = lambda t: " " + " ".join(decontaminate.WORD.findall((t or "").lower())) + " "
    items = [words(r.text) for r in read(spark, small, "benchmark").collect()]
    assert {i for i, t in before.items() if any(x in words(t) for x in items)} <= dirty
    docs = stages["decontamination"](spark, docs, small).cache()
    assert dirty and texts(docs) == {i: t for i, t in before.items() if i not in dirty}
    spans = {r.doc_id: r.spans for r in secrets.report(secrets.scan(docs)).collect()}
    want = {i: covered(t, spans[i]) for i, t in texts(docs).items()}
    docs = stages["secrets"](spark, docs, small).cache()
    assert texts(docs) == want
    assert all(r.n_chars == len(r.text) for r in docs.collect())
    ids = brute_pieces(want)
    rows = corpus_pipeline.run(spark, small).collect()
    by_doc, by_sequence = {}, {}
    for r in sorted(rows, key=lambda r: (r.doc_id, r.start)):
        assert r.start == by_doc.get(r.doc_id, 0) and r.doc_tokens == len(ids[r.doc_id])
        assert r.ids_crc32 == zlib.crc32(np.array(ids[r.doc_id][r.start : r.start + r.length], dtype="<u4").tobytes())
        by_doc[r.doc_id] = r.start + r.length
        by_sequence.setdefault(r.sequence_id, []).append((r.offset, r.length))
    assert by_doc == {i: len(x) for i, x in ids.items()}
    for k, pieces in by_sequence.items():
        assert [o for o, _ in sorted(pieces)] == [sum(n for o2, n in pieces if o2 < o) for o, _ in sorted(pieces)]
        assert sum(n for _, n in pieces) == 2048 or k == max(by_sequence)


def test_stages_keep_the_columns(spark, small):
    docs = read(spark, small, "documents")
    for _, stage in corpus_pipeline.STAGES[:-1]:
        docs = stage(spark, docs, small)
        assert docs.columns == ["doc_id", "text", "lang", "source", "n_chars"]


def test_odd_documents_go_through(spark, odd_docs, no_docs, small):
    for start in (odd_docs, no_docs):
        docs = start
        for _, stage in corpus_pipeline.STAGES[:-1]:
            docs = stage(spark, docs, small)
            assert docs.columns == start.columns
        corpus_pipeline.STAGES[-1][1](spark, docs, small).collect()
