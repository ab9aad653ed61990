"""Short benchmark items whose words were substituted, against brute force."""

from __future__ import annotations

from itertools import combinations

from corpusforge.llm import decontaminate


def test_short_items_with_substituted_ends(spark):
    rows, items = [], []
    for n in range(decontaminate.LEAST, decontaminate.OVERLAP + 1):
        own = [f"i{n}w{k}" for k in range(n)]
        items.append((n, " ".join(own)))
        for changed in (c for size in range(3) for c in combinations(range(n), size)):
            text = ["before", "this", *[f"x{k}" if k in changed else w for k, w in enumerate(own)], "after", "that"]
            rows.append((len(rows), " ".join(text), n, 5 * (n - len(changed)) >= 4 * n))
        rows.append((len(rows), " ".join(own[1:]), n, False))  # a part of the item is not the whole
    docs = spark.createDataFrame([r[:2] for r in rows], "doc_id long, text string").repartition(3)
    bench = spark.createDataFrame(items, "item_id long, text string")
    got = {(r.doc_id, r.item_id): (r.n_words, r.doc_start, r.item_start) for r in decontaminate.contaminated(docs, bench).collect()}
    assert got == {(i, n): (n, 2, 0) for i, _, n, over in rows if over}
    assert {r.doc_id for r in decontaminate.without_contaminated(docs, bench).collect()} == {i for i, _, _, over in rows if not over}
