"""The near-duplicate join on the given documents against all pairs."""

import os
from collections import Counter

from treefold.llm.near_dups import near_duplicates


def links_of_all_pairs(rows, n=5, threshold=0.8):
    """doc_id -> number of other rows whose set of word n-grams has the similarity; similarities of linked classes."""
    sets = {}
    for i, text in rows:
        words = (text or "").encode().split()
        span = min(n, len(words))
        grams = frozenset(tuple(words[k : k + span]) for k in range(len(words) - span + 1)) if span else frozenset()
        if grams:
            sets.setdefault(grams, []).append(i)
    classes = list(sets)
    holders = {}
    for c, grams in enumerate(classes):
        for g in grams:
            holders.setdefault(g, []).append(c)
    # common n-grams counted for every pair of classes that shares one
    shared = Counter()
    for found in holders.values():
        for x in range(len(found)):
            for y in range(x):
                shared[found[y], found[x]] += 1
    links = {i: len(ids) - 1 for ids in sets.values() for i in ids}
    likeness = []
    for (a, b), k in shared.items():
        j = k / (len(classes[a]) + len(classes[b]) - k)
        if j >= threshold - 1e-12:
            likeness.append((j, sets[classes[a]][0], sets[classes[b]][0]))
            for i in sets[classes[a]]:
                links[i] += len(sets[classes[b]])
            for i in sets[classes[b]]:
                links[i] += len(sets[classes[a]])
    return links, likeness


def test_no_link_is_lost(spark, sf):
    docs = spark.read.parquet(os.path.join(sf, "documents.parquet")).select("doc_id", "text")
    rows = [tuple(r) for r in docs.collect()]
    want, _ = links_of_all_pairs(rows)
    got = {r["doc_id"]: r["n_links"] for r in near_duplicates(docs).collect()}
    assert got == {i: want.get(i, 0) for i, _ in rows}
