"""A text that a third of the rows hold."""

import random

import numpy as np

from treefold.llm import fingerprints as fp


def _likeness(one, two, lexicon):
    """Likeness of two texts by comparing sets of words instead of hashes."""
    import xxhash

    code = {w: xxhash.xxh64_intdigest(w.encode(), seed=42) for w in {*one.split(), *two.split()}}
    sets = [{w for w in t.split() if w in lexicon} for t in (one, two)]
    same = seen = 0
    for first, width in fp.DENSITIES:
        for j in range(fp.PARTS):
            a, b = ({w for w in s if code[w] >> first & (1 << width) - 1 == j} for s in sets)
            if a or b:
                seen, same = seen + 1, same + (a == b)
    return (same + (sets[0] == sets[1])) / (seen + 1)


def test_fingerprints_of_a_hot_text(spark):
    rng = random.Random(5)
    words = [f"w{i}" for i in range(900)]
    texts = [" ".join(rng.sample(words, 60)) for _ in range(60)]
    hot = " ".join(words[:60])
    rows = [*enumerate(texts), *[(100 + i, hot) for i in range(30)]]
    rng.shuffle(rows)
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    distinct = [*texts, hot]
    df = {w: sum(w in t.split() for t in distinct) for w in words}
    high = int(fp.MAX_SHARE * len(distinct))
    lexicon = {w for w, n in df.items() if 2 <= n <= high}
    order = sorted(rows, reverse=True)
    got = {r["doc_id"]: r for r in fp.edited_likeness(docs, bucket_rows=20).collect()}
    for i, (doc, text) in enumerate(order):
        after = order[(i + 1) % len(order)][1]
        cut = len(text) // 3
        edited = text[: len(text) - cut] + after[:cut]
        assert np.isclose(got[doc]["near_edited"], _likeness(text, edited, lexicon)), doc
        assert np.isclose(got[doc]["near_next"], _likeness(text, after, lexicon)), doc
    assert min(got[100 + i]["near_edited"] for i in range(30)) > 0
