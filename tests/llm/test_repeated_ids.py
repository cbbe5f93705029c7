"""The near-duplicate stage on rows that repeat an id, with the same or other texts."""

import random

from treefold.llm.near_dups import near_duplicates


def test_near_duplicates_of_repeated_ids(spark):
    import corpus_pipeline as cp

    rng = random.Random(9)
    a, b, c, d = (" ".join(f"{x}{rng.randrange(10**6)}" for _ in range(80)) for x in "abcd")
    near_c = c.rsplit(" ", 1)[0] + " changed"
    rows = [
        (3, a, "en"), (5, a, "en"), (5, b, "en"),  # 5 goes with a's text, not with b's
        (7, c, "en"), (7, near_c, "en"), (8, c, "en"),  # one of the group of the least id
        (9, d, "en"), (9, d, "de"), (9, d, "en"),  # fully repeated rows
        (None, a, "en"), (None, a, "en"), (11, None, "en"), (11, "", "en"), (12, " ", "en"), (12, " ", "en"),
    ]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string").repartition(3)
    got = sorted(map(str, (tuple(r) for r in cp.ngram_jaccard_join(spark, docs, "").collect())))
    left = [r for r in map(tuple, rows) if r[0] not in (7, 8, 9) and r[:2] != (5, a)]
    sevens = [x for x in got if x.startswith("(7,")]
    assert len(sevens) == 1 and sevens[0] in {str((7, c, "en")), str((7, near_c, "en"))}
    assert [x for x in got if not x.startswith("(7,")] == sorted(map(str, [*left, (9, d, "de")]))
    assert near_duplicates(docs).columns == ["doc_id", "class_id", "n_links", "kept"]
