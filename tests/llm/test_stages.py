"""Every pipeline stage against a plain Python version, on rows that are awkward in every column."""

import random
import zlib

import numpy as np
import pytest
from treefold.llm import mixing, tokens
from treefold.llm.quality import score_quality

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, size long, kept_text string, __ld_lines string, __text_key string, draws array<int>"
WORDS = [f"word{i}" for i in range(400)]
BLANKS = " \t\n\x0b\x0c\r"


def _text(rng, n):
    words = [rng.choice(WORDS) for _ in range(n)]
    return "\n".join(" ".join(words[i : i + 9]) for i in range(0, n, 9))


@pytest.fixture(scope="module")
def rows():
    rng = random.Random(11)
    base = [_text(rng, 70) for _ in range(10)]
    near = [t.rsplit(" ", 1)[0] + " changed" for t in base[:4]]
    texts = [None, "", "\n", " \t ", "one", "A shared line of text\nother", "a SHARED line of text \nthird line is long", _text(rng, 5000), "étude naïve 日本語 \U0001f600 it's <|endoftext|>", *base, *near, base[0], base[0]]
    out = [(i, t) for i, t in enumerate(texts)]
    out += [out[9], (None, "no id at all but words"), (None, "no id at all but words"), (None, None), (9, base[5]), (30, base[9] + "\nan own end")]
    return [(i, t, "en", ["a", "b", None, "é"][k % 4], None, k, "x", "y", "z", [k]) for k, (i, t) in enumerate(out)]


@pytest.fixture(scope="module")
def docs(spark, rows):
    return spark.createDataFrame(rows, SCHEMA).repartition(3).cache()


@pytest.fixture(scope="module")
def folder(spark, rows, tmp_path_factory):
    out = tmp_path_factory.mktemp("tables")
    marks = [(i, i % 2, 0) for i in range(0, 20)]
    spark.createDataFrame(marks, "doc_id long, quality int, toxic int").write.parquet(str(out / "labels.parquet"))
    return str(out)


def _plain(out):
    return sorted(str(tuple(r)) for r in out.collect())


def _stage(name):
    import corpus_pipeline as cp

    return dict(cp.STAGES)[name]


def test_quality_stage(spark, docs, rows, folder):
    marks = spark.read.parquet(f"{folder}/labels.parquet")
    # scores of texts alone, row by row, as they are asked of the operator
    by_text = {}
    texts = sorted({r[1] or "" for r in rows})
    labelled = docs.select("doc_id", "text")
    numbered = spark.createDataFrame(list(enumerate(texts)), "n long, text string")
    for r in score_quality(labelled, marks).join(labelled.select("doc_id", "text"), "doc_id").collect():
        by_text.setdefault(r["text"] or "", set()).add(r["score"])
    kept = _stage("quality_classifier")(spark, docs, folder)
    assert kept.columns == docs.columns and numbered.count() == len(texts)
    alone = {t: s for t, s in by_text.items() if len(s) == 1}
    got = _plain(kept)
    for r in rows:
        if (r[1] or "") in alone:
            assert (str(tuple(r)) in got) == (min(alone[r[1] or ""]) >= 0.5)
    assert len(alone) >= 0.8 * len([t for t in by_text])


def _brute_lines(rows):
    def key(line):
        return "".join(c.lower() if "A" <= c <= "Z" else c for c in line.strip(BLANKS))

    holders = {}
    number = lambda r: r[0] if r[0] is not None else 1 << 62
    for r in rows:
        for line in (r[1] or "").split("\n"):
            if len(key(line)) >= 10:
                holders.setdefault(key(line), set()).add(number(r))
    out = []
    for r in rows:
        lines = [x for x in (r[1] or "").split("\n") if key(x) not in holders or min(holders[key(x)]) == number(r)]
        text = "\n".join(lines)
        out.append((r[0], text, *r[2:4], len(text), *r[5:]))
    return out


def test_line_stage(spark, docs, rows, folder):
    got = _stage("line_dedup")(spark, docs, folder)
    assert got.columns == docs.columns
    assert _plain(got) == sorted(str(r) for r in _brute_lines(rows))


def _grams(text):
    words = (text or "").encode().split()
    n = min(5, len(words))
    return {tuple(words[i : i + n]) for i in range(len(words) - n + 1)} if n else set()


def _brute_near(rows):
    """Rows that stay: of each group linked by a Jaccard similarity of 0.8, those of one id and text, once."""
    kinds = sorted({(r[0], r[1] or "") for r in rows if r[0] is not None and _grams(r[1])})
    sets = [_grams(t) for _, t in kinds]
    root = list(range(len(kinds)))

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for i in range(len(kinds)):
        for j in range(i):
            if len(sets[i] & sets[j]) >= 0.8 * len(sets[i] | sets[j]):
                a, b = find(i), find(j)
                root[max(a, b)] = min(a, b)
    groups = {}
    for i in range(len(kinds)):
        groups.setdefault(find(i), []).append(kinds[i])
    return groups


def test_near_duplicate_stage(spark, docs, rows, folder):
    got = _stage("ngram_jaccard_join")(spark, docs, folder)
    assert got.columns == docs.columns
    left = [tuple(r) for r in got.collect()]
    groups = _brute_near(rows)
    grouped = {k for g in groups.values() for k in g}
    # rows in no group stay as they are, repeats too
    free = lambda r: r[0] is None or (r[0], r[1] or "") not in grouped
    assert sorted(str(r) for r in left if free(r)) == sorted(str(r) for r in rows if free(r))
    # of each group one row of its least id stays
    for g in groups.values():
        stays = [r for r in left if (r[0], r[1] or "") in g]
        assert len(stays) == 1 and stays[0][0] == min(i for i, _ in g) and stays[0] in [tuple(r) for r in rows]


def test_mixing_stage(spark, docs, rows, folder):
    got = _stage("mixing")(spark, docs, folder)
    assert got.columns == docs.columns
    words = lambda t: (t or "").encode().split()
    taken, sources = {}, {}
    for r in got.collect():
        # what is kept of a text is a run of its words; its other columns are a row's own
        mine = [x for x in rows if x[5] == r["size"] and x[0] == r["doc_id"]]
        assert len(mine) == 1 and mine[0][2:4] == (r["lang"], r["source"]) and list(mine[0][9]) == r["draws"] and r["n_chars"] == len(r["text"])
        assert words(r["text"]) and (r["text"] in mine[0][1])
        taken[r["size"]] = taken.get(r["size"], 0) + len(words(r["text"]))
    sizes = {}
    for r in rows:
        sizes[r[3]] = sizes.get(r[3], 0) + len(words(r[1]))
        assert taken.get(r[5], 0) <= 2 * len(words(r[1]))
        sources[r[3]] = sources.get(r[3], 0) + taken.get(r[5], 0)
    order = sorted(sizes, key=lambda s: (s is None, s or ""))
    targets = mixing.share_out([sizes[s] for s in order], [(3, 1, 2)[i % 3] for i in range(len(order))], 1.5 * sum(sizes.values()))
    assert [sources[s] for s in order] == [round(t) for t in targets]
    # and row by row what the operator says
    said = sorted((r["doc_id"] if r["doc_id"] is not None else -1, r["taken"]) for r in mixing.mix(docs).collect())
    assert said == sorted((r[0] if r[0] is not None else -1, taken.get(r[5], 0)) for r in rows)


def test_packing_stage(spark, docs, rows, folder):
    packed = _stage("packing")(spark, docs, folder).collect()
    whole = tokens.tokenizer().whole
    want = []
    for r in rows:
        ids = [*whole.encode(r[1] or "", add_special_tokens=False).ids, 1]
        for at in range(0, len(ids), 2048):
            piece = ids[at : at + 2048]
            want.append((r[0] if r[0] is not None else -1, at, len(piece), zlib.crc32(np.array(piece, "<u4").tobytes()), len(ids)))
    assert sorted((r["doc_id"] if r["doc_id"] is not None else -1, r["start"], r["length"], r["ids_crc32"], r["doc_tokens"]) for r in packed) == sorted(want)
    places = {}
    for r in packed:
        places.setdefault(r["sequence_id"], []).append((r["offset"], r["length"]))
    for p in places.values():
        assert [o for o, _ in sorted(p)] == [sum(n for _, n in sorted(p)[:i]) for i in range(len(p))] and sum(n for _, n in p) <= 2048
    padded = sum(2048 if n & (n - 1) else n for n in (sum(x for _, x in p) for p in places.values()))
    assert padded <= 2048 * (-(-sum(r[2] for r in want) // 2048) + 1)
