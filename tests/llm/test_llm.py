"""The ten operators on a small awkward table, against brute force and their own bounds."""

import hashlib
import random
import zlib
from pathlib import Path

import numpy as np
import pytest

from treefold.llm import exact_dedup as ed
from treefold.llm import licenses, line_dedup, mixing, near_dups, packing, quality, token_files, tokens, toxicity
from treefold.llm.fingerprints import edited_likeness, fingerprints, lexicon_bitmap

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, size long, n_lines long, score double, kept boolean, group_size long"
WORDS = [f"word{i}" for i in range(300)]


def _text(rng, n):
    return " ".join(rng.choice(WORDS) for _ in range(n))


@pytest.fixture(scope="module")
def rows():
    rng = random.Random(7)
    long_text = _text(rng, 6000)
    base = [_text(rng, 80) for _ in range(8)]
    texts = [None, "", "\n", " \t ", "one", "Same line here\nother", "  SAME LINE HERE \nthird line is long", "same line here\nsame line here\nx", long_text, long_text]
    texts += base
    # near copies: one word of eighty changed keeps the similarity above the threshold
    for b in base[:3]:
        w = b.split()
        for at in (3, 40, 77):
            texts.append(" ".join([*w[:at], "changed", *w[at + 1 :]]))
    texts += [base[0], base[0], "étude naïve 日本語 \U0001f600", "MIT License\n" + "x"]
    out = [(i, t, "en", ["a", "b", None, "é"][i % 4], None, 5, 6, 0.5, True, 9) for i, t in enumerate(texts)]
    return [*out, out[10], (None, "no id at all, but a line", "en", "a", None, 1, 1, 0.1, False, 1)]


@pytest.fixture(scope="module")
def docs(spark, rows):
    return spark.createDataFrame(rows, SCHEMA).repartition(3).cache()


@pytest.fixture(scope="module")
def none(spark):
    return spark.createDataFrame([], SCHEMA)


# ---- exact dedup ----


def test_exact_dedup(docs, rows, none):
    groups = {}
    for r in rows:
        groups.setdefault(r[1] or "", []).append(r[0])
    want = []
    for r in rows:
        ids = groups[r[1] or ""]
        known = [i for i in ids if i is not None]
        keep = max(known) if known else None
        want.append((r[0], keep, len(ids), r[0] == keep, hashlib.sha256((r[1] or "").encode()).hexdigest()))
    assert sorted(map(str, map(tuple, ed.exact_dedup(docs).collect()))) == sorted(map(str, want))
    assert ed.exact_dedup(none).count() == 0


def test_deletion_on_tables(spark, docs, rows):
    from pyspark.sql import functions as F

    digested = docs.select("doc_id", F.unhex(F.sha2(F.coalesce("text", F.lit("")), 256)).alias("digest"))
    entries = ed.index_digests(digested, partitions=3).cache()
    texts = sorted({r[1] or "" for r in rows})
    gone = [hashlib.sha256(t.encode()).digest() for t in texts[::3]]
    some = spark.createDataFrame([(g,) for g in [*gone, gone[0], b"unknown"]], "digest binary")
    left = {bytes(r["digest"]): (r["keep_id"], r["group_size"]) for r in ed.delete_digests(entries, some).collect()}
    whole = {bytes(r["digest"]): (r["keep_id"], r["group_size"]) for r in entries.collect()}
    assert left == {k: v for k, v in whole.items() if k not in gone} and len(whole) == len(texts)
    # what was deleted may come again, later rows counting from one
    again = ed.index_digests(digested.where(F.col("digest").isin([bytearray(g) for g in gone])), partitions=2)
    assert {bytes(r["digest"]) for r in again.collect()} == set(gone)


def test_contents_are_checked(spark):
    from pyspark.sql import functions as F

    df = spark.createDataFrame([(1, "a"), (2, "b"), (3, "a"), (4, None), (5, ""), (6, "c")], "doc_id long, text string")
    wrong = F.when(F.col("text").isin("a", "b"), F.lit("x")).otherwise(F.coalesce("text", F.lit(""))).cast("binary")
    entries = ed.index_digests(df.select("doc_id", wrong.alias("digest")), partitions=2)
    assert [bytes(r[0]) for r in ed.unlike_contents(df, wrong, entries).collect()] == [b"x"]


def test_line_runs_can_be_opened_again(spark, tmp_path):
    first = [(i, f"a line that number {i % 3} shares\nan own line of {i}") for i in range(6)]
    second = [(10 + i, f"a line that number {i % 4} shares\nan own line of {i}") for i in range(6)]
    lines = lambda rows: line_dedup.hashed_lines(spark.createDataFrame(rows, "doc_id long, text string"))
    folder = str(tmp_path / "runs")
    runs = line_dedup.LineRuns(spark, folder=folder, buckets=2)
    assert runs.ingest(lines(first)).count() == 3
    runs.save()
    runs.close()
    opened = line_dedup.LineRuns.open(spark, folder)
    with line_dedup._bucket_order(spark):
        text = opened.runs()[0].hint("merge").join(opened.runs()[0], ["h1", "h2"])._jdf.queryExecution().executedPlan().toString()
    assert "SortMergeJoin" in text and "Sort [" not in text and "Exchange" not in text
    lost = {(r["__ld_doc"], r["__ld_pos"]) for r in opened.ingest(lines(second)).collect()}
    assert lost == {*((10 + i, 0) for i in (0, 1, 2, 4, 5)), *((10 + i, 1) for i in range(6))}
    opened.close()
    assert not [t for t in spark.catalog.listTables() if t.name.startswith("line_run_")]


def test_cuckoo_index():
    index = ed.CuckooIndex(8)
    keys = [hashlib.sha256(str(i).encode()).digest() for i in range(5000)]
    assert all(index.add(k, i) for i, k in enumerate(keys))
    assert index.resizes > 0
    assert not any(index.add(k, i + 1) for i, k in enumerate(keys))
    assert index.live[keys[3]] == [4, 2]
    assert all(index.remove(k) for k in keys[::2]) and not index.remove(keys[0])
    assert all(index.filter.contains(index.short(k)) for k in keys[1::2])
    assert sum(index.filter.contains(index.short(k)) for k in keys[::2]) < 50
    assert index.add(keys[0], 9) and index.filter.size == len(index.live)


# ---- line dedup ----


def _brute_lines(rows):
    strip = " \t\n\x0b\x0c\r"
    key = lambda s: "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in s.strip(strip))
    top = 2**63 - 1
    owner = {}
    for r in rows:
        for line in (r[1] or "").split("\n"):
            k = key(line)
            if len(k) >= 10:
                owner[k] = min(owner.get(k, top), r[0] if r[0] is not None else top)
    out = []
    for r in rows:
        lines = (r[1] or "").split("\n")
        kept = [x for x in lines if len(key(x)) < 10 or owner[key(x)] == (r[0] if r[0] is not None else top)]
        out.append((r[0], "\n".join(kept), len(lines), len(lines) - len(kept)))
    return out


@pytest.mark.parametrize("batches,fanout", [(1, 2), (4, 2), (5, 3)])
def test_line_dedup(docs, rows, batches, fanout):
    got = line_dedup.dedup_lines(docs, batches=batches, fanout=fanout).select("doc_id", "kept_text", "n_lines", "n_dropped").collect()
    assert sorted(map(str, map(tuple, got))) == sorted(map(str, _brute_lines(rows)))


def test_line_dedup_empty(none):
    assert line_dedup.dedup_lines(none).count() == 0


def test_line_runs_are_compacted(spark, docs):
    lines = line_dedup.hashed_lines(docs).cache()
    runs = line_dedup.LineRuns(spark, fanout=2, buckets=2)
    for i in range(4):
        runs.ingest(lines.where(f"__ld_doc % 4 = {i}")).count()
    assert runs.compactions == 3 and [len(x) for x in runs.levels] == [0, 0, 1]
    assert spark.table(runs.levels[2][0]).select("h1", "h2").distinct().count() == lines.select("h1", "h2").distinct().count()
    runs.close()


# ---- near duplicates ----


def _shingles(text):
    w = (text or "").encode().split()
    return frozenset(tuple(w[i : i + 5]) for i in range(len(w) - 4)) if len(w) >= 5 else (frozenset([tuple(w)]) if w else frozenset())


def _brute_near(rows):
    real = [(i, r[0], _shingles(r[1])) for i, r in enumerate(rows) if r[0] is not None]
    links, root = {}, {i: i for i in range(len(rows))}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for a in range(len(real)):
        for b in range(a):
            (i, _, s), (j, _, t) = real[a], real[b]
            if s and t and len(s & t) >= 0.8 * len(s | t) - 1e-9:
                links[i] = links.get(i, 0) + 1
                links[j] = links.get(j, 0) + 1
                x, y = find(i), find(j)
                root[max(x, y)] = min(x, y)
    label = {}
    for i, d, _ in real:
        label[find(i)] = min(label.get(find(i), d), d)
    return [(r[0], label[find(i)] if r[0] is not None else None, links.get(i, 0), r[0] is None or r[0] == label[find(i)]) for i, r in enumerate(rows)]


@pytest.mark.parametrize("options", [{}, {"bucket_block": 2, "block_classes": 2}])
def test_near_duplicates(docs, rows, options):
    got = near_dups.near_duplicates(docs, **options).collect()
    assert sorted(map(str, map(tuple, got))) == sorted(map(str, _brute_near(rows)))


def test_near_duplicates_of_an_id_with_two_texts(spark, none):
    rng = random.Random(1)
    a, b = _text(rng, 50), _text(rng, 50)
    df = spark.createDataFrame([(1, a), (1, b), (2, a), (3, b)], "doc_id long, text string")
    got = sorted(map(tuple, near_dups.near_duplicates(df).collect()))
    assert got == [(1, 1, 1, True), (1, 1, 1, True), (2, 1, 1, False), (3, 1, 1, False)]
    assert near_dups.near_duplicates(none).count() == 0


def test_bayesian_rules():
    rules = dict(near_dups.least_matches())
    # a pair at the threshold survives almost surely; one far below is dropped at the first look
    assert rules[20] <= 11 and rules[120] >= 75
    rng = np.random.default_rng(0)
    one = rng.integers(0, 65536, 120).astype(np.uint16)
    same = np.where(rng.random((500, 120)) < 0.8, one, rng.integers(0, 65536, (500, 120))).astype(np.uint16)
    far = np.where(rng.random((500, 120)) < 0.3, one, rng.integers(0, 65536, (500, 120))).astype(np.uint16)
    assert len(near_dups.survivors(one, same)) >= 498 and len(near_dups.survivors(one, far)) == 0


def test_components(spark):
    edges = [(1, 2), (2, 3), (10, 11), (11, 12), (12, 10), (50, 40), (40, 30), (30, 20), (20, 60), (7, 7)]
    got = {r["id"]: r["root"] for r in near_dups.components(spark.createDataFrame(edges, "a long, b long")).collect()}
    assert got == {1: 1, 2: 1, 3: 1, 10: 10, 11: 10, 12: 10, **dict.fromkeys((20, 30, 40, 50, 60), 20)}
    assert near_dups.components(spark.createDataFrame([], "a long, b long")).count() == 0


# ---- mixing ----


def test_targets():
    got = mixing.share_out([10, 100, 100], [3, 1, 2], 315)
    assert [float(x) for x in got] == [20, pytest.approx(295 / 3), pytest.approx(590 / 3)]
    assert sum(mixing.share_out([10, 0, 5], [1, 1, 1], 22)) == 22


def test_splitting_tree():
    quotas = [1000, 17, 0, 400]
    dealt = mixing.splitting_tree(quotas, 7, seed=3)
    assert dealt.sum(axis=1).tolist() == quotas
    assert dealt.sum(axis=0).max() - dealt.sum(axis=0).min() <= 3
    assert (dealt >= 0).all() and (dealt == mixing.splitting_tree(quotas, 7, seed=3)).all()


def test_mix(docs, rows, none):
    got = mixing.mix(docs, block_words=50, shards=3).collect()
    assert len(got) == len(rows)
    sizes = {}
    for r in rows:
        sizes[r[3]] = sizes.get(r[3], 0) + len((r[1] or "").encode().split())
    order = sorted(sizes, key=lambda s: (s is None, s or ""))
    targets = dict(zip(order, mixing.share_out([sizes[s] for s in order], [(3, 1, 2)[i % 3] for i in range(len(order))], 1.5 * sum(sizes.values()))))
    by_target = {}
    for r in got:
        assert 0 <= r["taken"] <= 2 * r["size"] and r["taken"] == sum(d["n_words"] for d in r["draws"])
        by_target.setdefault((r["source_size"], round(r["target"], 6)), [0])[0] += r["taken"]
    want = {(sizes[s], round(float(t), 6)): round(t) for s, t in targets.items()}
    assert {k: v[0] for k, v in by_target.items()} == want
    assert sorted(map(str, got)) == sorted(map(str, mixing.mix(docs.repartition(2), block_words=50, shards=3).collect()))
    # every reading of a block lies in one shard, and shards hold as many of each source as the tree says
    place = {}
    for r in got:
        for d in r["draws"]:
            place.setdefault((r["source_size"], round(r["target"], 6), d["epoch"], d["block"]), set()).add(d["shard"])
    assert all(len(v) == 1 for v in place.values())
    plan, _, shards = mixing._plan([(s, sizes[s]) for s in order], (3, 1, 2), 1.5, 2, 50, 3, 29)
    dealt = [[0, *line[-1]] for line in plan]
    for line, ends in zip(plan, dealt):
        for k in range(shards):
            held = sum(v == {k} for key, v in place.items() if key[:2] == (line[2], round(line[3], 6)))
            assert held == ends[k + 1] - ends[k]
    assert mixing.mix(none).count() == 0 and mixing.mixed_documents(none).count() == 0


def _brute_mix(spark, docs, block, shards, seed=29):
    """Words taken of each row, from the line of each source laid out in plain Python."""
    rows = docs.selectExpr("doc_id", "source", "coalesce(regexp_count(text, '[^\\\\x20\\\\x09-\\\\x0D]+'), 0) AS size", f"xxhash64({seed}, doc_id, coalesce(text, '')) AS h").collect()
    buckets = -(-len(rows) // mixing.BUCKET_ROWS)
    sizes = {}
    for r in rows:
        sizes[r["source"]] = sizes.get(r["source"], 0) + r["size"]
    plan, _, _ = mixing._plan(list(sizes.items()), (3, 1, 2), 1.5, 2, block, shards, seed)
    out = []
    for _, source, size, _, blocks, quota, last, step, turn, ends in plan:
        line = sorted((r for r in rows if r["source"] == source), key=lambda r: (r["h"] % buckets, r["h"], r["doc_id"] or 0, r["size"]))
        taken = [0] * size
        for e in range(2):
            for b in range(blocks):
                place = e * blocks + (b * step + turn) % blocks
                if place < ends[-1]:
                    stop = b * block + (last if place == quota - 1 else block)
                    for i in range(b * block, min(stop, size)):
                        taken[i] += 1
        at = 0
        for r in line:
            out.append((r["doc_id"], r["size"], sum(taken[at : at + r["size"]])))
            at += r["size"]
    return out


@pytest.mark.parametrize("block,shards", [(50, 3), (7, 5), (4096, None)])
def test_mix_against_brute_force(spark, docs, block, shards):
    got = [(r["doc_id"], r["size"], r["taken"]) for r in mixing.mix(docs, block_words=block, shards=shards).collect()]
    assert sorted(map(str, got)) == sorted(map(str, _brute_mix(spark, docs, block, shards)))


def test_the_tree_decides_what_is_drawn(docs, monkeypatch):
    def shard_words():
        out = {}
        for r in mixing.mix(docs, block_words=20, shards=4).collect():
            for d in r["draws"]:
                out[r["source_size"], d["shard"]] = out.get((r["source_size"], d["shard"]), 0) + d["n_words"]
        return out

    own = shard_words()
    whole = mixing.splitting_tree
    monkeypatch.setattr(mixing, "splitting_tree", lambda quotas, shards, seed: whole(quotas, shards, seed + 1))
    assert shard_words() != own
    monkeypatch.setattr(mixing, "splitting_tree", lambda quotas, shards, seed: np.zeros((len(quotas), shards), np.int64))
    assert shard_words() == {}


def test_line_positions_in_groups_of_buckets(spark, monkeypatch):
    monkeypatch.setattr(mixing, "GROUP_BUCKETS", 3)
    rows = [(s, b, i, (i * 7 + b) % 5) for s in (0, 1) for b in range(10) for i in range(4)]
    df = spark.createDataFrame(rows, "line int, __mix_bucket long, i int, size long")
    at, want = {}, set()
    for s, b, i, size in rows:
        want.add((s, b, i, at.get(s, 0)))
        at[s] = at.get(s, 0) + size
    got = mixing._running_totals(df, "line", "size", ["i"], 10)
    assert {tuple(r) for r in got.select("line", "__mix_bucket", "i", "__mix_at").collect()} == want


def test_mixed_documents(docs):
    mixed = mixing.mixed_documents(docs, block_words=50, shards=3)
    assert mixed.columns == docs.columns
    words = sum(len((r["text"] or "").encode().split()) for r in mixed.collect())
    assert words == sum(r["taken"] for r in mixing.mix(docs, block_words=50, shards=3).collect())


# ---- tokens, packing, token files ----

ODD = ["ΑΣ σας İstanbul", "a\xa0b c", "<|endoftext|> x <|startoftext|>", "don't I'LL we've", "é ẛ̣", "日本語 123 4½", "\x1c a\x1fb \x85 q", "", "x" * 500, "!!!... ,,, a.b,c ». ×,", "naïve, ÉCOLE. ﬁ ß ŉ ǆ", "word. word, Word. WORD"]


def test_word_tokenizer_is_exact(rows):
    t = tokens.WordTokenizer(cache_pieces=50, slice_chars=400)
    texts = [r[1] or "" for r in rows] + ODD
    for _ in range(2):  # the second time from the cache, after it was turned over
        want = t.whole.encode_batch(texts, add_special_tokens=False)
        assert [x.tolist() for x in t.encode(texts)] == [w.ids for w in want]


def test_word_tokenizer_on_random_strings():
    rng = random.Random(1)
    alphabet = "abzAZ09'.,!-|<>§éÉßİΣ½²\u0301\xa0\x1c\x7f\u2028  \n\t"
    t = tokens.WordTokenizer()
    texts = ["".join(rng.choice(alphabet) for _ in range(40)) for _ in range(5000)]
    want = t.whole.encode_batch(texts, add_special_tokens=False)
    assert [x.tolist() for x in t.encode(texts)] == [w.ids for w in want]


def _ids(text):
    return [*tokens.tokenizer().whole.encode(text or "", add_special_tokens=False).ids, 1]


def test_first_fit():
    rng = np.random.default_rng(1)
    for n in (0, 1, 7, 300):
        lengths = rng.integers(1, 2049, n)
        bins, offsets = packing.first_fit_decreasing(lengths)
        room = {}
        want = {}
        for i in np.argsort(-lengths, kind="stable"):
            b = next((b for b in sorted(room) if room[b] >= lengths[i]), len(room))
            room.setdefault(b, 2048)
            want[i] = (b, 2048 - room[b])
            room[b] -= lengths[i]
        assert {i: (bins[i], offsets[i]) for i in range(n)} == want


def test_pack(docs, rows, none):
    packed = packing.pack(docs, with_ids=True, group_pieces=16)
    got = packed.collect()
    by_doc, by_seq = {}, {}
    for r in got:
        assert r["length"] <= 2048 and r["ids_crc32"] == zlib.crc32(r["ids"]) and len(r["ids"]) == 4 * r["length"]
        by_doc.setdefault(r["doc_id"], []).append(r)
        by_seq.setdefault(r["sequence_id"], []).append((r["offset"], r["length"]))
    for places in by_seq.values():
        at = 0
        for offset, length in sorted(places):
            assert offset == at
            at += length
        assert at <= 2048
    copies = {}
    for r in rows:
        copies.setdefault(r[0], []).append(r[1])
    for doc_id, texts in copies.items():
        want = sorted(x for t in texts for i in range(0, len(_ids(t)), 2048) for x in [(i, np.array(_ids(t)[i : i + 2048], "<u4").tobytes(), len(_ids(t)))])
        assert sorted((r["start"], bytes(r["ids"]), r["doc_tokens"]) for r in by_doc[doc_id]) == want
    out = packing.sequences(packed).collect()
    assert len(out) == len(by_seq) and all(len(r["ids"]) // 4 in (2048, r["n_tokens"]) for r in out)
    assert packing.pack(none).count() == 0


def test_token_files(spark, docs, rows, none, tmp_path):
    path = str(tmp_path / "ids")
    got = sorted(map(tuple, token_files.round_trip(docs, path).collect()), key=lambda r: r[1])
    order = sorted(rows, key=lambda r: (r[0] is not None, r[0] or 0, r[1] or ""))
    at, want = 0, []
    for r in order:
        ids = _ids(r[1])
        want.append((r[0], at, len(ids), zlib.crc32(np.array(ids, "<u4").tobytes())))
        at += len(ids)
    assert got == want
    found = token_files.lookup(spark, path, [8]).collect()
    assert found[0]["ids"] == _ids(rows[8][1])
    assert "PushedFilters: [In(doc_id" in token_files.lookup(spark, path, [8, 9])._jdf.queryExecution().executedPlan().toString()
    assert token_files.read_token_files(spark, path).count() == len(rows)
    assert token_files.round_trip(none, str(tmp_path / "none")).count() == 0


# ---- licences ----


def test_licenses(spark, docs, rows, none):
    mit = dict(licenses.LICENSE_TEXTS)["MIT"]
    wrapped = "The MIT License\n" + mit.replace(" is hereby granted", "\nis hereby granted").upper() + "\nCopyright (c) 2021 Someone"
    british = dict(licenses.LICENSE_TEXTS)["Zlib"].replace("acknowledgment", "acknowledgement")
    parted = mit.replace("NONINFRINGEMENT", "NON-\nINFRINGEMENT")
    df = spark.createDataFrame(
        [(1, wrapped, 7), (2, british, 7), (3, mit + " and more", 7), (4, "text\n  licenced under the apache LICENSE version 2.0 \nCopyright 2020 X", 7), (5, None, 7), (6, parted, 7), (6, mit, 7), (None, mit, 7)],
        "doc_id long, text string, license int",
    )
    got = sorted((r["doc_id"] or 0, r["license"], tuple(r["notices"])) for r in licenses.scan_licenses(df).collect())
    assert got == [(0, "MIT", ()), (1, "MIT", ()), (2, "Zlib", ()), (3, None, ()), (4, None, ("Apache-2.0",)), (5, None, ()), (6, "MIT", ()), (6, "MIT", ())]
    assert licenses.scan_licenses(docs).count() == len(rows)
    assert licenses.scan_licenses(none).count() == 0


def test_copyright_lines_and_spellings(spark):
    mit = dict(licenses.LICENSE_TEXTS)["MIT"]
    gone = ["Copyright (c) 2020 X", "(c) Copyright 2020 X", "Copyright Jane Doe 2021", "Copyright © 2020 X", " * Copyright 1999, 2004-2010 The Foo Authors.", "© 2019 Foo", "Copyright [yyyy] [name]", "copyright by Jane Doe", "# All rights reserved.", "Copyright: Jane"]
    stay = ["C 1999 was a good year", "Copyright notice and this permission notice", "the copyright 2020 edition", "copyright law applies", "No rights are reserved"]
    df = spark.createDataFrame([(i, f"{line}\n{mit}") for i, line in enumerate(gone + stay)], "doc_id long, text string")
    got = {r["doc_id"]: r["license"] for r in licenses.scan_licenses(df).collect()}
    assert [line for i, line in enumerate(gone) if got[i] != "MIT"] == []
    assert [line for i, line in enumerate(stay, len(gone)) if got[i] is not None] == []
    pairs = [("programmers programme programmes", "programmers program programs"), ("to fulfil", "to fulfill"), ("Licence, LICENCES", "license licenses"), ("organised Reorganised", "organized reorganised"), ("copyright\nowner", "copyright holder"), ("non-commercial non commercial", "noncommercial noncommercial")]
    text = spark.createDataFrame(pairs, "text string, want string")
    assert [r[0] for r in text.select(licenses.canonical_text(text["text"])).collect()] == [want for _, want in pairs]


def test_digests_of_the_public_texts(spark):
    folder = Path("/usr/share/common-licenses")
    if not folder.is_dir():
        pytest.skip("no public licence texts on this machine")
    found = {}
    for file in folder.iterdir():
        if file.name not in ("README.txt",) and not file.is_symlink():
            text = file.read_text(encoding="utf-8")
            for part in {text, text.replace("Copyright (C)", "Copyright (c)"), " ".join(text.split(" "))}:
                found[len(found)] = (file.name, part)
    df = spark.createDataFrame([(i, text) for i, (_, text) in found.items()], "doc_id long, text string")
    got = {r["doc_id"]: r["license"] for r in licenses.scan_licenses(df).collect()}
    assert all(got.values()) and {got[i] for i in got} == {name for name, part, _ in licenses.LICENSE_DIGESTS if part == "whole"}


def test_licenses_against_sql(spark, tmp_path):
    import duckdb

    mit = dict(licenses.LICENSE_TEXTS)["MIT"]
    texts = [*[t for _, t in licenses.LICENSE_TEXTS], "MIT License\n\nCopyright (c) 2020 X\n\n" + mit, None, "", "Released under the MIT Licence.\nLicensed under CC BY 4.0.", "© programme\nnon\ncommercial fulfil", mit + " x"]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    df.write.parquet(str(tmp_path / "d"))
    con = duckdb.connect()
    con.sql(f"CREATE VIEW documents AS SELECT * FROM '{tmp_path}/d/*.parquet'")
    want = sorted(con.sql("SELECT doc_id, canonical_sha256, license, notices FROM (" + licenses.oracle() + ")").fetchall())
    got = sorted((r["doc_id"], r["canonical_sha256"], r["license"], ",".join(r["notices"])) for r in licenses.scan_licenses(df).collect())
    assert got == want and sum(r[2] is not None for r in got) == len(licenses.LICENSE_TEXTS) + 1


# ---- fingerprints ----


def test_fingerprints(spark, docs, rows, none):
    got = edited_likeness(docs, bucket_rows=5).collect()
    assert len(got) == len(rows)
    order = sorted(rows, key=lambda r: (r[0] is None, -(r[0] or 0)))
    by_id = {}
    for r in got:
        by_id.setdefault(r["doc_id"], []).append(r)
    prints = {}
    for i, r in enumerate(order):
        text, after = r[1] or "", order[(i + 1) % len(order)][1] or ""
        cut = len(text) // 3
        edited = text[: len(text) - cut] + after[:cut]
        mine = [x for x in by_id[r[0]] if x["edited_sha256"] == hashlib.sha256(edited.encode()).hexdigest()]
        assert mine and mine[0]["n_chars"] == len(text)
        assert 0 <= mine[0]["near_edited"] <= 1 and 0 <= mine[0]["near_next"] <= 1
        assert prints.setdefault(text, mine[0]["fingerprint"]) == mine[0]["fingerprint"]
    assert len(set(prints.values())) >= 0.7 * len(prints)  # texts with the same lexicon terms share theirs
    one = spark.createDataFrame([(5, "only one document")], "doc_id long, text string")
    assert edited_likeness(one).first()["near_next"] == 1.0
    assert edited_likeness(none).count() == 0


def test_lexicon_band(spark):
    df = spark.createDataFrame([(i, f"all half{i % 2} rare{i} pair{i // 2}") for i in range(40)], "doc_id long, text string")
    bits = lexicon_bitmap(df, min_share=0.0, max_share=0.5).first()["bits"]
    assert len(bits) == 1 << 16
    # half0, half1 and the twenty pairs are inside the band
    assert sum(bin(b & (2**64 - 1)).count("1") for b in bits) == 22
    assert fingerprints(df).select("subset_hashes").first()[0].__len__() == 65


# ---- classifiers ----


def _labelled(spark, bad, n=240):
    rng = random.Random(3)
    rows, marks = [], []
    for i in range(n):
        y = i % 3 == 0
        words = [rng.choice(WORDS) for _ in range(120)]
        rows.append((i, bad(rng, words) if y else " ".join(words)))
        marks.append((i, 0 if y else 1, 1 if y else 0))
    return spark.createDataFrame([*rows, (n, None), (n + 1, "")], "doc_id long, text string"), spark.createDataFrame([*marks, (None, 1, 1), (n, None, None)], "doc_id long, quality int, toxic int")


def _fold(i, modulus):
    return zlib.crc32(str(i).encode()) % modulus


def test_toxicity(spark):
    def insult(rng, words):
        for _ in range(8):
            words.insert(rng.randrange(len(words)), rng.choice(["vilegrubber", "scumnugget", "dirtwhistle"]))
        return " ".join(words)

    df, marks = _labelled(spark, insult)
    got = {r["doc_id"]: r for r in toxicity.score_toxicity(df, marks).collect()}
    held = [i for i in range(240) if _fold(i, 5) == 0]
    assert all(got[i]["held_out"] == (_fold(i, 5) == 0) for i in range(240))
    assert np.mean([got[i]["predicted"] == (i % 3 == 0) for i in held]) >= 0.95
    assert all(0 <= r["score"] <= 1 and r["predicted"] == int(r["score"] >= 0.5) for r in got.values())
    assert got[240]["score"] == got[241]["score"]
    empty = toxicity.score_toxicity(df, marks.limit(0)).collect()
    assert {r["score"] for r in empty} == {0.5}
    assert toxicity.score_toxicity(df.limit(0), marks).count() == 0


def test_telling_words_by_rate():
    rng = random.Random(4)
    plain = [_text(rng, 60).encode() for _ in range(400)]
    rude = []
    for d in plain[:200]:
        w = d.split()
        w.insert(rng.randrange(60), b"scumnugget,")
        rude.append(b" ".join(w))
    # a quotation in an ordinary document does not free the word, and copies of one text tell nothing
    quoted = [*plain[200:], b"he said scumnugget to me"]
    copies = [b"one rare copy of a text"] * 50
    assert toxicity.telling_words(rude + copies, quoted) == {b"scumnugget"}
    assert all(b"scumnugget" in w and len(w.split()) <= 3 for w in toxicity.telling_windows(rude + copies, quoted))


def test_quality(spark):
    def junk(rng, words):
        return " ".join(w.upper() + "!!" for w in words[:60]) if rng.random() < 0.5 else " ".join(w for w in words[:10] for _ in range(12))

    df, marks = _labelled(spark, junk, 600)
    got = {r["doc_id"]: r for r in quality.score_quality(df, marks).collect()}
    held = [i for i in range(600) if _fold(i, 3) == 1]
    assert all(got[i]["held_out"] == (_fold(i, 3) == 1) for i in range(600))
    assert np.mean([got[i]["predicted"] == (i % 3 != 0) for i in held]) >= 0.9
    assert all(0 <= r["score"] <= 1 for r in got.values())
    assert got[600]["score"] == pytest.approx(got[601]["score"])
    assert {r["score"] for r in quality.score_quality(df, marks.limit(0)).collect()} == {0.5}
    assert quality.score_quality(df.limit(0), marks).count() == 0


def test_index_vectors():
    table = quality._index_table()
    words = [b"abc", b"a", b"abc", b"xyz-long-word"]
    got = quality.index_vectors(words, table)
    assert np.allclose(got[0], got[2]) and not np.allclose(got[0], got[3])
    assert np.allclose(quality.index_vectors([b"a"], table)[0], got[1], atol=1e-5)
