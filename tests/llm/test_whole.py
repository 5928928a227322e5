"""Cases where an operator once did less than its whole job."""

from __future__ import annotations

import random
from collections import Counter

import corpus_pipeline
from tallymill.llm import bpe, decontaminate, paragraphs, suffixes
from tallymill.llm.queries import tokenizer


def test_pairs_in_crowded_buckets_are_found(spark):
    # 600 pairs at Jaccard 86 / 106 that share 85 of 100 words with all others, at 81 / 111
    out, common = [], [f"c{k}" for k in range(85)]
    for g in range(600):
        own = [f"g{g}x{k}" for k in range(15)]
        out += [(2 * g, " ".join(common + own)), (2 * g + 1, " ".join(common + own[:5] + [f"h{g}x{k}" for k in range(10)]))]
    got = paragraphs.clusters(spark.createDataFrame(out, "doc_id long, text string")).collect()
    found = {}
    for r in got:
        found.setdefault(r.cluster, set()).add(r.doc_id)
    assert sorted(map(sorted, found.values())) == [[2 * g, 2 * g + 1] for g in range(600)]


def test_shingles_of_many_labels_meet_by_size_and_place(spark):
    import numpy as np
    import pyarrow as pa

    rng = np.random.default_rng(4)
    rows = sorted({(int(s), int(rng.integers(20, 40)), int(rng.integers(0, 8)), int(rng.integers(0, 30)), p) for s in (1, 2, 3) for p in range(5 if s == 1 else 150)})
    want = set()
    for i, (s, size, at, label, p) in enumerate(rows):
        for s2, size2, at2, label2, p2 in rows[:i]:
            if s == s2 and label != label2 and 9 * min(size - at, size2 - at2) >= 4 * (size + size2):
                want.add((min(p, p2), max(p, p2)))
    batch = pa.record_batch([pa.array(c, pa.int64()) for c in zip(*rows)], names=["shingle", "size", "at", "label", "par"])
    got = [(a, b) for x in paragraphs._meetings(iter([batch.slice(0, 100), batch.slice(100)])) for a, b in zip(*(c.to_pylist() for c in x.columns))]
    assert set(got) == want


def test_short_paragraphs_repeat(spark):
    rows = [(1, "Share this page\nabc"), (2, "share  THIS page\nxyz"), (3, "一二三\n \nshare this"), (4, "一二三"), (5, "a b c d e f g\nabc def")]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    got = {r.doc_id: (r.n_paragraphs, r.n_repeated, r.removed_places) for r in paragraphs.by_document(docs).collect()}
    assert got == {1: (2, 1, []), 2: (2, 1, [0]), 3: (2, 1, []), 4: (1, 1, [0]), 5: (2, 0, [])}
    assert {r.doc_id: r.text for r in paragraphs.stripped(docs).collect()} == {1: rows[0][1], 2: "xyz", 3: rows[2][1], 4: "", 5: rows[4][1]}


def test_repeated_passages_count_by_words(spark):
    rng = random.Random(6)
    prose = lambda n: " ".join("".join(rng.choice("abcdeé") for _ in range(rng.randint(2, 4))) for _ in range(n))
    long, short = prose(51), prose(50)
    hanzi = "".join(chr(0x4E00 + rng.randrange(5000)) for _ in range(60))
    rows = [(k, f"{prose(40)} {long} {prose(30)}") for k in range(2)] + [(2, f"{prose(9)}\n{long.replace(' ', '  ')}\nend")]
    rows += [(10 + k, f"{prose(40)} {short} {prose(30)}") for k in range(2)] + [(20 + k, prose(30) + hanzi + prose(5)) for k in range(2)] + [(30, None), (31, "")]
    assert len(long.encode()) < 300
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    got = {r.doc_id: r.text for r in corpus_pipeline.without_repeats(spark, docs, "").collect()}
    for k, t in rows:
        gone = long.split() if k < 2 or k == 2 else []
        want = (t or "").replace(hanzi, " " if k >= 20 else "").split()
        for i in range(len(want) - 50 if gone else 0):
            if want[i : i + 51] == gone:
                want[i : i + 51] = []
                break
        assert ((got[k] or "").replace(hanzi, "?").split() == want) if k < 20 else hanzi not in (got[k] or "")
    assert got[30] is None and got[31] == ""


def test_seams_in_whitespace(spark):
    path, pattern = tokenizer()
    coder = bpe.encoding(path, pattern)
    gaps = ["\n\n", "\r\n\r\n", "\t\t ", "  ", "\n\n\n  "]
    body = "".join(f"word{k}{gaps[k % 5]}foo" for k in range(25))
    rows = [(k, "x" * k + " " + body) for k in range(40)]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    got = {r.doc_id: list(r.ids) for r in bpe.encode(docs, path, pattern, 64, 16).collect()}
    assert [k for k, t in rows if got[k] != coder.encode_ordinary(t)] == []


def test_rows_that_share_an_identity_stay_apart(spark):
    rng = random.Random(9)
    texts = [" ".join(rng.choice("abcdefgh") + str(rng.randint(0, 999)) for _ in range(60)) for _ in range(6)]
    rows = [(1, texts[0]), (5, texts[0]), (5, texts[1]), (None, texts[2]), (None, texts[3]), (None, texts[3]), (7, texts[4]), (7, texts[4]), (8, texts[5]), (None, texts[5])]
    docs = spark.createDataFrame([(i, t, "s") for i, t in rows], "doc_id long, text string, source string").repartition(3)
    out = corpus_pipeline.one_of_each(spark, docs, "")
    assert out.columns == docs.columns
    want = [(1, texts[0]), (5, texts[1]), (None, texts[2]), (None, texts[3]), (7, texts[4]), (8, texts[5])]
    assert Counter((r.doc_id, r.text) for r in out.collect()) == Counter(want)
    items = spark.createDataFrame([(1, texts[2])], "item_id long, text string")
    assert Counter((r.doc_id, r.text) for r in decontaminate.clean(out, items).collect()) == Counter(w for w in want if w[1] != texts[2])


def test_passages_inside_lines_are_told_from_short_lines(spark):
    rng = random.Random(21)
    vocabulary = ["".join(rng.choice("abcdefgh") for _ in range(rng.randint(2, 7))) for _ in range(3000)]
    prose = lambda n: " ".join(rng.choice(vocabulary) for _ in range(n))
    common = [prose(9) for _ in range(3)]
    rows = []
    for k in range(60):
        passage = prose(rng.randint(51, 80)).split()
        passage[rng.randint(5, 45)] += "\n"
        for j in range(2):  # neither end is an end of a line
            rows.append((10 * k + j, f"{prose(40)} {' '.join(passage)} {prose(rng.randint(1, 60))}\n{common[k % 3]}\n{prose(30)}"))
        rows.append((10 * k + 5, f"{prose(60)}\n{common[0]}\n{prose(30)}\n{common[1]}\n{prose(9)}\n{common[2]}"))
    docs = spark.createDataFrame(rows, "doc_id long, text string").repartition(4)
    got = {r.doc_id: r for r in paragraphs.by_document(docs).collect()}
    assert sum(got[10 * k + j].n_passages > 0 for k in range(60) for j in range(2)) >= 116
    assert not any(got[10 * k + 5].n_passages for k in range(60))
    assert all(got[10 * k + 5].n_repeated == 3 for k in range(60))
    # by windows of words: every one, and their words exactly
    exact = {r.doc_id: r for r in suffixes.remaining(docs, n_words=51).collect()}
    windows = Counter(w for _, t in rows for w in {tuple(t.split()[i : i + 51]) for i in range(len(t.split()) - 50)})
    for i, t in rows:
        own, hit = t.split(), set()
        for at in range(len(own) - 50):
            if windows[tuple(own[at : at + 51])] > 1:
                hit |= set(range(at, at + 51))
        assert exact[i].n_passage_words == len(hit) and exact[i].n_passages == sum(k - 1 not in hit for k in hit)


def test_equal_rows_keep_paragraphs_once(spark):
    rows = [(1, "a b c d e f\nx"), (1, "a b c d e f\nx"), (None, None), (None, None), (2, "")]
    docs = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    assert sorted((r.n_removed, r.removed_places) for r in paragraphs.by_document(docs).where("doc_id = 1").collect()) == [(0, []), (2, [0, 1])]
    assert sorted(r.text for r in paragraphs.stripped(docs).where("doc_id = 1").collect()) == ["", "a b c d e f\nx"]
    assert paragraphs.by_document(docs).count() == paragraphs.stripped(docs).count() == 5


def test_a_hot_key_is_joined_whole(spark):
    from tallymill.llm.shared import hot_join

    left = spark.createDataFrame([(0 if k % 3 else k, k) for k in range(5000)], "key long, at long")
    right = left.groupBy("key").count().selectExpr("key", "count AS n", "key * 2 AS twice").where("key % 2 = 0")
    got = {(r.key, r["at"], r.twice) for r in hot_join(left, right, "key", "n").collect()}
    assert got == {(k, j, 2 * k) for j in range(5000) for k in [0 if j % 3 else j] if k % 2 == 0}
