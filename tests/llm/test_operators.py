"""The operators against brute force on small tables, hostile rows included."""

from __future__ import annotations

import base64
import hashlib
import random
import re
import zlib
from collections import Counter, defaultdict

import numpy as np
import pytest
import tiktoken
import xxhash

from tallymill.llm import bpe, chats, decontaminate, imatch, langid, licenses, paragraphs, sharding, simhash, suffixes
from tallymill.llm.queries import tokenizer
from tallymill.llm.shared import components

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, text_hash string, fp int, spans string, shard string, kept_id int, block string"


def texts() -> list[tuple[int | None, str | None]]:
    rng = random.Random(3)
    words = ["".join(rng.choice("abcdeéß") for _ in range(rng.randint(1, 8))) for _ in range(400)]
    prose = lambda n: " ".join(rng.choice(words) for _ in range(n))
    base, passage = prose(300), prose(90)
    rows: list[tuple[int | None, str | None]] = [(k, prose(rng.randint(1, 120)) + "\n" + prose(20)) for k in range(30)]
    rows += [(40 + k, base) for k in range(3)]
    rows += [(50 + k, base[:700] + f" x{k} " + base[700:]) for k in range(4)]
    rows += [(60 + k, prose(40) + "\n" + passage + "\n" + prose(30)) for k in range(4)]
    rows += [(70, ""), (71, None), (72, " \n "), (73, "A"), (74, "ab ab ab ab " * 500), (75, "一二三 " * 400), (76, "!!! ???"), (77, "x" * 5000), (78, prose(9000))]
    rows += [(80, rows[0][1]), (80, rows[0][1]), (81, prose(60)), (81, prose(60)), (None, prose(50)), (None, None)]
    return rows


@pytest.fixture(scope="module")
def rows():
    return texts()


@pytest.fixture(scope="module")
def docs(spark, rows):
    return spark.createDataFrame([(i, t, None, None, None, "x", 1, "y", "z", 5, "w") for i, t in rows], SCHEMA).repartition(3)


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], SCHEMA)


def lower(t: str | None) -> str:
    return re.sub("[A-Z]", lambda m: m[0].lower(), t or "")


def listed(df, *names):
    return Counter(tuple(r[n] for n in names) for r in df.collect())


def test_components(spark):
    rng = random.Random(1)
    pairs = [(rng.randint(-200, 200), rng.randint(-200, 200)) for _ in range(150)] + [(k, k + 1) for k in range(1000, 1040)] + [(5000, k) for k in range(5001, 5300)]
    up = {}

    def root(x):
        while up.setdefault(x, x) != x:
            x = up[x]
        return x

    for a, b in pairs:
        x, y = root(a), root(b)
        if x != y:
            up[max(x, y)] = min(x, y)
    got = {r.node: r.label for r in components(spark.createDataFrame(pairs, "a long, b long")).collect()}
    loops = {a for a, b in pairs if a == b}
    assert {k: v for k, v in got.items()} == {k: root(k) for k in up if k in got or k not in loops}


def test_simhash(docs, empty, rows):
    prints = []
    for i, t in rows:
        w = re.findall(r"[^\x20\x09-\x0D]+", lower(t))
        s = [" ".join(w[k : k + 3]) for k in range(len(w) - 2)] or ([" ".join(w)] if w else [])
        h = [xxhash.xxh64_intdigest(x.encode(), 42) for x in s]
        prints.append((i, sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))))
    label = list(range(len(prints)))
    for _ in prints:
        for a in range(len(prints)):
            for b in range(len(prints)):
                if (prints[a][1] ^ prints[b][1]).bit_count() <= 2:
                    label[a] = label[b] = min(label[a], label[b])
    least = defaultdict(list)
    for (i, _), k in zip(prints, label):
        least[k] += [] if i is None else [i]
    want = Counter((i, f"{f:016x}", min(least[k], default=None)) for (i, f), k in zip(prints, label))
    assert listed(simhash.near_duplicates(docs), "doc_id", "fingerprint", "component_id") == want
    assert simhash.near_duplicates(empty).count() == 0
    kept = [r.doc_id for r in simhash.one_row(docs).collect()]
    assert kept.count(40) == 1 and 41 not in kept
    assert simhash.one_row(docs).columns == docs.columns


def test_simhash_links_of_close_words(spark):
    rng = np.random.default_rng(5)
    heart = rng.integers(0, 1 << 63, 40, dtype=np.uint64)
    near = [int(h) ^ sum(1 << int(b) for b in rng.choice(64, rng.integers(0, 4), replace=False)) for h in heart for _ in range(60)]
    near = sorted(set(near))
    signed = [x - (1 << 64) if x >> 63 else x for x in near]
    got = {r.node: r.label for r in components(simhash.links(spark.createDataFrame([(x,) for x in signed], "fp long"))).collect()}
    up = {x: x for x in near}

    def root(x):
        while up[x] != x:
            x = up[x]
        return x

    for k, a in enumerate(near):
        for b in near[:k]:
            if (a ^ b).bit_count() <= 2:
                up[root(a)] = root(b)
    want, found = defaultdict(set), defaultdict(set)
    for x, s in zip(near, signed):
        want[root(x)].add(s)
        found[got.get(s, s)].add(s)
    assert sorted(map(sorted, want.values())) == sorted(map(sorted, found.values()))


def test_suffixes(docs, empty, rows):
    for depth in (400, 60):
        seen = Counter(t.encode()[k : k + depth] for _, t in rows for t in [t or ""] for k in range(len(t.encode()) - depth + 1))
        want = Counter()
        for i, t in rows:
            b = (t or "").encode()
            gone = bytearray(len(b))
            for k in range(len(b) - depth + 1):
                if seen[b[k : k + depth]] > 1:
                    gone[k : k + depth] = b"\1" * depth
            kept = bytes(x for x, y in zip(b, gone) if not y)
            want[i, len(b), sum(gone), len(re.findall(b"\1+", bytes(gone))), hashlib.sha256(kept).hexdigest()] += 1
        assert listed(suffixes.digests(suffixes.remaining(docs, depth, 20)), "doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256") == want
    assert suffixes.remaining(empty).count() == 0
    out = suffixes.stripped(docs)
    assert out.columns == docs.columns and out.count() == len(rows)
    assert {r.text for r in out.where("doc_id = 41").collect()} == {""}


def test_language(spark, empty):
    rng = random.Random(2)
    make = lambda parts, n: " ".join("".join(rng.choice(parts) for _ in range(3)) for _ in range(n))
    parts = {"aa": ["the", "ing", "wh", "on"], "bb": ["ung", "ich", "ß", "tz"], "cc": ["eau", "é", "que", "ou"]}
    train = [(k, make(parts[g], rng.randint(3, 200)), g) for k in range(300) for g in [rng.choice(list(parts))]]
    model = langid.fit(spark.createDataFrame([*train, (None, None, "aa"), (7, "the", None)], "doc_id long, text string, lang string"))
    assert set(model.languages) == set(parts)
    held = [(k, make(parts[g], 30), g) for k in range(90) for g in [rng.choice(list(parts))]]
    test = spark.createDataFrame([*held, (900, None, "zz"), (901, "12 !?", "zz"), (902, "", "zz"), (903, "ωψφ χξ" * 40, "zz")], "doc_id long, text string, score string")
    got = {r.doc_id: r for r in langid.identify(test, model).collect()}
    assert np.mean([got[k].lang_pred == g for k, _, g in held]) > 0.98
    assert not any(got[k].rejected for k, _, _ in held)
    assert all(got[k].lang_pred == "und" and got[k].score == 0 for k in (900, 901, 902))
    assert got[903].rejected and 0 <= got[903].score <= 1
    assert langid.identify(empty, langid.fit(empty)).count() == 0


def test_decontamination(spark, docs, empty, rows):
    words = lambda t: re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", lower(t))
    pick = " ".join(words(rows[40][1])[5:40])
    bench = [(10, pick), (9, pick.upper()), (1, "ab AB"), (2, None), (3, ""), (4, "..."), (5, " ".join(words(rows[5][1])[:13])), (None, "zzz yyy"), (5, "nothing of the kind is in there at all, or so one would very much hope")]
    items = spark.createDataFrame([(i, t, 3) for i, t in bench], "item_id long, text string, n_words int")
    windows = defaultdict(set)
    for i, t in bench:
        w = words(t)
        for k in range(max(1, len(w) - 12)) if w else []:
            windows[tuple(w[k : k + 13])].add("" if i is None else str(i))
    want = Counter()
    for i, t in rows:
        w, hit, found = words(t), set(), set()
        for size in {len(x) for x in windows}:
            for k in range(len(w) - size + 1):
                if tuple(w[k : k + size]) in windows:
                    hit |= set(range(k, k + size))
                    found |= windows[tuple(w[k : k + size])]
        want[i, len(w), len(hit), tuple(sorted(found)), bool(hit) and 20 * len(hit) >= len(w)] += 1
    for block in (decontaminate.BLOCK_WORDS, 30):
        got = decontaminate.judged(decontaminate.overlaps(docs, items, block_words=block)).collect()
        assert Counter((r.doc_id, r.n_words, r.n_hit, tuple(r.item_ids), r.contaminated) for r in got) == want
    assert decontaminate.overlaps(empty, items).count() == 0
    assert decontaminate.overlaps(docs, empty.selectExpr("doc_id AS item_id", "text")).where("size(item_ids) > 0").count() == 0
    assert decontaminate.clean(docs, items).columns == docs.columns


def test_tokens(docs, empty, rows):
    path, pattern = tokenizer()
    with open(path, "rb") as f:
        ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
    coder = tiktoken.Encoding("own", pat_str=pattern, mergeable_ranks=ranks, special_tokens={})
    want = Counter((i, tuple(coder.encode_ordinary(t or "")), (t or "").encode()) for i, t in rows)
    for chunk, overlap in ((bpe.CHUNK, bpe.OVERLAP), (200, 40), (50, 20)):
        got = bpe.decode(bpe.encode(docs, path, pattern, chunk, overlap), path, pattern).collect()
        assert Counter((r.doc_id, tuple(r.ids), bytes(r.decoded)) for r in got) == want
    assert bpe.encode(empty, path, pattern).count() == 0


def test_stitching_never_trusts_a_seam_that_does_not_agree():
    assert bpe.stitch([(0, 30, [0, 5, 22]), (20, 50, [20, 22, 41]), (40, 60, [40, 41])]) == [0, 22, 41]
    assert bpe.stitch([(0, 30, [0, 25]), (20, 50, [20, 27, 41]), (40, 60, [40, 41])]) == [0]


def test_imatch(docs, empty, spark, rows):
    got = imatch.fingerprints(docs, blocks=5).collect()
    order = sorted(((i is not None, i, t or "") for i, t in rows), key=lambda x: (x[0], x[1] or 0, x[2]))
    want = Counter()
    for k, (_, i, t) in enumerate(order):
        n, after = len(t) // 2, order[(k + 1) % len(order)][2]
        want[i, len(t), hashlib.sha256((t[: len(t) - n] + after[:n]).encode()).hexdigest()] += 1
    assert Counter((r.doc_id, r.n_chars, r.edited_sha256) for r in got) == want
    # fingerprints and likenesses again, from the rule alone
    freq = Counter(w for _, t in rows for w in set(re.findall(r"[^\W_]+", (t or "").lower())))
    band = {w for w, n in freq.items() if imatch.LOW * len(rows) <= n <= imatch.HIGH * len(rows)}

    def mark(text):
        own = set(re.findall(r"[^\W_]+", text.lower()))
        own = own & band or own
        out = []
        for k in range(imatch.COMPONENTS):
            some = sorted(w for w in own if k in imatch.kept(w))
            out.append(1 + xxhash.xxh32_intdigest(" ".join(some).encode(), k) % 65535 if some else 0)
        return b"".join(v.to_bytes(2, "little") for v in out)

    def alike(a, b):
        if a == b:
            return 1.0
        x, y = ([int.from_bytes(m[k : k + 2], "little") for k in range(0, len(m), 2)] for m in (a, b))
        used = []
        for tier in range(imatch.TIERS):
            at = range(1 + tier * imatch.EACH, 1 + (tier + 1) * imatch.EACH)
            if min(sum(x[k] > 0 for k in at), sum(y[k] > 0 for k in at)) <= 0.75 * imatch.EACH:
                used += at
        used = [k for k in used or [0] if x[k] or y[k]]
        return sum(x[k] == y[k] for k in used) / len(used) if used else 0.0

    full = Counter()
    for k, (_, i, t) in enumerate(order):
        n, after = len(t) // 2, order[(k + 1) % len(order)][2]
        own, change, nxt = mark(t), mark(t[: len(t) - n] + after[:n]), mark(after)
        full[i, own.hex(), change.hex(), round(alike(own, change), 9), round(alike(own, nxt), 9)] += 1
    assert Counter((r.doc_id, r.fingerprint, r.edited_fingerprint, round(r.near_edited, 9), round(r.near_next, 9)) for r in got) == full
    by_text = defaultdict(set)
    for r in got:
        assert 0 <= r.near_edited <= 1 and 0 <= r.near_next <= 1
        by_text[r.doc_id].add(r.fingerprint)
    assert by_text[40] == by_text[41] == by_text[42]
    assert sum(r.near_edited for r in got) > 1.5 * sum(r.near_next for r in got)
    assert imatch.fingerprints(empty).count() == 0
    alone = imatch.fingerprints(spark.createDataFrame([(1, "ab cd")], "doc_id long, text string")).collect()
    assert len(alone) == 1 and alone[0].near_next == 1


def test_sharding(docs, empty, rows):
    got = sharding.sharded(docs, slot_blocks=16).collect()
    assert Counter((r.doc_id, r.size, r.text_crc32) for r in got) == Counter((i, len((t or "").encode()) + 1, zlib.crc32((t or "").encode())) for i, t in rows)
    slots, place = defaultdict(list), defaultdict(set)
    for r in got:
        slots[r.shard].append(r.slot)
        place[r.doc_id].add((r.shard, r.grown_shard))
        assert r.law == "key" and r.grown_shard in (r.shard, 8)
    assert all(sorted(v) == list(range(len(v))) for v in slots.values()) and set(slots) <= set(range(8))
    assert all(len(v) == 1 for v in place.values())
    assert sharding.sharded(empty).count() == 0
    # the draws again
    import math

    def least(key, level, children):
        u = {c: (int(hashlib.md5(f"{level}|{c}|{key}".encode()).hexdigest()[:13], 16) + 0.5) / 2**52 for c in children}
        return min(children, key=lambda c: -math.log(u[c]) / children[c])

    def again(key, n):
        regions = {0: 4.0, 1: 4.0} | ({9: 1.0} if n > 8 else {})
        r = least(key, "region", regions)
        if r == 9:
            return 8
        k = least(key, "rack", {2 * r: 2.0, 2 * r + 1: 2.0})
        return least(key, "shard", {2 * k: 1.0, 2 * k + 1: 1.0})

    tree = sharding.layout(8)
    assert {(s.region, s.rack, s.shard) for s in tree} == {(k // 4, k // 2, k) for k in range(8)}
    grown = 1 + max(s.region for s in tree)
    for r in got:
        key = "null" if r.doc_id is None else str(r.doc_id)
        assert r.shard == again(key, 8)
        regions = {0: 4.0, 1: 4.0, grown: 1.0}
        assert (r.grown_shard == 8) == (least(key, "region", regions) == grown)


def test_shards_follow_weights_and_moves_stay_in_the_changed_subtree(spark):
    from dataclasses import replace

    from pyspark.sql import functions as F

    tree = sharding.layout(8)
    heavy = [replace(s, weight=3.0) if s.shard == 5 else s for s in tree]
    swapped = [replace(s, weight={0: 1.5, 1: 0.5}.get(s.shard, 1.0)) for s in tree]
    key = F.col("id").cast("string")
    got = spark.range(40000).select(*(sharding.shard_of(key, t).alias(n) for n, t in (("a", tree), ("b", heavy), ("c", swapped)))).toPandas()
    assert got.a.value_counts(normalize=True).between(0.115, 0.135).all()
    assert abs((got.b == 5).mean() - 0.3) < 0.01
    # the region of shard 5 gains; none leaves it
    assert not ((got.a // 4 == 1) & (got.b // 4 == 0)).any()
    # a shift inside a rack moves rows inside that rack only
    assert ((got.a == got.c) | ((got.a < 2) & (got.c < 2))).all()


def test_paragraphs(docs, empty, rows):
    where = defaultdict(list)
    for i, t in rows:
        for k, line in enumerate((t or "").encode().split(b"\n")):
            w = line.lower().split()
            if len(w) >= 5:
                where[b" ".join(w)].append((i, t, k))
    names = list(where)
    sets = [{tuple(n.split()[k : k + 5]) for k in range(len(n.split()) - 4)} for n in names]
    label = list(range(len(names)))
    for _ in range(4):
        for a in range(len(names)):
            for b in range(len(names)):
                if len(sets[a] & sets[b]) >= 0.8 * len(sets[a] | sets[b]):
                    label[a] = label[b] = min(label[a], label[b])
    size = Counter()
    for n, k in zip(names, label):
        size[k] += len(where[n])
    want = Counter()
    for n, k in zip(names, label):
        for i, _, place in where[n]:
            want[i, place, size[k]] += 1
    got = paragraphs.clusters(docs).collect()
    assert Counter((r.doc_id, r.place, r["size"]) for r in got) == want
    removed = Counter(r.cluster for r in got if not r.removed)
    assert all(v == 1 or k is None for k, v in removed.items() if k not in {r.cluster for r in got if r.doc_id == 80})
    assert paragraphs.by_document(docs).count() == len(rows)
    assert paragraphs.by_document(empty).count() == 0
    kept = {r.doc_id: r.text for r in paragraphs.stripped(docs).where("doc_id BETWEEN 60 AND 63").collect()}
    assert sum(rows[40][1].split("\n")[1] in t for t in kept.values()) == 1


def test_similar_paragraphs_are_found(spark):
    rng, out = random.Random(8), []
    for g in range(30):
        base = [f"w{rng.randint(0, 10**6)}" for _ in range(150)]
        for k in range(40 if g == 0 else 2):
            own = list(base)
            own[rng.randint(0, 149)] = f"z{k}"
            out.append((100 * g + k, " ".join(own)))
    got = paragraphs.clusters(spark.createDataFrame(out, "doc_id long, text string")).collect()
    by_cluster = defaultdict(set)
    for r in got:
        by_cluster[r.cluster].add(r.doc_id // 100)
    assert len(by_cluster) == 30 and all(len(v) == 1 for v in by_cluster.values())


def test_chats(spark):
    rows = [(1, 0, "user", "a"), (1, 1, "assistant", "b"), (2, 0, "user", "a"), (2, 1, "assistant", "b"), (2, 2, "user", "c"), (3, 0, "user", "a"), (3, 1, "assistant", "x"), (4, 2, "user", "c"), (4, 0, "user", "a"), (4, 1, "assistant", "b"), (5, 0, None, None), (5, 0, None, None), (6, None, "user", ""), (None, 0, "user", "q"), (7, 0, "user", "a"), (8, 0, "user", "b"), (8, 1, "user", "a")]
    rows += [(20, k, "user", str(k)) for k in range(3000)] + [(21, k, "user", str(k)) for k in range(1500)]
    table = spark.createDataFrame([(*r, 1) for r in rows], "conv_id long, turn long, role string, text string, n int")
    got = {r.conv_id: r for r in chats.formatted(table).collect()}
    assert set(got) == {2, 3, 5, 6, 8, 20}
    assert got[2].rendered == "<|user|>\na\n<|assistant|>\nb\n<|user|>\nc\n" and got[2].n_turns == 3
    assert got[5].rendered == "<|unknown|>\n\n" and got[20].n_turns == 3000
    assert chats.formatted(table.where("false")).count() == 0


def test_licenses(spark, docs, empty):
    model = licenses.fit(docs)
    said = lambda t: (model.judge(t, licenses.tokens(t)) or ("none",))[0]
    assert np.mean([said(t) == f for f, t, _ in licenses.notices(seed=99)]) > 0.95
    # neither these wordings nor these names are in the training set
    unseen = [("gpl", "You may copy this under the GNU General Public License 3"), ("apache", "Made available by us under Apache License 2.0"), ("mpl", "Subject to the Mozilla Public License 2.0"), ("cc-by-sa", "Text is available under Creative Commons Attribution-ShareAlike 4.0"), ("agpl", "Server code: GNU Affero General Public License v3"), ("unknown", "Licensed under the Ruby License."), ("unknown", "Distributed under the terms of the Frobozz Licence, edition nine"), ("unknown", "This work is licensed under the Foo Bar License, version 7."), ("none", "The quick brown fox jumps over the lazy dog"), ("unknown", "SPDX-License-Identifier: Zlib"), ("none", "ab cd")]
    assert [said(t) for _, t in unseen] == [f for f, _ in unseen]
    table = spark.createDataFrame([(1, "some prose here\nReleased under the MIT License.\nmore"), (2, None), (3, ""), (4, "Licensed under the Frobozz Widget Terms, edition nine."), (5, "the version of the work was of this file")], "doc_id long, text string")
    got = {r.doc_id: r.found for r in licenses.scan(table, model).collect()}
    assert [(f.place, f.family, f.confirmed) for f in got[1]] == [(1, "mit", True)]
    assert got[2] == got[3] == got[5] == [] and got[4][0].family == "unknown"
    assert licenses.scan(empty, licenses.fit(empty)).count() == 0


def test_chats_with_nulls_ties_and_repeats_equal_sql(spark):
    import duckdb
    import pandas as pd

    rng, rows = random.Random(12), []
    some = lambda xs: rng.choice(xs)
    for c in range(400):
        for _ in range(rng.randint(1, 4)):
            rows.append((c, some([0, 0, 1, 2, None]), some(["user", "assistant", None]), some(["user", "a", "b", "", None])))
    rows += [(1000, 0, None, "user"), (1001, 0, "user", None), (1002, 0, "user", "a"), (1002, 0, "user", "a"), (1003, 0, "b", "a"), (1003, 0, "a", "b"), (1004, 0, "a", "b"), (None, 0, "user", "a")]
    frame = pd.DataFrame(rows, columns=["conv_id", "turn", "role", "text"]).astype({"conv_id": "Int64", "turn": "Int64"})
    con = duckdb.connect()
    con.register("conversations", frame)
    want = Counter((int(a), int(b), c) for a, b, c in con.sql(chats.FORMATTED_SQL).fetchall())
    table = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string").repartition(5)
    assert listed(chats.formatted(table), "conv_id", "n_turns", "rendered") == want
    # and both equal a plain reading of the rule
    turns = {}
    for c, t, r, x in {r for r in rows if r[0] is not None}:
        turns.setdefault(c, []).append((t is None, t or 0, r is None, r or "", x is None, hashlib.md5((x or "").encode()).hexdigest(), r, x))
    turns = {c: [(r, x) for *_, r, x in sorted(v, key=lambda k: k[:6])] for c, v in turns.items()}
    left = {c for c, v in turns.items() if not any(w[: len(v)] == v and (len(w) > len(v) or d < c) for d, w in turns.items() if d != c)}
    assert {c for c, _, _ in want} == left


def test_licence_lines_of_the_given_documents(spark):
    given = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    lines = {"GNU General Public License, version 3.": "gpl", "All rights reserved.": "proprietary", "CC BY-NC 4.0.": "cc-by-nc", "under the MIT License.": "mit", "Apache License, Version 2.0.": "apache"}
    want = Counter((r.doc_id, k, f) for r in given.collect() for k, line in enumerate(r.text.split("\n")) for tail, f in lines.items() if line.endswith(tail))
    got = Counter((r.doc_id, f.place, f.family) for r in licenses.scan(given, licenses.fit(given)).collect() for f in r.found)
    assert got == want and sum(want.values()) > 20
