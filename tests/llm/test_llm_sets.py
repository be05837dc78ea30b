"""Operators across texts and vectors: near duplicates, passages, search, components, pipeline."""

import random
import re

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from tuplestat.llm import components, passage_dedup, registry, segment_topk, shared, sketch_dedup as D
from tuplestat.llm.shared import shingle_hashes

WORDS = [f"w{i}" for i in range(4000)]


def docs(spark, texts):
    return spark.createDataFrame([(i, t) for i, t in enumerate(texts)], "doc_id long, text string")


def sets_of(text, size):
    w = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text or "")
    for c in "\t\n\x0b\x0c\r":
        w = w.replace(c, " ")
    w = [x for x in w.split(" ") if x]
    if not w:
        return set()
    return {tuple(w[i : i + size]) for i in range(len(w) - size + 1)} or {tuple(w)}


def brute_components(texts, size, percent=80):
    s = [sets_of(t, size) for t in texts]
    root = list(range(len(s)))

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    for i in range(len(s)):
        for j in range(i):
            both = len(s[i] & s[j])
            if both and 100 * both >= percent * (len(s[i]) + len(s[j]) - both):
                a, b = find(i), find(j)
                root[max(a, b)] = min(a, b)
    return [find(i) for i in range(len(s))], [len(x) for x in s]


def edited(rng, words, share):
    return [rng.choice(WORDS) if rng.random() < share else w for w in words]


@pytest.fixture(scope="module")
def corpus():
    rng = random.Random(7)
    base = [rng.choice(WORDS) for _ in range(140)]
    texts = [" ".join(edited(rng, base, rng.choice((0.02, 0.05, 0.09)))) for _ in range(70)]  # siblings, no base
    texts += [" ".join(rng.choice(WORDS) for _ in range(rng.randrange(1, 120))) for _ in range(60)]
    one = [rng.choice(WORDS) for _ in range(200)]
    for _ in range(12):  # a chain of edits
        one = edited(rng, one, 0.03)
        texts.append(" ".join(one))
    texts += ["", None, "  \n", "Hello", "hello", "HELLO\tWorld", "hello world", "é É", "é é", texts[3], texts[3].upper(), texts[100]]
    return texts


@pytest.mark.parametrize("size", [2, 5])
def test_near_duplicates_against_brute_force(spark, corpus, size):
    want, n = brute_components(corpus, size)
    got = {r.doc_id: r for r in D.near_duplicates(docs(spark, corpus), size=size).collect()}
    assert [got[i].n_shingles for i in range(len(corpus))] == n
    assert [got[i].component_id for i in range(len(corpus))] == want
    assert all(got[i].kept == (want[i] == i) for i in range(len(corpus)))


def test_near_duplicates_drop_registers_and_move_a_set_for_its_sides_only(spark, corpus, monkeypatch):
    """Tables with registers are gone when sets are compared; each side of a pair has its own sets."""
    kept, seen = D.verified, []

    def look(pairs, sets, percent):
        seen.extend(p for p in shared._STAGED if "-sketches-" in p or "-classes-" in p)
        a, b = ({r[0] for r in pairs.select(k).collect()} for k in "ab")
        assert a != b
        for k, ids in (("is_a", a), ("is_b", b)):
            assert {r.id for r in sets.where(k).collect()} == ids
        return kept(pairs, sets, percent)

    before = set(shared._STAGED)
    monkeypatch.setattr(D, "verified", look)
    D.near_duplicates(docs(spark, corpus), size=2)
    assert not set(seen) - before


def test_near_duplicates_on_odd_tables(spark):
    d = spark.createDataFrame([(1, "a b c"), (1, "a b c"), (None, "a b c"), (2, "a b c"), (3, None)], "doc_id long, text string").withColumn("n", F.lit(9))
    r = sorted((x.doc_id or -1, x.component_id, x.kept) for x in D.near_duplicates(d, size=2).collect())
    assert r == [(-1, None, True), (1, 1, True), (1, 1, True), (2, 1, False), (3, 3, True)]
    assert D.near_duplicates(d.limit(0)).count() == 0


def test_sketches_merge_and_estimate():
    rng = np.random.default_rng(3)
    for n, common in ((2000, 1800), (300, 100), (40, 38)):
        a = rng.integers(0, 2**63, n, dtype=np.uint64)
        b = np.concatenate([a[:common], rng.integers(0, 2**63, n - common, dtype=np.uint64)])
        s = D.sketch(np.concatenate([a, b]), np.array([0, n, 2 * n]))
        both = np.unique(np.concatenate([a, b]))
        assert (D.merged(s[:1], s[1:]) == D.sketch(both, np.array([0, len(both)]))).all()
        j = common / (2 * n - common)
        got = D.joint_estimate(s[:1], s[1:], np.array([n]), np.array([n]))[0]
        assert abs(got - j) < 6 * (j * (1 - j) / 256) ** 0.5 + 0.02


def test_shingles_do_not_depend_on_the_batch():
    texts = ["one two three", None, "", "two", "A a\tB", "x" * 300]
    whole, cut = shingle_hashes(pa.array(texts, pa.string()), 2)
    for i, t in enumerate(texts):
        alone, _ = shingle_hashes(pa.array([t], pa.string()), 2)
        assert whole[cut[i] : cut[i + 1]].tolist() == alone.tolist()
        assert len(alone) == len(sets_of(t, 2))


def test_word_hashes_name_the_words():
    rnd = random.Random(1)
    made = lambda: "".join(rnd.choice("aAbZ[`{@ \t\n\x0b\x0c\r\x08\x0eé日") for _ in range(rnd.randint(0, 200)))
    named = {}
    for _ in range(200):
        texts = [rnd.choice([None, "", "  ", made(), "x" * rnd.randint(1, 200), "Ab" * rnd.randint(1, 60) + " " + "y" * 64]) for _ in range(5)]
        raw, offsets = shared.text_bytes(pa.array(texts, pa.string()))
        starts, ends, row = shared.word_spans(raw, offsets)
        want = [(k, w) for k, t in enumerate(texts) for w in re.findall("[^\x20\x09-\x0d]+", t or "")]
        assert [(k, bytes(raw[a:b]).decode()) for k, a, b in zip(row, starts, ends)] == want
        for (_, w), h in zip(want, shared.word_hashes(raw, starts, ends).tolist()):
            assert named.setdefault(re.sub("[A-Z]", lambda m: m.group().lower(), w), h) == h
    assert len(set(named.values())) == len(named)


def test_components(spark):
    rng = random.Random(1)
    edges = [(i, i + 1) for i in range(30)] + [(100, k) for k in range(101, 160)] + [(rng.randrange(200, 260), rng.randrange(200, 260)) for _ in range(40)] + [(5, 5), (7, 6)]
    got = {r.id: r.component for r in components.connected(spark.createDataFrame(edges, "a long, b long")).collect()}
    root = {}

    def find(i):
        while root.setdefault(i, i) != i:
            i = root[i]
        return i

    for a, b in edges:
        if a != b:
            x, y = find(a), find(b)
            root[max(x, y)] = min(x, y)
    assert got == {i: find(i) for i in root}
    assert components.connected(spark.createDataFrame([], "a long, b long")).count() == 0


# ------------------------------------------------------------------ passages


def test_repeated_passages(spark):
    rng = random.Random(2)
    say = lambda k: " ".join(rng.choice(WORDS) for _ in range(k))
    passages = [say(56) for _ in range(6)]
    texts = [f"{say(rng.randrange(80))} {p} {say(rng.randrange(80))}" for p in passages for _ in range(3)]
    clean = [say(rng.randrange(200)) for _ in range(40)] + ["", None, say(3)]
    d = docs(spark, texts + clean)
    found = passage_dedup.repeated_passages(d).collect()
    assert {r.doc_id for r in found} == set(range(len(texts)))
    assert {r.doc_id for r in found if r.removed} == {i for i in range(len(texts)) if i % 3}
    for r in found:  # occurrences are word ranges of the texts
        assert len(texts[r.doc_id].split()[r.at : r.end]) == 20
    spans = {r.doc_id: [(s.at, s.end) for s in r.spans] for r in passage_dedup.removal_spans(passage_dedup.repeated_passages(d)).collect()}
    assert all(b > a for s in spans.values() for a, b in s) and set(spans) == {i for i in range(len(texts)) if i % 3}
    assert passage_dedup.repeated_passages(d.limit(0)).count() == 0


def test_paragraph_pairs_are_verified_exactly(spark):
    rng = random.Random(4)
    base = [rng.choice(WORDS) for _ in range(300)]
    texts = [" ".join(base), " ".join(edited(rng, base, 0.02)), " ".join(edited(rng, base, 0.5))]
    found = passage_dedup.repeated_passages(docs(spark, texts)).collect()
    parts = {}
    for r in found:
        w = texts[r.doc_id].split()[r.at : r.end]
        parts.setdefault(r.component_id, []).append({tuple(w[i : i + 5]) for i in range(16)})
    for sets in parts.values():  # every member is linked with some other one
        for k, a in enumerate(sets):
            assert any(100 * len(a & b) >= 80 * len(a | b) for j, b in enumerate(sets) if j != k)


def test_short_texts_are_paragraphs(spark):
    rng = random.Random(3)
    say = lambda k: " ".join(rng.choice(WORDS) for _ in range(k))
    a, b = say(19), say(5)
    found = passage_dedup.repeated_passages(docs(spark, [a, b, a, say(12), "x y z w", "x y z w", b])).collect()
    assert sorted((r.doc_id, r.at, r.end, r.removed) for r in found) == [(0, 0, 19, False), (1, 0, 5, False), (2, 0, 19, True), (6, 0, 5, True)]


def test_removals_cover_the_whole_passage(spark):
    rng = random.Random(11)
    say = lambda k: [rng.choice(WORDS) for _ in range(k)]
    texts, places = [], []
    for length in [50, 56, 60, 90, 200] * 6:
        p = say(length)
        for copy in range(3):
            head = say(rng.randrange(80))
            texts.append(" ".join(head + p + say(rng.randrange(80))))
            places.append((len(head), len(head) + length, copy))
    found = passage_dedup.repeated_passages(docs(spark, texts))
    spans = {r.doc_id: [(s.at, s.end) for s in r.spans] for r in passage_dedup.removal_spans(found).collect()}
    for i, (at, end, copy) in enumerate(places):
        inside = sum(min(b, end) - max(a, at) for a, b in spans.get(i, []) if min(b, end) > max(a, at))
        outside = sum(b - a for a, b in spans.get(i, [])) - inside
        assert (inside, outside <= 1) == ((end - at if copy else 0), True)


def test_links_are_those_of_all_pairs(spark):
    """A shared start with varying tails makes mixed buckets; two of the tails are nearly equal."""
    rng = random.Random(8)
    texts = []
    for _ in range(12):
        start, tail = [rng.choice(WORDS) for _ in range(12)], [rng.choice(WORDS) for _ in range(40)]
        texts += [start + [rng.choice(WORDS) for _ in range(40)] for _ in range(10)]
        texts += [start + tail, start + tail[:7] + [rng.choice(WORDS)] + tail[8:], start[1:] + tail]
    loop = [rng.choice(WORDS) for _ in range(7)]  # repeated shingles make sets of unequal sizes
    texts += [[rng.choice(WORDS) for _ in range(k)] + loop * 2 + [rng.choice(WORDS) for _ in range(9)] for k in range(9)]
    d = docs(spark, [" ".join(t) for t in texts])
    cut = passage_dedup.cut_paragraphs(d, 20, 3, "print shingles").dropDuplicates(["print"]).collect()
    sets = sorted((r["print"], frozenset(r.shingles)) for r in cut)
    want, near, sizes = {p: p for p, _ in sets}, 0, {len(x) for _, x in sets}
    for i, (p, x) in enumerate(sets):
        for q, y in sets[i + 1 :]:
            if 100 * len(x & y) >= 80 * len(x | y):
                near += 1
                old, new = max(want[p], want[q]), min(want[p], want[q])
                want = {k: new if v == old else v for k, v in want.items()}
    assert near > 50 and len(sizes) > 1
    got = components.connected(passage_dedup.near_links(d, 20, 3, 80)).collect()
    assert {r.id: r.component for r in got} == {p: c for p, c in want.items() if list(want.values()).count(c) > 1}


def test_landmarks_are_dense_and_local():
    rng = np.random.default_rng(0)
    s = rng.integers(0, 2**63, 500, dtype=np.uint64)
    marks = passage_dedup.landmarks(s, np.array([0, 200, 500]), np.array([200, 300]), 20)
    want = set()
    for lo, hi in ((0, 200), (200, 500)):
        for a in range(lo - 19, hi):
            b = max(a, lo)
            want.add(b + int(s[b : min(a + 20, hi)].argmin()))
    assert set(marks.tolist()) == want


# ------------------------------------------------------------------ search


def brute_search(rows, k=10):
    v = {}
    for i, x in rows:
        if i is not None and x is not None and all(a is not None and np.isfinite(a) for a in x):
            v.setdefault(i, []).append([int(np.floor(1024 * float(np.float32(a)))) for a in x])
    out = []
    for q in v:
        if q % 100 == 0:
            for x in {tuple(y) for y in v[q]}:
                s = sorted((-sum(a * b for a, b in zip(x, y)), i) for i, ys in v.items() if i != q for y in ys)
                out += [(q, r + 1, i, -n) for r, (n, i) in enumerate(s[:k])]
    return sorted(out)


def test_search_against_brute_force(spark):
    rng = np.random.default_rng(5)
    rows = [(i, rng.normal(size=24).round(2).tolist()) for i in range(700)]
    rows += [(1000 + i, rows[0][1]) for i in range(40)]  # ties
    rows += [(2000, None), (2100, [1.0, None]), (2200, [float("nan")] * 24), (2300, [float("inf")] * 24), (None, rows[1][1]), (2400, [0.5, -0.5]), (2500, [])]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<float>").withColumn("v", F.lit(1)).withColumn("rank", F.lit(1))
    got = segment_topk.top_k(df, F.col("vec_id") % 100 == 0, query_block=4, row_block=150)
    assert sorted((r.query_id, r["rank"], r.vec_id, r.score) for r in got.collect()) == brute_search(rows)
    assert segment_topk.top_k(df.limit(0), F.col("vec_id") % 100 == 0).count() == 0


def test_bounds_hold_and_prune():
    rng = np.random.default_rng(6)
    a, b = rng.integers(-900, 900, (40, 37)), rng.integers(-900, 900, (60, 37))
    exact = a @ b.T
    last = None
    for parts in segment_topk.LEVELS:
        bound = segment_topk.segment_stats(a, parts) @ segment_topk.segment_stats(b, parts).T
        assert (bound + 1e-6 >= exact).all()
        last = bound if last is None else last
    centres = rng.normal(size=(30, 64)) * 300
    rows = (centres[rng.integers(30, size=6000)] + rng.normal(size=(6000, 64)) * 5 + np.repeat(rng.normal(size=(6000, 4)) * 300, 16, axis=1)).astype(np.int64)
    s = segment_topk.Search(np.arange(5), rows[:5], 10)
    for lo in range(0, 6000, 2000):
        s.add(np.arange(lo, lo + 2000), rows[lo : lo + 2000])
    assert s.products < 0.8 * 5 * 6000
    for q in range(5):
        score = rows @ rows[q]
        order = [i for i in np.lexsort((np.arange(6000), -score)) if i != q][:10]
        assert s.found[q].tolist() == order


# ------------------------------------------------------------------ pipeline


def test_pipeline_stages(spark):
    import corpus_pipeline as P

    sf = "/root/testdata/sf0.001"
    before = registry.table(spark, sf, "documents")
    sizes, now = [before.count()], before
    for name, stage in P.STAGES:
        now = stage(spark, now, sf).cache()
        sizes.append(now.count())
        if name != "sentencepiece":
            assert now.columns == before.columns
        if name == "decontamination":
            kept = now
        if name == "secrets":
            assert not [r for r in now.select("text").collect() if "AKIA" in (r.text or "") and len(r.text.split("AKIA")[1].split()[0]) >= 12]
            assert {r.doc_id for r in now.collect()} == {r.doc_id for r in kept.collect()}
    assert sizes == sorted(sizes, reverse=True) and sizes[-1] > 0.5 * sizes[0]
    ran = {r.doc_id: (r.n_tokens, r.ids_crc32) for r in P.run(spark, sf).collect()}
    assert ran == {r.doc_id: (r.n_tokens, r.ids_crc32) for r in now.collect()}


def test_pipeline_on_odd_rows(spark):
    import corpus_pipeline as P

    sf = "/root/testdata/sf0.001"
    schema = "doc_id long, text string, lang string, source string, n_chars long"
    rows = [(1, None, None, None, None), (2, "", "en", "s", 0), (None, "fine words here", "en", "s", 5), (3, "same " * 50, "en", "s", 1), (4, "same " * 50, "en", "s", 1)]
    now = spark.createDataFrame(rows, schema)
    for k, (_, stage) in enumerate(P.STAGES):
        now = stage(spark, now, sf)
        if k < 4:
            assert now.columns == ["doc_id", "text", "lang", "source", "n_chars"]
    assert sorted((r.doc_id or -1) for r in now.collect()) == [-1, 1, 2, 3]
    empty = spark.createDataFrame([], schema)
    for _, stage in P.STAGES:
        empty = stage(spark, empty, sf)
    assert empty.count() == 0


def test_pipeline_tells_texts_of_one_id_apart(spark):
    import corpus_pipeline as P

    a, b, c = "one text " * 3 + "here", "another text that two ids hold in full", "a third text that only this id holds"
    rows = [(1, a), (1, a), (2, b), (3, b), (3, c), (4, None), (4, ""), (4, None), (None, a), (None, a), (5, "alone"), (2, b)]
    d = spark.createDataFrame(rows, "doc_id long, text string").withColumn("row_id", F.lit(7))
    out = P.drop_near_duplicates(spark, d, "")
    assert out.columns == d.columns
    want = [(1, a), (2, b), (3, c), (4, None), (4, ""), (5, "alone"), (None, a), (None, a)]
    assert sorted(((r.doc_id, r.text) for r in out.collect()), key=repr) == sorted(want, key=repr)


def test_rows_of_one_id_share_a_component(spark):
    a, b, c = "one text " * 3 + "here", "another text that two ids hold in full", "a third text that only this id holds"
    rows = [(3, a), (5, a), (5, b), (7, b), (9, b), (9, b), (11, c), (11, None), (12, None)]
    d = spark.createDataFrame(rows, "doc_id long, text string")
    got = sorted((r.doc_id, r.component_id, r.kept) for r in D.near_duplicates(d, size=2).collect())
    want = [(3, 3), (5, 3), (5, 3), (7, 3), (9, 3), (9, 3), (11, 11), (11, 11), (12, 12)]
    assert got == [(i, c, i == c) for i, c in want]


def test_search_with_very_large_components(spark):
    rows = [(0, [1e12, -1e12]), (1, [1e12, 0.0]), (2, [1e17, 0.0]), (3, [-1e300, 0.0]), (4, [0.5, 0.5]), (100, [1e17, 1e17]), (5, [-1e17, -1e17])]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>")
    most = 2**63 - 1
    held = {i: [max(-most, min(most, int(np.floor(1024.0 * a)) if abs(1024.0 * a) < 2.0**63 else int(np.sign(a)) * most)) for a in x] for i, x in rows}
    want = []
    for q in (0, 100):
        s = sorted((-max(-most - 1, min(most, sum(a * b for a, b in zip(held[q], y)))), i) for i, y in held.items() if i != q)
        want += [(q, r + 1, i, -n) for r, (n, i) in enumerate(s)]
    got = segment_topk.top_k(df, F.col("vec_id") % 100 == 0).collect()
    assert sorted((r.query_id, r["rank"], r.vec_id, r.score) for r in got) == want
