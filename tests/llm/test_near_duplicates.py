"""Joins on similarity against brute force over all pairs."""

import itertools
import random

import pytest


def variants(seed=5, n=60):
    """Texts in families of copies and edits, with null, empty and short ones."""
    rng = random.Random(seed)
    words = [f"w{i}" for i in range(400)]
    out = [None, "", "  ", "...", "one", "one two", "One, two!", "a b c d", "a b c d e"]
    for _ in range(12):
        base = [rng.choice(words) for _ in range(rng.randrange(30, 120))]
        out.append(" ".join(base))
        for _ in range(rng.randrange(1, 8)):
            x = list(base)
            for _ in range(rng.randrange(0, 4)):
                x[rng.randrange(len(x))] = rng.choice(words)
            out.append(" ".join(x))
    out += [" ".join(rng.choice(words) for _ in range(50)) for _ in range(n - 40)]
    return out


def brute(texts, sets, threshold):
    """doc -> linked docs, and doc -> smallest doc reached."""
    links = {i: set() for i in range(len(texts))}
    for i, j in itertools.combinations(range(len(texts)), 2):
        a, b = sets[i], sets[j]
        if a and b and len(a & b) >= threshold * len(a | b):
            links[i].add(j)
            links[j].add(i)
    comp = list(range(len(texts)))
    moved = True
    while moved:
        moved = False
        for i, near in links.items():
            m = min([comp[i], *(comp[j] for j in near)])
            moved |= m != comp[i]
            comp[i] = m
    return links, comp


@pytest.mark.parametrize("seed", [1, 2])
def test_jaccard_join_is_brute_force(spark, seed):
    from mlcurate.llm import jaccard_join as j

    texts = variants(seed)
    links, comp = brute(texts, [j.shingles(t) for t in texts], 0.8)
    df = spark.createDataFrame([(i, t, "clash", 3) for i, t in enumerate(texts)], "doc_id long, text string, id string, n int").repartition(4)
    got = {r.doc_id: r for r in j.near_duplicates(df).collect()}
    assert got.keys() == links.keys()
    for i in links:
        assert got[i].n_links == len(links[i]), (i, texts[i])
        assert got[i].group_id == comp[i]
        same = [k for k, t in enumerate(texts) if (t or "") == (texts[i] or "")]
        assert (got[i].class_id, got[i].n_copies) == (same[0], len(same))
    kept = j.keep_one(df)
    assert kept.columns == df.columns
    assert sorted(r.doc_id for r in kept.collect()) == sorted({comp[i] for i in links})


def test_jaccard_join_in_small_blocks(spark, monkeypatch):
    """A family of texts at all distances, dealt into many blocks, some of them empty."""
    from mlcurate.llm import jaccard_join as j

    rng = random.Random(9)
    words = [f"w{i}" for i in range(300)]
    base = [rng.choice(words) for _ in range(80)]
    texts = []
    for _ in range(90):
        x = list(base)
        for _ in range(rng.randrange(0, 6)):
            x[rng.randrange(len(x))] = rng.choice(words)
        texts.append(" ".join(x))
    monkeypatch.setattr(j, "BLOCK_TEXTS", 7)
    monkeypatch.setattr(j, "BLOCK_CHARS", 3500)
    links, comp = brute(texts, [j.shingles(t) for t in texts], 0.8)
    got = {r.doc_id: r for r in j.near_duplicates(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")).collect()}
    assert {i: got[i].n_links for i in got} == {i: len(v) for i, v in links.items()}
    assert [got[i].group_id for i in range(len(texts))] == comp


def test_jaccard_join_of_the_documents(spark):
    from mlcurate.llm import jaccard_join as j

    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    rows = {r.doc_id: r.text for r in docs.collect()}
    inv, sets = {}, {k: j.shingles(t) for k, t in rows.items()}
    for k, s in sets.items():
        for x in s:
            inv.setdefault(x, []).append(k)
    count = {}
    for ks in inv.values():
        for p in itertools.combinations(ks, 2):
            count[p] = count.get(p, 0) + 1
    want = dict.fromkeys(rows, 0)
    for (a, b), n in count.items():
        if n >= 0.8 * (len(sets[a]) + len(sets[b]) - n):
            want[a] += 1
            want[b] += 1
    assert {r.doc_id: r.n_links for r in j.near_duplicates(docs).collect()} == want


def test_jaccard_join_edges(spark):
    from mlcurate.llm import jaccard_join as j

    assert j.near_duplicates(spark.createDataFrame([], "doc_id long, text string")).count() == 0
    got = j.near_duplicates(spark.createDataFrame([(None, "a b"), (3, "a b"), (3, "a b"), (4, None)], "doc_id long, text string")).collect()
    assert sorted((r.doc_id or -1, r.class_id, r.group_id) for r in got) == [(-1, None, None), (3, 3, 3), (3, 3, 3), (4, 4, 4)]


def test_keep_one_by_text(spark):
    """Texts under one doc_id are documents of their own: no unrelated one goes, and one of each group stays."""
    from mlcurate.llm import jaccard_join as j

    a, b, c = (" ".join(f"{x}{i}" for i in range(40)) for x in "abc")
    near = a + " more"
    rows = [(1, a, 1), (5, a, 2), (5, b, 3), (1, c, 4), (5, near, 5), (None, a, 6), (9, None, 7), (9, "", 8), (2, b, 9)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, h1 int")
    kept = j.keep_one(docs)
    assert kept.columns == docs.columns
    assert sorted(r.h1 for r in kept.collect()) == [1, 4, 6, 7, 8, 9]
    got = {(r.doc_id, r.n_links, r.group_id) for r in j.near_duplicates(docs.where("h1 in (1, 2, 4, 5)")).collect()}
    assert got == {(1, 2, 1), (5, 2, 1), (1, 0, 1)}
    assert j.keep_one(docs.limit(0)).count() == 0


def test_pruning_keeps_what_reaches_the_threshold():
    import numpy as np

    from mlcurate.llm import jaccard_join as j

    rng = np.random.default_rng(0)
    a = rng.integers(0, 1 << 30, (4000, j.HASHES))
    hit = rng.random((4000, j.HASHES)) < np.repeat([0.85, 0.3], 2000)[:, None]
    b = np.where(hit, a, a + 1)
    alive = j.surviving(a, b, j.least_agreeing(0.8))
    assert (alive < 2000).sum() == 2000 and (alive >= 2000).sum() < 5


@pytest.mark.parametrize("algo", ["star", "minlabel"])
def test_components(spark, algo):
    from mlcurate.dedup.components import connected

    rng = random.Random(2)
    edges = [(i, i + 1) for i in range(100, 140)] + [(rng.randrange(1000, 1200), rng.randrange(1000, 1200)) for _ in range(120)] + [(7, i) for i in range(8, 60)] + [(5, 5), (None, 4)]
    want = {}
    for a, b in edges:
        if a is not None and a != b:
            want.setdefault(a, {a}).add(b)
            want.setdefault(b, {b}).add(a)
    comp = {k: k for k in want}
    for _ in range(200):
        comp = {k: min(comp[x] for x in v) for k, v in want.items()}
    got = {r.id: r.comp for r in connected(spark.createDataFrame(edges, "src long, dst long"), algo).collect()}
    assert got == comp
