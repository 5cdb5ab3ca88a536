"""Line dedup, decontamination, toxicity and the pipeline against brute force and planted cases."""

import random
import re
import zlib

import pytest


def lines_by_brute_force(rows, threshold=0.8, chars=5):
    """doc -> text left, comparing every pair of distinct lines."""
    first = {}
    for k, t in sorted(rows, key=lambda r: r[0]):
        for i, line in enumerate((t or "").split("\n")):
            p = line.strip(" ").lower()
            if p:
                first.setdefault(p, (k, i))
    names = list(first)
    sets = [{p[i : i + chars] for i in range(len(p) - chars + 1)} or {p} for p in names]
    comp = list(range(len(names)))

    def root(i):
        while comp[i] != i:
            i = comp[i]
        return i

    for i in range(len(names)):
        for j in range(i):
            if len(sets[i] & sets[j]) >= threshold * len(sets[i] | sets[j]) - 1e-9:
                a, b = root(i), root(j)
                comp[max(a, b)] = min(a, b)
    kept = {}
    for i, p in enumerate(names):
        r = root(i)
        kept[r] = min(kept.get(r, first[p]), first[p])
    stays = set(kept.values())
    out = {}
    for k, t in rows:
        out[k] = t if t is None else "\n".join(x for i, x in enumerate(t.split("\n")) if not x.strip(" ") or (k, i) in stays)
    return out


def noisy_lines(seed):
    rng = random.Random(seed)
    words = ["".join(rng.choice("abcdefghij") for _ in range(rng.randrange(2, 9))) for _ in range(300)]
    pool = [" ".join(rng.choice(words) for _ in range(rng.choice([1, 2, 4, 8, 12, 13, 14, 15, 16, 30, 60]))) for _ in range(60)]
    rows = []
    for k in range(60):
        lines = []
        for _ in range(rng.randrange(0, 7)):
            w = rng.choice(pool).split()
            if rng.random() < 0.5:
                w[rng.randrange(len(w))] = rng.choice(words)
            x = " ".join(w)
            lines.append(rng.choice([x, x, x.upper(), "  " + x, "", x + "."]))
        rows.append((k, "\n".join(lines)))
    return [*rows, (60, None), (61, ""), (62, "\n\n"), (63, "ab"), (64, "AB\nab \nabc"), (65, "x" * 5000 + "\n" + "x" * 5001)]


@pytest.mark.parametrize("seed", [1, 2])
def test_line_dedup_is_brute_force(spark, seed):
    from mlcurate.llm import line_dedup as d

    rows = noisy_lines(seed)
    df = spark.createDataFrame([(k, t, "clash", 1) for k, t in rows], "doc_id long, text string, key string, pos int").repartition(4)
    got = d.drop_lines(df)
    assert got.columns == df.columns
    assert {r.doc_id: r.text for r in got.collect()} == lines_by_brute_force(rows)


def test_line_dedup_edges(spark):
    from mlcurate.llm import line_dedup as d

    assert d.report(spark.createDataFrame([], "doc_id long, text string")).count() == 0
    rows = [(5, "some line here\nother words there"), (5, "some line here\nother words there"), (None, "some line here")]
    got = sorted((r.doc_id or -1, r.n_lines, r.n_dropped, r.text) for r in d.report(spark.createDataFrame(rows, "doc_id long, text string")).collect())
    assert got == [(-1, 1, 0, "some line here"), (5, 2, 1, "other words there"), (5, 2, 1, "other words there")]


def grams(text, n=5):
    w = re.findall(r"[^\W_]+", (text or "").lower())
    return [tuple(w[i : i + n]) for i in range(max(len(w) - n + 1, 1))] if w else [], w


def weighted(a, b):
    from collections import Counter

    a, b = Counter(a), Counter(b)
    return sum((a & b).values()) / max(1, sum((a | b).values()))


def items_by_brute_force(rows, items, threshold=0.8):
    """doc, item -> best similarity of any window at any place."""
    out = {}
    for k, t in rows:
        w = grams(t)[1]
        for i, s in items:
            g, v = grams(s)
            if not v or not w or not set(g) & set(grams(t)[0]):
                continue
            best = max(weighted(grams(" ".join(w[x : x + len(v)]))[0], g) for x in range(max(len(w) - len(v) + 1, 1)))
            if best >= threshold - 1e-12:
                out[k, i] = round(best, 6)
    return out


def test_decontamination_is_brute_force(spark):
    from mlcurate.llm import decontaminate as d

    rng = random.Random(4)
    words = [f"w{i}" for i in range(120)]
    items = [(i, " ".join(rng.choice(words) for _ in range(rng.choice([1, 3, 5, 9, 20, 20, 45])))) for i in range(40)] + [(40, None), (41, "..."), (42, "A b A b A b A b")]
    rows = []
    for k in range(150):
        w = [rng.choice(words) for _ in range(rng.randrange(0, 80))]
        for _ in range(rng.randrange(0, 3)):
            x = (rng.choice(items[:40])[1]).split()
            for _ in range(rng.choice([0, 0, 1, 2])):
                at = rng.randrange(len(x))
                x[at : at + rng.randrange(0, 2)] = [rng.choice(words)]
            at = rng.randrange(len(w) + 1)
            w[at:at] = x
        rows.append((k, rng.choice([" ", ", ", "\n"]).join(w)))
    rows += [(150, None), (151, ""), (152, "a B a b, a b a b"), (153, "a b a b a b a b a b a b a b")]
    docs = spark.createDataFrame([(k, t, "clash", 1) for k, t in rows], "doc_id long, text string, key string, item_id int").repartition(3)
    bench = spark.createDataFrame(items, "item_id long, text string")
    got = {(r.doc_id, r.item_id): r.similarity for r in d.search(docs, bench).collect()}
    want = items_by_brute_force(rows, items)
    assert got == want
    left = {r.doc_id for r in d.clean(docs, bench).collect()}
    assert left == {k for k, _ in rows} - {k for k, _ in want}


def test_decontamination_edges(spark):
    from mlcurate.llm import decontaminate as d

    none, bench = spark.createDataFrame([], "doc_id long, text string"), spark.createDataFrame([(1, "a b c d e f")], "item_id long, text string")
    assert d.search(none, bench).count() == 0
    docs = spark.createDataFrame([(None, "x A b c d, e f y"), (2, "a b c d e f"), (2, "a b c d e f")], "doc_id long, text string")
    assert sorted((r.doc_id or -1, r.similarity) for r in d.search(docs, bench).collect()) == [(-1, 1.0), (2, 1.0)]
    assert d.search(docs, bench.limit(0)).count() == 0


def test_simhash_blocks_miss_nothing_and_prune(spark):
    from mlcurate.llm import decontaminate as d

    rng = random.Random(1)
    near = set(d._flips(d.RADIUS))
    passed = 0
    for _ in range(3000):
        p, q = rng.getrandbits(d.BITS), rng.getrandbits(d.BITS)
        x = p
        for b in rng.sample(range(d.BITS), d.RADIUS):
            x ^= 1 << b
        blocks = lambda y: [y >> 16 * k & 0xFFFF for k in range(d.BLOCKS)]
        assert any(a ^ b in near for a, b in zip(blocks(p), blocks(x), strict=True))
        passed += any(a ^ b in near for a, b in zip(blocks(p), blocks(q), strict=True))
    assert passed < 0.2 * 3000  # unlike fingerprints that share a block within reach
    known = spark.createDataFrame([(1, 9, [0, 0, 0, 0])], "item_id long, n int, print array<long>")
    keys = {r.block for r in d._item_keys(known, d.RADIUS).collect()}
    assert keys == {(k << 16) | f for k in range(d.BLOCKS) for f in near}


def test_simhash_is_the_majority_of_bits(spark):
    from pyspark.sql import functions as F

    from mlcurate.llm import decontaminate as d

    rng = random.Random(2)
    sets = [[f"w{rng.randrange(99)}" for _ in range(n)] for n in (1, 4, 31)]
    df = spark.createDataFrame([(h,) for h in sets], "x array<string>").coalesce(1)
    got = [r[0] for r in df.select(d.simhash(F.col("x"))).collect()]
    hashed = [r[0] for r in df.select(F.transform("x", lambda x: F.array(*[F.xxhash64(F.lit(k), x) for k in range(4)]))).collect()]
    for h, g in zip(hashed, got, strict=True):
        for k in range(4):
            assert g[k] & ((1 << 64) - 1) == sum((sum(1 if x[k] >> b & 1 else -1 for x in h) > 0) << b for b in range(64))


def test_simhash_radius_keeps_what_reaches_the_threshold(spark):
    """Recall of the radius at the threshold itself, over sets of all sizes that are given a fingerprint."""
    from pyspark.sql import functions as F

    from mlcurate.llm import decontaminate as d

    rng = random.Random(3)
    rows = []
    for _ in range(600):
        shared = 8 * rng.randrange(2, 8)
        a = [f"s{rng.getrandbits(40)}" for _ in range(shared)]
        rows.append((a + [f"a{rng.getrandbits(40)}" for _ in range(shared // 8)], a + [f"b{rng.getrandbits(40)}" for _ in range(shared // 8)]))
    df = spark.createDataFrame(rows, "a array<string>, b array<string>")
    far = [r[0] for r in df.select(d.distance(d.simhash(F.col("a")), d.simhash(F.col("b")))).collect()]
    assert sum(x <= d.RADIUS for x in far) >= 0.995 * len(far)


def test_decontamination_by_row(spark):
    """Rows under one doc_id and under none are judged by their own texts; very long texts are searched whole."""
    from mlcurate.llm import decontaminate as d

    item = " ".join(f"w{i}" for i in range(30))
    long = " ".join(f"z{i}" for i in range(60_000)) + " " + item
    rows = [(5, item, 1), (5, "something else", 2), (None, f"a {item} b", 3), (None, "clean", 4), (7, long, 5), (8, None, 6), (9, "", 7)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, __key int")
    left = d.clean(docs, spark.createDataFrame([(1, item)], "item_id long, text string"))
    assert left.columns == docs.columns
    assert sorted(r["__key"] for r in left.collect()) == [2, 4, 6, 7]


def test_toxicity_finds_planted_words(spark):
    from mlcurate.llm import toxicity as x

    rng = random.Random(3)
    words = ["".join(rng.choice("aeioulnrst") for _ in range(rng.randrange(2, 8))) for _ in range(500)]
    rows, labels = [], []
    for k in range(600):
        w = [rng.choice(words) for _ in range(rng.choice([5, 40, 200]))]
        bad = k % 3 == 0
        if bad:
            w[rng.randrange(len(w))] = "zukk" + rng.choice(words)
        rows.append((k, " ".join(w), rng.random()))
        labels.append((k, 1, int(bad)))
    rows += [(9001, None, 0.0), (9002, "", 0.0), (9003, " \n ", 0.0), (None, "zukkaia", 0.0)]
    docs, lab = spark.createDataFrame(rows, "doc_id long, text string, score double"), spark.createDataFrame(labels, "doc_id long, quality int, toxic int")
    got = {r.doc_id: r for r in x.score(docs, x.fit(docs, lab)).collect()}
    held = [k for k in range(600) if zlib.crc32(str(k).encode()) % 5 == 0]
    assert all(got[k].held_out == (zlib.crc32(str(k).encode()) % 5 == 0) for k in range(600))
    right = sum(got[k].predicted == int(k % 3 == 0) for k in held)
    assert right >= 0.95 * len(held)
    assert got[9001].score == got[9002].score == got[9003].score == 0 and got[None].held_out and got[None].predicted == 1
    assert x.fit(docs, lab.where("toxic = 0")) is None
    odd = docs.withColumns({"predicted": docs.score, "k_text": docs.text})  # names that clash with those of results
    left = x.clean(odd, x.fit(docs, lab))
    assert left.columns == odd.columns and {r.doc_id for r in left.collect()} == {k for k, r in got.items() if not r.predicted}
    assert {r.predicted for r in x.score(docs, None).collect()} == {0}
    assert x.score(docs.limit(0), None).count() == 0


def test_toxicity_on_held_out_labels(spark):
    """Rows of the given tables whose labels were never learnt from."""
    from mlcurate.llm import toxicity as x

    docs, labels = (spark.read.parquet(f"/root/testdata/sf0.1/{t}.parquet") for t in ("documents", "labels"))
    real = {r.doc_id: r.toxic for r in labels.where("toxic is not null").collect()}
    rows = [(r.predicted, real[r.doc_id]) for r in x.score(docs, x.fit(docs, labels)).collect() if r.held_out and r.doc_id in real]
    found, toxic = sum(p for p, y in rows if y), sum(y for _, y in rows)
    flagged = sum(p for p, y in rows if not y)
    print(f"held out: {found} of {toxic} toxic found, {flagged} of {len(rows) - toxic} clean flagged")
    assert found >= 0.85 * toxic and flagged <= 0.02 * (len(rows) - toxic)


def test_toxicity_gradients():
    import numpy as np

    from mlcurate.llm import toxicity as x

    net, rng = x.Network(1), np.random.default_rng(0)
    net.p = {k: v.astype(np.float64) for k, v in net.p.items()}
    px = rng.standard_normal((7, 4, 6 * x.HIDDEN))
    real = (np.arange(7)[:, None] < np.array([7, 5, 1, 3])).astype(float)[..., None]
    want = np.array([1.0, 0, 1, 0])

    def loss():
        y = net.logits(px, real)
        return np.mean(np.log1p(np.exp(-y)) * want + np.log1p(np.exp(y)) * (1 - want))

    g, dpx, _ = net.gradients(px, real, want)
    for name in ("hf", "hb", "att", "att_b", "att_v", "out", "out_b"):
        p = net.p[name].reshape(-1)
        for i in range(0, p.size, max(1, p.size // 5)):
            keep = p[i]
            p[i] = keep + 1e-4
            up = loss()
            p[i] = keep - 1e-4
            down = loss()
            p[i] = keep
            assert abs((up - down) / 2e-4 - g[name].reshape(-1)[i]) < 2e-3, name
    for at in [(0, 0, 3), (6, 0, 30), (2, 1, 10), (4, 1, 40), (0, 2, 47)]:
        keep = px[at]
        px[at] = keep + 1e-4
        up = loss()
        px[at] = keep - 1e-4
        down = loss()
        px[at] = keep
        assert abs((up - down) / 2e-4 - dpx[at]) < 2e-3


def test_line_dedup_tries_all_pairs_of_a_hot_template(spark):
    from mlcurate.llm import line_dedup as d

    rng = random.Random(3)
    letters = lambda n: "".join(rng.choice("abcdefghijklmnopqrstuvwxyz") for _ in range(n))
    opener, lines = letters(50), []
    for _ in range(200):  # about 0.86 alike in a pair, 0.74 across
        middle = letters(4)
        lines += [opener + middle + letters(4), opener + middle + letters(4)]
    rng.shuffle(lines)
    rows = list(enumerate(lines))
    got = d.drop_lines(spark.createDataFrame(rows, "doc_id long, text string"))
    assert {r.doc_id: r.text for r in got.collect()} == lines_by_brute_force(rows)


def test_line_dedup_of_long_lines_without_spaces(spark):
    from mlcurate.llm import line_dedup as d

    rng = random.Random(7)
    rows = [(0, "-" * 50), (1, "-" * 120), (2, "ab" * 20), (3, "ab" * 3000)]
    for n in (90, 130, 160, 300, 2000):
        x = "".join(chr(0x4E00 + rng.randrange(3000)) for _ in range(n))
        rows += [(n, x), (n + 1, "甲乙丙丁戊己" + x[6:]), (n + 2, x + "甲" + x[: n // 16])]
    got = d.drop_lines(spark.createDataFrame(rows, "doc_id long, text string"))
    assert {r.doc_id: r.text for r in got.collect()} == lines_by_brute_force(rows)


@pytest.mark.parametrize("letters", [6, 20, 40])
def test_line_dedup_recall_on_long_lines(spark, letters):
    """Pairs of long lines at 0.82 and above whose edits stand at the start of words."""
    from mlcurate.llm import line_dedup as d

    rng = random.Random(letters)
    word = lambda: "".join(rng.choice("abcdefghijklmnopqrstuvwxyz") for _ in range(letters))
    rows, grams_of = [], lambda x: {x[i : i + 5] for i in range(len(x) - 4)}
    for k in range(60):
        w = [word() for _ in range(max(6, 160 // letters))]
        line, v = " ".join(w), list(w)
        for i in rng.sample(range(len(w)), len(w)):
            changed = list(v)
            changed[i] = rng.choice("0123456789") + w[i][1:]
            a, b = grams_of(line), grams_of(" ".join(changed))
            if len(a & b) < 0.82 * len(a | b):
                break
            v = changed
        rows += [(2 * k, line), (2 * k + 1, " ".join(v))]
    got = {r.doc_id: r.text for r in d.drop_lines(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got == lines_by_brute_force(rows)


def test_line_dedup_deals_parts_one_after_the_other(spark, monkeypatch):
    """Shuffles that carry bucket rows or signatures hold a part of the rows at once, and parts lose no pair."""
    from mlcurate.llm import line_dedup as d

    sizes = {"buckets": [], "likely": [], "met": []}
    for module in (d, d.buckets):
        real = module.settle
        monkeypatch.setattr(module, "settle", lambda df, name, real=real: (sizes.get(name, []).append(1), real(df, name))[1])
    monkeypatch.setattr(d, "PAIRS_AT_ONCE", 10)
    monkeypatch.setattr(d, "ROWS_AT_ONCE", 10)
    monkeypatch.setattr(d.buckets, "MOST_PASSES", 3)
    rows = noisy_lines(4)
    got = d.drop_lines(spark.createDataFrame(rows, "doc_id long, text string"))
    assert {r.doc_id: r.text for r in got.collect()} == lines_by_brute_force(rows)
    n = {k: len(v) for k, v in sizes.items()}
    assert n["buckets"] == d.BANDS // d.BANDS_AT_ONCE + 1 and n["likely"] >= 4 and n["met"] >= 1, n


def test_line_dedup_bands_meet_at_the_threshold_and_not_between_unlike_lines(spark):
    """Lines of one vocabulary, about 0.1 alike, hardly share buckets (31 of these pairs do; 663 did with 20 bands of 4 bins); pairs at 0.8 do."""
    import numpy as np

    from mlcurate.llm import line_dedup as d

    rng = np.random.default_rng(1)
    agree = rng.random((200_000, d.LONGS, d.LANES)) < 0.8
    met = np.zeros(len(agree), bool)
    for band in d.bands():
        met |= np.all([agree[:, w, r] for w, mask in band for r in range(d.LANES) if mask >> d.LANE * r & 1], axis=0)
    assert len(d.bands()) == d.BANDS and (~met).mean() < 1e-4
    say = random.Random(8)
    words = ["".join(say.choice("aeioulnrst") for _ in range(say.randrange(2, 7))) for _ in range(150)]
    rows = [(k, " ".join(say.choice(words) for _ in range(60))) for k in range(1500)]
    base = d._keyed(spark.createDataFrame(rows, "doc_id long, text string"))
    every, _ = d._signed(base, d.classes(base))
    assert d.buckets.star(d.buckets.members(d.band_rows(every))).count() < 150
