"""Pairs meet by the beginnings of their sets, and none at the threshold is lost."""

import random

import pytest


@pytest.mark.parametrize("least", [0.5, 0.8])
def test_beginnings_lose_no_pair_and_join_few(spark, monkeypatch, least):
    from mlcurate.dedup import minhash as H

    rng = random.Random(7)
    common = ["".join(rng.choice("abcdefgh") for _ in range(4)) for _ in range(30)]
    texts = []
    for _ in range(12):
        base = [f"w{rng.randrange(10**6)}" for _ in range(rng.choice([3, 8, 60]))]
        for _ in range(6):
            w = list(base)
            for _ in range(rng.randrange(4)):
                w[rng.randrange(len(w))] = f"x{rng.randrange(10**6)}"
            texts.append(" ".join(w[: rng.randrange(len(w) // 2, len(w)) + 1] + common))
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").withColumn("lang", H.F.lit("x"))
    sets = {r.doc_id: set(r.g) for r in df.select("doc_id", H.F.transform(H._grams(df, H.Config()), lambda s: H._hash(s, H.Config())).alias("g")).collect()}
    sim = {(a, b): len(s & t) / len(s | t) for a, s in sets.items() for b, t in sets.items() if a < b}
    made, real = {}, H.settle
    monkeypatch.setattr(H, "settle", lambda d, n: (lambda out: (made.update({n: made.get(n, 0) + out.count()}), out)[1])(real(d, n)))
    monkeypatch.setattr(H, "AT_ONCE", 40_000)
    got = {(r.a, r.b): round(r.sim, 9) for r in H.exact_pairs(df, least).collect()}
    assert got == {p: round(s, 9) for p, s in sim.items() if s >= least} and got
    met = sum(1 for (a, b) in sim if sets[a] & sets[b])
    assert met > 2000 and (least < 0.5 or made["candidates"] < 0.5 * met)


def test_recall_takes_each_pair_once(spark):
    from mlcurate.dedup import minhash as H

    pairs = spark.createDataFrame([(1, 2, 0.95), (1, 3, 0.95), (2, 9, 0.55), (3, 4, 1.0)], "a long, b long, sim double")
    bands = spark.createDataFrame([(1, 0, "p"), (2, 0, "p"), (1, 1, "q"), (2, 1, "q"), (3, 1, "p"), (3, 2, "z"), (4, 2, "z")], "doc_id long, band int, bkey string")
    assert sorted(map(tuple, H.recall(pairs, bands).collect())) == [(0.5, 1, 0), (0.9, 2, 1), (1.0, 1, 1)]
