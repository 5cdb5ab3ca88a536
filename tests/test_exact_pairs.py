"""Exact pairs against brute force; copies are never paired by shingle."""

import random


def test_exact_pairs_are_brute_force(spark, monkeypatch):
    from mlcurate.dedup import minhash as H

    rng = random.Random(2)
    base = [[rng.choice("abcdefghijklmnopq") for _ in range(40)] for _ in range(5)]
    rows = []
    for i in range(60):
        w = list(rng.choice(base))
        for _ in range(rng.choice([0, 0, 0, 1, 3])):
            w[rng.randrange(40)] = "z"
        rows.append((i, rng.choice("xy"), " ".join(w)))
    rows += [(60, None, rows[0][2]), (61, "x", ""), (62, "x", None), (63, "x", "one"), (64, "x", "One!")]
    df = spark.createDataFrame(rows, "doc_id long, lang string, text string")
    sets = {(r.doc_id, r.lang): set(r.g) for r in df.select("doc_id", "lang", H.F.transform(H._grams(df, H.Config()), lambda s: H._hash(s, H.Config())).alias("g")).collect() if r.g and r.lang}
    want = {(a, b): round(len(s & t) / len(s | t), 9) for (a, k), s in sets.items() for (b, j), t in sets.items() if a < b and k == j and len(s & t) >= 0.5 * len(s | t)}
    made, real = [], H.settle
    monkeypatch.setattr(H, "settle", lambda d, n: (lambda out: (made.append(out.count()) if n == "shared" else None, out)[1])(real(d, n)))
    got = [(r.a, r.b, round(r.sim, 9)) for r in H.exact_pairs(df, 0.5).collect()]
    assert len(got) == len(want) and {(a, b): s for a, b, s in got} == want
    assert len(made) == H.PASSES and sum(made) < sum(map(len, sets.values()))
