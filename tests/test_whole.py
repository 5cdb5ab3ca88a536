"""Nothing is cut off: long pages, rare words, and folds of identification models."""


def test_parser_reads_whole_pages():
    from mlcurate.functions import html

    page = "<title>t</title>" + "<p>word word</p>" * 400_000 + "<p>the end</p>"
    assert len(page) > 5_000_000
    assert html.read(page)[1].endswith("\nthe end")


def merges_by_hand(counts, merges):
    from collections import Counter

    words, out = {tuple(w): n for w, n in counts.items()}, []
    while len(out) < merges:
        pairs = Counter()
        for w, n in words.items():
            for p in zip(w, w[1:], strict=False):
                pairs[p] += n
        if not pairs:
            break
        a, b = min(pairs, key=lambda p: (-pairs[p], p))
        out.append((a, b))
        nxt = Counter()
        for w, n in words.items():
            s = []
            for x in w:
                if s and s[-1] == a and x == b and not (a == b and len(s) > 1 and s[-1] != a):
                    s[-1] = a + b
                else:
                    s.append(x)
            nxt[tuple(s)] += n
        words = nxt
    return out


def test_merges_count_all_words(spark):
    import random
    from collections import Counter

    from mlcurate.operators import subword

    rng = random.Random(5)
    rare = ["b" + "".join(rng.choice("cdefghij") for _ in range(8)) for _ in range(52_000)] + ["xy" + "".join(rng.choice("klmn") for _ in range(8)) for _ in range(20_000)]
    common = ["".join(rng.choice("klmnopaa") for _ in range(rng.randrange(1, 7))) for _ in range(5000)] * 2
    docs = spark.createDataFrame([(i, " ".join(x)) for i, x in enumerate([rare, common])], "doc_id long, text string")
    got = subword.train_bpe(docs, 20)
    assert got == merges_by_hand(Counter(rare + common), 20)
    assert got[0] == ("x", "y")


def test_folds(spark, monkeypatch):
    from pyspark.sql import functions as F

    from mlcurate.io import table
    from mlcurate.operators import lid
    from mlcurate.plans import pipeline as P
    from mlcurate.workloads import lid as workload
    from mlcurate.workloads import pipelines

    sf, seen = "/root/testdata/sf0.001", []
    monkeypatch.setattr(lid.NgramBayes, "fit", lambda self, docs: seen.append(docs) or self)
    monkeypatch.setattr(P, "run", lambda *a: None)
    pipelines.stages(spark, sf, None)
    assert seen[0].count() == table(spark, sf, "documents").count()
    monkeypatch.setattr(lid.HashedSoftmax, "fit", lambda self, docs: seen.append(docs) or self)
    monkeypatch.setattr(lid.HashedSoftmax, "predict", lambda self, docs: seen.append(docs) or docs.select("doc_id", F.col("lang").alias("label")))
    assert all(r.recall == 1 for r in workload.w_lid_softmax(spark, sf).collect())
    assert seen[1].join(seen[2], "doc_id").isEmpty()
