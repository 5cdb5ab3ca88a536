"""Words, shingles, metrics and stopwords follow the tokenizer of each row's language."""

from pyspark.sql import functions as F


def test_unspaced_words(spark):
    from mlcurate.functions import words as W

    rows = [("zh", "我喜歡 Spark4 和詞"), ("cmn_Hani", "詞典"), ("en", "two 詞典 words"), ("th", "กำ"), (None, "詞典 x"), ("ko", "두 단어"), ("zh", None), ("zh", "")]
    df = spark.createDataFrame(rows, "lang string, text string")
    got = [r.w for r in df.select(W.words_in(F.col("text"), F.col("lang")).alias("w")).collect()]
    assert got == [["我", "喜", "歡", "spark4", "和", "詞"], ["詞", "典"], ["two", "詞典", "words"], ["ก", "ำ"], ["詞典", "x"], ["두", "단어"], [], []]
    assert df.select(W.tokens_in(F.lit("詞,典"), F.lit("zh")).alias("t")).first().t == ["詞", ",", "典"]


def test_own_tokenizer(spark):
    from mlcurate.functions import words as W

    W.register("pairs", W.longest_match(["詞典"]))
    before = W.BY_LANGUAGE["zh"]
    try:
        W.assign("zh", "pairs")
        df = spark.createDataFrame([("zh", "詞典詞")], "lang string, text string")
        assert df.select(W.words_in(F.col("text"), F.col("lang")).alias("w")).first().w == ["詞典", "詞"]
    finally:
        W.assign("zh", before)


def test_unspaced_near_copies_share_a_cluster(spark):
    import random

    from mlcurate.dedup import minhash

    rng = random.Random(3)
    text = "".join(chr(0x4E00 + rng.randrange(3000)) for _ in range(400))
    other = "".join(chr(0x4E00 + rng.randrange(3000)) for _ in range(400))
    rows = [(1, "zh", text), (2, "zh", text[:200] + "詞" + text[201:]), (3, "zh", other), (4, "zh", ""), (5, "zh", None)]
    got = {r.doc_id: r.comp for r in minhash.clusters(spark.createDataFrame(rows, "doc_id long, lang string, text string")).collect()}
    assert got[1] == got[2] == 1 and got[3] == 3


def test_signature_is_the_minimum_of_every_function(spark):
    import numpy as np

    from mlcurate.dedup import minhash

    cfg = minhash.Config()
    a, b = (np.array(c, np.int64) for c in zip(*cfg.coefficients))
    g = np.random.default_rng(1).integers(0, 1 << 28, 2 * minhash.SLICE + 5)
    assert minhash.minima(g, a, b).tolist() == [min((int(x) * i + j) % minhash.PRIME for x in g) for i, j in zip(a.tolist(), b.tolist())]
    df = spark.createDataFrame([(1, "en", "one two three four five six"), (2, "en", ""), (3, "en", None), (4, "en", "one")], "doc_id long, lang string, text string")
    for family in ("affine31", "xx"):
        s = {r.doc_id: r.sig for r in minhash.signatures(df, minhash.Config(family=family)).collect()}
        assert sorted(s) == [1, 4] and all(len(x) == 112 for x in s.values())


def test_repeats_weigh_in_bigrams(spark):
    from mlcurate.operators import reports

    train = [(1, "en", "a b a b", 3), (2, "en", "a c a c", 1)]
    flat = [(10 * i + j, lang, t, 1) for i, lang, t, k in train for j in range(k)]
    cols = "doc_id long, lang string, text string, n long"
    held = spark.createDataFrame([(99, "en", "a b c a")], "doc_id long, lang string, text string")
    one = reports.bigram_entropy(spark.createDataFrame(train, cols), held, weight="n").collect()
    assert one == reports.bigram_entropy(spark.createDataFrame(flat, cols), held).collect()


def test_split_with_many_copies_stays_within_its_size(spark):
    from mlcurate.operators import reports

    text = F.when(F.col("id") < 600, F.lit("the same")).otherwise(F.concat(F.lit("text "), "id"))
    docs = spark.range(2000).select(F.col("id").alias("doc_id"), F.lit("x").alias("lang"), text.alias("text"))
    for rate in (0.01, 0.2, 0.5):
        parts = reports.train_test(docs, rate=rate).join(docs, "doc_id")
        assert parts.count() == 2000 and parts.where("part = 'test'").count() <= 2000 * rate
        assert parts.where("text = 'the same'").select("part").distinct().count() == 1


def test_english_leaves_first_and_hands_set_cuts(spark):
    from mlcurate.plans import pipeline as P
    from mlcurate.workloads import pipelines

    docs, model, clean = pipelines.inputs(spark, "/root/testdata/sf0.001")
    assert set(model.largest(0.5)) < set(model.labels) and model.largest(1.0)[0] == "en"
    s = P.run(docs, model, clean, P.hand_tuned("de"))
    assert {r.lang for r in s.identified.select("lang").distinct().collect()} == {"de"}
    assert s.filtered.count() <= s.deduped.count() <= s.identified.count()
    cuts = {r.rule: r.threshold for r in P._cuts(docs, clean, P.hand_tuned("de")).collect()}
    assert cuts == P.HAND_TUNED


def test_runs_that_differ_in_weights_share_their_tables(spark, monkeypatch):
    """Decisions and wordlists of the same documents and settings are made once; weights are each run's own."""
    from mlcurate.plans import pipeline as P
    from mlcurate.workloads import pipelines

    made, real = [], P.settle
    monkeypatch.setattr(P, "settle", lambda df, name: (made.append(name), real(df, name))[1])
    given, shared = pipelines.inputs(spark, "/root/testdata/sf0.001"), {}
    a, b = (P.run(*given, P.Config(weights=w), shared=shared) for w in (None, "steps"))
    assert all(made.count(x) == 1 for x in ("hits", "reasons", "wordlist")), made
    assert {r.weight for r in a.weighted.collect()} == {1.0}
    assert sorted(r.doc_id for r in a.filtered.collect()) == sorted(r.doc_id for r in b.filtered.collect())
