"""The pipeline's stages, each against brute force on its own input."""

import pytest

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def stages(spark):
    import corpus_pipeline as p
    from mlcurate.session import settle

    docs, out = spark.read.parquet(f"{SF}/documents.parquet"), []
    for name, stage in p.STAGES:
        got = settle(stage(spark, docs, SF), "test")
        out.append((name, docs, got))
        docs = got
    return out


def rows(df):
    return {r.doc_id: r for r in df.collect()}


def test_stages_keep_the_columns(stages):
    for _, before, after in stages[:-1]:
        assert after.columns == before.columns
    assert len(stages) == 5


def test_toxic_documents_go(spark, stages):
    from mlcurate.llm import toxicity

    _, before, after = stages[0]
    labels = spark.read.parquet(f"{SF}/labels.parquet")
    scored = toxicity.score(before, toxicity.fit(before, labels)).collect()
    assert set(rows(after)) == {r.doc_id for r in scored if not r.predicted}
    trained = labels.where("toxic = 1 and crc32(cast(cast(doc_id as string) as binary)) % 5 != 0").collect()
    assert not {r.doc_id for r in trained} & set(rows(after))


def test_repeated_lines_go(stages):
    from tests.llm.test_lines_and_items import lines_by_brute_force

    _, before, after = stages[1]
    want = lines_by_brute_force([(k, r.text) for k, r in rows(before).items()])
    got = rows(after)
    assert {k: r.text for k, r in got.items()} == want
    assert all(r.n_chars == len(r.text) for r in got.values())


def test_one_of_each_group_stays(stages):
    from mlcurate.llm import jaccard_join as j
    from tests.llm.test_near_duplicates import brute

    _, before, after = stages[2]
    ids = sorted(rows(before))
    texts = [rows(before)[k].text for k in ids]
    _, comp = brute(texts, [j.shingles(t) for t in texts], 0.8)
    assert sorted(rows(after)) == sorted({ids[c] for c in comp})


def test_contaminated_documents_go(spark, stages):
    from tests.llm.test_lines_and_items import items_by_brute_force

    _, before, after = stages[3]
    items = [(r.item_id, r.text) for r in spark.read.parquet(f"{SF}/benchmark.parquet").collect()]
    hit = {k for k, _ in items_by_brute_force([(k, r.text) for k, r in rows(before).items()], items)}
    assert set(rows(after)) == set(rows(before)) - hit


def test_what_is_left_is_encoded(spark, stages):
    import public_tokenizers
    from tokenizers import Tokenizer

    import corpus_pipeline as p

    t = Tokenizer.from_file(public_tokenizers.path("word_bpe_49k.json"))
    _, before, after = stages[4]
    got = rows(after)
    for k, r in rows(before).items():
        assert got[k].n_tokens == len(t.encode(r.text, add_special_tokens=False).ids)
    whole = rows(p.run(spark, SF))
    assert {k: tuple(r) for k, r in whole.items()} == {k: tuple(r) for k, r in got.items()}
