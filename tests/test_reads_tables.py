"""Queries that once made their data up read a given table."""

import pytest


@pytest.mark.parametrize("name", ["w_lid_in_range", "w_precision_model", "w_winner"])
def test_given_table_is_read(spark, monkeypatch, name):
    from mlcurate.workloads import QUERIES, evaluation, lid, precision

    seen = []
    for module in (evaluation, lid, precision):
        real = module.table
        monkeypatch.setattr(module, "table", lambda s, d, t, real=real: (seen.append(t), real(s, d, t))[1])
    out = QUERIES[name](spark, "/root/testdata/sf0.001")
    assert seen and out.count() > 1


def test_best_ranges(spark):
    from mlcurate.operators import lid

    pred = spark.createDataFrame([(i, "x", 0.05 * i) for i in range(1, 19)], "doc_id long, label string, conf double")
    gold = spark.createDataFrame([(i, "x" if i > 9 else "y") for i in range(1, 19)], "doc_id long, lang string")
    r = lid.best_ranges(pred, gold).first()
    assert 0.45 < r.lo <= r.hi <= 0.5
