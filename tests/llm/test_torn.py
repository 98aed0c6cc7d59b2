"""Keys with several components are looked up where the rows are."""

from wordlid.llm import minhash


def test_few_torn_keys_move_no_rows(spark, monkeypatch):
    rows = spark.createDataFrame([(1, 10, 10), (1, 11, 10), (2, 10, 10), (2, 12, 12), (2, 13, 12), (3, 14, 14)], "key long, node long, root long")
    expected = [(2, 10, 10, 3), (2, 12, 12, 3), (2, 13, 12, 3)]
    assert sorted(map(tuple, minhash._several(rows, "t").select("key", "node", "root", "many").collect())) == expected
    with monkeypatch.context() as m:
        m.setattr(minhash, "spread_join", None)
        assert minhash._several(rows, "t").columns == ["key", "node", "root", "many"]
    monkeypatch.setattr(minhash, "MOST_SENT", 0)  # and with many keys the same rows
    assert sorted(map(tuple, minhash._several(rows, "t").select("key", "node", "root", "many").collect())) == expected
