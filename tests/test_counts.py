"""Counts that tasks make in Python against the same by rows."""

import numpy as np
from pyspark.sql import functions as F

from wordlid.functions import text as T
from wordlid.operators import corpus as C
from wordlid.operators import estimators as E
from wordlid.operators import features as X
from wordlid.operators import vectors as V

ODD = [("a.,! b?\nc...\r d!\r\ne,.  \u0085f.\r.! Gİx Été!? ... \t.x", "en"), ("x.\r.\ny,.\r.", "fr"), (None, "en"), ("", None), ("foo. foo, foo", None), ("ΣΣ ẞß.", "de"), ("w.,.\r\nw!,\r", "xx")]


def test_types_are_those_of_the_tokens(spark):
    docs = spark.createDataFrame([("s", i, *r) for i, r in enumerate(ODD)], "source string, doc_id long, text string, lang string")
    rows = lambda df: sorted(map(tuple, df.collect()))
    assert rows(C.count_types(docs)) == rows(C.word_types(C.to_tokens(C.to_sentences(docs))))
    assert rows(C.count_types(docs.limit(0))) == []


def test_words_of_sentences_are_the_tokens(spark):
    """Sentences of documents with one id stay apart."""
    docs = spark.createDataFrame([("s", i, *r) for i, r in enumerate(ODD)] + [("s", 99, "a b,. c", "en"), ("s", 99, "d e", "en")], "source string, doc_id long, text string, lang string")
    got = sorted(map(str, (r["seq"] for r in C.sentence_words(C.to_sentences(docs)).collect())))
    found: dict = {}
    for r in C.to_tokens(C.to_sentences(docs.filter("doc_id < 99"))).orderBy("pos").collect():
        found.setdefault((r["doc_id"], r["sent_no"]), []).append(r["word"])
    assert got == sorted(map(str, [*found.values(), ["a", "b"], ["c"], ["d", "e"]]))


def test_vectors_train_in_more_partitions_where_sequences_are_many(spark, monkeypatch):
    seen, fit = [], V.Word2Vec
    monkeypatch.setattr(V, "Word2Vec", lambda **how: seen.append(how["numPartitions"]) or fit(**how))
    monkeypatch.setattr(V, "SEQUENCES_EACH", 10)
    for rows in (8, 60, 200):
        units = V.train_skipgram(spark.range(rows).selectExpr("array('a', 'b', cast(id % 4 as string)) AS seq"), "seq", 4)
        assert units.count() == 6
    assert seen == [4, 6, 8]


def test_features_are_those_of_the_column_functions(spark):
    words = spark.createDataFrame([("banana", ["ban", "ana"], 1), ("a", ["a"], 0), ("é\U0001F600x", ["é", "\U0001F600x"], 2), ("zz", None, 3)], "word string, pieces array<string>, y int")
    each = words.select("word", F.explode(T.families(F.col("word"), F.coalesce("pieces", F.array().cast("array<string>")))).alias("x")).groupBy("word", "x.family", "x.feature").agg(F.count("*").alias("n")).collect()
    uses = {(r["family"], r["feature"]): (r["words"], r["uses"]) for r in X.feature_uses(words, "spgb").collect()}
    kinds = sorted({(r["family"], r["feature"]) for r in each})
    assert uses == {k: (sum(1 for r in each if (r["family"], r["feature"]) == k), sum(r["n"] for r in each if (r["family"], r["feature"]) == k)) for k in kinds}
    places = {f: {} for f in "spgb"}
    for i, (f, x) in enumerate(kinds):
        places[f][x] = i
    for r in X.count_rows(words, places).collect():
        own = sorted((places[x["family"]][x["feature"]], float(x["n"])) for x in each if x["word"] == r["word"])
        assert list(zip(r["idx"], r["val"], strict=True)) == own


def test_sparse_products_are_the_dense_ones_and_kept():
    rng = np.random.default_rng(0)
    sizes = rng.integers(0, 50, 300)
    first = np.concatenate([[0], np.cumsum(sizes)])
    idx = np.concatenate([rng.choice(5000, k, replace=False) for k in sizes])
    x, w, d = E.Sparse(first, idx, rng.random(len(idx)).astype(np.float32)), rng.random((5000, 7), np.float32), rng.random((300, 7), np.float32)
    dense = np.zeros((300, 5000), np.float32)
    dense[np.repeat(np.arange(300), sizes), idx] = x.val
    for part in (slice(0, 300), slice(0, 64), slice(0, 0)):
        one = x[part]
        at, g = one.back(d[part])
        whole = np.zeros_like(w)
        whole[at] = g
        assert np.allclose(one @ w, dense[part] @ w, rtol=1e-4) and np.allclose(whole, dense[part].T @ d[part], rtol=1e-4)
    one = x[slice(0, 64)]
    assert one @ w is not None and one._kept() is one._kept()  # not made anew in each epoch


def test_composed_vectors_need_no_row_for_each_unit(spark):
    unit = lambda names, dim: spark.createDataFrame([(u, [float(i + 1)] * dim) for i, u in enumerate(names)], "unit string, v array<float>")
    types = spark.createDataFrame([("ab", ["a", "b"]), ("abc", ["ab", "x", "c"]), ("q", None)], "word string, pieces array<string>")
    out = V.compose(types, unit(["ab"], 2), unit(["a", "ab", "c"], 1), unit(["a", "b"], 1), (2, 1, 1), (2, 2))
    assert {r["word"]: r["vec"] for r in out.collect()} == {"ab": [1, 1, 1, 0, 1, 2], "abc": [0, 0, 2, 0, 1, 2], "q": [0] * 6}
    assert "Generate" not in out._jdf.queryExecution().toString()


def test_padding_of_the_language_model_is_not_scored():
    from wordlid.operators import recurrent as R

    rng = np.random.default_rng(0)
    w = R.single(R.lm_weights(20, 4, 5, 2))
    ids, mask = rng.integers(0, 20, (3, 9)), (np.arange(9)[None] < np.array([9, 4, 2])[:, None]).astype(float)
    x, m, y = ids[:, :-1], mask[:, 1:], ids[:, 1:]
    at, states, scores, own = R._next(w, R.encode(w, x, m)[0], m, y)
    assert len(at) == len(states) == len(scores) == len(own) == 8 + 3 + 1
    p = R.softmax(R.encode(w, x, m)[0] @ w["o"] + w["ob"])
    losses = -np.log(np.take_along_axis(p, y[..., None], 2)[..., 0]) * m
    loss, grads = R.lm_gradient(0.0)(w, (ids, mask), rng)
    assert np.isclose(loss, losses.sum() / 12, rtol=1e-5)
    for name, at in (("o", (2, 3)), ("ob", (3,)), ("l1h", (1, 2)), ("e", (int(ids[0, 1]), 1))):
        up, down = ({k: v.astype(np.float64) for k, v in w.items()} for _ in range(2))
        up[name][at] += 1e-5
        down[name][at] -= 1e-5
        slope = (R.lm_gradient(0.0)(up, (ids, mask), rng)[0] - R.lm_gradient(0.0)(down, (ids, mask), rng)[0]) / 2e-5
        assert np.isclose(slope, grads[name][at], rtol=1e-2, atol=1e-5)
