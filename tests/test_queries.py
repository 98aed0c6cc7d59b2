"""Every registered query that has SQL gives what DuckDB gives, on the smallest table."""

import os

import duckdb
import pytest

from wordlid import registry

DIR = "/root/testdata/sf0.001"
pytestmark = pytest.mark.skipif(not os.path.isdir(DIR), reason="the tables are not here")
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def plain(v):
    if v is None or type(v).__name__ in ("NAType", "NaTType") or v != v:
        return "null"
    if isinstance(v, bool) or type(v).__name__ == "bool_":
        return str(bool(v))
    if hasattr(v, "__float__") and not isinstance(v, str):
        return f"{float(v) + 0.0:.5f}"
    return str(v)


def rows(df):
    columns = sorted(df.columns)
    return columns, sorted(tuple(plain(v) for v in r) for r in df[columns].astype(object).itertuples(index=False))


@pytest.fixture(scope="module")
def duck():
    con = duckdb.connect()
    for t in TABLES:
        con.sql(f"create view {t} as select * from read_parquet('{DIR}/{t}.parquet')")
    return con


@pytest.mark.parametrize("name", sorted(registry.ORACLE))
def test_query(spark, duck, name):
    assert rows(registry.QUERIES[name](spark, DIR).toPandas()) == rows(duck.sql(registry.ORACLE[name]).df())


def test_votes_beat_majority(spark):
    from wordlid.operators import metrics as M

    f1 = lambda name: M.macro(M.per_tag(M.confusion(registry.QUERIES[name](spark, DIR)))).first()["macro_f1"]
    assert f1("m_ngram_vote") > 0.5 > f1("b1")


FOUR = ("m_embedding_vote", "m_ngram_vote", "m_recurrent", "m_lm_transfer")


@pytest.fixture(scope="module")
def predictions(spark, duck):
    """What the four taggers say of the held-out words, as a table of DuckDB."""
    import pandas as pd

    every = pd.concat([registry.QUERIES[name](spark, DIR).toPandas()[["word", "gold", "pred"]].assign(model=name) for name in FOUR])
    duck.register("predictions", every)
    return every


def test_taggers_have_the_same_words_and_six_tags(predictions, duck):
    words = predictions.groupby("model")["word"].apply(lambda w: tuple(sorted(w)))
    assert len(set(words)) == 1
    held = duck.sql(registry.ORACLE["w5_split"].replace("SELECT word, tag, n, part FROM sp", "SELECT word, tag FROM test")).df()
    assert set(words.iloc[0]) == set(held["word"])
    support = predictions.groupby(["model", "gold"]).size().unstack()
    assert support.shape == (4, 6) and (support > 0).all(axis=None) and (support.nunique() == 1).all()


SCORES = """WITH t AS (SELECT unnest(['local', 'en', 'mixed', 'name', 'location', 'other']) AS tag), m AS (SELECT DISTINCT model FROM predictions),
 c AS (SELECT m.model, t.tag, (SELECT count(*) FROM predictions p WHERE p.model = m.model AND gold = t.tag) AS support, (SELECT count(*) FROM predictions p WHERE p.model = m.model AND pred = t.tag) AS said,
   (SELECT count(*) FROM predictions p WHERE p.model = m.model AND gold = t.tag AND pred = t.tag) AS hit FROM m, t),
 r AS (SELECT model, tag, support, CASE WHEN said > 0 THEN hit / said::DOUBLE ELSE 0 END AS p, CASE WHEN support > 0 THEN hit / support::DOUBLE ELSE 0 END AS r FROM c),
 sc AS (SELECT model, tag, support, round(p, 6) AS precision, round(r, 6) AS recall, round(CASE WHEN p + r > 0 THEN 2 * p * r / (p + r) ELSE 0 END, 6) AS f1 FROM r)"""


@pytest.mark.parametrize("name, sql", [
    ("w11_four_taggers", "SELECT model, tag, support, precision, recall, f1 FROM sc"),
    ("w12_f1_pivot_taggers", "SELECT model, " + ", ".join(f"max(f1) FILTER (tag = '{t}') AS \"{t}\"" for t in ("local", "en", "mixed", "name", "location", "other")) + " FROM sc GROUP BY model"),
    ("w10_compare", "SELECT model, sum(support) AS words, round(avg(precision), 5) AS macro_precision, round(avg(recall), 5) AS macro_recall, round(avg(f1), 5) AS macro_f1 FROM sc GROUP BY model"),
])
def test_measures_of_the_taggers(spark, duck, predictions, name, sql):
    """The measures of fitted taggers, on their stored predictions, in SQL."""
    got = registry.QUERIES[name](spark, DIR).toPandas()
    assert rows(got[got["model"].isin(FOUR)]) == rows(duck.sql(f"{SCORES} {sql}").df())


def test_taggers_learn(spark):
    f1 = {r["model"]: r["macro_f1"] for r in registry.QUERIES["w10_compare"](spark, DIR).collect()}
    assert f1["m_ngram_vote"] >= max(f1[f"m_single_{k}_ngrams"] for k in ("svm", "lr", "mlp")) - 0.03
    assert min(f1[m] for m in ("m_ngram_vote", "m_embedding_vote", "m_recurrent")) > 0.5


def test_tuning_lowers_perplexity(spark):
    got = {r["stage"]: r for r in registry.QUERIES["m_lm_finetuned"](spark, DIR).collect()}
    assert got["after"]["perplexity"] < got["before"]["perplexity"] and got["after"]["pieces"] == got["before"]["pieces"]


def test_contrasts(spark):
    got = {r["contrast"]: r["delta"] for r in registry.QUERIES["w13_tagger_deltas"](spark, DIR).collect()}
    f1 = {r["model"]: r["macro_f1"] for r in registry.QUERIES["w10_compare"](spark, DIR).collect()}
    assert got["ngrams over vectors, vote"] == pytest.approx(f1["m_ngram_vote"] - f1["m_embedding_vote"], abs=2e-5) and len(got) == 14 and None not in got.values()


def test_near_duplicates_by_minimal_hashes(spark, tmp_path):
    import random

    rng = random.Random(4)
    base = [" ".join(f"w{rng.randrange(10**6)}" for _ in range(200)) for _ in range(20)]
    texts = [*base, *(t + " end" for t in base), *(t.upper() for t in base[:5]), "too short", None]
    spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").write.parquet(f"{tmp_path}/documents.parquet")
    got = {r["doc_id"]: r for r in registry.QUERIES["op_minhash"](spark, str(tmp_path)).collect()}
    assert set(got) == set(range(45))
    assert all(got[20 + i]["linked_to"] == i and got[i]["linked_to"] is None for i in range(20)) and all(got[40 + i]["class_id"] == i for i in range(5))


def test_overlaps_cross_hours(spark, tmp_path):
    """An interval of several hours meets each overlapping one once."""
    import pandas as pd

    at = pd.Timestamp("2024-01-01 10:50:00")
    rows = [(e, at + pd.Timedelta(minutes=m), 1, kind) for e, m, kind in ((89, 0, "click"), (179, 5, "purchase"), (269, 95, "purchase"), (1, 94, "purchase"), (2, 400, "purchase"))]
    spark.createDataFrame(pd.DataFrame(rows, columns=["event_id", "ts", "user_id", "event_type"])).selectExpr("event_id", "cast(ts as timestamp_ntz) ts", "user_id", "event_type").write.parquet(f"{tmp_path}/events.parquet")
    got = registry.QUERIES["op_interval_events"](spark, str(tmp_path)).collect()
    assert [(r["event_id"], r["overlaps"], r["shared_us"]) for r in got] == [(89, 1, 89 * 60_000_000)]


def test_maps_count_the_whole_text(spark, tmp_path):
    texts = ["", "a b a", " ".join(f"w{i} W{i}" for i in range(900)), None]
    spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").write.parquet(f"{tmp_path}/documents.parquet")
    got = {r["doc_id"]: r["kinds"] for r in registry.QUERIES["op_maps"](spark, str(tmp_path)).collect()}
    assert got == {i: None if t is None else len(set(t.lower().split(" "))) for i, t in enumerate(texts)}


def test_streamed_tables_may_be_folders(spark, duck, tmp_path):
    """A table of several files, and one without any row, give what one file gives."""
    docs = spark.read.parquet(f"{DIR}/documents.parquet")
    for folder, some in (("many", docs.repartition(3)), ("none", docs.limit(0))):
        some.write.parquet(f"{tmp_path}/{folder}/documents.parquet")
    got = registry.QUERIES["st_static_join"](spark, f"{tmp_path}/many").toPandas()
    assert rows(got) == rows(duck.sql(registry.ORACLE["st_static_join"]).df())
    assert registry.QUERIES["st_static_join"](spark, f"{tmp_path}/none").count() == 0


def test_samples_are_words_of_the_tables(spark):
    """The features in the form of the worked samples are those of the tagged words, which come from the documents."""
    from wordlid.plans.common import tagged

    got = {r["word"]: r["features"].split(" ") for r in registry.QUERIES["w6_samples"](spark, DIR).collect()}
    assert set(got) == {r["word"] for r in tagged(spark, DIR).collect() if r["word"].isascii() and r["word"].isalpha() and r["word"].islower() and len(r["word"]) >= 3}
    assert all(f[:3] == [w, w[-3:], w[:3]] for w, f in got.items())


def test_fresh_weights_need_no_language_model(spark, monkeypatch):
    """The transfer without pretraining takes pieces and shapes of the language model, and trains none."""
    from wordlid.operators import recurrent
    from wordlid.plans import common, models

    def refuse(*_, **__):
        raise AssertionError("a language model is trained")

    common.forget()
    monkeypatch.setattr(recurrent, "train_lm", refuse)
    assert models.transfer(spark, "/root/testdata/sf0.001", "none").count() > 0


def test_taggers_learn_from_all_training_words(spark, monkeypatch):
    """Every word is in one of both parts, however many there are, and every sentence with a tag that may be learned reaches the sequence tagger."""
    import numpy as np
    from pyspark.sql import functions as F

    from wordlid.plans import models

    words = spark.range(60_000).select(F.concat(F.lit("w"), "id").alias("word"))
    train, test = models.split(words)
    assert train.filter(models.is_train()).count() == train.count() > 40_000 and train.count() + test.count() == 60_000
    many = spark.range(30_000).select(F.concat(F.lit("s"), "id").alias("sid"), F.array(F.lit("w")).alias("words"), F.array(F.lit(1)).alias("tags"), F.array(F.lit(True)).alias("train"), *[F.array(F.lit(x)).alias(c) for c, x in (("v", 0.5), ("p", 1), ("c", 1))])
    monkeypatch.setattr(models, "packed", lambda spark, d: many)
    monkeypatch.setattr(models, "kept", lambda spark, d, name, make: make())
    monkeypatch.setattr(models, "unit_table", lambda spark, d, level: ({}, np.zeros((2, 1))))
    seen = []
    monkeypatch.setattr(models.R, "fit_tagger", lambda rows, *rest: seen.append(rows.count()))
    monkeypatch.setattr(models.R, "tag_sequences", lambda rows, *rest: spark.createDataFrame([("w", "local", "local")], "word string, gold string, pred string"))
    models.recurrent(spark, "none")
    assert seen == [30_000]
