"""Worked samples, widths, counts and measures that the method's description gives, and invariants."""

import hashlib
from collections import Counter

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from wordlid.functions import text as T
from wordlid.operators import corpus as C
from wordlid.operators import estimators as E
from wordlid.operators import metrics as M
from wordlid.operators import recurrent as R
from wordlid.operators import segment as G
from wordlid.operators import training
from wordlid.operators import vectors as V


def test_worked_sample(spark):
    rows = spark.createDataFrame([("nayigalige", "n ay ig al ig e".split()), ("dogsgalige", "d og s g al ig e".split())], "word string, pieces array<string>")
    out = {r["word"]: r["f"] for r in rows.select("word", T.features(F.col("word"), F.col("pieces"), T.SAMPLE_SIZES).alias("f")).collect()}
    assert out["nayigalige"] == "nayigalige ige nay ge na e n _nay nayi ayig yiga igal gali alig lige ige_ _ay_ _ig_ _al_ _ig_".split()
    assert out["dogsgalige"][-4:] == "ige_ _og_ _al_ _ig_".split()


def test_widths_and_counts():
    assert V.composed_width() == 1300 and V.composed_width(piece_slots=5) == 1000
    assert R.param_counts(19162, 1000, 300, 7) == {"embedding": 19162000, "bilstm": 3122400, "dense": 4207}


def test_compose_pads_with_zeros(spark):
    types = spark.createDataFrame([("abcdef", list("abcde")), ("x", [])], "word string, pieces array<string>")
    unit = lambda names, d: spark.createDataFrame([(n, [1.0] * d) for n in names], "unit string, v array<float>")
    got = {r["word"]: np.array(r["vec"]) for r in V.compose(types, unit(["abcdef"], 200), unit("abcde", 100), unit("abcdef", 30), (200, 100, 30), (8, 10)).collect()}
    assert len(got["abcdef"]) == 1300
    assert got["abcdef"][:700].all() and not got["abcdef"][700:1000].any() and got["abcdef"][1000:1180].all() and not got["abcdef"][1180:].any()
    assert len(got["x"]) == 1300 and not got["x"].any()


def test_macro_is_mean_of_f1(spark):
    pred = spark.createDataFrame([("a", "local", "local"), ("b", "en", "local"), ("c", "en", "en"), ("d", "other", "name")], "word string, gold string, pred string")
    scores = M.per_tag(M.confusion(pred))
    f1 = {r["tag"]: r["f1"] for r in scores.collect()}
    assert f1["name"] == f1["location"] == 0 and f1["local"] == pytest.approx(2 / 3, abs=1e-6)
    assert M.macro(scores).first()["macro_f1"] == pytest.approx(sum(f1.values()) / 6, abs=1e-5)
    assert M.confusion(pred).count() == 36


def test_bpe_against_naive():
    words = [("low", 5), ("lower", 2), ("newest", 6), ("widest", 3), ("aaaa", 4)]
    seqs, naive = [list(w) for w, _ in words], []
    for _ in range(12):
        uses = {}
        for s, (_, n) in zip(seqs, words):
            for p in zip(s, s[1:]):
                uses[p] = uses.get(p, 0) + n
        if not uses or max(uses.values()) < 2:
            break
        pair = min(uses, key=lambda p: (-uses[p], p))
        naive.append(pair)
        for k, s in enumerate(seqs):
            i, new = 0, []
            while i < len(s):
                if i + 1 < len(s) and (s[i], s[i + 1]) == pair:
                    new.append(s[i] + s[i + 1])
                    i += 2
                else:
                    new.append(s[i])
                    i += 1
            seqs[k] = new
    assert G.train_bpe(words, 12) == naive
    ranks = {p: i for i, p in enumerate(naive)}
    assert all("".join(G.split_bpe(w, ranks)) == w for w in ("lowest", "xyz", "a", ""))


def test_unigram_split_is_best():
    logp = G.train_unigram([("abab", 10), ("ab", 20), ("ba", 3), ("c", 1)], 6)
    assert abs(sum(np.exp(list(logp.values()))) - 1) < 1e-9

    def every(w):
        return [[w]] + [[w[:i], *rest] for i in range(1, len(w)) for rest in every(w[i:])]

    score = lambda s: sum(logp.get(p, -1e9) for p in s)
    assert score(G.split_unigram("abab", logp)) == pytest.approx(max(score(s) for s in every("abab")))


def test_coupling_agrees_with_exact_case():
    p = np.array([[0.5, 0.3, 0.2]])
    r = p[:, :, None] / (p[:, :, None] + p[:, None, :])
    assert np.allclose(E.couple(r, 200), p, atol=1e-6)


def _numeric(gradient, w, batch):
    rng = np.random.default_rng(0)
    loss, grads = gradient(w, batch, np.random.default_rng(5))
    for k in grads:
        at = tuple(rng.integers(0, n) for n in w[k].shape)
        if k == "e":
            at = (1, at[1])
        old, eps = w[k][at], 1e-5
        w[k][at] = old + eps
        up = gradient(w, batch, np.random.default_rng(5))[0]
        w[k][at] = old - eps
        down = gradient(w, batch, np.random.default_rng(5))[0]
        w[k][at] = old
        assert grads[k][at] == pytest.approx((up - down) / (2 * eps), rel=1e-3, abs=1e-7), k


def test_gradients():
    rng = np.random.default_rng(1)
    net = {k: v.astype(float) for k, v in E.network(7, (5, 4), 1).items()}
    _numeric(E.cross_entropy(0.0), net, (rng.normal(size=(6, 7)), np.array([0, 1, 2, 3, 4, 5])))
    ids = np.array([[1, 2, 1, 0], [2, 1, 0, 0]])
    mask = (ids > 0).astype(float)
    table = rng.normal(size=(3, 4))
    counts = mask * np.array([[1, 0, 1, 0], [1, 1, 0, 0]])  # a word without a tag is read but does not count
    for both in (True, False):
        _numeric(R.tagger_gradient(), R.tagger_weights(4, 3, both), (table[ids], mask, counts, np.array([[0, 6, 2, 6], [3, 4, 6, 6]])))
    _numeric(R.lm_gradient(0.3), R.lm_weights(3, 4, 3, 2), (ids, mask))
    w = {k: v for k, v in R.lm_weights(3, 4, 3, 2).items() if k not in ("o", "ob")} | {"c": rng.normal(size=(9, 6)), "cb": np.zeros(6)}
    _numeric(R.transfer_gradient(), w, (ids, mask, np.array([1, 4])))
    for opened, want in ((0, set()), (1, {"l1x", "l1h", "l1b"}), (2, {f"l{k}{x}" for k in (0, 1) for x in "xhb"})):
        grads = R.transfer_gradient(opened)(w, (ids, mask, np.array([1, 4])), rng)[1]
        assert set(grads) == want | {"c", "cb"}


def test_lm_loss_counts_every_piece():
    rng = np.random.default_rng(4)
    w = R.lm_weights(9, 3, 4, 1)
    seqs = [[int(x) for x in rng.integers(1, 9, n)] for n in (1, 2, 5, 6, 11, 23)]
    total = 0.0
    for s in seqs:
        for i in range(1, len(s)):
            # a window starts at every fifth piece
            ids = np.array([s[(i - 1) // 5 * 5 : i]])
            total -= np.log(R.softmax(R.encode(w, ids, np.ones(ids.shape))[0][:, -1] @ w["o"] + w["ob"])[0, s[i]])
    loss, n = R.lm_loss(w, seqs, 5)
    assert n == sum(len(s) - 1 for s in seqs) and np.isclose(loss, total)


def test_reverse_direction_is_forward_on_reversed_input():
    rng = np.random.default_rng(2)
    w, x = R.cell(3, 2, rng, "f"), rng.normal(size=(1, 5, 3))
    one = np.ones((1, 5))
    both = R.states(w | {k.replace("f", "r", 1): v for k, v in w.items()}, x, one)[0]
    assert np.allclose(both[:, :, 2:], R.run_cell(w, "f", x[:, ::-1], one)[0][:, ::-1])


def test_cleaning_rules(spark):
    rows = [(1, "en", "small need take"), (2, "en", "Small need take"), (3, "en", "ok go"), (4, "fr", "ಕನ್ one two"), (5, "fr", "coolagiru need baruthe"), (6, "fr", "")]
    docs = spark.createDataFrame(rows, "doc_id long, lang string, text string")
    lexicon = spark.createDataFrame([(w,) for w in ("small", "need", "take", "ok", "go")], "word string")
    got = {r["doc_id"]: r for r in C.clean_flags(docs, lexicon, "[ಀ-೿]").collect()}
    assert got[2]["duplicate"] and not got[1]["duplicate"] and got[3]["short"] and got[4]["script"]
    assert got[1]["english_only"] and not got[5]["english_only"]
    assert spark.range(1).select(C.strip_unprintable(F.lit("a‍\U0001f600b\n"))).first()[0] == "ab\n"
    assert spark.range(1).select(T.squeeze_runs(F.lit("goooood"))).first()[0] == "good"


def test_empty_table(spark):
    none = spark.createDataFrame([], "doc_id long, source string, lang string, text string, n_chars long")
    assert C.to_tokens(C.to_sentences(none)).count() == 0


def test_sparse_rows_are_dense_rows():
    rng = np.random.default_rng(3)
    x = rng.integers(0, 3, (7, 9)).astype(np.float32)
    x[2] = 0  # a row without entries
    lists = [np.flatnonzero(r) for r in x]
    batch = pa.RecordBatch.from_arrays([pa.array([i.tolist() for i in lists], pa.list_(pa.int32())), pa.array([r[i].tolist() for r, i in zip(x, lists)], pa.list_(pa.float32()))], names=["idx", "val"])
    got, w, delta = E.matrix(batch, 9), rng.normal(size=(9, 4)), rng.normal(size=(7, 4))
    assert isinstance(got, E.Sparse) and np.allclose(got @ w, x @ w) and np.allclose(got[2:5] @ w, x[2:5] @ w)
    at, g = got.back(delta)
    full = np.zeros((9, 4))
    full[at] = g
    assert np.allclose(full, x.T @ delta)
    y = rng.integers(0, 6, 7)
    for gradient, weights in ((E.cross_entropy(0.0), {k: v.astype(float) for k, v in E.network(9, (5,), 1).items()}), (E.hinge(0.0), {"w": rng.normal(size=(9, 15)), "b": np.zeros(15)})):
        loss, sparse = gradient(weights, (got, y), rng)
        same, dense = gradient(weights, (x, y), rng)
        name = "w" if "w" in weights else "w0"
        full = np.zeros(weights[name].shape)
        full[sparse[name][0]] = sparse[name][1]
        assert loss == pytest.approx(same) and np.allclose(full, dense[name], atol=1e-6)


def _words(n, seed=5):
    """Words of six kinds of syllables, and their features."""
    rng = np.random.default_rng(seed)
    parts = [["ka", "lo"], ["th", "er"], ["pur", "ra"], ["zi", "no"], ["qu", "ix"], ["99", "#"]]
    rows = []
    for i in range(n):
        y = int(rng.integers(0, 6))
        word = "".join(rng.choice(parts[y] if rng.random() < 0.8 else parts[int(rng.integers(0, 6))]) for _ in range(4)) + str(i)
        idx = Counter(hash_of(word[k : k + 2]) for k in range(len(word) - 1))
        rows.append((word, y, list(idx), [float(v) for v in idx.values()]))
    return rows


def hash_of(s):
    return int(hashlib.md5(s.encode()).hexdigest()[:4], 16) % 512


@pytest.mark.parametrize("kind", ["lr", "svm", "mlp"])
def test_averaged_training_is_as_good_as_one_fit(spark, kind):
    rows = spark.createDataFrame(_words(3000), "word string, y int, idx array<int>, val array<float>")
    train, test = rows.filter(T.bucket(F.col("word")) < 70), rows.filter(T.bucket(F.col("word")) >= 70)
    right = lambda tagger: E.predict([tagger], test, 512).agg(F.avg((F.col("gold") == F.col("pred")).cast("int"))).first()[0]
    one, six = (right(E.fit(kind, train, 512, parts=p)) for p in (1, 6))
    assert one > 0.7 and six > one - 0.04


def test_calibration_sees_all_that_is_held_back(spark):
    """However many words there are: the sigmoid of each pair is that of all margins of the held-back fifth."""
    word, y = F.col("id").cast("string"), (F.xxhash64(F.lit(8), "id") % 3 != 0).cast("int")
    noise = lambda k: (F.pmod(F.xxhash64(F.lit(k), "id"), F.lit(1000)) / 1000).cast("float")
    rows = spark.range(130_000).select(word.alias("word"), y.alias("y"), F.array(F.lit(0), F.lit(1)).alias("idx"), F.array(y + 2 * noise(1), noise(2)).cast("array<float>").alias("val"))
    one = E.fit("svm", rows, 2, rounds=1, parts=4, classes=2)
    held = rows.filter(F.pmod(F.xxhash64("word"), F.lit(1 << 30)) < (1 << 30) // 5).toPandas()
    assert len(held) > 25_000
    margin = np.stack(held["val"]).astype(np.float32) @ one.weights["w"] + one.weights["b"]
    assert one.sigmoids[0] == pytest.approx(E.platt(margin[:, 0].astype(float), np.where(held["y"] == 0, 1, -1)), rel=1e-4)


def test_rows_are_dealt_over_partitions(spark):
    rows = spark.createDataFrame(_words(2500), "word string, y int, idx array<int>, val array<float>").coalesce(1)
    dealt, parts = training.dealt(rows, 400)
    sizes = [r["count"] for r in dealt.groupBy(F.spark_partition_id()).count().collect()]
    assert parts == 7 and len(sizes) == 7 and sum(sizes) == 2500 and max(sizes) < 500


def test_weights_are_averaged_in_a_tree(spark):
    """With a gradient that adds what a partition's rows say, the result is the mean weighted by rows, whatever the number of partitions."""

    def gradient(w, batch, rng):
        return 0.0, {"x": np.zeros(1)}

    rows = spark.createDataFrame([(f"w{i}", float(i)) for i in range(300)], "word string, v double")

    def load(got, size):
        return []

    start = {"x": np.array([7.0])}
    for parts in (1, 3, 20):
        assert training.fit(rows, load, gradient, dict(start), rounds=1, parts=parts)["x"].tolist() == [7.0]
    sets = [(n, {"x": np.array([float(v)])}) for n, v in ((1, 3), (2, 6), (5, -1))]
    batches = [pa.RecordBatch.from_arrays([pa.array([float(n)]), pa.array([0.5 * n]), pa.array([training.packed(w)], pa.binary())], names=["n", "loss", "w"]) for n, w in sets]
    (got,) = list(training._sum(iter(batches)))
    assert training.unpacked(got.column("w")[0].as_py())["x"][0] == pytest.approx((3 + 12 - 5) / 8) and got.column("loss")[0].as_py() == pytest.approx((0.5 + 2 + 12.5) / 8)


def test_slanted_rate_rises_and_falls():
    rate = [training.slanted(t, 100) for t in range(100)]
    assert np.argmax(rate) == 10 and max(rate) == 1.0 and rate[0] == pytest.approx(1 / 32) and all(a < b for a, b in zip(rate[:10], rate[1:11])) and all(a > b for a, b in zip(rate[10:99], rate[11:]))


def test_layer_rates_fall_with_depth():
    rates = R.layer_rates(R.lm_weights(5, 3, 4, 3))
    assert rates["l2x"] == pytest.approx(1 / 2.6) and rates["l0h"] == pytest.approx(2.6**-3) and rates["e"] == pytest.approx(2.6**-4)


def test_vectors_are_composed_where_they_are_read():
    made = R.Vectors(np.array([[0, 0], [1, 2], [3, 4]]), np.array([[0], [5]]), (2, 2, 1), (2, 3))
    batch = pa.RecordBatch.from_arrays([pa.array([[0.5, 0.25, 1.0, 2.0], [9.0, 8.0]], pa.list_(pa.float32())), pa.array([[1, 2, 0, 0], [2, 0]], pa.list_(pa.int32())), pa.array([[1, 0, 0, 1, 1, 1], [0, 1, 0]], pa.list_(pa.int32()))], names=["v", "p", "c"])
    a, b = made.of(batch)
    assert a.tolist() == [[0.5, 0.25, 1, 2, 3, 4, 5, 0, 0], [1, 2, 0, 0, 0, 0, 5, 5, 5]] and b.tolist() == [[9, 8, 3, 4, 0, 0, 0, 5, 0]]


def test_long_sequences_are_cut_into_windows():
    made = R.Vectors(np.zeros((1, 1)), np.zeros((1, 1)), (1, 1, 1), (1, 1))
    batch = pa.RecordBatch.from_arrays([pa.array([[float(i) for i in range(7)]], pa.list_(pa.float32())), pa.array([[0] * 7], pa.list_(pa.int32())), pa.array([[0] * 7], pa.list_(pa.int32())), pa.array([[0, -1, 2, 3, -1, 5, 1]], pa.list_(pa.int32()))], names=["v", "p", "c", "ys"])
    seen = []
    for x, mask, counts, y in R._tag_loader(made, 3, True)([batch], 2):
        assert (counts <= mask).all()
        seen += [(v, t) for v, t, c in zip(x[..., 0].ravel(), y.ravel(), counts.ravel()) if c]
    assert sorted(seen) == [(0, 0), (2, 2), (3, 3), (5, 5), (6, 1)]
    assert all((counts == 1 - mask + (y < 6)).all() for (_, mask, counts, y), (_, real, *_rest) in zip(R._tag_loader(made, 3, False)([batch], 2), R._tag_loader(made, 3, True)([batch], 2)) for mask in (real,))


def test_negative_sampling(spark):
    assert sorted(map(tuple, V._pairs(np.array([1, 2, 3, 4, 5]), np.array([0, 3, 5]), 2).tolist())) == sorted([(1, 2), (2, 1), (2, 3), (3, 2), (1, 3), (3, 1), (4, 5), (5, 4)])
    rng = np.random.default_rng(0)
    w = {"in": rng.normal(size=(4, 3)), "out": rng.normal(size=(4, 3))}
    batch, gradient = np.array([[0, 1], [2, 1], [0, 3]]), V.negative_gradient(np.full(4, 0.25), 2)
    loss, grads = gradient(w, batch, np.random.default_rng(5))
    for k, (at, g) in grads.items():
        for r, row in zip(at, g):
            old = w[k][r, 1]
            w[k][r, 1] = old + 1e-5
            up = gradient(w, batch, np.random.default_rng(5))[0]
            w[k][r, 1] = old - 1e-5
            down = gradient(w, batch, np.random.default_rng(5))[0]
            w[k][r, 1] = old
            assert row[1] == pytest.approx((up - down) / 2e-5, rel=1e-3, abs=1e-7)
    seqs = spark.createDataFrame([(list(rng.choice(list("abc"), 6)) if i % 2 else list(rng.choice(list("xyz"), 6)),) for i in range(400)], "seq array<string>")
    got = {r["unit"]: np.array(r["v"]) for r in V.train_skipgram_negative(seqs, "seq", 8, 2, epochs=8).collect()}
    cosine = lambda a, b: got[a] @ got[b] / np.linalg.norm(got[a]) / np.linalg.norm(got[b])
    assert cosine("a", "b") > cosine("a", "x") and cosine("y", "z") > cosine("c", "z")


def test_rare_units_are_left_out_where_there_are_many(spark):
    seqs = spark.createDataFrame([(list("aaabbc"),), (list("abd"),)], "seq array<string>")
    assert [V.least_uses(seqs, "seq", 1, most) for most in (9, 4, 3, 2, 1)] == [1, 1, 2, 2, 4]


def test_merges_in_spark_are_those_of_the_loop(spark):
    words = [("low", 5), ("lower", 2), ("newest", 6), ("widest", 3), ("aaaa", 4), ("x", 9), ("lowest", 7)]
    types = spark.createDataFrame(words, "word string, n long")
    assert G.train_bpe_spark(types, 9) == G.train_bpe(words, 9) == G.learn_merges(types, 9)
    several = G.train_bpe_spark(types, 9, 3)
    ranks = {p: i for i, p in enumerate(several)}
    assert len(several) == 9 and all("".join(G.split_bpe(w, ranks)) == w for w, _ in words)
    assert G.learn_merges(types, 9, driver_types=2) == G.train_bpe(words, 9)


def test_unigram_in_spark_is_that_of_the_loop(spark):
    words = [("abab", 10), ("ab", 20), ("ba", 3), ("c", 1), ("cabba", 4), ("bab", 2)]
    types = spark.createDataFrame(words, "word string, n long").repartition(3)
    one, other = G.train_unigram(words, 6), G.train_unigram_spark(types, 6)
    assert one.keys() == other.keys() and all(other[k] == pytest.approx(one[k], rel=1e-6) for k in one)
    got = {r["word"]: r["p"] for r in types.select("word", G.encode_unigram(types, one).alias("p")).collect()}
    assert all(got[w] == G.split_unigram(w, one) for w, _ in words)


def test_tokenizer_round_trip(spark):
    words = spark.createDataFrame([("low", 5), ("lower", 2), ("newest", 6), ("widest", 3)], "word string, n long")
    table = G.train_tokenizer(words, 24)
    assert len(table) <= 24 - 3 and len({p for p, _, _ in table}) == len(table) and sorted(i for _, i, _ in table) == list(range(3, 3 + len(table)))
    texts = spark.createDataFrame([("lower newest",), ("zebra low",), ("",), ("w",)], "text string")
    back = texts.select("text", G.decode(G.tokenize(texts, "text", table)).alias("back")).collect()
    assert all(r["text"] == r["back"] for r in back)


def test_smallest_of_each_group(spark):
    rows = [(f"w{i}", "abc"[i % 3]) for i in range(200)] + [("only", "d")]
    df = spark.createDataFrame(rows, "word string, tag string")
    for k in (0, 1, 17, 500):
        want = {w for t in "abcd" for w in sorted((w for w, x in rows if x == t), key=lambda w: hashlib.md5(w.encode()).hexdigest())[:k]}
        assert {r["word"] for r in C.smallest(df, F.lit(k), digits=1).collect()} == want
    over = Counter(r["tag"] for r in C.balance(df, 70, "over").collect())
    assert over == {"a": 70, "b": 70, "c": 70, "d": 70} and Counter(r["tag"] for r in C.balance(df, 70).collect()) == {"a": 67, "b": 67, "c": 66, "d": 1}


def test_planted_words_stand_in_sentences(spark):
    spliced = spark.createDataFrame([(f"s{i}", [("x" + str(i),), ("y" + str(i),)]) for i in range(20)], "sid string, words array<struct<word:string>>")
    words = spark.createDataFrame([(f"new{i}",) for i in range(50)], "word string")
    got = C.insert_words(spliced, words, 0).collect()
    flat = Counter(w for r in got for w in r["words"])
    assert flat == Counter([f"new{i}" for i in range(50)] + [f"{c}{i}" for c in "xy" for i in range(20)])
    assert all([w for w in r["words"] if not w.startswith("new")] == ["x" + r["sid"][1:], "y" + r["sid"][1:]] for r in got)
    assert any(r["words"][0].startswith("new") for r in got) and any(not r["words"][0].startswith("new") for r in got)


def test_mixed_words_have_both_orders(spark):
    base = spark.createDataFrame([("small", 5, "en"), ("holding", 9, "en"), ("baruthe", 4, "local"), ("hogu", 3, "local"), ("rare", 1, "en")], "word string, n long, tag string")
    assert {r["word"] for r in C.mixed_words(base, "en", "local").collect()} <= {"smallthe", "holdingthe"}
    assert {r["word"] for r in C.mixed_words(base, "local", "en").collect()} <= {"baruthe" + "ing", "hoguing"}


def test_cleaned_comments(spark):
    rows = [(1, "en", "Small need take"), (2, "en", "small need take"), (3, "fr", "ok go"), (4, "fr", "ಕನ್ one two"), (5, "fr", "coolagiru\u200d need 😀 baruthe"), (6, "fr", "😀 😀 😀"), (7, "fr", None)]
    docs = spark.createDataFrame(rows, "doc_id long, lang string, text string")
    lexicon = spark.createDataFrame([(w,) for w in ("small", "need", "take", "ok", "go")], "word string")
    kept, funnel = C.clean_comments(docs, lexicon, "[ಀ-೿]")
    assert [(r["doc_id"], r["text"]) for r in kept.collect()] == [(5, "coolagiru need  baruthe")] and kept.columns == docs.columns
    assert tuple(funnel.first()) == (6, 5, 4, 2, 1)  # a null is no comment
    kept, _ = C.clean_comments(docs, lexicon, "[ಀ-೿]", rules=("duplicate",), emoji_mode="drop_only_emoji")
    assert {r["doc_id"]: r["text"] for r in kept.collect()}.keys() >= {1, 3, 4, 5} and 6 not in {r["doc_id"] for r in kept.collect()}


def test_usual_spellings(spark):
    words = spark.createDataFrame([("goooood",), ("gr8",), ("omg",), ("plain",), ("b4",), ("sooon",)], "w string")
    got = [r[0] for r in words.select(T.normalise(F.col("w"))).collect()]
    assert got == ["good", "great", "oh my god", "plain", "before", "soon"]
    assert [r[0] for r in words.select(T.normalise(F.col("w"), ())).collect()] == ["goooood", "gr8", "omg", "plain", "b4", "sooon"]


def test_artifacts_have_kind_and_version(spark, tmp_path):
    from wordlid import io

    df = spark.createDataFrame([("a", 1)], "word string, n int")
    io.save_artifact(df, f"{tmp_path}/x", "words", 2)
    assert io.load_artifact(spark, f"{tmp_path}/x", "words", 2).collect() == df.collect()
    with pytest.raises(ValueError):
        io.load_artifact(spark, f"{tmp_path}/x", "words", 1)


def test_cost_report(spark):
    got = M.cost_report(spark, lambda: spark.range(1000).groupBy((F.col("id") % 7).alias("k")).count().collect(), {"dense": 7}).collect()
    assert [r["tasks"] for r in got if r["kind"] == "parameters"] == [7]
    assert sum(r["shuffle_bytes"] for r in got if r["kind"] == "stage") > 0


def test_written_tables_and_kept_ones(spark, tmp_path):
    from wordlid import io
    from wordlid.plans import common

    t = io.cut_lineage(spark.range(5))
    io.discard(t, t, None)
    assert t._wordlid_path not in io._written
    spark.range(3).write.parquet(f"{tmp_path}/a.parquet")
    count = lambda: common.kept(spark, str(tmp_path), "n", lambda: spark.read.parquet(f"{tmp_path}/a.parquet")).count()
    assert count() == 3
    spark.range(8).write.mode("overwrite").parquet(f"{tmp_path}/a.parquet")
    assert count() == 8  # other files under the same path

    class Context:
        applicationId, master = "app", "yarn"

        def getCheckpointDir(self):
            return None

    class Session:
        sparkContext, conf = Context(), {}

    with pytest.raises(ValueError):  # no machine's own folder on a cluster
        io.shared_root(Session())


def test_written_tables_may_have_any_name(spark):
    """Signs that a reader takes for a pattern are not in the path."""
    from wordlid.io import cut_lineage, discard

    for name in ("weights-[1.0, 2.0, 1.0]", "a{b,c}*?", "x/y"):
        t = cut_lineage(spark.range(3), name)
        assert t.count() == 3
        discard(t)


def test_merges_in_arrays_are_those_of_the_loop():
    import random

    rng = random.Random(1)
    for letters in ("ab", "abcdé\U0001F600"):
        for _ in range(40):
            words = list({"".join(rng.choice(letters) for _ in range(rng.randrange(1, 12))) for _ in range(rng.randrange(1, 40))})
            counts = [rng.randrange(1, 6) for _ in words]
            assert G.train_bpe_arrays(words, np.array(counts), 60) == G.train_bpe(list(zip(words, counts, strict=True)), 60)
    assert G.train_bpe_arrays([], np.zeros(0, np.int64), 5) == []


def test_single_precision_trains_like_double():
    """One step in single precision gives the weights of one in double, and stays in single precision; padded sequences too."""
    rng = np.random.default_rng(2)
    w = R.lm_weights(20, 6, 5, 2)
    ids = rng.integers(3, 20, (4, 8))
    mask = np.ones(ids.shape)
    mask[1, 5:] = mask[2, 3:] = 0
    loss, grads = R.lm_gradient(0.0)(w, (ids, mask), rng)
    low, got = R.lm_gradient(0.0)(R.single(w), (ids, mask), rng)
    assert abs(loss - low) < 1e-4
    for k, g in grads.items():
        assert got[k].dtype == np.float32 and np.allclose(g, got[k], atol=1e-4), k
