"""The four taggers, their component estimators and parts, trained and tested on the tagged word set.

All taggers have the same six tags, learn from all of the same 70 % of the tagged words and are tested on all of the other 30 %. Raw text,
which language models and vectors learn from, is read whole. Sizes and schedules of the neural models are small here, as every query has to
end on one machine; the operators' defaults are the published ones.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from wordlid.functions import text as T
from wordlid.io import bound_batches, read_table, small_table
from wordlid.operators import corpus as C
from wordlid.operators import estimators as E
from wordlid.operators import features as X
from wordlid.operators import metrics as M
from wordlid.operators import recurrent as R
from wordlid.operators import segment as G
from wordlid.operators import vectors as V
from wordlid.plans.common import BUCKET, LOCAL, PAIR, SENT, SPLIT, TYP, kept, once, sentences, tagged, types

Q: dict = {}
S: dict = {}
#: Features of the fitted vectors: the most frequent ones of the training words. Places of the hashed ones.
MOST_FEATURES, PLACES = 1 << 16, 1 << 18
DIMS, SLOTS = (40, 20, 10), (8, 10)
#: Merges of the English segmenter and of the language model, pieces of the unigram model and of the tokenizer.
ENGLISH_MERGES, LM_MERGES, UNIGRAM_PIECES, TOKENIZER_PIECES = 1000, 300, 500, 10_000
#: Hidden units and longest window of the recurrent tagger; width, hidden units, layers and window of the language model.
RECURRENT, LANGUAGE_MODEL = (32, 64), (32, 48, 2, 40)
KINDS = ("svm", "lr", "mlp")


def query(name: str, sql: str | None = None):
    def put(f):
        Q[name] = f
        if sql:
            S[name] = sql
        return f

    return put


def number(c="tag"):
    return (F.array_position(F.array(*map(F.lit, C.TAGS)), F.col(c)) - 1).cast("int")


def english(spark, d):
    """Merges learned from all English types, which expose English stems inside mixed words."""
    return once(spark, d, "bpe", lambda: G.learn_merges(types(spark, d).filter("e > 0").filter(F.col("word").rlike("^[a-z]+$")), ENGLISH_MERGES))


def pieced(spark, d):
    def make():
        t = tagged(spark, d)
        return t.select("word", "tag", G.encode_bpe(t, english(spark, d)).alias("pieces"))

    return kept(spark, d, "pieced", make)


def is_train(key="word"):
    return T.bucket(F.col(key), "t") < 70


def split(df):
    return df.filter(is_train()), df.filter(~is_train())


# ---- features -----------------------------------------------------------------


def feature_bag(spark, d):
    """word, family, feature, n of all tagged words."""
    rows = lambda: pieced(spark, d).select("word", F.explode(T.families(F.col("word"), F.col("pieces"))).alias("x"))
    return kept(spark, d, "feature-bag", lambda: rows().groupBy("word", "x.family", "x.feature").agg(F.count("*").alias("n")))


def vocabulary(spark, d, families):
    """idx, family, feature, words, uses: the features of the training words, the most used ones first."""

    def make():
        uses = X.feature_uses(pieced(spark, d).filter(is_train()), families)
        order = (F.desc("uses"), "family", "feature")
        top = uses.orderBy(*order).limit(MOST_FEATURES)
        return top.select((F.row_number().over(Window.orderBy(*order)) - 1).alias("idx"), "family", "feature", "words", "uses")  # MOST_FEATURES rows

    return kept(spark, d, f"vocabulary-{families}", make)


def ngram_rows(spark, d, families="spgb"):
    """Counts under the fitted vocabulary; a word without any known feature has an empty row."""

    def make():
        places: dict[str, dict[str, int]] = {f: {} for f in families}
        for r in vocabulary(spark, d, families).collect():  # MOST_FEATURES rows
            places[r["family"]][r["feature"]] = r["idx"]
        return X.count_rows(pieced(spark, d).select("word", number().alias("y"), "pieces"), places)

    return kept(spark, d, f"ngrams-{families}", make)


def hashed_rows(spark, d):
    """Counts under hashed places: no vocabulary is kept anywhere."""

    def make():
        place = F.pmod(F.xxhash64("family", "feature"), F.lit(PLACES)).cast("int")
        each = feature_bag(spark, d).groupBy("word", place.alias("idx")).agg(F.sum("n").cast("float").alias("n")).groupBy("word").agg(F.array_sort(F.collect_list(F.struct("idx", "n"))).alias("a"))
        rows = tagged(spark, d).select("word", number().alias("y")).join(each, "word")
        return rows.select("word", "y", F.transform("a", lambda x: x["idx"]).alias("idx"), F.transform("a", lambda x: x["n"]).alias("val"))

    return kept(spark, d, "hashed", make)


_ENDS = lambda side, mark: "(" + " || ".join(f"CASE WHEN length(word) >= {k} THEN [{{'family': '{mark}', 'feature': {side}(word, {k})}}] ELSE [] END" for k in (1, 2, 3)) + ")"
_GRAMS = lambda k: f"CASE WHEN length(word) + 2 >= {k} THEN list_transform(generate_series(1, length(word) + 3 - {k}), lambda i: {{'family': 'g', 'feature': substr('_' || word || '_', i::INTEGER, {k})}}) ELSE [] END"
BAG = f"bag AS (SELECT word, x.family AS family, x.feature AS feature, count(*) AS n FROM (SELECT word, unnest({_ENDS('right', 's')} || {_ENDS('left', 'p')} || " + " || ".join(f"({_GRAMS(k)})" for k in (2, 3, 5)) + ") AS x FROM tagged) GROUP BY ALL)"
query("w7_feature_bag", f"WITH {SPLIT}, {BAG} SELECT word, family, feature, n FROM bag")(lambda spark, d: feature_bag(spark, d).filter("family <> 'b'"))
query("w7_piece_bag")(lambda spark, d: feature_bag(spark, d).filter("family = 'b'"))
query("w7_count_vectors", f"WITH {SPLIT}, {BAG}, u AS (SELECT family, feature, count(*) AS words, sum(n)::BIGINT AS uses FROM bag JOIN train USING (word) GROUP BY ALL ORDER BY uses DESC, family, feature LIMIT {MOST_FEATURES}) SELECT (row_number() OVER (ORDER BY uses DESC, family, feature) - 1)::INTEGER AS idx, family, feature, words, uses FROM u")(lambda spark, d: vocabulary(spark, d, "spg"))


@query("w7_hash_collisions")
def collisions(spark, d):
    """How many features share a place of the hashed vectors."""
    place = F.pmod(F.xxhash64("family", "feature"), F.lit(PLACES))
    each = feature_bag(spark, d).select("family", "feature").distinct().groupBy(place.alias("place")).agg(F.count("*").alias("k"))
    return each.agg(F.sum("k").alias("features"), F.count("*").alias("used"), F.sum(F.when(F.col("k") > 1, F.col("k")).otherwise(0)).alias("colliding"))


def skipgram(spark, d, level):
    def make():
        if level == "word":
            return V.train_skipgram(C.sentence_words(sentences(spark, d).filter(F.col("lang").isin("en", LOCAL))), "seq", DIMS[0], min_count=3)
        if level == "piece":
            return V.train_skipgram(pieced(spark, d).select(F.col("pieces").alias("seq")).filter(F.size("seq") > 0), "seq", DIMS[1], epochs=3)
        return V.train_skipgram(pieced(spark, d).select(letters("word").alias("seq")), "seq", DIMS[2], epochs=3)

    return kept(spark, d, f"skipgram-{level}", make)


def letters(c):
    return F.filter(F.split(c, ""), lambda x: x != "")


def composed(spark, d):
    return kept(spark, d, "composed", lambda: V.compose(pieced(spark, d).select("word", "pieces"), *[skipgram(spark, d, x) for x in V.BLOCKS], DIMS, SLOTS))


def composed_rows(spark, d, first=0, last=None):
    """Composed vectors, or the places [first, last) of them."""
    width = (V.composed_width(*DIMS, *SLOTS) if last is None else last) - first
    rows = composed(spark, d).join(tagged(spark, d).select("word", "tag"), "word")
    return rows.select("word", number().alias("y"), F.sequence(F.lit(0), F.lit(width - 1)).alias("idx"), F.slice("vec", first + 1, width).alias("val")), width


def hybrid_rows(spark, d):
    """n-gram counts and composed vectors side by side."""
    rows, width = composed_rows(spark, d)
    b = rows.select("word", F.transform("idx", lambda i: i + MOST_FEATURES).alias("i2"), F.col("val").alias("v2"))
    return ngram_rows(spark, d).join(b, "word").select("word", "y", F.concat("idx", "i2").alias("idx"), F.concat("val", "v2").alias("val")), MOST_FEATURES + width


def vectors_of(spark, d, kind):
    if kind == "composed":
        return composed_rows(spark, d)
    if kind == "hybrid":
        return hybrid_rows(spark, d)
    if kind == "hashed":
        return hashed_rows(spark, d), PLACES
    if kind == "binary":  # whether a word has a feature, not how often
        return ngram_rows(spark, d).withColumn("val", F.transform("val", lambda _: F.lit(1.0).cast("float"))), MOST_FEATURES
    return ngram_rows(spark, d, {"ngrams": "spgb", "affixes": "sp", "word_ngrams": "g", "piece_ngrams": "b"}[kind]), MOST_FEATURES


# ---- estimators and votes -------------------------------------------------------


def estimator(spark, d, kind, features, balanced=False):
    def make():
        rows, width = vectors_of(spark, d, features)
        return E.fit(kind, split(rows)[0], width, balanced=balanced)

    return once(spark, d, f"{kind}-{features}-{balanced}", make)


def tag(spark, d, kinds, features, mode="soft", weights=None, balanced=False):
    def make():
        rows, width = vectors_of(spark, d, features)
        return E.predict([estimator(spark, d, k, features, balanced) for k in kinds], split(rows)[1], width, mode, weights).select("word", "gold", "pred")

    return kept(spark, d, f"pred-{'-'.join(kinds)}-{features}-{mode}-{weights}-{balanced}", make)


for _k in KINDS:
    for _f in ("ngrams", "composed"):
        query(f"m_single_{_k}_{_f}")(lambda spark, d, k=_k, f=_f: tag(spark, d, (k,), f))
query("m_ngram_vote")(lambda spark, d: tag(spark, d, KINDS, "ngrams"))
query("m_embedding_vote")(lambda spark, d: tag(spark, d, KINDS, "composed"))
for _f in ("affixes", "word_ngrams", "piece_ngrams", "hashed", "binary"):
    query(f"m_single_lr_{_f}")(lambda spark, d, f=_f: tag(spark, d, ("lr",), f))
query("m_ngram_hard_vote")(lambda spark, d: tag(spark, d, KINDS, "ngrams", "hard"))
query("m_ngram_weighted_vote")(lambda spark, d: tag(spark, d, KINDS, "ngrams", "soft", [1.0, 2.0, 1.0]))
query("m_single_lr_balanced")(lambda spark, d: tag(spark, d, ("lr",), "ngrams", balanced=True))
for _k in KINDS:
    query(f"m_hybrid_{_k}")(lambda spark, d, k=_k: tag(spark, d, (k,), "hybrid"))
query("m_hybrid_vote")(lambda spark, d: tag(spark, d, KINDS, "hybrid"))
for _x in V.BLOCKS:
    query(f"m_skipgram_{_x}")(lambda spark, d, x=_x: skipgram(spark, d, x))
query("m_skipgram_negative")(lambda spark, d: kept(spark, d, "skipgram-negative", lambda: V.train_skipgram_negative(pieced(spark, d).select(letters("word").alias("seq")), "seq", DIMS[2])))
query("m_similar")(lambda spark, d: V.similar(composed(spark, d), composed(spark, d).agg(F.min_by("word", F.md5("word"))).first()[0]))
query("w8_compose")(lambda spark, d: composed(spark, d))


@query("w8_block_ablation")
def blocks(spark, d):
    """Macro scores of the regression on the word block, on words and pieces, and on whole composed vectors."""
    ends = {"word": DIMS[0], "word+piece": DIMS[0] + SLOTS[0] * DIMS[1], "word+piece+char": V.composed_width(*DIMS, *SLOTS)}
    out = None
    for name, last in ends.items():
        def make(last=last):
            rows, width = composed_rows(spark, d, 0, last)
            train, test = split(rows)
            return E.predict([E.fit("lr", train, width)], test, width).select("word", "gold", "pred")

        one = M.macro(M.per_tag(M.confusion(kept(spark, d, f"pred-blocks-{last}", make)))).withColumn("blocks", F.lit(name))
        out = one if out is None else out.unionByName(one)
    return out


_WORDS = "(SELECT regexp_extract_all(text, '[^ ]+') AS word, list_filter(string_split(text, ''), lambda c: c <> ' ') AS char FROM sent)"
query("w8_suggest_dims", f"WITH {SENT}, w AS {_WORDS} " + " UNION ALL ".join(f"SELECT '{x}' AS level, (SELECT count(DISTINCT u) FROM (SELECT unnest({x}) AS u FROM w)) AS different, round(avg(len(list_distinct({x}))), 6) AS average FROM w" for x in ("word", "char")))(
    lambda spark, d: V.suggest_dims(sentences(spark, d).select(F.regexp_extract_all("text", F.lit("[^ ]+"), F.lit(0)).alias("word"), F.filter(F.split("text", ""), lambda c: (c != " ") & (c != "")).alias("char")), ("word", "char"))
)


@query("w15_dense")
def dense(spark, d):
    """The three estimators and their vote on the dense table, ten classes: share of the held-out rows that is right."""
    e = read_table(spark, d, "embeddings")
    rows = e.select(F.col("vec_id").cast("string").alias("word"), F.col("label").cast("int").alias("y"), F.sequence(F.lit(0), F.lit(63)).alias("idx"), F.col("embedding").alias("val"), (F.col("vec_id") % 10 < 7).alias("train"))
    train, test, names = rows.filter("train").drop("train"), rows.filter("not train"), tuple(map(str, range(10)))
    fitted = {k: once(spark, d, f"dense-{k}", lambda k=k: E.fit(k, train, 64, classes=10)) for k in KINDS}
    out = None
    for name, some in [*((k, [fitted[k]]) for k in KINDS), ("vote", list(fitted.values()))]:
        one = E.predict(some, test, 64, names=names).agg(F.count("*").alias("rows"), F.round(F.avg((F.col("gold") == F.col("pred")).cast("double")), 6).alias("accuracy")).withColumn("estimator", F.lit(name))
        out = one if out is None else out.unionByName(one)
    return out


# ---- sub-words -----------------------------------------------------------------


def table_of(spark, kind, rows):
    import pyarrow as pa

    columns = list(zip(*rows, strict=True)) if rows else [[] for _ in kind]
    return small_table(spark, **{name: pa.array(c, t) for (name, t), c in zip(kind.items(), columns, strict=True)})


@query("m_bpe")
def bpe(spark, d):
    import pyarrow as pa

    return table_of(spark, {"rank": pa.int32(), "left": pa.string(), "right": pa.string()}, [(i, a, b) for i, (a, b) in enumerate(english(spark, d))])


query("w6_pieces")(lambda spark, d: pieced(spark, d).select("word", "pieces"))


@query("op_pandas_encode")
def encoded(spark, d):
    """All types of letters through an Arrow UDF."""
    t = types(spark, d).filter(F.col("word").rlike("^[a-z]+$"))
    return t.select("word", G.encode_bpe(t, english(spark, d)).alias("pieces")).select("word", "pieces", F.size("pieces").alias("n_pieces"))


@query("w8_piece_slots")
def piece_slots(spark, d):
    """Pieces and characters of a word, at most and on average, and the width that they make."""
    p = pieced(spark, d).select(F.size("pieces").alias("p"), F.length("word").alias("c"))
    return p.agg(F.max("p").alias("max_pieces"), F.round(F.avg("p"), 6).alias("avg_pieces"), F.max("c").alias("max_chars"), F.round(F.avg("c"), 6).alias("avg_chars"), (200 + 100 * F.max("p") + 30 * F.max("c")).alias("width"))


def unigram_model(spark, d):
    return once(spark, d, "unigram", lambda: G.train_unigram_spark(types(spark, d).filter(F.col("word").rlike("^[a-z]+$")), UNIGRAM_PIECES))


@query("m_unigram")
def unigram(spark, d):
    import pyarrow as pa

    return table_of(spark, {"piece": pa.string(), "score": pa.float64()}, sorted(unigram_model(spark, d).items()))


@query("w6_unigram_pieces")
def unigram_pieces(spark, d):
    t = tagged(spark, d)
    return t.select("word", G.encode_unigram(t, unigram_model(spark, d)).alias("pieces"))


def raw_sentences(spark, d, held=False):
    """The pair's sentences but for the tenth that is held out, or that tenth."""
    out = T.bucket(F.concat_ws(":", "doc_id", "sent_no"), "s") < 10
    return sentences(spark, d).filter(F.col("lang").isin("en", LOCAL)).filter(out if held else ~out)


def tokenizer(spark, d):
    """Learned from all words of the raw sentences."""
    words = lambda: raw_sentences(spark, d).select(F.explode(F.split("text", " +")).alias("word")).filter("word <> ''").groupBy("word").agg(F.count("*").alias("n"))
    return once(spark, d, "tokenizer", lambda: G.train_tokenizer(kept(spark, d, "raw-words", words), TOKENIZER_PIECES))


@query("w9_tokenizer")
def tokenizer_table(spark, d):
    import pyarrow as pa

    return table_of(spark, {"piece": pa.string(), "id": pa.int32(), "score": pa.float64()}, tokenizer(spark, d))


@query("w9_decode", f"WITH {SENT} SELECT count(*) AS sentences, count(*) AS same FROM sent WHERE {PAIR} AND {BUCKET("'s' || doc_id || ':' || sent_no")} < 10")
def decoded(spark, d):
    """Held-out sentences that come back from their pieces as they were."""
    s = raw_sentences(spark, d, True)
    back = G.decode(G.tokenize(s, "text", tokenizer(spark, d)))
    return s.select((back == F.array_join(F.split("text", " +"), " ")).alias("same")).agg(F.count("*").alias("sentences"), F.count_if("same").alias("same"))


# ---- sequence tagger -------------------------------------------------------------


def sequences(spark, d):
    """sid, words: spliced sentences in which every planted word of the tagged set stands somewhere; a tagged word that no sentence has is a
    sequence of its own, so all of them can be tagged."""

    def make():
        s = kept(spark, d, "splices", lambda: C.splice(sentences(spark, d)))
        full = C.insert_words(s, tagged(spark, d).filter(F.col("tag").isin("name", "location", "mixed")))
        full = kept(spark, d, "inserted", lambda: full)
        alone = tagged(spark, d).select("word").join(full.select(F.explode("words").alias("word")).distinct(), "word", "left_anti")
        return full.unionByName(alone.select(F.concat(F.lit("w-"), "word").alias("sid"), F.array("word").alias("words")))

    return kept(spark, d, "sequences", make)


def unit_table(spark, d, level):
    """Ids from 1 of pieces or characters, and their vectors; row 0 is zero. Bounded by merges and alphabet."""

    def make():
        rows = skipgram(spark, d, level).orderBy("unit").collect()
        dim = DIMS[V.BLOCKS.index(level)]
        return {r["unit"]: i + 1 for i, r in enumerate(rows)}, np.concatenate([np.zeros((1, dim)), np.array([r["v"] for r in rows]).reshape(-1, dim)])

    return once(spark, d, f"units-{level}", make)


def packed(spark, d):
    """sid, words, tags (-1: none), train (whether a tag may be learned), and word vectors, piece and character ids side by side."""

    def make():
        (pieces, _), (chars, _) = unit_table(spark, d, "piece"), unit_table(spark, d, "char")
        sent = spark.sparkContext.broadcast(({p: i for i, p in enumerate(english(spark, d))}, pieces, chars))

        @F.pandas_udf("p array<int>, c array<int>")
        def codes(words: pd.Series) -> pd.DataFrame:
            ranks, piece_ids, char_ids = sent.value
            fill = lambda ids, n: (ids + [0] * n)[:n]
            return pd.DataFrame({"p": [fill([piece_ids.get(x, 0) for x in G.split_bpe(w, ranks)], SLOTS[0]) for w in words], "c": [fill([char_ids.get(x, 0) for x in w], SLOTS[1]) for w in words]})

        bound_batches(spark)
        at = sequences(spark, d).select("sid", F.posexplode("words").alias("pos", "word"))
        known = at.select("word").distinct().join(skipgram(spark, d, "word").withColumnRenamed("unit", "word"), "word", "left").join(tagged(spark, d).select("word", number().alias("y")), "word", "left")
        known = known.select("word", F.coalesce("v", F.array_repeat(F.lit(0.0).cast("float"), DIMS[0])).alias("v"), F.coalesce("y", F.lit(-1)).alias("y"), codes("word").alias("k"))
        one = at.join(known, "word").groupBy("sid").agg(F.array_sort(F.collect_list(F.struct("pos", "word", "y", "v", "k.p", "k.c"))).alias("a"))
        flat = lambda name: F.flatten(F.transform("a", lambda x: x[name])).alias(name)
        return one.select("sid", F.transform("a", lambda x: x["word"]).alias("words"), F.transform("a", lambda x: x["y"]).alias("tags"), F.transform("a", lambda x: T.bucket(x["word"], "t") < 70).alias("train"), flat("v"), flat("p"), flat("c"))

    return kept(spark, d, "packed", make)


def recurrent(spark, d, both=True, masked=True):
    """Test words, each with the tag that most of its places in the sentences get."""

    def make():
        rows = packed(spark, d)
        vectors = R.Vectors(unit_table(spark, d, "piece")[1], unit_table(spark, d, "char")[1], DIMS, SLOTS)
        seen = lambda keep: F.zip_with("tags", "train", lambda y, t: F.when(t if keep else ~t, y).otherwise(-1)).alias("ys")
        train = rows.select("sid", seen(True), "v", "p", "c").filter(F.exists("ys", lambda y: y >= 0))
        hidden, window = RECURRENT
        w = R.fit_tagger(train, vectors, hidden, ((4, 64), (2, 32)), window, 4, both, masked)
        test = rows.select("words", seen(False), "v", "p", "c").filter(F.exists("ys", lambda y: y >= 0))
        each = R.tag_sequences(test, w, vectors, masked).filter("gold is not null").groupBy("word", "gold", "pred").agg(F.count("*").alias("n"))
        return each.groupBy("word", "gold").agg(F.min_by("pred", F.struct(-F.col("n"), number("pred"))).alias("pred"))

    return kept(spark, d, f"pred-recurrent-{both}-{masked}", make)


query("m_recurrent")(recurrent)
query("m_recurrent_forward")(lambda spark, d: recurrent(spark, d, both=False))
query("m_recurrent_unmasked")(lambda spark, d: recurrent(spark, d, masked=False))


# ---- language model and transfer -------------------------------------------------


def language_pieces(spark, d):
    """Merges and ids of the language model, its alphabet from all types."""

    def make():
        merges = english(spark, d)[:LM_MERGES]
        return merges, G.vocabulary(types(spark, d), merges)

    return once(spark, d, "lm-pieces", make)


def language_model(spark, d):
    """Learned from all raw sentences of the pair."""

    def make():
        merges, vocab = language_pieces(spark, d)
        s = raw_sentences(spark, d)
        width, hidden, layers, window = LANGUAGE_MODEL
        return R.train_lm(s.select(G.piece_ids(s, "text", merges, vocab).alias("xs")), len(vocab) + 3, width, hidden, layers, ((2, 32),), window, 2), merges, vocab

    return once(spark, d, "lm", make)


def perplexities(rows, by, w):
    """Perplexity of the rows' pieces (xs) by a column."""
    sent = rows.sparkSession.sparkContext.broadcast(w)
    window = LANGUAGE_MODEL[3]

    def losses(batches):
        for b in batches:
            for name, g in b.groupby(by):
                total, n = R.lm_loss(sent.value, [list(x) for x in g["xs"]], window)
                yield pd.DataFrame({by: [name], "loss": [total], "n": [n]})

    return rows.select(by, "xs").mapInPandas(losses, f"{by} string, loss double, n long").groupBy(by).agg(F.sum("n").alias("pieces"), F.exp(F.sum("loss") / F.sum("n")).alias("perplexity"))


@query("m_lm")
def lm(spark, d):
    """Perplexity by language of the held-out tenth under the recurrent language model."""
    w, merges, vocab = language_model(spark, d)
    held = raw_sentences(spark, d, True)
    return perplexities(held.select("lang", G.piece_ids(held, "text", merges, vocab).alias("xs")), "lang", w)


@query("m_next_words")
def next_words(spark, d):
    """The five likeliest pieces at the start of a sentence, and after the most frequent word of the local language."""
    import pyarrow as pa

    w, merges, vocab = language_model(spark, d)
    names = {i: piece for piece, i in vocab.items()} | {2: "<word>", 1: "<unknown>", 0: "<pad>"}
    common = types(spark, d).filter("l * 5 >= n * 4").orderBy(F.desc("n"), "word").limit(1).collect()
    ranks = {p: i for i, p in enumerate(merges)}
    prefixes = {"": []} | {r["word"]: [2, *(vocab.get(p, 1) for p in G.split_bpe(r["word"], ranks))] for r in common}
    rows = [(prefix, at, names.get(i, ""), p) for prefix, ids in prefixes.items() for at, (i, p) in enumerate(R.next_pieces(w, ids))]
    return table_of(spark, {"prefix": pa.string(), "rank": pa.int32(), "piece": pa.string(), "probability": pa.float64()}, rows)


def word_pieces(spark, d):
    merges, vocab = language_pieces(spark, d)
    t = tagged(spark, d)
    return kept(spark, d, "word-pieces", lambda: t.select("word", number().alias("y"), G.piece_ids(t, "word", merges, vocab).alias("xs")).filter(F.size("xs") > 0))


def tuned(spark, d):
    """The language model, tuned further on the text of the training words."""

    def make():
        w, _, vocab = language_model(spark, d)
        width, hidden, layers, window = LANGUAGE_MODEL
        return R.train_lm(split(word_pieces(spark, d))[0].select("xs"), len(vocab) + 3, width, hidden, layers, ((3, 32),), window, 2, start=w, rate=0.02)

    return once(spark, d, "lm-tuned", make)


@query("m_lm_finetuned")
def finetuned(spark, d):
    """Perplexity of the test words' text before and after the language model is tuned on the training words."""
    out = None
    for stage, w in (("before", language_model(spark, d)[0]), ("after", tuned(spark, d))):
        one = perplexities(split(word_pieces(spark, d))[1].withColumn("stage", F.lit(stage)), "stage", w)
        out = one if out is None else out.unionByName(one)
    return out


def transfer(spark, d, mode):
    def make():
        train, test = split(word_pieces(spark, d))
        width, hidden, layers, _ = LANGUAGE_MODEL
        # fresh weights have the language model's shapes only, so none is trained for them
        start = tuned(spark, d) if mode != "none" else R.lm_weights(len(language_pieces(spark, d)[1]) + 3, width, hidden, layers)
        return R.tag_words(test, R.fit_transfer(train, start, mode, ((4, 32),)))

    return kept(spark, d, f"pred-transfer-{mode}", make)


query("m_lm_transfer")(lambda spark, d: transfer(spark, d, "full"))
query("m_lm_transfer_frozen")(lambda spark, d: transfer(spark, d, "frozen"))
query("m_lm_transfer_fresh")(lambda spark, d: transfer(spark, d, "none"))


# ---- comparisons -----------------------------------------------------------------

FOUR = ("m_embedding_vote", "m_ngram_vote", "m_recurrent", "m_lm_transfer")
SINGLE = tuple(f"m_single_{k}_{f}" for f in ("composed", "ngrams") for k in KINDS)


def scored(spark, d, names):
    """model and per-tag scores, of predictions that are written once."""
    out = None
    for name in names:
        one = M.per_tag(M.confusion(Q[name](spark, d))).withColumn("model", F.lit(name))
        out = one if out is None else out.unionByName(one)
    return out


@query("w10_compare")
def compare(spark, d):
    """Macro precision, recall and F1 of every tagger on the same held-out words."""
    one = scored(spark, d, [*SINGLE, *FOUR]).groupBy("model")
    return one.agg(F.sum("support").alias("words"), *[F.round(F.avg(c), 5).alias(f"macro_{c}") for c in ("precision", "recall", "f1")])


query("w11_four_taggers")(lambda spark, d: scored(spark, d, FOUR))
query("w12_f1_pivot_taggers")(lambda spark, d: M.f1_pivot(scored(spark, d, FOUR)))


@query("w13_tagger_deltas")
def deltas(spark, d):
    """Differences of macro F1: of features under the same learners, of deep and shallow learners on the same vectors, of votes and their
    best single estimator, of pretraining, of feature families, of balanced training."""
    names = [*SINGLE, *FOUR, "m_lm_transfer_fresh", "m_lm_transfer_frozen", "m_single_lr_affixes", "m_single_lr_word_ngrams", "m_single_lr_piece_ngrams", "m_single_lr_balanced", "m_recurrent_forward"]
    m = scored(spark, d, names).groupBy("model").agg(F.avg("f1").alias("f1")).agg(F.map_from_entries(F.collect_list(F.struct("model", "f1"))).alias("m"))  # one row
    of = lambda x: F.element_at("m", x)
    best = lambda f: F.greatest(*[of(f"m_single_{k}_{f}") for k in KINDS])
    pairs = {
        "ngrams over vectors, vote": of("m_ngram_vote") - of("m_embedding_vote"), **{f"ngrams over vectors, {k}": of(f"m_single_{k}_ngrams") - of(f"m_single_{k}_composed") for k in KINDS},
        "recurrent over vote, vectors": of("m_recurrent") - of("m_embedding_vote"), "vote over best single, ngrams": of("m_ngram_vote") - best("ngrams"), "vote over best single, vectors": of("m_embedding_vote") - best("composed"),
        "pretrained over fresh": of("m_lm_transfer") - of("m_lm_transfer_fresh"), "whole over frozen": of("m_lm_transfer") - of("m_lm_transfer_frozen"), "both directions over one": of("m_recurrent") - of("m_recurrent_forward"),
        **{f"all features over {f}": of("m_single_lr_ngrams") - of(f"m_single_lr_{f}") for f in ("affixes", "word_ngrams", "piece_ngrams")}, "balanced over plain": of("m_single_lr_balanced") - of("m_single_lr_ngrams"),
    }
    return m.select(F.explode(F.array(*[F.struct(F.lit(k).alias("contrast"), F.round(v, 5).alias("delta")) for k, v in pairs.items()])).alias("x")).select("x.*")


@query("v_cost")
def cost(spark, d):
    """What the comparison of a closed-form tagger costs: jobs, tasks, rows and bytes of each stage, and the parameters of the published layers."""
    from wordlid.plans.workloads import scores

    return M.cost_report(spark, lambda: scores(spark, d, "b3").collect(), R.param_counts(19162, 1000, 300, 7))
