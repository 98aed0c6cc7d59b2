"""The experiment workloads on the given tables, and their SQL."""

from __future__ import annotations

from pyspark.sql import functions as F
from pyspark.sql.window import Window

from wordlid.functions import text as T
from wordlid.io import read_table
from wordlid.operators import baselines as B
from wordlid.operators import corpus as C
from wordlid.operators import metrics as M
from wordlid.plans.common import BUCKET, LOCAL, ORDER, PAIR, ROM, SENT, SPLIT, TAGGED, TOK, TYP, docs, kept, parts, sentences, tagged, tokens, types

Q: dict = {}
S: dict = {}
TAGS = C.TAGS


def query(name: str, sql: str | None = None):
    def put(f):
        Q[name] = f
        if sql:
            S[name] = sql
        return f

    return put


WORDS = r"len(regexp_extract_all(text, '[^\x20\x09-\x0D]+'))"
SCRIPT = r"regexp_matches(text, '[^\x00-\x7F]')"


@query("w1_collect", f"WITH {SENT} SELECT source, count(DISTINCT doc_id) AS comments, count(*) AS sentences FROM sent GROUP BY source")
def w1(spark, d):
    return sentences(spark, d).groupBy("source").agg(F.count_distinct("doc_id").alias("comments"), F.count("*").alias("sentences"))


def pair(spark, d):
    return docs(spark, d).select("doc_id", "source", "lang", "text").filter(F.col("lang").isin("en", LOCAL))


def lexicon(spark, d):
    """Words that are at least four fifths English, lower-cased and with accents kept."""
    words = docs(spark, d).select("lang", F.explode(F.regexp_extract_all(F.lower("text"), F.lit(r"[^\x20\x09-\x0D]+"), F.lit(0))).alias("w"))
    counts = words.select("lang", F.regexp_replace("w", "[.,!?]+$", "").alias("word")).filter("word <> ''").groupBy("word").agg(F.count("*").alias("n"), F.count_if(F.col("lang") == "en").alias("e"))
    return kept(spark, d, "lexicon", lambda: counts.filter("e * 5 >= n * 4").select("word"))


FLAGS = rf"""lw AS (SELECT doc_id, lang, regexp_replace(unnest(regexp_extract_all(lower(text), '[^\x20\x09-\x0D]+')), '[.,!?]+$', '') AS word FROM documents),
 lex AS (SELECT word FROM lw WHERE word <> '' GROUP BY word HAVING count(*) FILTER (lang = 'en') * 5 >= count(*) * 4),
 p AS (SELECT doc_id, lang, text FROM documents WHERE {PAIR}),
 en AS (SELECT doc_id, bool_and(word IN (SELECT word FROM lex)) AS e FROM lw WHERE word <> '' GROUP BY doc_id),
 fl AS (SELECT p.doc_id, {SCRIPT} AS script, {WORDS} < 3 AS short, coalesce(en.e, true) AS english_only,
        p.doc_id <> min(p.doc_id) OVER (PARTITION BY lower(text)) AS duplicate FROM p LEFT JOIN en USING (doc_id))"""


def flags(spark, d):
    return kept(spark, d, "flags", lambda: C.clean_flags(pair(spark, d), lexicon(spark, d)))


@query("w2_funnel", f"WITH {FLAGS} SELECT count(*) AS comments, count(*) FILTER (NOT duplicate) AS after_dup, count(*) FILTER (NOT duplicate AND NOT script) AS after_script, count(*) FILTER (NOT duplicate AND NOT script AND NOT short) AS after_short, count(*) FILTER (NOT duplicate AND NOT script AND NOT short AND NOT english_only) AS after_english FROM fl")
def w2(spark, d):
    keep, out = F.lit(True), [F.count("*").alias("comments")]
    for rule, name in (("duplicate", "after_dup"), ("script", "after_script"), ("short", "after_short"), ("english_only", "after_english")):
        keep = keep & ~F.col(rule)
        out.append(F.count_if(keep).alias(name))
    return flags(spark, d).agg(*out)


for _rule, _name in (("duplicate", "w2_dup"), ("short", "w2_short"), ("script", "w2_script"), ("english_only", "w2_english_only")):
    query(_name, f"WITH {FLAGS} SELECT doc_id FROM fl WHERE NOT {_rule}")(lambda spark, d, r=_rule: flags(spark, d).filter(~F.col(r)).select("doc_id"))


@query("w3_split", f"WITH {SENT} SELECT doc_id, sent_no, CASE WHEN {BUCKET("'s' || doc_id || ':' || sent_no")} < 10 THEN 'tagged' ELSE 'raw' END AS part FROM sent WHERE {PAIR}")
def w3(spark, d):
    b = T.bucket(F.concat_ws(":", "doc_id", "sent_no"), "s")
    return sentences(spark, d).filter(F.col("lang").isin("en", LOCAL)).select("doc_id", "sent_no", F.when(b < 10, "tagged").otherwise("raw").alias("part"))


_STRIP = r"regexp_replace(text, '[\p{So}\p{Sk}\p{Cf}]|[\x00-\x09\x0B-\x1F\x7F-\x{9F}]', '', 'g')"
_WORDS3 = r"len(regexp_extract_all(text, '[^\x20\x09-\x0D]+')) >= 3"


@query("w2_clean", f"""WITH c AS (SELECT doc_id, {_STRIP} AS text FROM documents WHERE {PAIR}), lw AS (SELECT lang, regexp_replace(unnest(regexp_extract_all(lower(text), '[^\\x20\\x09-\\x0D]+')), '[.,!?]+$', '') AS word FROM documents),
 lex AS (SELECT word FROM lw WHERE word <> '' GROUP BY word HAVING count(*) FILTER (lang = 'en') * 5 >= count(*) * 4),
 cw AS (SELECT doc_id, regexp_replace(unnest(regexp_extract_all(lower(text), '[^\\x20\\x09-\\x0D]+')), '[.,!?]+$', '') AS word FROM c),
 en AS (SELECT doc_id, bool_and(word IN (SELECT word FROM lex)) AS e FROM cw WHERE word <> '' GROUP BY doc_id)
 SELECT doc_id, length(text) AS n_chars, md5(text) AS digest FROM (SELECT doc_id, text FROM c QUALIFY doc_id = min(doc_id) OVER (PARTITION BY lower(text))) LEFT JOIN en USING (doc_id) WHERE NOT regexp_matches(text, '[^\\x00-\\x7F]') AND {_WORDS3} AND NOT coalesce(e, true)""")
def w2c(spark, d):
    """The cleaned comments under all published rules."""
    kept_, _ = C.clean_comments(pair(spark, d), lexicon(spark, d))
    return kept_.select("doc_id", F.length("text").cast("long").alias("n_chars"), F.md5("text").alias("digest"))


@query("w2_corpus", f"""WITH c AS (SELECT doc_id, {_STRIP} AS text FROM documents WHERE {PAIR}) SELECT doc_id, length(text) AS n_chars, md5(text) AS digest FROM c WHERE {_WORDS3} QUALIFY doc_id = min(doc_id) OVER (PARTITION BY lower(text))""")
def w2k(spark, d):
    """The corpus that later steps can use on these tables: duplicates and short comments go, comments in English alone stay, and the
    rule on the script means the real block of the local script."""
    kept_, _ = C.clean_comments(pair(spark, d), lexicon(spark, d), "[\u0C80-\u0CFF]", rules=("duplicate", "script", "short"))
    return kept_.select("doc_id", F.length("text").cast("long").alias("n_chars"), F.md5("text").alias("digest"))


query("w4_tagged", f"WITH {TAGGED} SELECT word, tag, n FROM tagged")(tagged)


@query("w4_distribution", f"WITH {TAGGED} SELECT tag, count(*) AS types, round(count(*) / sum(count(*)) OVER ()::DOUBLE, 6) AS share FROM tagged GROUP BY tag")
def w4d(spark, d):
    counts = tagged(spark, d).groupBy("tag").agg(F.count("*").alias("types"))
    total = counts.agg(F.sum("types").alias("total"))
    return counts.crossJoin(F.broadcast(total)).select("tag", "types", F.round(F.col("types") / F.col("total"), 6).alias("share"))


@query("w4_stats", f"WITH {TOK} SELECT lang, count(DISTINCT (doc_id, sent_no)) AS sentences, count(*) AS words, count(DISTINCT word) AS unique_words FROM tok GROUP BY lang")
def w4s(spark, d):
    return tokens(spark, d).groupBy("lang").agg(F.count_distinct("doc_id", "sent_no").alias("sentences"), F.count("*").alias("words"), F.count_distinct("word").alias("unique_words"))


query("w5_split", f"WITH {SPLIT} SELECT word, tag, n, part FROM sp")(lambda spark, d: C.split_train_test(tagged(spark, d)))


@query("w5_leakage", f"WITH {SPLIT}, a AS (SELECT DISTINCT right(word, 3) AS x FROM train), b AS (SELECT right(word, 3) AS x FROM test) SELECT (SELECT count(*) FROM train JOIN test USING (word)) AS shared_types, count(*) FILTER (x IN (SELECT x FROM a)) AS known_suffix, count(*) AS test_types FROM b")
def w5(spark, d):
    train, test = parts(spark, d)
    known = train.select(F.right("word", F.lit(3)).alias("x")).distinct().withColumn("k", F.lit(1))
    out = test.select("word", F.right("word", F.lit(3)).alias("x")).join(known, "x", "left").join(train.select("word", F.lit(1).alias("t")), "word", "left")
    return out.agg(F.count("t").alias("shared_types"), F.count("k").alias("known_suffix"), F.count("*").alias("test_types"))


_PART = BUCKET("'o' || doc_id || ':' || sent_no")


@query("w5_oov", f"WITH {TOK}, t AS (SELECT word, {_PART} < 70 AS train FROM tok WHERE {PAIR}), k AS (SELECT DISTINCT word FROM t WHERE train) SELECT count(*) AS tokens, count(*) FILTER (k.word IS NULL) AS unknown_tokens, count(DISTINCT t.word) AS types, count(DISTINCT t.word) FILTER (k.word IS NULL) AS unknown_types FROM t LEFT JOIN k USING (word) WHERE NOT train")
def w5o(spark, d):
    """Words of the sentences held out that no other sentence has."""
    t = tokens(spark, d).filter(F.col("lang").isin("en", LOCAL)).select("word", (T.bucket(F.concat_ws(":", "doc_id", "sent_no"), "o") < 70).alias("train"))
    uses = t.groupBy("word").agg(F.count_if("train").alias("a"), F.count_if(~F.col("train")).alias("b")).filter("b > 0")  # one shuffle
    new = F.col("a") == 0
    return uses.agg(F.sum("b").alias("tokens"), F.coalesce(F.sum(F.when(new, F.col("b"))), F.lit(0)).alias("unknown_tokens"), F.count("*").alias("types"), F.count_if(new).alias("unknown_types"))


@query("w7_context_bag", f"WITH {TOK}, x AS (SELECT lag(word) OVER w AS a, lead(word) OVER w AS b FROM tok WHERE lang = '{LOCAL}' WINDOW w AS (PARTITION BY doc_id, sent_no ORDER BY pos)), y AS (SELECT -1 AS off, right(a, 3) AS feature FROM x WHERE a IS NOT NULL UNION ALL SELECT 1, right(b, 3) FROM x WHERE b IS NOT NULL) SELECT off, feature, count(*) AS n FROM y GROUP BY off, feature")
def w7x(spark, d):
    """Suffixes of the words on either side."""
    return C.context_bag(tokens(spark, d).filter(F.col("lang") == LOCAL)).groupBy(F.col("offset").alias("off"), "feature").agg(F.count("*").alias("n"))


#: Pieces that SQL can make, too: what stands up to and with a run of vowels.
_CUT = "[^aeiou]*[aeiou]+|[^aeiou]+"
_PIECE4 = "flatten(list_transform(pieces, lambda p: CASE WHEN length(p) >= 2 THEN list_transform(generate_series(1, length(p) - 1), lambda i: substr('_' || p || '_', i::INTEGER, 4)) ELSE [] END))"


@query("w6_samples", f"WITH {TAGGED}, s AS (SELECT word, regexp_extract_all(word, '{_CUT}') AS pieces FROM tagged WHERE regexp_full_match(word, '[a-z]{{3,}}')) SELECT word, array_to_string([word, right(word, 3), left(word, 3), right(word, 2), left(word, 2), right(word, 1), left(word, 1)] || list_transform(generate_series(1, length(word) - 1), lambda i: substr('_' || word || '_', i::INTEGER, 4)) || {_PIECE4}, ' ') AS features FROM s")
def w6s(spark, d):
    """The features of the tagged words of three letters or more in the form of the worked samples, with pieces that end at vowels."""
    rows = tagged(spark, d).filter(F.col("word").rlike("^[a-z]{3,}$")).select("word", F.regexp_extract_all("word", F.lit(_CUT), F.lit(0)).alias("pieces"))
    return rows.select("word", F.array_join(T.features(F.col("word"), F.col("pieces"), T.SAMPLE_SIZES), " ").alias("features"))


@query("w6_pairs_round1", f"WITH {TYP}, x AS (SELECT word, n FROM typ WHERE e > 0 AND regexp_full_match(word, '[a-z]+') AND length(word) >= 2), y AS (SELECT substr(word, i::INTEGER, 1) AS l, substr(word, i::INTEGER + 1, 1) AS r, n FROM (SELECT word, n, unnest(generate_series(1, length(word) - 1)) AS i FROM x)) SELECT l, r, sum(n)::BIGINT AS uses FROM y GROUP BY l, r")
def w6(spark, d):
    w = types(spark, d).filter("e > 0 and length(word) >= 2").filter(F.col("word").rlike("^[a-z]+$"))
    pairs = w.select("n", F.explode(F.transform(F.sequence(F.lit(1), F.length("word") - 1), lambda i: F.struct(F.substring("word", i, F.lit(1)).alias("l"), F.substring("word", i + 1, F.lit(1)).alias("r")))).alias("p"))
    return pairs.groupBy("p.l", "p.r").agg(F.sum("n").alias("uses"))


AFF = "[right(word, 1), left(word, 1)] || CASE WHEN length(word) >= 2 THEN [right(word, 2), left(word, 2)] ELSE [] END || CASE WHEN length(word) >= 3 THEN [right(word, 3), left(word, 3)] ELSE [] END"
GRAM = lambda k: f"CASE WHEN length(word) + 2 >= {k} THEN list_transform(generate_series(1, length(word) + 3 - {k}), lambda i: substr('_' || word || '_', i::INTEGER, {k})) ELSE [] END"


@query("w7_affix", f"WITH {TAGGED} SELECT word, '[' || array_to_string(list_sort({AFF}), ', ') || ']' AS affixes FROM tagged")
def w7a(spark, d):
    shown = F.concat(F.lit("["), F.array_join(F.array_sort(T.affixes(F.col("word"))), ", "), F.lit("]"))
    return tagged(spark, d).filter("length(word) > 0").select("word", shown.alias("affixes"))


def gram_bag(spark, d, sizes=(2, 3, 5)):
    return tagged(spark, d).select("word", "tag", F.explode(T.char_ngrams(F.col("word"), sizes)).alias("feature"))


ALLG = f"(({GRAM(2)}) || ({GRAM(3)}) || ({GRAM(5)}))"


@query("w7_word_ngrams", f"WITH {TAGGED}, g AS (SELECT tag, unnest({ALLG}) AS feature FROM tagged) SELECT tag, feature, count(*) AS uses FROM g GROUP BY tag, feature")
def w7n(spark, d):
    return gram_bag(spark, d).groupBy("tag", "feature").agg(F.count("*").alias("uses"))


@query("w7_bag", f"WITH {TAGGED}, g AS (SELECT word, unnest({ALLG}) AS feature FROM tagged) SELECT word, feature, count(*) AS n FROM g GROUP BY word, feature")
def w7b(spark, d):
    return gram_bag(spark, d).groupBy("word", "feature").agg(F.count("*").alias("n"))


@query("w7_doc_freq", f"WITH {TAGGED}, g AS (SELECT word, unnest({ALLG}) AS feature FROM tagged) SELECT feature, count(DISTINCT word) AS words FROM g GROUP BY feature HAVING count(DISTINCT word) >= 2")
def w7f(spark, d):
    return gram_bag(spark, d).select("word", "feature").distinct().groupBy("feature").agg(F.count("*").alias("words")).filter("words >= 2")


@query("w8_slots", f"WITH {TAGGED} SELECT max(length(word))::INTEGER AS max_chars, round(avg(length(word)), 6) AS avg_chars, 200 + 8 * 100 + max(length(word))::INTEGER * 30 AS width FROM tagged")
def w8(spark, d):
    return tagged(spark, d).agg(F.max(F.length("word")).alias("max_chars"), F.round(F.avg(F.length("word")), 6).alias("avg_chars"), (200 + 8 * 100 + F.max(F.length("word")) * 30).alias("width"))


@query("w8_pairs", f"WITH {TOK}, x AS (SELECT doc_id, sent_no, word, lead(word, 1) OVER w AS w1, lead(word, 2) OVER w AS w2 FROM tok WHERE lang = '{LOCAL}' WINDOW w AS (PARTITION BY doc_id, sent_no ORDER BY pos)), y AS (SELECT word AS a, w1 AS b FROM x WHERE w1 IS NOT NULL UNION ALL SELECT word, w2 FROM x WHERE w2 IS NOT NULL) SELECT a, b, count(*) AS n FROM y GROUP BY a, b HAVING count(*) > 1")
def w8p(spark, d):
    w = Window.partitionBy("doc_id", "sent_no").orderBy("pos")
    rows = tokens(spark, d).filter(F.col("lang") == LOCAL).select(F.col("word").alias("a"), F.array(F.lead("word", 1).over(w), F.lead("word", 2).over(w)).alias("bs"))
    return rows.select("a", F.explode(F.array_compact("bs")).alias("b")).groupBy("a", "b").agg(F.count("*").alias("n")).filter("n > 1")


BI = f"{TOK}, raw AS (SELECT *, {BUCKET("'s' || doc_id || ':' || sent_no")} < 10 AS held FROM tok WHERE {PAIR}), bi AS (SELECT held, coalesce(lag(word) OVER (PARTITION BY doc_id, sent_no ORDER BY pos), '<s>') AS h, word FROM raw)"


def bigrams(spark, d):
    rows = tokens(spark, d).filter(F.col("lang").isin("en", LOCAL))
    before = F.coalesce(F.lag("word").over(Window.partitionBy("doc_id", "sent_no").orderBy("pos")), F.lit("<s>"))
    return rows.select((T.bucket(F.concat_ws(":", "doc_id", "sent_no"), "s") < 10).alias("held"), before.alias("h"), "word")


@query("w9_vocab", f"WITH {TOK} SELECT word, count(*) AS n FROM tok WHERE {PAIR} GROUP BY word ORDER BY n DESC, word LIMIT 10000")
def w9v(spark, d):
    return tokens(spark, d).filter(F.col("lang").isin("en", LOCAL)).groupBy("word").agg(F.count("*").alias("n")).orderBy(F.desc("n"), "word").limit(10000)


@query("w9_bigram_lm", f"WITH {BI}, c AS (SELECT h, word, count(*) AS n FROM bi WHERE NOT held GROUP BY h, word), t AS (SELECT h, sum(n) AS hn FROM c GROUP BY h) SELECT c.h, c.word, c.n, round(c.n / t.hn::DOUBLE, 6) AS p FROM c JOIN t USING (h) WHERE c.n >= 2")
def w9b(spark, d):
    c = bigrams(spark, d).filter(~F.col("held")).groupBy("h", "word").agg(F.count("*").alias("n"))
    t = c.groupBy("h").agg(F.sum("n").alias("hn"))
    return c.join(t, "h").filter("n >= 2").select("h", "word", "n", F.round(F.col("n") / F.col("hn"), 6).alias("p"))


@query("w9_perplexity", f"WITH {BI}, c AS (SELECT h, word, count(*) AS n FROM bi WHERE NOT held GROUP BY h, word), t AS (SELECT h, sum(n) AS hn FROM c GROUP BY h), v AS (SELECT count(DISTINCT word) + 1 AS v FROM c) SELECT count(*) AS tokens, round(exp(-avg(ln((coalesce(c.n, 0) + 0.1::DOUBLE) / (coalesce(t.hn, 0) + 0.1::DOUBLE * v.v)))), 3) AS perplexity FROM bi LEFT JOIN c ON c.h = bi.h AND c.word = bi.word LEFT JOIN t ON t.h = bi.h, v WHERE held")
def w9p(spark, d):
    """Of the held-out tenth under a bigram model with add-0.1."""
    rows = bigrams(spark, d)
    c = rows.filter(~F.col("held")).groupBy("h", "word").agg(F.count("*").alias("n"))
    t = c.groupBy("h").agg(F.sum("n").alias("hn"))
    v = c.agg((F.count_distinct("word") + 1).alias("v"))
    joined = rows.filter("held").join(c, ["h", "word"], "left").join(t, "h", "left").crossJoin(F.broadcast(v))
    logp = F.log((F.coalesce("n", F.lit(0)) + 0.1) / (F.coalesce("hn", F.lit(0)) + 0.1 * F.col("v")))
    return joined.agg(F.count("*").alias("tokens"), F.round(F.exp(-F.avg(logp)), 3).alias("perplexity"))


# ---- baselines and measures -------------------------------------------------
_TOP = lambda src, by, out: f"(SELECT {by}, arg_min(tag, -n * 10 + {ORDER}) AS {out} FROM (SELECT {by}, tag, count(*) AS n FROM {src} GROUP BY {by}, tag) GROUP BY {by})"
_MAJ = f"mj AS (SELECT arg_min(tag, -n * 10 + {ORDER}) AS top FROM (SELECT tag, count(*) AS n FROM train GROUP BY tag))"
_SUF = lambda k: f"(SELECT right(word, {k}) AS s{k}, tag FROM train WHERE length(word) >= {k})"
_G = lambda src, ks: "SELECT word, tag, unnest(" + " || ".join(f"({GRAM(k)})" for k in ks) + f") AS g FROM {src}"
_CNT = ", ".join(f"count(*) FILTER (tag = '{t}') AS {t}" for t in TAGS)
_BEST = "[" + ", ".join(f"'{t}'" for t in TAGS) + "][list_position([" + ", ".join(TAGS) + "], greatest(" + ", ".join(TAGS) + "))]"
_NB = f"""tg AS ({_G('train', (2, 3))}), ct AS (SELECT g, {_CNT} FROM tg GROUP BY g),
 tt AS (SELECT count(*) AS v, {', '.join(f'sum({t}) AS t_{t}' for t in TAGS)} FROM ct), pr AS (SELECT count(*) AS m, {', '.join(f"count(*) FILTER (tag = '{t}') AS m_{t}" for t in TAGS)} FROM train),
 fd AS ({_G('test', (2, 3))}), x AS (SELECT word, tag AS gold, {', '.join(f'sum(ln((coalesce({t}, 0) + 1) / (t_{t} + v)::DOUBLE)) AS x_{t}' for t in TAGS)} FROM fd LEFT JOIN ct USING (g), tt GROUP BY word, tag),
 nb AS (SELECT word, gold, {', '.join(f'round(x_{t} + ln((m_{t} + 1) / (m + 6)::DOUBLE), 6) AS {t}' for t in TAGS)} FROM x, pr)"""
_CL = f"""t3 AS (SELECT g, {_CNT} FROM ({_G('train', (3,))}) GROUP BY g), t2 AS (SELECT substr(g, 1, 2) AS h, {', '.join(f'sum({t}) AS h_{t}' for t in TAGS)} FROM t3 GROUP BY 1),
 cl AS (SELECT word, tag AS gold, {', '.join(f'round(sum(ln((coalesce({t}, 0) + 0.5::DOUBLE) / (coalesce(h_{t}, 0) + 15::DOUBLE))), 6) AS {t}' for t in TAGS)} FROM ({_G('test', (3,))}) f LEFT JOIN t3 USING (g) LEFT JOIN t2 ON t2.h = substr(f.g, 1, 2) GROUP BY word, tag)"""
PRED = {
    "b1": f"WITH {SPLIT}, {_MAJ}, out AS (SELECT word, tag AS gold, top AS pred FROM test, mj)",
    "b2": f"WITH {SPLIT}, {_MAJ}, out AS (SELECT word, tag AS gold, coalesce(f, top) AS pred FROM test LEFT JOIN {_TOP('train', 'word', 'f')} t USING (word), mj)",
    "b2_stem": f"WITH {SPLIT}, {_MAJ}, out AS (SELECT word, tag AS gold, coalesce(f, top) AS pred FROM test LEFT JOIN {_TOP('(SELECT substr(word, 1, greatest(length(word) - 1, 1)) AS stem, tag FROM train)', 'stem', 'f')} t ON t.stem = substr(word, 1, greatest(length(word) - 1, 1)), mj)",
    "b3": f"WITH {SPLIT}, {_MAJ}, out AS (SELECT word, tag AS gold, coalesce(p3, top) AS pred FROM test LEFT JOIN {_TOP(_SUF(3), 's3', 'p3')} t ON length(word) >= 3 AND t.s3 = right(word, 3), mj)",
    "b4": f"WITH {SPLIT}, {_NB}, out AS (SELECT word, gold, {_BEST} AS pred FROM nb)",
    "b5": f"WITH {SPLIT}, {_MAJ}, out AS (SELECT word, tag AS gold, coalesce(p5, p4, p3, p2, p1, top) AS pred FROM test " + " ".join(f"LEFT JOIN {_TOP(_SUF(k), f's{k}', f'p{k}')} q{k} ON length(word) >= {k} AND q{k}.s{k} = right(word, {k})" for k in range(1, 6)) + ", mj)",
    "b6": f"WITH {SPLIT}, {_CL}, out AS (SELECT word, gold, {_BEST} AS pred FROM cl)",
}


def predicted(spark, d, name):
    return kept(spark, d, name, lambda: B.BASELINES[name](*parts(spark, d)))


for _b in PRED:
    query(_b, PRED[_b] + " SELECT word, gold, pred FROM out")(lambda spark, d, b=_b: predicted(spark, d, b))

_TAGROWS = "tags AS (SELECT unnest([" + ", ".join(f"'{t}'" for t in TAGS) + "]) AS tag)"
_PER = f"""{_TAGROWS}, s3 AS (SELECT tag, (SELECT count(*) FROM out WHERE gold = tag) AS support, (SELECT count(*) FROM out WHERE pred = tag) AS pn, (SELECT count(*) FROM out WHERE gold = tag AND pred = tag) AS hit FROM tags),
 s4 AS (SELECT tag, support, CASE WHEN pn > 0 THEN hit / pn::DOUBLE ELSE 0 END AS p, CASE WHEN support > 0 THEN hit / support::DOUBLE ELSE 0 END AS r FROM s3),
 sc AS (SELECT tag, support, round(p, 6) AS precision, round(r, 6) AS recall, round(CASE WHEN p + r > 0 THEN 2 * p * r / (p + r) ELSE 0 END, 6) AS f1 FROM s4)"""


def scores(spark, d, b):
    return M.per_tag(M.confusion(predicted(spark, d, b)))


query("v_confusion", PRED["b3"] + f", {_TAGROWS} SELECT a.tag AS gold, b.tag AS pred, (SELECT count(*) FROM out WHERE gold = a.tag AND pred = b.tag) AS n FROM tags a, tags b")(lambda spark, d: M.confusion(predicted(spark, d, "b3")))
query("v_per_tag", PRED["b3"] + f", {_PER} SELECT tag, support, precision, recall, f1 FROM sc")(lambda spark, d: scores(spark, d, "b3"))
query("v_macro", PRED["b3"] + f", {_PER} SELECT round(avg(precision), 5) AS macro_precision, round(avg(recall), 5) AS macro_recall, round(avg(f1), 5) AS macro_f1 FROM sc")(lambda spark, d: M.macro(scores(spark, d, "b3")))
query("v_averages", PRED["b3"] + f", {_PER} SELECT round(sum(precision * support) / sum(support), 5) AS weighted_precision, round(sum(recall * support) / sum(support), 5) AS weighted_recall, round(sum(f1 * support) / sum(support), 5) AS weighted_f1, (SELECT round(count(*) FILTER (gold = pred) / count(*)::DOUBLE, 5) FROM out) AS accuracy FROM sc")(lambda spark, d: M.averages(M.confusion(predicted(spark, d, "b3"))))

query("v_kappa", PRED["b3"] + f", {_TAGROWS}, k AS (SELECT (SELECT count(*) FROM out)::DOUBLE AS t, (SELECT count(*) FROM out WHERE gold = pred) AS same, (SELECT sum((SELECT count(*) FROM out WHERE gold = tag) * (SELECT count(*) FROM out WHERE pred = tag)) FROM tags) AS c) SELECT round((same / t - c / (t * t)) / (1 - c / (t * t)), 5) AS kappa FROM k")(lambda spark, d: M.kappa(M.confusion(predicted(spark, d, "b3"))))


_RULE = lambda least: f"CASE WHEN NOT regexp_full_match(word, '[a-z]+') THEN 'other' WHEN e * 100 >= n * {least} THEN 'en' WHEN l * 100 >= n * {least} THEN 'local' ELSE 'other' END"


@query("v_kappa_rules", f"WITH {TYP}, out AS (SELECT {_RULE(80)} AS gold, {_RULE(55)} AS pred FROM typ), {_TAGROWS}, k AS (SELECT (SELECT count(*) FROM out)::DOUBLE AS t, (SELECT count(*) FROM out WHERE gold = pred) AS same, (SELECT sum((SELECT count(*) FROM out WHERE gold = tag) * (SELECT count(*) FROM out WHERE pred = tag)) FROM tags) AS c) SELECT round((same / t - c / (t * t)) / (1 - c / (t * t)), 5) AS kappa FROM k")
def kappa_rules(spark, d):
    """Agreement of a strict and a lenient rule, which stand for two annotators."""
    strict, lenient = (C.base_tags(types(spark, d), least).select("word", F.col("tag").alias(name)) for least, name in ((80, "gold"), (55, "pred")))
    return M.kappa(M.confusion(strict.join(lenient, "word")))


def by_model(spark, d, names=("b3", "b4", "b6")):
    out = None
    for b in names:
        one = scores(spark, d, b).withColumn("model", F.lit(b))
        out = one if out is None else out.unionByName(one)
    return out


def _each(select: str) -> str:
    """The per-tag scores of three closed-form taggers as one table, in SQL."""
    body = f"WITH {SPLIT}, {_MAJ}, {_NB}, {_CL}, {_TAGROWS}, o AS (" + " UNION ALL ".join([
        f"SELECT 'b3' AS model, word, tag AS gold, coalesce(p3, top) AS pred FROM test LEFT JOIN {_TOP(_SUF(3), 's3', 'p3')} t ON length(word) >= 3 AND t.s3 = right(word, 3), mj",
        f"SELECT 'b4', word, gold, {_BEST} FROM nb", f"SELECT 'b6', word, gold, {_BEST} FROM cl"]) + """),
 s3 AS (SELECT m.model, tag, (SELECT count(*) FROM o WHERE gold = tag AND o.model = m.model) AS support, (SELECT count(*) FROM o WHERE pred = tag AND o.model = m.model) AS pn, (SELECT count(*) FROM o WHERE gold = tag AND pred = tag AND o.model = m.model) AS hit FROM tags, (SELECT DISTINCT model FROM o) m),
 s4 AS (SELECT model, tag, support, CASE WHEN pn > 0 THEN hit / pn::DOUBLE ELSE 0 END AS p, CASE WHEN support > 0 THEN hit / support::DOUBLE ELSE 0 END AS r FROM s3),
 sc AS (SELECT model, tag, support, round(p, 6) AS precision, round(r, 6) AS recall, round(CASE WHEN p + r > 0 THEN 2 * p * r / (p + r) ELSE 0 END, 6) AS f1 FROM s4) """
    return body + select


query("w11_by_tag", _each("SELECT model, tag, support, precision, recall, f1 FROM sc"))(by_model)
query("w12_f1_pivot", _each("SELECT model, " + ", ".join(f"max(f1) FILTER (tag = '{t}') AS {t}" for t in TAGS) + " FROM sc GROUP BY model"))(lambda spark, d: M.f1_pivot(by_model(spark, d)))


@query("w13_deltas", _each("SELECT round(avg(f1) FILTER (model = 'b4') - avg(f1) FILTER (model = 'b3'), 5) AS ngrams_over_suffix, round(avg(f1) FILTER (model = 'b4') - avg(f1) FILTER (model = 'b6'), 5) AS bayes_over_charlm FROM sc"))
def w13(spark, d):
    m = lambda x: F.avg(F.when(F.col("model") == x, F.col("f1")))
    return by_model(spark, d).agg(F.round(m("b4") - m("b3"), 5).alias("ngrams_over_suffix"), F.round(m("b4") - m("b6"), 5).alias("bayes_over_charlm"))


_SOFT = lambda t: f"exp({t} - g) / ({' + '.join(f'exp({x} - g)' for x in TAGS)})"
_PROB = lambda name: f"(SELECT word, gold, {', '.join(f'{_SOFT(t)} AS p_{t}' for t in TAGS)} FROM (SELECT *, greatest({', '.join(TAGS)}) AS g FROM {name}))"


def softmax(scores):
    top = F.greatest(*TAGS)
    return scores.select("word", "gold", *[F.exp(F.col(t) - top).alias(t) for t in TAGS]).select("word", "gold", *[(F.col(t) / sum(F.col(x) for x in TAGS)).alias(f"p_{t}") for t in TAGS])


_B3 = f"SELECT word, coalesce(p3, top) AS p FROM test LEFT JOIN {_TOP(_SUF(3), 's3', 'p3')} t ON length(word) >= 3 AND t.s3 = right(word, 3), mj"


@query("w14_soft_vote", f"WITH {SPLIT}, {_MAJ}, {_NB}, {_CL}, sx AS ({_B3}) SELECT a.word, a.gold, {', '.join(f"round((a.p_{t} + b.p_{t} + CASE WHEN sx.p = '{t}' THEN 1 ELSE 0 END) / 3, 4) AS {t}" for t in TAGS)} FROM {_PROB('nb')} a JOIN {_PROB('cl')} b ON a.word = b.word AND a.gold = b.gold JOIN sx ON sx.word = a.word")
def w14(spark, d):
    """Mean of the class probabilities of three closed-form scorers, one of which is sure of its tag."""
    train, test = parts(spark, d)
    a, b = (softmax(f(train, test)).toDF("word", "gold", *[f"{x}_{t}" for t in TAGS]) for x, f in (("a", B.nb_scores), ("b", B.charlm_scores)))
    sure = predicted(spark, d, "b3").select("word", "gold", F.col("pred").alias("c"))
    each = a.join(b, ["word", "gold"]).join(sure, ["word", "gold"])
    return each.select("word", "gold", *[F.round((F.col(f"a_{t}") + F.col(f"b_{t}") + (F.col("c") == t).cast("int")) / 3, 4).alias(t) for t in TAGS])


@query("w14_hard_vote", f"WITH {SPLIT}, {_MAJ}, {_NB}, {_CL}, a AS (SELECT word, gold, {_BEST} AS p FROM nb), b AS (SELECT word, {_BEST} AS p FROM cl), c AS (SELECT word, coalesce(p3, top) AS p FROM test LEFT JOIN {_TOP(_SUF(3), 's3', 'p3')} t ON length(word) >= 3 AND t.s3 = right(word, 3), mj) SELECT a.word, a.gold, CASE WHEN b.p = c.p THEN b.p ELSE a.p END AS pred FROM a JOIN b USING (word) JOIN c USING (word)")
def w14h(spark, d):
    """The tag of at least two of three taggers; where all differ, that of the first."""
    a, b, c = (predicted(spark, d, x).select("word", "gold", F.col("pred").alias(x)) for x in ("b4", "b6", "b3"))
    return a.join(b, ["word", "gold"]).join(c, ["word", "gold"]).select("word", "gold", F.when(F.col("b6") == F.col("b3"), F.col("b6")).otherwise(F.col("b4")).alias("pred"))


@query("w15_centroid", "WITH x AS (SELECT vec_id, label, unnest(generate_series(1, 64)) AS i, unnest(embedding)::DOUBLE AS v FROM embeddings), c AS (SELECT label AS k, i, avg(v) AS m FROM x WHERE vec_id % 10 < 7 GROUP BY 1, 2), dd AS (SELECT x.vec_id, x.label, c.k, round(sum((v - m) * (v - m)), 6) AS dist FROM x JOIN c USING (i) WHERE vec_id % 10 >= 7 GROUP BY 1, 2, 3) SELECT vec_id, label, arg_min(k, (dist, k)) AS pred FROM dd GROUP BY 1, 2")
def w15(spark, d):
    """Nearest class centroid on the dense table; 64 means of 10 classes are broadcast."""
    e = read_table(spark, d, "embeddings").select("vec_id", "label", "embedding")
    x = e.select("vec_id", "label", F.posexplode("embedding").alias("i", "v")).withColumn("v", F.col("v").cast("double"))
    c = x.filter("vec_id % 10 < 7").groupBy(F.col("label").alias("k"), "i").agg(F.avg("v").alias("m"))
    dist = x.filter("vec_id % 10 >= 7").join(c, "i").groupBy("vec_id", "label", "k").agg(F.round(F.sum((F.col("v") - F.col("m")) ** 2), 6).alias("dist"))
    return dist.groupBy("vec_id", "label").agg(F.min_by("k", F.struct("dist", "k")).alias("pred"))


@query("b2_tokens", f"WITH {TYP}, t AS (SELECT word, tag, {_PART} < 70 AS train FROM tok JOIN base USING (word) WHERE {PAIR}), train AS (SELECT DISTINCT word, tag FROM t WHERE train), mj AS (SELECT arg_min(tag, -n * 10 + {ORDER}) AS top FROM (SELECT tag, count(*) AS n FROM t WHERE train GROUP BY tag)) SELECT t.tag AS gold, coalesce(train.tag, top) AS pred, count(*) AS n FROM t LEFT JOIN train USING (word), mj WHERE NOT t.train GROUP BY 1, 2")
def b2t(spark, d):
    """The look-up where it can find words: on the tokens of held-out sentences."""
    t = tokens(spark, d).filter(F.col("lang").isin("en", LOCAL)).select("word", (T.bucket(F.concat_ws(":", "doc_id", "sent_no"), "o") < 70).alias("train"))
    uses = t.groupBy("word").agg(F.count_if("train").alias("a"), F.count_if(~F.col("train")).alias("b")).join(C.base_tags(types(spark, d)).select("word", "tag"), "word")
    rank = F.array_position(F.array(*map(F.lit, TAGS)), F.col("tag"))
    top = uses.groupBy("tag").agg(F.sum("a").alias("n")).filter("n > 0").agg(F.min_by("tag", F.struct(-F.col("n"), rank)).alias("top"))  # one row
    out = uses.filter("b > 0").crossJoin(F.broadcast(top)).select(F.col("tag").alias("gold"), F.when(F.col("a") > 0, F.col("tag")).otherwise(F.col("top")).alias("pred"), "b")
    return out.groupBy("gold", "pred").agg(F.sum("b").alias("n"))


MIX = "mixp AS (SELECT doc_id, count(*) FILTER (tag = 'local') AS n_local, count(*) FILTER (tag = 'en') AS n_en, count(*) FILTER (tag = 'other') AS n_other, count(*) AS n_words FROM tok JOIN base USING (word) GROUP BY doc_id)"


def mixp(spark, d):
    return C.mix_profile(tokens(spark, d), C.base_tags(types(spark, d)), ["doc_id"])


query("w16_mix_profile", f"WITH {TYP}, {MIX} SELECT * FROM mixp")(mixp)


_TURN = f"c0 AS (SELECT conv_id, turn, regexp_split_to_array({ROM}, '[.!?]*\\n|[.!?]+ ') AS a FROM conversations), c1 AS (SELECT conv_id, turn, unnest(a) AS s FROM c0), c2 AS (SELECT conv_id, turn, unnest(regexp_extract_all(s, '[^ ]+')) AS w FROM c1), c3 AS (SELECT conv_id, turn, regexp_replace(w, '[.,!?]+$', '') AS word FROM c2)"


@query("w16_turn_profile", f"WITH {TYP}, {_TURN} SELECT conv_id, turn, count(*) FILTER (tag = 'local') AS n_local, count(*) FILTER (tag = 'en') AS n_en, count(*) FILTER (tag = 'other') AS n_other, count(*) AS n_words FROM c3 JOIN base USING (word) WHERE word <> '' GROUP BY conv_id, turn")
def w16t(spark, d):
    """The same for each turn of a conversation."""
    turns = read_table(spark, d, "conversations").select(F.struct("conv_id", "turn").alias("doc_id"), F.col("role").alias("source"), F.lit("").alias("lang"), "text")
    out = C.mix_profile(C.to_tokens(C.to_sentences(turns)), C.base_tags(types(spark, d)), ["doc_id"])
    return out.select("doc_id.conv_id", "doc_id.turn", "n_local", "n_en", "n_other", "n_words")


@query("w17_mixed_docs", f"WITH {TOK}, u AS (SELECT word, lang, count(*) AS k FROM tok GROUP BY word, lang), m AS (SELECT word, max(k) AS k, sum(k) AS n FROM u GROUP BY word), own AS (SELECT u.word, u.lang AS home FROM u JOIN m USING (word) WHERE u.k * 5 >= m.n * 4), z AS (SELECT tok.doc_id, count(*) AS n, count(*) FILTER (home <> lang) AS far FROM tok LEFT JOIN own USING (word) GROUP BY doc_id) SELECT doc_id, n, far FROM z WHERE far >= 3 AND far * 10 >= n")
def w17(spark, d):
    """Documents with at least a tenth and three of their words at home in another language."""
    t = tokens(spark, d)
    u = t.groupBy("word", "lang").agg(F.count("*").alias("k"))
    own = u.groupBy("word").agg(F.max_by("lang", "k").alias("home"), F.max("k").alias("top"), F.sum("k").alias("n")).filter("top * 5 >= n * 4").select("word", "home")
    z = t.join(own, "word", "left").groupBy("doc_id").agg(F.count("*").alias("n"), F.count_if(F.col("home") != F.col("lang")).alias("far"))
    return z.filter("far >= 3 and far * 10 >= n")


@query("w18_quality_by_mix", f"WITH {TYP}, {MIX} SELECT quality, toxic, count(*) AS docs, round(avg(n_other / n_words::DOUBLE), 6) AS other_share FROM mixp JOIN labels USING (doc_id) GROUP BY quality, toxic")
def w18(spark, d):
    return mixp(spark, d).join(read_table(spark, d, "labels"), "doc_id").groupBy("quality", "toxic").agg(F.count("*").alias("docs"), F.round(F.avg(F.col("n_other") / F.col("n_words")), 6).alias("other_share"))
