"""The relational operators that users of the taggers need, each on a given table, with its SQL."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from wordlid.functions import text as T
from wordlid.io import load_artifact, read_table, save_artifact, temporary
from wordlid.operators import corpus as C
from wordlid.operators import metrics as M
from wordlid.plans.common import LOCAL, PAIR, SENT, SPLIT, TAGGED, TOK, TYP, docs, kept, parts, sentences, tagged, tokens, types
from wordlid.plans.workloads import PRED, predicted
from wordlid.sources.html import html_to_text

Q: dict = {}
S: dict = {}


def query(name: str, sql: str | None = None):
    def put(f):
        Q[name] = f
        if sql:
            S[name] = sql
        return f

    return put


def table(name):
    return lambda spark, d: read_table(spark, d, name)


events, pages = table("events"), table("pages")
_ENT = "html"
for _e, _c in (("&lt;", "<"), ("&gt;", ">"), ("&quot;", '"'), ("&#39;", "''"), ("&nbsp;", " "), ("&amp;", "&")):
    _ENT = f"replace({_ENT}, '{_e}', '{_c}')"
query("op_html_to_text", rf"SELECT page_id, trim(regexp_replace({_ENT}, '[\x20\x09-\x0D]+', ' ', 'g')) AS text FROM (SELECT page_id, regexp_replace(regexp_replace(html, '(?is)<(script|style)\b.*?</(script|style)>', ' ', 'g'), '<[^>]*>', ' ', 'g') AS html FROM pages)")(lambda spark, d: pages(spark, d).select("page_id", html_to_text(F.col("html")).alias("text")))


def _roundtrip(kind):
    def run(spark, d):
        rows = table("customer")(spark, d).select("c_custkey", "c_name", "c_nationkey")
        path = temporary(spark, kind)
        rows.write.mode("overwrite").format(kind).option("header", "true").save(path)
        return spark.read.schema(rows.schema).format(kind).option("header", "true").load(path)

    return run


for _k in ("parquet", "json", "csv", "orc"):
    query(f"op_{_k}_roundtrip", "SELECT c_custkey, c_name, c_nationkey FROM customer")(_roundtrip(_k))

query("op_filter_regex", f"WITH {TYP} SELECT word, n FROM typ WHERE regexp_matches(word, '(ing|tion)$') AND n BETWEEN 2 AND 50")(lambda spark, d: types(spark, d).filter(F.col("word").rlike("(ing|tion)$") & F.col("n").between(2, 50)).select("word", "n"))
query("op_case_tag", f"WITH {TYP} SELECT word, tag FROM base")(lambda spark, d: C.base_tags(types(spark, d)).select("word", "tag"))
query("op_null_safe", "SELECT count(*) FILTER (l.quality IS NOT DISTINCT FROM l.toxic) AS same_or_both_null, count(*) FILTER (l.quality = l.toxic) AS same, count(*) AS n FROM documents d LEFT JOIN labels l USING (doc_id)")(
    lambda spark, d: docs(spark, d).join(table("labels")(spark, d), "doc_id", "left").agg(F.count_if(F.col("quality").eqNullSafe(F.col("toxic"))).alias("same_or_both_null"), F.count_if(F.col("quality") == F.col("toxic")).alias("same"), F.count("*").alias("n"))
)


@query("op_artifact_roundtrip", f"WITH {TAGGED} SELECT word, tag, n FROM tagged")
def artifact(spark, d):
    """The tagged word set, saved to share and loaded again."""
    path = temporary(spark, "artifact")
    save_artifact(tagged(spark, d), path, "tagged-words")
    return load_artifact(spark, path, "tagged-words")



@query("op_broadcast_lexicon", f"WITH {TYP}, u AS (SELECT word FROM typ ORDER BY n DESC, word LIMIT 100) SELECT lang, count(*) AS uses FROM tok JOIN u USING (word) GROUP BY lang")
def broadcast_lexicon(spark, d):
    """The hundred most frequent types are broadcast to all tokens."""
    top = types(spark, d).orderBy(F.desc("n"), "word").limit(100).select("word")
    return tokens(spark, d).join(F.broadcast(top), "word").groupBy("lang").agg(F.count("*").alias("uses"))


@query("op_sortmerge_types", f"WITH {TYP} SELECT doc_id, count(*) FILTER (tag = 'local') AS n_local FROM tok JOIN base USING (word) GROUP BY doc_id")
def sortmerge_types(spark, d):
    """Head words are broadcast, only the tail is shuffled by word."""
    base = C.base_tags(types(spark, d))
    head = base.orderBy(F.desc("n"), "word").limit(2000)  # 2,000 rows
    known = tokens(spark, d).select("doc_id", "word").join(F.broadcast(head.select("word", F.col("tag").alias("h"))), "word", "left")
    tail = known.filter("h is null").select("doc_id", "word").join(base.select("word", "tag").hint("merge"), "word").select("doc_id", "tag")
    every = known.filter("h is not null").select("doc_id", F.col("h").alias("tag")).unionByName(tail)
    return every.groupBy("doc_id").agg(F.count_if(F.col("tag") == "local").alias("n_local"))


@query("op_theta_affix", f"WITH {TAGGED} SELECT m.word, r.r_name FROM tagged m, region r WHERE length(m.word) > length(r.r_name) AND m.word LIKE '%' || lower(r.r_name) UNION ALL SELECT m.word, s.s FROM tagged m, (SELECT unnest(['tion', 'ment']) AS s) s WHERE m.word LIKE '%' || s.s AND length(m.word) > length(s.s)")
def theta_affix(spark, d):
    """A theta join with a side of a few fixed rows."""
    suffixes = table("region")(spark, d).select(F.col("r_name").alias("r_name")).union(spark.range(1).select(F.explode(F.array(F.lit("tion"), F.lit("ment")))))
    m = tagged(spark, d).select("word")
    return m.join(F.broadcast(suffixes), (F.length("word") > F.length("r_name")) & F.col("word").endswith(F.lower("r_name"))).select("word", "r_name")


@query("op_range_events", "SELECT a.event_id, count(*) AS near FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts BETWEEN a.ts - INTERVAL 1 HOUR AND a.ts + INTERVAL 1 HOUR GROUP BY a.event_id")
def range_events(spark, d):
    """A range join by buckets of an hour: each row meets its own bucket and both neighbours."""
    e = events(spark, d).select("event_id", "user_id", "ts", F.floor(F.unix_seconds(F.col("ts").cast("timestamp")) / 3600).alias("h"))
    b = e.select("user_id", F.col("ts").alias("t"), F.explode(F.array(F.col("h") - 1, F.col("h"), F.col("h") + 1)).alias("h"))
    hour = F.expr("interval 1 hour")
    return e.join(b, ["user_id", "h"]).filter(F.col("t").between(F.col("ts") - hour, F.col("ts") + hour)).groupBy("event_id").agg(F.count("*").alias("near"))


@query("op_interval_events", "WITH i AS (SELECT event_id, user_id, event_type, epoch_us(ts) AS a, epoch_us(ts) + 60000000 * (5 + event_id % 90) AS b FROM events) SELECT x.event_id, count(*) AS overlaps, sum(least(x.b, y.b) - greatest(x.a, y.a))::BIGINT AS shared_us FROM i x JOIN i y ON x.user_id = y.user_id AND x.event_type = 'click' AND y.event_type = 'purchase' AND x.a < y.b AND y.a < x.b GROUP BY x.event_id")
def interval_events(spark, d):
    """An overlap join of intervals: each is put into the hours that it touches, and a pair counts in the hour in which it begins to overlap."""
    hour = 3_600_000_000
    i = events(spark, d).select("event_id", "user_id", "event_type", F.unix_micros(F.col("ts").cast("timestamp")).alias("a")).withColumn("b", F.col("a") + 60_000_000 * (5 + F.col("event_id") % 90))
    i = i.withColumn("h", F.explode(F.sequence(F.floor(F.col("a") / hour), F.floor((F.col("b") - 1) / hour))))
    x, y = i.filter("event_type = 'click'"), i.filter("event_type = 'purchase'").select("user_id", "h", F.col("a").alias("c"), F.col("b").alias("e"))
    met = x.join(y, ["user_id", "h"]).filter((F.col("a") < F.col("e")) & (F.col("c") < F.col("b")) & (F.col("h") == F.floor(F.greatest("a", "c") / hour)))
    return met.groupBy("event_id").agg(F.count("*").alias("overlaps"), F.sum(F.least("b", "e") - F.greatest("a", "c")).alias("shared_us"))


@query("op_asof_events", "SELECT a.event_id, max_by(b.event_id, (b.ts, b.event_id)) AS last_click FROM events a LEFT JOIN events b ON a.user_id = b.user_id AND b.event_type = 'click' AND (b.ts, b.event_id) < (a.ts, a.event_id) GROUP BY a.event_id")
def asof_events(spark, d):
    """The last click before each event, by one window instead of a join."""
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    return events(spark, d).select("event_id", F.last(F.when(F.col("event_type") == "click", F.col("event_id")), ignorenulls=True).over(w).alias("last_click"))


query("op_semi_sources", "SELECT doc_id, source FROM documents WHERE source IN ('src1', 'src3', 'src5')")(lambda spark, d: C.collect_comments(docs(spark, d), ["src1", "src3", "src5"]).select("doc_id", "source"))
query("op_anti_oov", f"WITH {SPLIT}, a AS (SELECT DISTINCT left(word, 4) AS x FROM train) SELECT word FROM test WHERE left(word, 4) NOT IN (SELECT x FROM a)")(
    lambda spark, d: parts(spark, d)[1].withColumn("x", F.left("word", F.lit(4))).join(parts(spark, d)[0].select(F.left("word", F.lit(4)).alias("x")).distinct(), "x", "left_anti").select("word")
)


def vocab(spark, d, lang):
    return tokens(spark, d).filter(F.col("lang") == lang).select("word").distinct()


@query("op_full_vocab", f"WITH {TOK}, a AS (SELECT DISTINCT word FROM tok WHERE lang = 'en'), b AS (SELECT DISTINCT word FROM tok WHERE lang = 'fr') SELECT count(*) FILTER (a.word IS NULL) AS only_local, count(*) FILTER (b.word IS NULL) AS only_en, count(*) FILTER (a.word = b.word) AS both FROM a FULL JOIN b ON a.word = b.word")
def full_vocab(spark, d):
    a, b = vocab(spark, d, "en").withColumn("a", F.lit(1)), vocab(spark, d, "fr").withColumn("b", F.lit(1))
    return a.join(b, "word", "full").agg(F.count_if(F.col("a").isNull()).alias("only_local"), F.count_if(F.col("b").isNull()).alias("only_en"), F.count_if(F.col("a") == F.col("b")).alias("both"))


for _n, _op in (("intersect", "INTERSECT"), ("except", "EXCEPT"), ("union", "UNION")):
    query(f"op_vocab_{_n}", f"WITH {TOK} SELECT word FROM tok WHERE lang = 'en' {_op} SELECT word FROM tok WHERE lang = 'fr'")(
        lambda spark, d, k=_n: {"intersect": lambda a, b: a.intersect(b), "except": lambda a, b: a.subtract(b), "union": lambda a, b: a.union(b).distinct()}[k](vocab(spark, d, "en"), vocab(spark, d, "fr"))
    )
query("op_intersect_all", "SELECT n_chars FROM documents WHERE lang = 'en' INTERSECT ALL SELECT n_chars FROM documents WHERE lang <> 'en'")(lambda spark, d: docs(spark, d).filter("lang = 'en'").select("n_chars").intersectAll(docs(spark, d).filter("lang <> 'en'").select("n_chars")))

_GID = "lang, source, count(*) AS docs, sum(n_chars)::BIGINT AS chars FROM documents GROUP BY"
agg = lambda: (F.count("*").alias("docs"), F.sum("n_chars").alias("chars"))
query("op_tag_lang_cube", f"SELECT {_GID} CUBE (lang, source)")(lambda spark, d: docs(spark, d).cube("lang", "source").agg(*agg()))
query("op_rollup_source", f"SELECT {_GID} ROLLUP (lang, source)")(lambda spark, d: docs(spark, d).rollup("lang", "source").agg(*agg()))
query("op_grouping_sets", f"SELECT {_GID} GROUPING SETS ((lang), (source))")(lambda spark, d: docs(spark, d).groupingSets([["lang"], ["source"]], "lang", "source").agg(*agg()))
query("op_distinct_types", f"WITH {TOK} SELECT source, count(DISTINCT word) AS types FROM tok GROUP BY source")(lambda spark, d: tokens(spark, d).groupBy("source").agg(F.count_distinct("word").alias("types")))
query("op_approx_types")(lambda spark, d: tokens(spark, d).groupBy("source").agg(F.approx_count_distinct("word", 0.02).alias("types")))
query("op_percentile_len", "SELECT lang, quantile_disc(n_chars, 0.5) AS p50, quantile_disc(n_chars, 0.9) AS p90 FROM documents GROUP BY lang")(lambda spark, d: docs(spark, d).groupBy("lang").agg(F.expr("percentile_disc(0.5) within group (order by n_chars)").cast("long").alias("p50"), F.expr("percentile_disc(0.9) within group (order by n_chars)").cast("long").alias("p90")))
query("op_max_by", "SELECT source, arg_max(doc_id, (n_chars, doc_id)) AS longest FROM documents GROUP BY source")(lambda spark, d: docs(spark, d).groupBy("source").agg(F.max_by("doc_id", F.struct("n_chars", "doc_id")).alias("longest")))


@query("op_topk_words_per_lang", f"WITH {TOK}, c AS (SELECT lang, word, count(*) AS n FROM tok GROUP BY lang, word) SELECT lang, word, n, rank FROM (SELECT *, row_number() OVER (PARTITION BY lang ORDER BY n DESC, word) AS rank FROM c) WHERE rank <= 10")
def topk(spark, d):
    c = tokens(spark, d).groupBy("lang", "word").agg(F.count("*").alias("n"))
    return c.withColumn("rank", F.row_number().over(Window.partitionBy("lang").orderBy(F.desc("n"), "word"))).filter("rank <= 10").select("lang", "word", "n", "rank")


@query("op_rank_suffix", f"WITH {TAGGED}, c AS (SELECT tag, right(word, 3) AS s, count(*) AS n FROM tagged GROUP BY 1, 2) SELECT tag, s, n, rank() OVER w AS r, dense_rank() OVER w AS dr FROM c WINDOW w AS (PARTITION BY tag ORDER BY n DESC)")
def rank_suffix(spark, d):
    w = Window.partitionBy("tag").orderBy(F.desc("n"))
    c = tagged(spark, d).groupBy("tag", F.right("word", F.lit(3)).alias("s")).agg(F.count("*").alias("n"))
    return c.select("tag", "s", "n", F.rank().over(w).alias("r"), F.dense_rank().over(w).alias("dr"))


@query("op_context_lag_lead", f"WITH {TOK} SELECT doc_id, sent_no, pos, word, lag(word) OVER w AS before, lead(word) OVER w AS after FROM tok WHERE lang = 'fr' WINDOW w AS (PARTITION BY doc_id, sent_no ORDER BY pos)")
def context(spark, d):
    w = Window.partitionBy("doc_id", "sent_no").orderBy("pos")
    return tokens(spark, d).filter("lang = 'fr'").select("doc_id", "sent_no", "pos", "word", F.lag("word").over(w).alias("before"), F.lead("word").over(w).alias("after"))


@query("op_running_vocab", f"WITH {TOK}, f AS (SELECT source, word, min(doc_id) AS doc_id FROM tok GROUP BY source, word), c AS (SELECT source, doc_id, count(*) AS fresh FROM f GROUP BY source, doc_id) SELECT source, doc_id, fresh, (sum(fresh) OVER (PARTITION BY source ORDER BY doc_id))::BIGINT AS vocab FROM c")
def running_vocab(spark, d, block=1 << 12):
    """Running sums inside blocks of doc_ids, and over the blocks' totals, so that no task holds a source."""
    first = tokens(spark, d).groupBy("source", "word").agg(F.min("doc_id").alias("doc_id"))
    c = first.groupBy("source", "doc_id").agg(F.count("*").alias("fresh")).withColumn("block", F.floor(F.col("doc_id") / block))
    before = Window.partitionBy("source").orderBy("block").rowsBetween(Window.unboundedPreceding, -1)
    starts = c.groupBy("source", "block").agg(F.sum("fresh").alias("n")).select("source", "block", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("start"))
    inside = F.sum("fresh").over(Window.partitionBy("source", "block").orderBy("doc_id"))
    return c.withColumn("inside", inside).join(starts, ["source", "block"]).select("source", "doc_id", "fresh", (F.col("start") + F.col("inside")).alias("vocab"))


@query("op_range_frame", "SELECT doc_id, count(*) OVER (PARTITION BY lang ORDER BY n_chars RANGE BETWEEN 100 PRECEDING AND 100 FOLLOWING) AS alike FROM documents")
def range_frame(spark, d):
    """The frame is counted once for each length that occurs, not for each document."""
    w = Window.partitionBy("lang").orderBy("n_chars").rangeBetween(-100, 100)
    lengths = docs(spark, d).groupBy("lang", "n_chars").agg(F.count("*").alias("n")).select(F.col("lang").alias("_lang"), F.col("n_chars").alias("_n"), F.sum("n").over(w).alias("alike"))
    rows = docs(spark, d).select("doc_id", "lang", "n_chars")
    return rows.join(lengths, F.col("lang").eqNullSafe(F.col("_lang")) & F.col("n_chars").eqNullSafe(F.col("_n"))).select("doc_id", "alike")


query("op_top_suffixes", f"WITH {TOK} SELECT right(word, 3) AS suffix, count(*) AS n FROM tok WHERE length(word) >= 3 GROUP BY 1 ORDER BY n DESC, suffix LIMIT 25")(lambda spark, d: tokens(spark, d).filter("length(word) >= 3").groupBy(F.right("word", F.lit(3)).alias("suffix")).agg(F.count("*").alias("n")).orderBy(F.desc("n"), "suffix").limit(25))
query("op_top_documents", "SELECT doc_id, n_chars FROM documents ORDER BY n_chars DESC, doc_id LIMIT 20")(lambda spark, d: docs(spark, d).select("doc_id", "n_chars").orderBy(F.desc("n_chars"), "doc_id").limit(20))
query("op_strings", f"WITH {TYP} SELECT word, upper(word) AS up, reverse(word) AS back, md5(word) AS digest, regexp_replace(word, '[aeiou]', '', 'g') AS bare, substr(word, 2, 3) AS mid FROM typ WHERE n >= 5")(
    lambda spark, d: types(spark, d).filter("n >= 5").select("word", F.upper("word").alias("up"), F.reverse("word").alias("back"), F.md5("word").alias("digest"), F.regexp_replace("word", "[aeiou]", "").alias("bare"), F.substring("word", 2, 3).alias("mid"))
)
query("op_dates", "SELECT strftime(o_orderdate, '%Y-%m') AS m, count(*) AS orders, max(date_diff('day', o_orderdate::DATE, DATE '2000-01-01')) AS days FROM orders GROUP BY 1")(
    lambda spark, d: table("orders")(spark, d).groupBy(F.date_format("o_orderdate", "yyyy-MM").alias("m")).agg(F.count("*").alias("orders"), F.max(F.datediff(F.lit("2000-01-01").cast("date"), F.col("o_orderdate").cast("date"))).cast("long").alias("days"))
)
query("op_math", "SELECT doc_id, round(ln(1 + n_chars), 6) AS l, round(sqrt(n_chars), 6) AS r, n_chars % 7 AS m FROM documents")(lambda spark, d: docs(spark, d).select("doc_id", F.round(F.log1p("n_chars"), 6).alias("l"), F.round(F.sqrt("n_chars"), 6).alias("r"), (F.col("n_chars") % 7).alias("m")))
query("op_arrays", "SELECT vec_id, round(list_sum(list_transform(embedding, lambda x: x::DOUBLE * x::DOUBLE)), 5) AS norm2, len(list_filter(embedding, lambda x: x > 0)) AS positive FROM embeddings")(
    lambda spark, d: table("embeddings")(spark, d).select("vec_id", F.round(F.aggregate("embedding", F.lit(0.0), lambda a, x: a + x.cast("double") * x.cast("double")), 5).alias("norm2"), F.size(F.filter("embedding", lambda x: x > 0)).cast("long").alias("positive"))
)


@query("op_maps", "SELECT doc_id, len(list_distinct(regexp_split_to_array(lower(text), ' '))) AS kinds FROM documents")
def maps(spark, d):
    words = F.array_distinct(F.split(F.lower("text"), " "))
    return docs(spark, d).select("doc_id", F.size(F.map_keys(F.map_from_entries(F.transform(words, lambda w: F.struct(w, F.length(w)))))).cast("long").alias("kinds"))


query("op_json_props", "SELECT event_id, json_extract(props, '$.k')::BIGINT AS k FROM events")(lambda spark, d: events(spark, d).select("event_id", F.from_json("props", "k long")["k"].alias("k")))
query("op_levenshtein", f"WITH {TAGGED}, x AS (SELECT word, right(word, 4) AS s FROM tagged WHERE tag = 'mixed') SELECT a.word AS a, b.word AS b, levenshtein(a.word, b.word) AS dist FROM x a JOIN x b ON a.s = b.s AND a.word < b.word WHERE levenshtein(a.word, b.word) <= 2")(
    lambda spark, d: (lambda x: x.toDF("a", "s").join(x.toDF("b", "s"), "s").filter("a < b").select("a", "b", F.levenshtein("a", "b").cast("long").alias("dist")).filter("dist <= 2"))(tagged(spark, d).filter("tag = 'mixed'").select("word", F.right("word", F.lit(4)).alias("s")))
)


@query("op_udaf_macro_f1", PRED["b3"] + ", tg AS (SELECT DISTINCT gold AS tag FROM out UNION SELECT DISTINCT pred FROM out), f AS (SELECT tag, 2.0::DOUBLE * (SELECT count(*) FROM out WHERE gold = tag AND pred = tag) / ((SELECT count(*) FROM out WHERE gold = tag) + (SELECT count(*) FROM out WHERE pred = tag)) AS f1 FROM tg) SELECT round(avg(f1), 5) AS macro_f1 FROM f")
def udaf_macro_f1(spark, d):
    """A grouped-aggregate UDF over the confusion counts, which are 36 rows at any size."""
    @F.pandas_udf("double")
    def macro_f1(gold: pd.Series, pred: pd.Series, n: pd.Series) -> float:
        tags = sorted(set(gold[n > 0]) | set(pred[n > 0]))
        return float(sum(2 * n[(gold == t) & (pred == t)].sum() / (n[gold == t].sum() + n[pred == t].sum()) for t in tags) / max(1, len(tags)))

    return M.confusion(predicted(spark, d, "b3")).agg(F.round(macro_f1("gold", "pred", "n"), 5).alias("macro_f1"))


@query("op_udtf_word_features", f"WITH {TAGGED}, x AS (SELECT word FROM tagged WHERE tag = 'location') SELECT word, unnest(CASE WHEN length(word) >= 3 THEN [left(word, 3), right(word, 3)] ELSE [] END) AS feature FROM x")
def udtf_features(spark, d):
    from pyspark.sql.functions import udtf

    @udtf(returnType="feature string")
    class WordFeatures:
        def eval(self, word: str):
            if len(word) >= 3:
                yield (word[:3],)
                yield (word[-3:],)

    spark.udtf.register("word_features", WordFeatures)
    tagged(spark, d).filter("tag = 'location'").createOrReplaceTempView("wordlid_places")
    return spark.sql("SELECT word, feature FROM wordlid_places, LATERAL word_features(word)")


query("op_exact_dups", "SELECT doc_id FROM documents QUALIFY doc_id = min(doc_id) OVER (PARTITION BY lower(text))")(lambda spark, d: C.drop_duplicate_comments(docs(spark, d)).select("doc_id"))


@query("op_shingle_pairs", f"""WITH {SENT}, x AS (SELECT DISTINCT doc_id, md5(text) AS h FROM sent WHERE length(text) >= 40), k AS (SELECT doc_id, md5(string_agg(h, '' ORDER BY h)) AS k, count(*) AS sentences FROM x GROUP BY doc_id), c AS (SELECT k, min(doc_id) AS class_id FROM k GROUP BY k),
 u AS (SELECT h, count(DISTINCT k) AS classes FROM x JOIN k USING (doc_id) GROUP BY h) SELECT doc_id, class_id, k.sentences, s.shared FROM k JOIN c USING (k) JOIN (SELECT doc_id, count(*) FILTER (classes > 1) AS shared FROM x JOIN u USING (h) GROUP BY doc_id) s USING (doc_id)""")
def shingle_classes(spark, d):
    """Documents by their long sentences: those with the same set are one class, and `shared` says how many of a document's sentences other
    classes have. A sentence that very many have is counted like others, and no pairs are made."""
    x = sentences(spark, d).filter("length(text) >= 40").select("doc_id", F.md5("text").alias("h")).distinct()
    own = x.groupBy("doc_id").agg(F.array_sort(F.collect_list("h")).alias("hs")).select("doc_id", "hs", F.md5(F.array_join("hs", "")).alias("k"))
    own = kept(spark, d, "sentence-sets", lambda: own)
    classes = kept(spark, d, "sentence-classes", lambda: own.groupBy("k").agg(F.min("doc_id").alias("class_id"), F.any_value("hs").alias("hs")))
    each = classes.select("class_id", F.explode("hs").alias("h"))
    common = each.groupBy("h").agg(F.count("*").alias("classes")).filter("classes > 1")
    shared = each.join(common, "h").groupBy("class_id").agg(F.count("*").alias("shared"))
    named = classes.select("k", "class_id").join(shared, "class_id", "left")
    return own.select("doc_id", "k", F.size("hs").cast("long").alias("sentences")).join(named, "k").select("doc_id", "class_id", "sentences", F.coalesce("shared", F.lit(0)).cast("long").alias("shared"))


@query("op_minhash")
def minhash_stars(spark, d, hashes=32, band=4, least=0.8):
    """Near-duplicates by minimal hashes of word 5-grams, in column functions: equal sets are one class, each bucket of a band of hashes gives
    its smallest document edges to the others, and an edge stays if the sets are `least` alike. One row for each document: its class, and
    the document that it is linked to, if any."""
    words = docs(spark, d).select("doc_id", F.regexp_extract_all(F.lower("text"), F.lit(r"[^\x20\x09-\x0D]+"), F.lit(0)).alias("w")).filter("size(w) >= 5")
    grams = F.array_sort(F.array_distinct(F.transform(F.sequence(F.lit(1), F.size("w") - 4), lambda i: F.xxhash64(F.array_join(F.slice("w", i, 5), " ")))))
    sets = kept(spark, d, "gram-sets", lambda: words.select("doc_id", grams.alias("g")).withColumn("k", F.md5(F.array_join("g", ","))))
    classes = kept(spark, d, "gram-classes", lambda: sets.groupBy("k").agg(F.min("doc_id").alias("class_id"), F.any_value("g").alias("g")))
    least_of = lambda seed: F.array_min(F.transform("g", lambda x: F.xxhash64(F.lit(seed), x)))
    bands = F.array(*[F.xxhash64(F.lit(b), *[least_of(b * band + i) for i in range(band)]) for b in range(hashes // band)])
    at = classes.select("class_id", F.explode(bands).alias("bucket"))
    stars = at.groupBy("bucket").agg(F.min("class_id").alias("centre"))
    edges = at.join(stars, "bucket").filter("class_id <> centre").select("class_id", "centre").distinct()
    both = edges.join(classes.select("class_id", "g"), "class_id").join(classes.select(F.col("class_id").alias("centre"), F.col("g").alias("o")), "centre")
    common = F.size(F.array_intersect("g", "o"))
    links = both.select("class_id", "centre", (common / (F.size("g") + F.size("o") - common)).alias("similarity")).filter(F.col("similarity") >= least)
    best = links.groupBy("class_id").agg(F.min("centre").alias("linked_to"), F.min_by("similarity", "centre").alias("similarity"))
    named = classes.select("k", "class_id").join(best, "class_id", "left")
    return sets.select("doc_id", "k").join(named, "k").select("doc_id", "class_id", "linked_to", F.round("similarity", 6).alias("similarity"))


@query("op_benchmark_overlap", rf"WITH w AS (SELECT doc_id, regexp_extract_all(lower(text), '[^\x20\x09-\x0D]+') AS a FROM documents), g AS (SELECT DISTINCT doc_id, md5(array_to_string(a[i:i + 7], ' ')) AS h FROM (SELECT doc_id, a, unnest(generate_series(1, len(a) - 7)) AS i FROM w)), bw AS (SELECT item_id, regexp_extract_all(lower(text), '[^\x20\x09-\x0D]+') AS a FROM benchmark), bg AS (SELECT DISTINCT md5(array_to_string(a[i:i + 7], ' ')) AS h FROM (SELECT item_id, a, unnest(generate_series(1, len(a) - 7)) AS i FROM bw)) SELECT doc_id, count(*) AS shared FROM g JOIN bg USING (h) GROUP BY doc_id")
def benchmark_overlap(spark, d):
    """Eight-word n-grams of documents that occur in the benchmark passages."""
    def grams(df, key):
        words = df.select(key, F.regexp_extract_all(F.lower("text"), F.lit(r"[^\x20\x09-\x0D]+"), F.lit(0)).alias("a")).filter(F.size("a") >= 8)
        return words.select(key, F.explode(F.transform(F.sequence(F.lit(1), F.size("a") - 7), lambda i: F.md5(F.array_join(F.slice("a", i, 8), " ")))).alias("h")).distinct()

    bench = grams(table("benchmark")(spark, d), "item_id").select("h").distinct()
    return grams(docs(spark, d), "doc_id").join(bench, "h", "left_semi").groupBy("doc_id").agg(F.count("*").alias("shared"))


query("op_pricing_summary", "SELECT l_returnflag, l_linestatus, count(*) AS n, round(sum(l_quantity), 2) AS qty, round(sum(l_extendedprice * (1 - l_discount)), 2) AS revenue FROM lineitem GROUP BY 1, 2")(
    lambda spark, d: table("lineitem")(spark, d).groupBy("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), F.round(F.sum("l_quantity"), 2).alias("qty"), F.round(F.sum(F.col("l_extendedprice") * (1 - F.col("l_discount"))), 2).alias("revenue"))
)


@query("op_revenue_by_nation", "SELECT n_name, round(sum(l_extendedprice * (1 - l_discount)), 2) AS revenue FROM lineitem JOIN supplier ON l_suppkey = s_suppkey JOIN nation ON s_nationkey = n_nationkey GROUP BY n_name")
def revenue(spark, d):
    """Nations are a fixed 25 rows; suppliers are joined as the optimiser sees fit."""
    lines = table("lineitem")(spark, d).select("l_suppkey", (F.col("l_extendedprice") * (1 - F.col("l_discount"))).alias("v"))
    sup = table("supplier")(spark, d).join(F.broadcast(table("nation")(spark, d)), F.col("s_nationkey") == F.col("n_nationkey")).select("s_suppkey", "n_name")
    return lines.join(sup, F.col("l_suppkey") == F.col("s_suppkey")).groupBy("n_name").agg(F.round(F.sum("v"), 2).alias("revenue"))


_SQUEEZED = "word"
for _c in "abcdefghijklmnopqrstuvwxyz0123456789":
    _SQUEEZED = f"regexp_replace({_SQUEEZED}, '{_c}{{3,}}', '{_c}{_c}', 'g')"
_SPELT = "CASE sq " + " ".join(f"WHEN '{k}' THEN '{v}'" for k, v in (T.DIGIT_SPELLINGS | T.ABBREVIATIONS).items()) + " ELSE sq END"


@query("op_normalise", f"WITH {TYP}, z AS (SELECT word, {_SQUEEZED} AS sq FROM typ WHERE regexp_full_match(word, '[a-z0-9]+')) SELECT word, {_SPELT} AS spelt FROM z")
def normalised(spark, d):
    """Types in their usual spelling: runs of a character squeezed, spellings with digits and abbreviations written out."""
    return types(spark, d).filter(F.col("word").rlike("^[a-z0-9]+$")).select("word", T.normalise(F.col("word")).alias("spelt"))


@query("op_balance", f"WITH {TAGGED} SELECT word, tag FROM tagged QUALIFY row_number() OVER (PARTITION BY tag ORDER BY md5(word)) <= 100")
def balanced(spark, d):
    return C.balance(tagged(spark, d), 100).select("word", "tag")


@query("op_balance_over", f"WITH {TAGGED}, few AS (SELECT word, tag, row_number() OVER (PARTITION BY tag ORDER BY md5(word)) AS r, least(count(*) OVER (PARTITION BY tag), 100) AS k FROM tagged) SELECT word, tag, (100 // k + CASE WHEN r <= 100 % k THEN 1 ELSE 0 END)::BIGINT AS copies FROM few WHERE r <= 100")
def oversampled(spark, d):
    """A hundred rows of each tag; where there are fewer words, words are repeated."""
    return C.balance(tagged(spark, d), 100, "over").groupBy("word", "tag").agg(F.count("*").alias("copies"))


_LEN = lambda t: f"len(list_filter(regexp_extract_all({t}, '[^ ]+'), lambda w: regexp_replace(w, '[.,!?]+$', '') <> ''))"


@query("op_splice", f"WITH {SENT}, h AS (SELECT lang, text, md5(doc_id || ':' || sent_no) AS h FROM sent WHERE {PAIR}), r AS (SELECT lang, text, substr(h, 1, 2) AS b, row_number() OVER (PARTITION BY lang, substr(h, 1, 2) ORDER BY h) AS r FROM h) SELECT e.b || '-' || e.r AS sid, ({_LEN('e.text')} + {_LEN('l.text')})::INTEGER AS n_words FROM r e JOIN r l ON e.b = l.b AND e.r = l.r AND e.lang = 'en' AND l.lang = '{LOCAL}'")
def spliced(spark, d):
    out = kept(spark, d, "splices", lambda: C.splice(sentences(spark, d)))
    return out.select("sid", F.size("words").alias("n_words"))
