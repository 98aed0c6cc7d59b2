"""Tables that many queries start from, in DataFrames (written once for each session and input) and in SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from wordlid.functions.text import ACCENTED, PLAIN
from wordlid.io import cut_lineage, discard, file_state, read_table
from wordlid.operators import corpus

LOCAL = "fr"
_kept: dict = {}


def kept(spark: SparkSession, sf_dir: str, name: str, make) -> DataFrame:
    """What make() returns, written to the shared folder the first time and again when the tables' files have changed."""
    key = (spark.sparkContext.applicationId, sf_dir, name)
    state = file_state(spark, sf_dir)
    if key in _kept and _kept[key][0] != state:
        discard(_kept.pop(key)[1])
    if key not in _kept:
        _kept[key] = (state, cut_lineage(make(), name))
    return _kept[key][1]


def once(spark: SparkSession, sf_dir: str, name: str, make):
    """A fitted object, which is small, made once for the same files."""
    key = (spark.sparkContext.applicationId, sf_dir, name, file_state(spark, sf_dir))
    if key not in _made:
        _made[key] = make()
    return _made[key]


def forget() -> None:
    """Drop what is kept of all tables."""
    discard(*[t for _, t in _kept.values()])
    _kept.clear()
    _made.clear()


_made: dict = {}


def docs(spark, d):
    return read_table(spark, d, "documents")


def sentences(spark, d):
    return corpus.to_sentences(docs(spark, d))


def tokens(spark, d):
    return corpus.to_tokens(sentences(spark, d))


def types(spark, d):
    return kept(spark, d, "types", lambda: corpus.count_types(docs(spark, d), LOCAL))


def tagged(spark, d):
    t = lambda n: read_table(spark, d, n)
    return kept(spark, d, "tagged", lambda: corpus.tagged_words(types(spark, d), t("customer"), t("supplier"), t("nation"), t("region")))


def parts(spark, d):
    split = corpus.split_train_test(tagged(spark, d))
    return tuple(split.filter(f"part = '{p}'").select("word", "tag") for p in ("train", "test"))


PAIR = f"lang IN ('en', '{LOCAL}')"
ROM = f"translate(lower(text), '{ACCENTED}', '{PLAIN}')"
BUCKET = lambda key, of=100: f"(('0x' || substr(md5({key}), 1, 8))::BIGINT % {of})::INTEGER"
SENT = rf"""s0 AS (SELECT source, doc_id, lang, regexp_split_to_array({ROM}, '[.!?]*\n|[.!?]+ ') AS a FROM documents),
 sent AS (SELECT * FROM (SELECT source, doc_id, lang, unnest(generate_series(0, len(a) - 1))::INTEGER AS sent_no, trim(unnest(a)) AS text FROM s0) WHERE text <> '')"""
TOK = SENT + r""",
 t0 AS (SELECT source, doc_id, lang, sent_no, regexp_extract_all(text, '[^ ]+') AS a FROM sent),
 tok AS (SELECT * FROM (SELECT source, doc_id, lang, sent_no, unnest(generate_series(0, len(a) - 1))::INTEGER AS pos, regexp_replace(unnest(a), '[.,!?]+$', '') AS word FROM t0) WHERE word <> '')"""
TYP = TOK + f""",
 typ AS (SELECT word, count(*) AS n, count(*) FILTER (lang = 'en') AS e, count(*) FILTER (lang = '{LOCAL}') AS l FROM tok GROUP BY word),
 base AS (SELECT word, n, CASE WHEN NOT regexp_full_match(word, '[a-z]+') THEN 'other' WHEN e * 5 >= n * 4 THEN 'en' WHEN l * 5 >= n * 4 THEN 'local' ELSE 'other' END AS tag FROM typ)"""
_SYL = "[" + ", ".join(f"'{s}'" for s in corpus.SYLLABLES) + "]"
_SPELL = lambda x: f"array_to_string(list_transform(regexp_extract_all(({x})::VARCHAR, '.'), lambda c: {_SYL}[c::INTEGER + 1]), '')"
_TOP20 = lambda lang: f"(SELECT suffix, row_number() OVER (ORDER BY uses DESC, suffix) - 1 AS k FROM (SELECT right(word, 3) AS suffix, sum(n) AS uses FROM base WHERE tag = '{lang}' AND length(word) >= 6 GROUP BY 1 ORDER BY uses DESC, suffix LIMIT 20))"
_MIX = lambda stem, other: f"SELECT b.word || top.suffix, 'mixed' FROM base b JOIN {_TOP20(other)} top ON top.k = {BUCKET('b.word', 20)} WHERE b.tag = '{stem}' AND length(b.word) BETWEEN 3 AND 8 AND b.n >= 2"
TAGGED = TYP + f""",
 pl0 AS (SELECT {_SPELL('c_custkey + 100')} AS word, 'name' AS tag FROM customer UNION SELECT {_SPELL('s_suppkey + 5000000')}, 'name' FROM supplier
   UNION SELECT regexp_replace(lower(r_name), '[^a-z]', '', 'g'), 'location' FROM region UNION SELECT {_SPELL('n_nationkey + 1000')} || 'pur', 'location' FROM nation
   UNION {_MIX('en', 'local')} UNION {_MIX('local', 'en')}),
 pl AS (SELECT word, min(tag) AS tag FROM pl0 WHERE word NOT IN (SELECT word FROM typ) GROUP BY word),
 evry AS (SELECT word, n, tag FROM base UNION ALL SELECT word, 1, tag FROM pl),
 tot AS (SELECT floor(count(*) FILTER (tag = 'local') / {2 * corpus.SHARES['local']}::DOUBLE) AS total FROM evry),
 rk AS (SELECT *, row_number() OVER (PARTITION BY tag ORDER BY md5(word)) AS r FROM evry),
 tagged AS (SELECT word, tag, n FROM rk, tot WHERE r <= floor(total * (CASE tag {' '.join(f"WHEN '{t}' THEN {s}::DOUBLE" for t, s in corpus.SHARES.items())} END)))"""
SPLIT = TAGGED + f""",
 sp AS (SELECT word, tag, n, CASE WHEN {BUCKET("'t' || word")} < 70 THEN 'train' ELSE 'test' END AS part FROM tagged),
 train AS (SELECT word, tag FROM sp WHERE part = 'train'), test AS (SELECT word, tag FROM sp WHERE part = 'test')"""
ORDER = "CASE tag " + " ".join(f"WHEN '{t}' THEN {i}" for i, t in enumerate(corpus.TAGS)) + " END"
