"""From comments to sentences, tokens, word types and a weakly tagged word set."""

from __future__ import annotations

import re
from collections import Counter
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from wordlid.functions.text import ACCENTED, PLAIN, bucket, romanise
from wordlid.io import bound_batches, cut_lineage

#: Tags, in the order in which ties are broken.
TAGS = ("local", "en", "mixed", "name", "location", "other")
#: The syllable of each digit in planted names.
SYLLABLES = ("ra", "mi", "ku", "sa", "ve", "no", "ta", "hi", "du", "ja")
SENTENCE = r"[.!?]*\n|[.!?]+ "
#: Line ends, apart from the one that parts sentences, before which Java's `$` stands too; and the signs at a word's end under that `$`.
_LINE_ENDS, _ENDING = re.compile("[\r\u0085\u2028\u2029]"), re.compile("[.,!?]+(?=[\r\u0085\u2028\u2029]?\\Z)")
#: Different tokens that a task counts before it sends its counts on.
HELD = 300_000
#: Share of each tag in the tagged word set.
SHARES = {"local": 0.448, "en": 0.3232, "mixed": 0.075, "name": 0.06, "location": 0.02, "other": 0.0738}


def collect_comments(docs: DataFrame, sources: list[str]) -> DataFrame:
    """Comments of the listed videos; few ids become a filter that reaches the scan."""
    return docs.select("source", "doc_id", "lang", "text").filter(F.col("source").isin(sources))


def to_sentences(docs: DataFrame) -> DataFrame:
    parts = docs.select("source", "doc_id", "lang", F.posexplode(F.split(romanise(F.col("text")), SENTENCE, -1)).alias("sent_no", "s"))
    return parts.select("source", "doc_id", "lang", "sent_no", F.trim("s").alias("text")).filter("text <> ''")


def to_tokens(sentences: DataFrame) -> DataFrame:
    parts = sentences.select("source", "doc_id", "lang", "sent_no", F.posexplode(F.regexp_extract_all("text", F.lit("[^ ]+"), F.lit(0))).alias("pos", "w"))
    return parts.select("source", "doc_id", "lang", "sent_no", "pos", F.regexp_replace("w", "[.,!?]+$", "").alias("word")).filter("word <> ''")


def sentence_words(sentences: DataFrame) -> DataFrame:
    """lang, seq: the words of each sentence in their order, as to_tokens has them, without a row for each."""
    words = F.transform(F.regexp_extract_all("text", F.lit("[^ ]+"), F.lit(0)), lambda w: F.regexp_replace(w, "[.,!?]+$", ""))
    return sentences.select("lang", F.filter(words, lambda w: w != "").alias("seq")).filter(F.size("seq") > 0)


def word_types(tokens: DataFrame, local: str = "fr") -> DataFrame:
    """word, n, uses in English and in the local language; one aggregation with partial sums."""
    return tokens.groupBy("word").agg(F.count("*").alias("n"), F.count_if(F.col("lang") == "en").alias("e"), F.count_if(F.col("lang") == local).alias("l"))


def count_types(docs: DataFrame, local: str = "fr") -> DataFrame:
    """word_types of the tokens of docs (text, lang), without a row for each token: a task counts the words of whole batches of texts.

    Every space and line end parts two tokens, and the signs before it go either way, with the sentence's end or from the word's. A text with
    another line end, before which a sign also stands at the end for the patterns, is taken apart step by step.
    """
    bound_batches(docs.sparkSession)
    kinds = {"en": 0, local: 1}

    def sums(counts: list[Counter]) -> pa.RecordBatch:
        found: dict[str, list[int]] = {}
        for kind, tokens in enumerate(counts):
            for token, n in tokens.items():
                if word := token if _LINE_ENDS.search(token) else token.rstrip(".,!?"):
                    own = found.setdefault(word, [0, 0, 0])
                    own[0] += n
                    if kind < 2:
                        own[kind + 1] += n
            tokens.clear()
        columns = zip(*found.values(), strict=True) if found else ((), (), ())
        return pa.RecordBatch.from_arrays([pa.array(list(found), pa.string()), *(pa.array(c, pa.int64()) for c in columns)], names=["word", "n", "e", "l"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counts: list[Counter] = [Counter(), Counter(), Counter()]
        for b in batches:
            texts: list[list[str]] = [[], [], []]
            for text, lang in zip(b.column("text").to_pylist(), b.column("lang").to_pylist(), strict=True):
                texts[kinds.get(lang, 2)].append(text)
            for own, some in zip(counts, texts, strict=True):
                plain = "\n".join(t for t in some if not _LINE_ENDS.search(t))
                own.update(_plain(plain).replace("\n", " ").split(" "))
                for text in filter(_LINE_ENDS.search, some):
                    own.update(_ENDING.sub("", w) for s in re.split(SENTENCE, _plain(text)) for w in s.split(" "))
            if sum(map(len, counts)) > HELD:
                yield sums(counts)
        yield sums(counts)

    rows = docs.select(F.lower("text").alias("text"), "lang").filter("text is not null")
    return rows.mapInArrow(run, "word string, n long, e long, l long").groupBy("word").agg(*[F.sum(c).alias(c) for c in "nel"])


def _plain(text: str) -> str:
    """Lower-case text in Roman letters, as romanise gives."""
    if not text.isascii():
        for a, b in zip(ACCENTED, PLAIN, strict=True):
            text = text.replace(a, b)
    return text


def base_tags(types: DataFrame, least: int = 80) -> DataFrame:
    """A type of which at least so many of a hundred uses are in one language has its tag; ambiguous, foreign and non-letter types are `other`."""
    share = lambda c: F.col(c) * 100 >= F.col("n") * least
    tag = F.when(~F.col("word").rlike("^[a-z]+$"), "other").when(share("e"), "en").when(share("l"), "local").otherwise("other")
    return types.select("word", "n", tag.alias("tag"))


def spelled(number, digits=SYLLABLES):
    return F.array_join(F.transform(F.filter(F.split(number.cast("string"), ""), lambda d: d != ""), lambda d: F.element_at(F.array(*map(F.lit, digits)), d.cast("int") + 1)), "")


def mixed_words(base: DataFrame, stem: str, other: str) -> DataFrame:
    """Stems of one language (3 to 8 letters, used twice or more), each with one of the 20 most frequent 3-letter suffixes of the other."""
    suffix = base.filter((F.col("tag") == other) & (F.length("word") >= 6)).groupBy(F.right("word", F.lit(3)).alias("suffix")).agg(F.sum("n").alias("uses"))
    top = suffix.orderBy(F.desc("uses"), "suffix").limit(20).withColumn("k", F.row_number().over(Window.orderBy(F.desc("uses"), "suffix")) - 1)  # 20 rows
    stems = base.filter((F.col("tag") == stem) & F.length("word").between(3, 8) & (F.col("n") >= 2)).select("word", bucket(F.col("word"), of=20).alias("k"))
    return stems.join(F.broadcast(top), "k").select(F.concat("word", "suffix").alias("word"), F.lit("mixed").alias("tag"))


def planted(types: DataFrame, customer: DataFrame, supplier: DataFrame, nation: DataFrame, region: DataFrame) -> DataFrame:
    """Names, places and mixed words, in both orders, that follow fixed rules; words that occur anyway are left out."""
    base = base_tags(types)
    names = customer.select(spelled(F.col("c_custkey") + 100).alias("word")).union(supplier.select(spelled(F.col("s_suppkey") + 5000000).alias("word"))).distinct().select("word", F.lit("name").alias("tag"))
    places = region.select(F.regexp_replace(F.lower("r_name"), "[^a-z]", "").alias("word")).union(nation.select(F.concat(spelled(F.col("n_nationkey") + 1000), F.lit("pur")).alias("word"))).distinct().select("word", F.lit("location").alias("tag"))
    mixed = mixed_words(base, "en", "local").union(mixed_words(base, "local", "en")).distinct()
    every = names.unionByName(places).unionByName(mixed).groupBy("word").agg(F.min("tag").alias("tag"))
    return every.join(types.select("word"), "word", "left_anti")


def smallest(rows: DataFrame, quota, by: str = "tag", key: str = "word", digits: int = 4) -> DataFrame:
    """Of each group the rows whose key has the smallest MD5, as many as the column `quota` says.

    Rows are counted by the first digits of the MD5, so that only those of one prefix in each group are ranked: no task sorts a group.
    """
    names = rows.columns
    hashed = rows.withColumn("_h", F.md5(key)).withColumn("_p", F.substring("_h", 1, digits))
    before = Window.partitionBy(by).orderBy("_p").rowsBetween(Window.unboundedPreceding, -1)
    counts = hashed.groupBy(by, "_p").agg(F.count("*").alias("_n")).withColumn("_start", F.coalesce(F.sum("_n").over(before), F.lit(0)))
    placed = hashed.join(F.broadcast(counts), [by, "_p"])  # 16 ** digits rows for each group at the most
    whole = placed.filter(F.col("_start") + F.col("_n") <= quota)
    torn = placed.filter((F.col("_start") < quota) & (F.col("_start") + F.col("_n") > quota))
    ranked = torn.withColumn("_r", F.row_number().over(Window.partitionBy(by, "_p").orderBy("_h"))).filter(F.col("_start") + F.col("_r") <= quota)
    return whole.select(names).unionByName(ranked.select(names))


def tagged_words(types: DataFrame, customer: DataFrame, supplier: DataFrame, nation: DataFrame, region: DataFrame) -> DataFrame:
    """word, tag, n: each tag up to its share, the words with the smallest MD5."""
    every = base_tags(types).unionByName(planted(types, customer, supplier, nation, region).withColumn("n", F.lit(1).cast("long")))
    every = cut_lineage(every, "every")  # it is read for the total, for the counts, and twice for the words
    goal = every.agg(F.floor(F.count_if(F.col("tag") == "local") / F.lit(2 * SHARES["local"])).alias("total"))  # one row
    share = F.element_at(F.create_map(*[F.lit(x) for kv in SHARES.items() for x in kv]), F.col("tag"))
    return smallest(every.crossJoin(F.broadcast(goal)), F.floor(F.col("total") * share)).select("word", "tag", "n")


def split_train_test(tagged: DataFrame, seed: str = "t", share: int = 70) -> DataFrame:
    return tagged.withColumn("part", F.when(bucket(F.col("word"), seed) < share, "train").otherwise("test"))


def splice(sentences: DataFrame, local: str = "fr", run: int = 2, digits: int = 2) -> DataFrame:
    """Code-mixed sentences: equal ranks of local and English sentences, interleaved by runs of words. Ranks are taken among sentences
    whose MD5 begins with the same digits; more digits for more sentences keep what a task ranks small."""
    ranked = sentences.filter(F.col("lang").isin("en", local)).withColumn("h", F.md5(F.concat_ws(":", "doc_id", "sent_no"))).withColumn("b", F.substring("h", 1, digits))
    ranked = ranked.withColumn("r", F.row_number().over(Window.partitionBy("lang", "b").orderBy("h")))
    one = lambda lang, name: ranked.filter(F.col("lang") == lang).select("b", "r", F.regexp_extract_all("text", F.lit("[^ ]+"), F.lit(0)).alias(name))
    both = one("en", "e").join(one(local, "l"), ["b", "r"])
    def placed(side: str, late: int, origin: str):
        return F.transform(side, lambda w, i: F.struct((F.floor(i / run) * 2 + late).alias("g"), i.alias("i"), F.regexp_replace(w, "[.,!?]+$", "").alias("word"), F.lit(origin).alias("origin")))

    flat = F.concat(placed("e", 0, "en"), placed("l", 1, "local"))
    return both.select(F.concat_ws("-", "b", "r").alias("sid"), F.filter(F.array_sort(flat), lambda x: x["word"] != "").alias("words"))


def insert_words(spliced: DataFrame, words: DataFrame, digits: int = 2) -> DataFrame:
    """sid, words (strings): each of the words stands once in some sentence, at a place that its MD5 names."""
    home = F.substring(F.md5("sid"), 1, digits)
    rank = lambda by: F.row_number().over(Window.partitionBy("b").orderBy(F.md5(by)))
    here = spliced.select("sid", F.transform("words", lambda x: x["word"]).alias("words"), home.alias("b")).withColumn("r", rank("sid"))
    many = here.groupBy("b").agg(F.count("*").alias("many"))  # 16 ** digits rows
    new = words.select("word", F.substring(F.md5("word"), 1, digits).alias("b")).withColumn("r", rank("word")).join(F.broadcast(many), "b")
    new = new.groupBy("b", ((F.col("r") - 1) % F.col("many") + 1).alias("r")).agg(F.collect_list("word").alias("new"))
    both = here.join(new, ["b", "r"], "left")
    old = F.transform("words", lambda w, i: F.struct(i.cast("double").alias("at"), w.alias("word")))
    put = F.transform(F.coalesce("new", F.array().cast("array<string>")), lambda w: F.struct((bucket(w, of=1 << 20) % (F.size("words") + 1) - 0.5).alias("at"), w.alias("word")))
    return both.select("sid", F.transform(F.array_sort(F.concat(old, put)), lambda x: x["word"]).alias("words"))


def drop_duplicate_comments(comments: DataFrame) -> DataFrame:
    """One row of each lower-cased text, that with the smallest doc_id; only digests are shuffled."""
    keys = comments.select("doc_id", F.md5(F.lower("text")).alias("k"))
    return comments.join(keys.groupBy("k").agg(F.min("doc_id").alias("doc_id")).select("doc_id"), "doc_id", "left_semi")


def strip_unprintable(c):
    return F.regexp_replace(c, r"[\p{So}\p{Sk}\p{Cf}\p{Cn}&&[^\n]]|[\p{Cc}&&[^\n]]", "")


def clean_flags(comments: DataFrame, lexicon: DataFrame, script: str = r"[^\x00-\x7F]", least: int = 3) -> DataFrame:
    """doc_id and what each rule says of a comment: script, short, english_only, duplicate. A null is no comment."""
    words = comments.select("doc_id", F.explode(F.regexp_extract_all(F.lower("text"), F.lit(r"[^\x20\x09-\x0D]+"), F.lit(0))).alias("w")).select("doc_id", F.regexp_replace("w", "[.,!?]+$", "").alias("word")).filter("word <> ''")
    known = words.join(lexicon.withColumn("known", F.lit(1)), "word", "left").groupBy("doc_id").agg(F.min(F.coalesce("known", F.lit(0))).alias("all_en"))
    comments = comments.filter("text is not null")
    # the first of each text by doc_id: a text that very many have is one row of the aggregate and no key of a join
    first = comments.select("doc_id", F.md5(F.lower("text")).alias("k")).groupBy("k").agg(F.min("doc_id").alias("doc_id")).select("doc_id", F.lit(True).alias("first"))
    flags = comments.select("doc_id", F.col("text").rlike(script).alias("script"), (F.size(F.regexp_extract_all("text", F.lit(r"[^\x20\x09-\x0D]+"), F.lit(0))) < least).alias("short"))
    return flags.join(first, "doc_id", "left").join(known, "doc_id", "left").select("doc_id", "script", "short", (F.coalesce("all_en", F.lit(1)) == 1).alias("english_only"), F.col("first").isNull().alias("duplicate"))


RULES = ("duplicate", "script", "short", "english_only")
ONLY_SIGNS = r"^[\p{So}\p{Sk}\p{Cf}\p{Cc}\s]+$"


def clean_comments(comments: DataFrame, lexicon: DataFrame, script: str = r"[^\x00-\x7F]", least: int = 3, rules: tuple[str, ...] = RULES, emoji_mode: str = "strip") -> tuple[DataFrame, DataFrame]:
    """The cleaned comments, with all their columns, and a row of counts after each rule.

    Emojis and unprintable characters go first (strip), or comments of nothing else go (drop_only_emoji); then what each of the rules names,
    as the text is by then. Without the rules script and english_only, comments in the local script or in English alone stay.
    """
    if emoji_mode == "strip":
        text = comments.withColumn("text", strip_unprintable(F.col("text")))
    else:
        text = comments.filter(~F.coalesce(F.col("text").rlike(ONLY_SIGNS), F.lit(False)))
    flags = clean_flags(text.select("doc_id", "text"), lexicon, script, least)
    keep, counts = F.lit(True), [F.count("*").alias("comments")]
    for rule in rules:
        keep = keep & ~F.col(rule)
        counts.append(F.count_if(keep).alias(f"after_{rule}"))
    return text.join(flags.filter(keep).select("doc_id"), "doc_id", "left_semi"), flags.agg(*counts)


def balance(tagged: DataFrame, target: int, mode: str = "under") -> DataFrame:
    """At most `target` words of each tag, those with the smallest MD5 (under); or exactly `target` rows of each tag, fewer words repeated (over)."""
    few = smallest(tagged, F.lit(target))
    if mode == "under":
        return few
    many = tagged.groupBy("tag").agg(F.count("*").alias("_many"))  # one row a tag
    rows = few.join(F.broadcast(many), "tag").withColumn("_many", F.least("_many", F.lit(target)))
    whole = rows.withColumn("_copy", F.explode(F.sequence(F.lit(1), F.floor(F.lit(target) / F.col("_many")).cast("int"))))
    rest = smallest(rows, F.lit(target) % F.col("_many"))
    return whole.select(tagged.columns).unionByName(rest.select(tagged.columns))


def mix_profile(tokens: DataFrame, tags: DataFrame, level: list[str]) -> DataFrame:
    """Counts of each tag at a coarser level."""
    found = tokens.join(tags.select("word", "tag"), "word")
    return found.groupBy(*level).agg(*[F.count_if(F.col("tag") == t).alias(f"n_{t}") for t in ("local", "en", "other")], F.count("*").alias("n_words"))


def context_bag(tokens: DataFrame, k: int = 1, length: int = 3) -> DataFrame:
    """doc_id, sent_no, pos, word, offset, feature: the suffix of each neighbour up to k words away, marked by where it stands."""
    w = Window.partitionBy("doc_id", "sent_no").orderBy("pos")
    near = [F.struct(F.lit(o).alias("offset"), F.right(F.lead("word", o).over(w) if o > 0 else F.lag("word", -o).over(w), F.lit(length)).alias("feature")) for o in range(-k, k + 1) if o]
    rows = tokens.select("doc_id", "sent_no", "pos", "word", F.array(*near).alias("near"))
    return rows.select("doc_id", "sent_no", "pos", "word", F.explode("near").alias("x")).select("doc_id", "sent_no", "pos", "word", "x.offset", "x.feature").filter("feature is not null")
