"""Closed-form taggers: every one takes train (word, tag) and test (word, tag) and returns word, gold, pred."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from wordlid.functions.text import char_ngrams
from wordlid.operators.corpus import TAGS

def _top(counts: DataFrame, by: str, name: str) -> DataFrame:
    """The tag with the most words for each key; ties by tag order."""
    rank = F.array_position(F.array(*map(F.lit, TAGS)), F.col("tag"))
    return counts.groupBy(by).agg(F.min_by("tag", F.struct(-F.col("n"), rank)).alias(name))


def majority(train: DataFrame) -> DataFrame:
    return _top(train.groupBy("tag").agg(F.count("*").alias("n")).withColumn("one", F.lit(1)), "one", "top").select("top")


def b1(train: DataFrame, test: DataFrame) -> DataFrame:
    return test.crossJoin(F.broadcast(majority(train))).select("word", F.col("tag").alias("gold"), F.col("top").alias("pred"))  # one row


def b2(train: DataFrame, test: DataFrame) -> DataFrame:
    """Look the word up among the training words; one that is not there has the majority tag. Of types that are split, none is there;
    of tokens whose sentences are split, most are."""
    known = _top(train.groupBy("word", "tag").agg(F.count("*").alias("n")), "word", "found")
    return test.join(known, "word", "left").crossJoin(F.broadcast(majority(train))).select("word", F.col("tag").alias("gold"), F.coalesce("found", "top").alias("pred"))


def b2_stem(train: DataFrame, test: DataFrame) -> DataFrame:
    """Look up the word without its last letter among training words without theirs."""
    stem = lambda df: df.withColumn("stem", F.expr("substring(word, 1, greatest(length(word) - 1, 1))"))
    known = _top(stem(train).groupBy("stem", "tag").agg(F.count("*").alias("n")), "stem", "found")
    return stem(test).join(known, "stem", "left").crossJoin(F.broadcast(majority(train))).select("word", F.col("tag").alias("gold"), F.coalesce("found", "top").alias("pred"))


def _by_suffix(train: DataFrame, k: int) -> DataFrame:
    long_enough = train.filter(F.length("word") >= k)
    return _top(long_enough.groupBy(F.right("word", F.lit(k)).alias(f"s{k}"), "tag").agg(F.count("*").alias("n")), f"s{k}", f"p{k}")


def b5(train: DataFrame, test: DataFrame, longest: int = 5) -> DataFrame:
    """The majority tag of the longest suffix that training words have."""
    out = test.crossJoin(F.broadcast(majority(train)))
    for k in range(longest, 0, -1):
        out = out.withColumn(f"s{k}", F.when(F.length("word") >= k, F.right("word", F.lit(k)))).join(_by_suffix(train, k), f"s{k}", "left")
    return out.select("word", F.col("tag").alias("gold"), F.coalesce(*[f"p{k}" for k in range(longest, 0, -1)], "top").alias("pred"))


def b3(train: DataFrame, test: DataFrame, k: int = 3) -> DataFrame:
    out = test.withColumn(f"s{k}", F.when(F.length("word") >= k, F.right("word", F.lit(k)))).join(_by_suffix(train, k), f"s{k}", "left")
    return out.crossJoin(F.broadcast(majority(train))).select("word", F.col("tag").alias("gold"), F.coalesce(f"p{k}", "top").alias("pred"))


def grams(words: DataFrame, sizes) -> DataFrame:
    return words.select("word", "tag", F.explode(char_ngrams(F.col("word"), sizes)).alias("g"))


def nb_scores(train: DataFrame, test: DataFrame, sizes=(2, 3)) -> DataFrame:
    """Multinomial naive Bayes with add-one on character n-grams: word, gold and a log-score for each tag."""
    counts = grams(train, sizes).groupBy("g").agg(*[F.count_if(F.col("tag") == t).alias(t) for t in TAGS])
    totals = counts.agg(F.count("*").alias("v"), *[F.sum(t).alias(f"t_{t}") for t in TAGS])
    prior = train.agg(F.count("*").alias("m"), *[F.count_if(F.col("tag") == t).alias(f"m_{t}") for t in TAGS])
    one = F.broadcast(totals.crossJoin(prior))  # one row
    found = grams(test, sizes).join(counts, "g", "left").crossJoin(one)
    term = lambda t: F.sum(F.log((F.coalesce(t, F.lit(0)) + 1) / (F.col(f"t_{t}") + F.col("v")))).alias(f"x_{t}")
    scores = found.groupBy("word", F.col("tag").alias("gold")).agg(*[term(t) for t in TAGS])
    return scores.crossJoin(one).select("word", "gold", *[F.round(F.col(f"x_{t}") + F.log((F.col(f"m_{t}") + 1) / (F.col("m") + len(TAGS))), 6).alias(t) for t in TAGS])


def best(scores: DataFrame) -> DataFrame:
    values = F.array(*TAGS)
    return scores.select("word", "gold", F.element_at(F.array(*map(F.lit, TAGS)), F.array_position(values, F.array_max(values)).cast("int")).alias("pred"))


def b4(train: DataFrame, test: DataFrame) -> DataFrame:
    return best(nb_scores(train, test))


def charlm_scores(train: DataFrame, test: DataFrame, k: float = 0.5) -> DataFrame:
    """Log-probability of the word under each tag's character trigram model with add-k and an alphabet of 30."""
    three = grams(train, (3,)).groupBy("g").agg(*[F.count_if(F.col("tag") == t).alias(t) for t in TAGS])
    two = three.groupBy(F.substring("g", 1, 2).alias("h")).agg(*[F.sum(t).alias(f"h_{t}") for t in TAGS])
    found = grams(test, (3,)).withColumn("h", F.substring("g", 1, 2)).join(three, "g", "left").join(two, "h", "left")
    term = lambda t: F.round(F.sum(F.log((F.coalesce(t, F.lit(0)) + k) / (F.coalesce(f"h_{t}", F.lit(0)) + 30 * k))), 6).alias(t)
    return found.groupBy("word", F.col("tag").alias("gold")).agg(*[term(t) for t in TAGS])


def b6(train: DataFrame, test: DataFrame) -> DataFrame:
    return best(charlm_scores(train, test))


BASELINES = {"b1": b1, "b2": b2, "b2_stem": b2_stem, "b3": b3, "b4": b4, "b5": b5, "b6": b6}
