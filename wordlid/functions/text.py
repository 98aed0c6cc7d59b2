"""Column functions on text: romanisation, buckets, affixes, character n-grams."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

#: Accented letters of the given languages and their Roman stand-ins, in the same order.
ACCENTED = "àâäáãçéèêëíîïñóôöúùûüß"
PLAIN = "aaaaaceeeeiiinooouuuus"
#: Sizes as the text of the method states them, and as its worked sample shows them.
PROSE_SIZES = {"affixes": (1, 2, 3), "word": (2, 3, 5), "piece": (1, 2, 3), "include_word": False}
SAMPLE_SIZES = {"affixes": (3, 2, 1), "word": (4,), "piece": (4,), "include_word": True}


def romanise(c: Column) -> Column:
    return F.translate(F.lower(c), ACCENTED, PLAIN)


def squeeze_runs(c: Column) -> Column:
    """Letters that are repeated three times or more are kept twice."""
    return F.regexp_replace(c, r"(.)\1{2,}", "$1$1")


#: Informal spellings with digits, abbreviations, and what they stand for.
DIGIT_SPELLINGS = {"gr8": "great", "l8r": "later", "b4": "before", "2day": "today", "2nite": "tonight", "m8": "mate", "w8": "wait", "4ever": "forever"}
ABBREVIATIONS = {"omg": "oh my god", "lol": "laughing out loud", "btw": "by the way", "idk": "i do not know", "thx": "thanks", "pls": "please", "u": "you", "r": "are"}


def normalise(word: Column, rules: tuple[str, ...] = ("runs", "digits", "abbreviations")) -> Column:
    """A lower-case word in its usual spelling, under the rules that are on."""
    out = squeeze_runs(word) if "runs" in rules else word
    known = (DIGIT_SPELLINGS if "digits" in rules else {}) | (ABBREVIATIONS if "abbreviations" in rules else {})
    if not known:
        return out
    return F.coalesce(F.create_map(*[F.lit(x) for pair in known.items() for x in pair])[out], out)


def bucket(key: Column, seed: str = "", of: int = 100) -> Column:
    """The first eight hexadecimal digits of an MD5, modulo `of`; DuckDB computes the same."""
    return (F.conv(F.substring(F.md5(F.concat(F.lit(seed), key)), 1, 8), 16, 10).cast("long") % of).cast("int")


def affixes(c: Column, lengths=(1, 2, 3)) -> Column:
    """Suffix, then prefix, of each length that the word has."""
    parts = []
    for k in lengths:
        parts += [F.when(F.length(c) >= k, F.right(c, F.lit(k))), F.when(F.length(c) >= k, F.left(c, F.lit(k)))]
    return F.array_compact(F.array(*parts))


def char_ngrams(c: Column, sizes=(2, 3, 5), pad: str = "_") -> Column:
    """Character n-grams of the padded word, size by size, as counts allow repeats."""
    padded = F.concat(F.lit(pad), c, F.lit(pad))
    one = lambda k: F.when(F.length(padded) >= k, F.transform(F.sequence(F.lit(1), F.greatest(F.length(padded) - k + 1, F.lit(1))), lambda i: F.substring(padded, i, F.lit(k)))).otherwise(F.array().cast("array<string>"))
    return F.concat(*[one(k) for k in sizes])


def piece_ngrams(pieces: Column, sizes=(1, 2, 3), pad: str = "_") -> Column:
    return F.flatten(F.transform(pieces, lambda p: char_ngrams(p, sizes, pad)))


def families(word: Column, pieces: Column, sizes: dict = PROSE_SIZES) -> Column:
    """All features with their family: w the whole word, s suffix, p prefix, g n-gram of the word, b n-gram of a piece."""
    marked = lambda mark, c: F.transform(c, lambda x: F.struct(F.lit(mark).alias("family"), x.alias("feature")))
    ends = lambda side: F.array_compact(F.array(*[F.when(F.length(word) >= k, side(word, F.lit(k))) for k in sizes["affixes"]]))
    whole = [marked("w", F.array(word))] if sizes["include_word"] else []
    return F.concat(*whole, marked("s", ends(F.right)), marked("p", ends(F.left)), marked("g", char_ngrams(word, sizes["word"])), marked("b", piece_ngrams(pieces, sizes["piece"])))


def features(word: Column, pieces: Column, sizes: dict = PROSE_SIZES) -> Column:
    """One array of all features, without family marks, in the order whole word, affixes, word n-grams, piece n-grams."""
    whole = [F.array(word)] if sizes["include_word"] else []
    return F.concat(*whole, affixes(word, sizes["affixes"]), char_ngrams(word, sizes["word"]), piece_ngrams(pieces, sizes["piece"]))
