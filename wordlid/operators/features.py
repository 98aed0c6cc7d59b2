"""Feature counts of words, made and looked up where the words are: no row for each feature of a word is written or shuffled."""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterator
from itertools import chain

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from wordlid.functions.text import PROSE_SIZES
from wordlid.io import bound_batches

#: Different features that a task counts before it sends its counts on.
HELD = 300_000


def _grams(text: str, sizes: tuple[int, ...]) -> list[str]:
    padded = f"_{text}_"
    return [padded[i : i + k] for k in sizes for i in range(len(padded) - k + 1)]


def listed(word: str, pieces: list[str], family: str, sizes: dict = PROSE_SIZES) -> list[str]:
    """The features of one family, repeats included, as functions.text.families makes them."""
    if family == "s":
        return [word[-k:] for k in sizes["affixes"] if len(word) >= k]
    if family == "p":
        return [word[:k] for k in sizes["affixes"] if len(word) >= k]
    if family == "g":
        return _grams(word, sizes["word"])
    return [x for p in pieces or () for x in _grams(p, sizes["piece"])]


def feature_uses(rows: DataFrame, families: str) -> DataFrame:
    """family, feature, words, uses of rows (word, pieces) of different words; counts are summed in each task first."""
    bound_batches(rows.sparkSession)

    def sums(words: dict, uses: dict) -> Iterator[pa.RecordBatch]:
        for f in families:
            names = list(uses[f])
            columns = [pa.array([f] * len(names), pa.string()), pa.array(names, pa.string()), pa.array([words[f][x] for x in names], pa.int64()), pa.array(list(uses[f].values()), pa.int64())]
            yield pa.RecordBatch.from_arrays(columns, names=["family", "feature", "words", "uses"])
            words[f].clear()
            uses[f].clear()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        words, uses = ({f: Counter() for f in families} for _ in range(2))
        for b in batches:
            each = list(zip(b.column("word").to_pylist(), b.column("pieces").to_pylist(), strict=True))
            for f in families:
                own = [listed(w, p, f) for w, p in each]
                uses[f].update(chain.from_iterable(own))
                words[f].update(chain.from_iterable(map(set, own)))
            if sum(map(len, uses.values())) > HELD:
                yield from sums(words, uses)
        yield from sums(words, uses)

    counts = rows.select("word", "pieces").mapInArrow(run, "family string, feature string, words long, uses long")
    return counts.groupBy("family", "feature").agg(F.sum("words").alias("words"), F.sum("uses").alias("uses"))


def count_rows(rows: DataFrame, places: dict[str, dict[str, int]]) -> DataFrame:
    """word, y, idx, val of rows (word, y, pieces): the counts of the features that have a place, by family, in the order of places."""
    bound_batches(rows.sparkSession)
    sent = rows.sparkSession.sparkContext.broadcast(places)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            idx, val = [], []
            for w, p in zip(b.column("word").to_pylist(), b.column("pieces").to_pylist(), strict=True):
                found = Counter()
                for f, known in sent.value.items():
                    found.update(known[x] for x in listed(w, p, f) if x in known)
                idx.append(sorted(found))
                val.append([found[i] for i in idx[-1]])
            yield pa.RecordBatch.from_arrays([b.column("word"), b.column("y"), pa.array(idx, pa.list_(pa.int32())), pa.array(val, pa.list_(pa.float32()))], names=["word", "y", "idx", "val"])

    return rows.select("word", "y", "pieces").mapInArrow(run, "word string, y int, idx array<int>, val array<float>")
