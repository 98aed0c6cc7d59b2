"""Skip-gram vectors of words, pieces and characters, and their composition into one vector for each word."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.ml.feature import Word2Vec
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from wordlid.io import bound_batches, cut_lineage, discard, small_table
from wordlid.operators import training

BLOCKS = ("word", "piece", "char")
#: Units that get vectors: the most frequent ones. The driver holds a row of `dim` floats for each.
MOST_UNITS = 200_000
#: Partitions that vectors are trained in: one for so many sequences, in these bounds.
SEQUENCES_EACH, LEAST_PARTS, MOST_PARTS = 50_000, 4, 8


def composed_width(word: int = 200, piece: int = 100, char: int = 30, piece_slots: int = 8, char_slots: int = 10) -> int:
    return word + piece_slots * piece + char_slots * char


def least_uses(seqs: DataFrame, column: str, min_count: int, most: int = MOST_UNITS) -> int:
    """The least number of uses, min_count or more, that no more than `most` units have."""
    counts = seqs.select(F.explode(column).alias("unit")).groupBy("unit").agg(F.count("*").alias("n")).filter(F.col("n") >= min_count)
    uses = counts.groupBy("n").agg(F.count("*").alias("units"))  # numbers of uses are few: those of rare units are shared, and frequent units are few
    left = most
    for r in uses.orderBy(F.desc("n")).toLocalIterator():
        left -= r["units"]
        if left < 0:
            return max(min_count, r["n"] + 1)
    return min_count


def train_skipgram(seqs: DataFrame, column: str, dim: int, window: int = 5, min_count: int = 1, epochs: int = 1, seed: int = 1, most: int = MOST_UNITS) -> DataFrame:
    """unit, v: skip-gram with hierarchical softmax. The driver holds `dim` floats for each unit, so rare ones are left out where there are more than `most`."""
    from pyspark.ml.functions import vector_to_array

    seqs = cut_lineage(seqs.select(column), "sequences")  # it is read for the uses, for the vocabulary and for the training
    least, parts = least_uses(seqs, column, min_count, most), min(MOST_PARTS, max(LEAST_PARTS, seqs.count() // SEQUENCES_EACH))
    model = Word2Vec(vectorSize=dim, windowSize=window, minCount=least, maxIter=epochs, seed=seed, inputCol=column, outputCol="_o", numPartitions=parts)
    found = model.fit(seqs).getVectors()  # on the driver
    discard(seqs)
    return found.select(F.col("word").alias("unit"), vector_to_array("vector", "float32").alias("v"))


def suggest_dims(sequences: DataFrame, levels: tuple[str, ...] = BLOCKS) -> DataFrame:
    """level, different (units in the table), average (different units in a sentence): sequences has an array column for each level."""
    out = None
    for level in levels:
        kinds = F.array_distinct(level)
        one = sequences.select(F.explode(kinds).alias("unit")).agg(F.count_distinct("unit").alias("different")).crossJoin(sequences.agg(F.round(F.avg(F.size(kinds)), 6).alias("average"))).select(F.lit(level).alias("level"), "different", "average")
        out = one if out is None else out.unionByName(one)
    return out


def _pairs(load_ids: np.ndarray, ends: np.ndarray, window: int) -> np.ndarray:
    """(unit, neighbour) up to `window` places apart in the same sequence."""
    of = np.repeat(np.arange(len(ends) - 1), np.diff(ends))
    out = []
    for k in range(1, window + 1):
        same = np.flatnonzero(of[:-k] == of[k:]) if len(of) > k else np.zeros(0, np.int64)
        a, b = load_ids[same], load_ids[same + k]
        out += [np.stack([a, b], 1), np.stack([b, a], 1)]
    return np.concatenate(out) if out else np.zeros((0, 2), np.int64)


def negative_gradient(share: np.ndarray, negatives: int):
    """Loss and gradient of skip-gram with negative samples; share is the distribution that they are drawn from."""

    def gradient(w: dict, batch: np.ndarray, rng) -> tuple[float, dict]:
        a, b = batch[:, 0], batch[:, 1]
        other = np.concatenate([b[:, None], rng.choice(len(share), (len(b), negatives), p=share)], 1)
        sign = np.full(other.shape, -1.0)
        sign[:, 0] = 1.0
        x, y = w["in"][a], w["out"][other]
        score = sign * np.einsum("nd,nkd->nk", x, y)
        pull = -sign / (1 + np.exp(np.clip(score, -30, 30))) / len(a)
        grads = {}
        for name, at, g in (("in", a, np.einsum("nk,nkd->nd", pull, y)), ("out", other.ravel(), (pull[..., None] * x[:, None]).reshape(-1, x.shape[1]))):
            rows, where = np.unique(at, return_inverse=True)
            total = np.zeros((len(rows), g.shape[1]), w[name].dtype)
            np.add.at(total, where, g.astype(total.dtype))
            grads[name] = (rows, total)
        return float(np.log1p(np.exp(-np.clip(score, -30, 30))).sum(1).mean()), grads

    return gradient


def train_skipgram_negative(seqs: DataFrame, column: str, dim: int, window: int = 5, negatives: int = 5, min_count: int = 1, epochs: int = 1, rounds: int = 1, seed: int = 1, most: int = MOST_UNITS) -> DataFrame:
    """unit, v: skip-gram with negative samples, trained by rounds of local steps and averaging."""
    counts = seqs.select(F.explode(column).alias("unit")).groupBy("unit").agg(F.count("*").alias("n")).filter(F.col("n") >= min_count)
    top = counts.orderBy(F.desc("n"), "unit").limit(most).toArrow()
    units, n = top["unit"].to_pylist(), top["n"].to_numpy()
    spark = seqs.sparkSession
    ids = small_table(spark, unit=pa.array(units, pa.string()), id=pa.array(range(len(units)), pa.int32()))
    keyed = seqs.select(F.monotonically_increasing_id().alias("s"), F.col(column).alias("seq"))
    known = cut_lineage(keyed, "sequences").select("s", F.posexplode("seq").alias("at", "unit")).join(F.broadcast(ids) if len(units) <= MOST_UNITS else ids, "unit")
    rows = known.groupBy("s").agg(F.array_sort(F.collect_list(F.struct("at", "id"))).alias("a")).select(F.transform("a", lambda x: x["id"]).alias("xs")).filter("size(xs) > 1")

    def load(got: list[pa.RecordBatch], size: int) -> list:
        out = []
        for b in got:
            lists = b.column("xs")
            pairs = _pairs(lists.flatten().to_numpy(zero_copy_only=False).astype(np.int64), np.concatenate([[0], np.cumsum(lists.value_lengths().to_numpy(zero_copy_only=False))]), window)
            out += [pairs[i : i + size] for i in range(0, len(pairs), size)]
        return out

    rng = np.random.default_rng(seed)
    share = n**0.75 / (n**0.75).sum() if len(n) else np.ones(1)
    start = {"in": rng.normal(0, 0.5 / dim, (max(1, len(units)), dim)).astype(np.float32), "out": np.zeros((max(1, len(units)), dim), np.float32)}
    w = training.fit(rows, load, negative_gradient(share, negatives), start, rounds, 0.025, ((epochs, 1024),), seed, rows_each=5000)
    return small_table(spark, unit=pa.array(units, pa.string()), v=pa.array(list(w["in"][: len(units)]), pa.list_(pa.float32())))


def compose(types: DataFrame, words: DataFrame, pieces: DataFrame, chars: DataFrame, dims: tuple[int, int, int], slots: tuple[int, int], blocks: tuple[str, ...] = BLOCKS) -> DataFrame:
    """word, vec: the word's vector, its pieces' and its characters', each block filled up with zeros to its slots.

    types has word and pieces. An unknown word has a zero block; pieces and characters beyond the slots are cut.
    Blocks that are not in `blocks` are left out.
    """
    tables = {}
    for name, table in (("piece", pieces), ("char", chars)):  # bounded by merges and alphabet
        found = table.select("unit", "v").collect()
        dim = dims[BLOCKS.index(name)]
        tables[name] = {r["unit"]: i + 1 for i, r in enumerate(found)}, np.concatenate([np.zeros((1, dim), np.float32), np.array([r["v"] for r in found], np.float32).reshape(-1, dim)])
    sent = types.sparkSession.sparkContext.broadcast(tables)
    bound_batches(types.sparkSession)

    def filled(name: str, units: list, n: int) -> np.ndarray:
        ids, table = sent.value[name]
        at = np.array([[ids.get(u, 0) for u in own[:n]] + [0] * (n - len(own)) for own in units], np.int64).reshape(len(units), n)
        return table[at].reshape(len(units), -1)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            names = b.column("word").to_pylist()
            own, known = b.column("v"), np.zeros((len(names), dims[0]), np.float32)
            known[np.flatnonzero(own.is_valid().to_numpy(zero_copy_only=False))] = own.flatten().to_numpy(zero_copy_only=False).reshape(-1, dims[0])
            parts = {"word": lambda known=known: known, "piece": lambda b=b: filled("piece", [p or [] for p in b.column("pieces").to_pylist()], slots[0]), "char": lambda names=names: filled("char", [w or "" for w in names], slots[1])}
            vec = np.concatenate([parts[x]() for x in blocks], axis=1)
            lists = pa.ListArray.from_arrays(pa.array(np.arange(len(vec) + 1, dtype=np.int32) * vec.shape[1]), pa.array(vec.ravel()))
            yield pa.RecordBatch.from_arrays([b.column("word"), lists], names=["word", "vec"])

    wide = types.select("word", "pieces").join(words.select(F.col("unit").alias("word"), F.col("v").cast("array<float>").alias("v")), "word", "left")
    return wide.select("word", "pieces", "v").mapInArrow(run, "word string, vec array<float>")


def similar(vectors: DataFrame, word: str, k: int = 10) -> DataFrame:
    """The k words with the largest cosine to a word."""
    dot = lambda a, b: F.aggregate(F.zip_with(a, b, lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda s, x: s + x)
    one = vectors.filter(F.col("word") == word).select(F.col("vec").alias("q")).limit(1)
    cosine = dot("vec", "q") / F.greatest(F.sqrt(dot("vec", "vec") * dot("q", "q")), F.lit(1e-12))
    return vectors.filter(F.col("word") != word).crossJoin(F.broadcast(one)).select("word", cosine.alias("cosine")).orderBy(F.desc("cosine"), "word").limit(k)
