"""Quality classifier: a generalised additive model with pairwise interactions.

A text is measured by a few shape features, each cut into quantile bins. Boosting goes round the features in turn
and fits a shallow tree to the residuals of the logistic loss on one feature's bins at a time, so that what is
learned of a feature is one lookup table; then the pairs of features whose joint bins explain most of the rest
get tables of their own in the same way. A score is the sum of the table entries of a text's bins.

Learning uses at most `budget` labelled rows (in expectation, picked by a hash of doc_id); scoring uses whole texts
and neither labels nor lang, source or doc_id.

Nulls: a null text is empty; empty texts are scored by their features like others. Rows whose label is null or
that repeat a doc_id with other labels count by their mean label. Without labelled rows every score is 0.5. An empty table
gives an empty result; extra columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from wordlid.llm.arrowtext import _space, mapped, pieces, utf8, words

FEATURES = ("log_bytes", "upper", "digit", "mark", "bang", "bar", "comma_stop", "wide", "space", "line", "word_size", "word_spread", "distinct", "again", "short", "top_word", "marked_words")
BINS, PAIR_BINS = 48, 8
BUDGET = 20_000

_kind = np.full(256, 7, np.uint8)
_kind[65:91] = 0
_kind[97:123] = 1
_kind[48:58] = 2
_kind[[ord(c) for c in "#$%&*@^~<>{}[]=_+\\/"]] = 3
_kind[[ord("!"), ord("?")]] = 4
_kind[ord("|")] = 5
_kind[[ord(","), ord("."), ord(";"), ord(":")]] = 6
_kind[128:] = 8
_kind[_space] = 9
_kind[10] = 10


def measure(data: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    """One row of FEATURES for each text that offsets bound in data."""
    n, low = len(offsets) - 1, int(offsets[0])
    part = _kind[data[low : int(offsets[-1])]]
    text = np.repeat(np.arange(n), np.diff(offsets))
    counts = np.bincount(text * 11 + part, minlength=11 * n).reshape(n, 11).astype(np.float64)
    size = np.maximum(counts.sum(1), 1)
    letters = np.maximum(counts[:, [0, 1, 8]].sum(1), 1)
    word, of = words(data, offsets)
    out = np.zeros((n, len(FEATURES)))
    out[:, 0] = np.log1p(counts.sum(1))
    out[:, 1] = counts[:, 0] / letters
    for column, kind in ((2, 2), (3, 3), (4, 4), (5, 5), (6, 6), (7, 8)):
        out[:, column] = counts[:, kind] / size
    out[:, 8] = (counts[:, 9] + counts[:, 10]) / size
    out[:, 9] = counts[:, 10] / size
    many = np.bincount(of, minlength=n).astype(np.float64)
    each = np.maximum(many, 1)
    black = ~_space[data[low : int(offsets[-1])]]
    if len(word):
        begin = black.copy()
        begin[1:] &= ~black[:-1]
        heads = (offsets[:-1] - low)[np.diff(offsets) > 0]
        begin[heads] = black[heads]
        starts = np.flatnonzero(begin)
        sizes = np.add.reduceat(black.astype(np.int64), starts)
        out[:, 10] = np.bincount(of, sizes, n) / each
        out[:, 11] = np.sqrt(np.maximum(np.bincount(of, sizes.astype(float) ** 2, n) / each - out[:, 10] ** 2, 0))
        out[:, 14] = np.bincount(of, sizes <= 3, n) / each
        bad = np.add.reduceat(((part == 3) | (part == 4) | (part == 5)).astype(np.int64), starts) > 0
        out[:, 16] = np.bincount(of, bad, n) / each
        same = (word[1:] == word[:-1]) & (of[1:] == of[:-1])
        out[:, 13] = np.bincount(of[1:], same, n) / each
        order = np.lexsort((word, of))
        w, t = word[order], of[order]
        new = np.append(True, (w[1:] != w[:-1]) | (t[1:] != t[:-1]))
        out[:, 12] = np.bincount(t, new, n) / each
        runs = np.diff(np.append(np.flatnonzero(new), len(w)))
        most = np.zeros(n)
        np.maximum.at(most, t[new], runs)
        out[:, 15] = most / each
    return out


def _tree(total: np.ndarray, weight: np.ndarray, leaves: int, calm: float = 1.0) -> np.ndarray:
    """Values of a tree of a few leaves on ordered bins: each split is the one that gains most."""
    edges = [0, len(total)]
    t, w = np.append(0, np.cumsum(total)), np.append(0, np.cumsum(weight))
    worth = lambda a, b: (t[b] - t[a]) ** 2 / (w[b] - w[a] + calm)
    for _ in range(leaves - 1):
        best = (1e-9, None)
        for a, b in zip(edges[:-1], edges[1:], strict=True):
            k = np.arange(a + 1, b)
            if len(k):
                gain = worth(a, k) + worth(k, b) - worth(a, b)
                i = int(gain.argmax())
                best = max(best, (float(gain[i]), int(k[i])), key=lambda x: x[0])
        if best[1] is None:
            break
        edges = sorted([*edges, best[1]])
    out = np.zeros(len(total))
    for a, b in zip(edges[:-1], edges[1:], strict=True):
        out[a:b] = (t[b] - t[a]) / (w[b] - w[a] + calm)
    return out


class Additive:
    """Bins and tables; the tables of pairs are indexed by first bin * PAIR_BINS + second bin."""

    def __init__(self):
        self.base, self.edges, self.tables, self.coarse, self.pairs, self.pair_tables = 0.0, [], [], [], [], []

    def fit(self, x: np.ndarray, y: np.ndarray, rounds: int = 120, rate: float = 0.15, pairs: int = 6) -> Additive:
        n, k = x.shape
        rate_of = float(np.clip(y.mean() if n else 0.5, 1e-3, 1 - 1e-3))
        self.base = float(np.log(rate_of / (1 - rate_of))) if n else 0.0
        cut = lambda column, bins: np.unique(np.quantile(column, np.arange(1, bins) / bins)) if n else np.zeros(0)
        self.edges = [cut(x[:, f], BINS) for f in range(k)]
        self.coarse = [cut(x[:, f], PAIR_BINS) for f in range(k)]
        self.tables = [np.zeros(len(e) + 1) for e in self.edges]
        if not n:
            return self
        fine = [np.searchsorted(self.edges[f], x[:, f], side="right") for f in range(k)]
        rough = [np.searchsorted(self.coarse[f], x[:, f], side="right") for f in range(k)]
        score = np.full(n, self.base)
        for _ in range(rounds):
            for f in range(k):
                self._step(self.tables[f], fine[f], score, y, rate)
        p = 1 / (1 + np.exp(-score))
        gains = []
        for a, b in combinations(range(k), 2):
            cell = rough[a] * PAIR_BINS + rough[b]
            total = np.bincount(cell, y - p, PAIR_BINS**2)
            gains.append((float((total**2 / (np.bincount(cell, p * (1 - p), PAIR_BINS**2) + 1)).sum()), a, b))
        self.pairs = [(a, b) for _, a, b in sorted(gains, reverse=True)[:pairs]]
        self.pair_tables = [np.zeros(PAIR_BINS**2) for _ in self.pairs]
        for _ in range(rounds // 3):
            for (a, b), table in zip(self.pairs, self.pair_tables, strict=True):
                self._step(table, rough[a] * PAIR_BINS + rough[b], score, y, rate)
        return self

    @staticmethod
    def _step(table: np.ndarray, cell: np.ndarray, score: np.ndarray, y: np.ndarray, rate: float) -> None:
        p = 1 / (1 + np.exp(-score))
        change = rate * _tree(np.bincount(cell, y - p, len(table)), np.bincount(cell, p * (1 - p), len(table)), 4)
        table += change
        score += change[cell]

    def score(self, x: np.ndarray) -> np.ndarray:
        out = np.full(len(x), self.base)
        for f, (edges, table) in enumerate(zip(self.edges, self.tables, strict=True)):
            out += table[np.searchsorted(edges, x[:, f], side="right")]
        for (a, b), table in zip(self.pairs, self.pair_tables, strict=True):
            out += table[np.searchsorted(self.coarse[a], x[:, a], side="right") * PAIR_BINS + np.searchsorted(self.coarse[b], x[:, b], side="right")]
        return 1 / (1 + np.exp(-np.clip(out, -30, 30)))


def _measured(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        data, offsets = utf8(batch.column("text"))
        for i, j in pieces(offsets):
            rows = measure(data, offsets[i : j + 1])
            lists = pa.ListArray.from_arrays(pa.array(np.arange(j - i + 1, dtype=np.int32) * rows.shape[1]), pa.array(rows.ravel()))
            yield pa.RecordBatch.from_arrays([batch.column("label").slice(i, j - i), lists], names=["label", "x"])


def train(docs: DataFrame, labels: DataFrame, budget: int = BUDGET, learn: Column | None = None) -> Additive:
    """Fit to labels (doc_id, quality); `learn` is a condition on doc_id that picks the labels that may be seen."""
    seen = labels.filter(F.col("quality").isNotNull() & F.col("doc_id").isNotNull()).select("doc_id", "quality")
    if learn is not None:
        seen = seen.filter(learn)
    many = seen.count()
    draw = F.pmod(F.xxhash64(F.lit(10), F.col("doc_id")), F.lit(1 << 30)) < int(min(1.0, budget / max(many, 1)) * (1 << 30))
    picked = seen.filter(draw).groupBy(F.col("doc_id").alias("_doc")).agg(F.avg("quality").alias("label"))
    texts = docs.select("doc_id", "text").filter(draw)
    got = mapped(texts.join(picked, F.col("doc_id") == F.col("_doc")).select("label", "text"), _measured, "label double, x array<double>").toArrow()
    x = np.array(got["x"].to_pylist(), float).reshape(got.num_rows, len(FEATURES))
    y = got["label"].to_numpy() if got.num_rows else np.zeros(0)
    order = np.lexsort((*x.T, y))  # the order in which rows arrive shall not matter
    return Additive().fit(x[order], y[order])


def classify(docs: DataFrame, model: Additive) -> DataFrame:
    """doc_id, score."""
    shared = docs.sparkSession.sparkContext.broadcast(model)  # a fixed number of table entries

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            data, offsets = utf8(batch.column("text"))
            for i, j in pieces(offsets):
                yield pa.RecordBatch.from_arrays([batch.column("doc_id").slice(i, j - i), pa.array(shared.value.score(measure(data, offsets[i : j + 1])))], names=["doc_id", "score"])

    return mapped(docs.select("doc_id", "text"), run, "doc_id long, score double")
