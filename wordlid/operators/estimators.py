"""Estimators on feature vectors: logistic regression, a ReLU network, a linear SVM with probabilities, and votes.

All take rows (word, y, idx, val): a sparse vector of known width; composed vectors are dense, with idx counting up.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from wordlid.io import cut_lineage, discard
from wordlid.operators import training
from wordlid.operators.corpus import TAGS

#: Rows of a sparse matrix whose columns are made dense together.
TOGETHER = 128


def pairs(classes: int) -> list[tuple[int, int]]:
    return [(a, b) for a in range(classes) for b in range(a + 1, classes)]


class Sparse:
    """Rows of a sparse matrix. Products take `TOGETHER` rows at a time, as a small dense matrix of the columns that these have."""

    def __init__(self, first: np.ndarray, idx: np.ndarray, val: np.ndarray):
        self.first, self.idx, self.val = first, idx, val  # the entries of row i are first[i] .. first[i + 1]
        self._dense: list[tuple[slice, np.ndarray, np.ndarray]] | None = None

    def __len__(self) -> int:
        return len(self.first) - 1

    def __getitem__(self, part: slice) -> Sparse:
        low, high = part.start, min(part.stop, len(self))
        a, b = self.first[low], self.first[high]
        return Sparse(self.first[low : high + 1] - a, self.idx[a:b], self.val[a:b])

    def _blocks(self) -> Iterator[tuple[slice, np.ndarray, np.ndarray]]:
        """Which rows, the columns that are not zero in them, and these columns."""
        for low in range(0, len(self), TOGETHER):
            ends = self.first[low : low + TOGETHER + 1]
            a, b = ends[0], ends[-1]
            columns, where = np.unique(self.idx[a:b], return_inverse=True)
            dense = np.zeros((len(ends) - 1, len(columns)), self.val.dtype)
            np.add.at(dense, (np.repeat(np.arange(len(ends) - 1), np.diff(ends)), where), self.val[a:b])
            yield slice(low, low + len(ends) - 1), columns, dense

    def __matmul__(self, w: np.ndarray) -> np.ndarray:
        out = np.zeros((len(self), w.shape[1]), w.dtype)
        for rows, columns, dense in self._kept():
            out[rows] = dense @ w[columns]
        return out

    def _kept(self):
        """The blocks; a batch of training, which is one block, comes again in each epoch and keeps it."""
        if len(self) > TOGETHER:
            return self._blocks()
        if self._dense is None:
            self._dense = list(self._blocks())
        return self._dense

    def back(self, delta: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The rows of transpose @ delta that are not zero: which, and their values."""
        each = [(columns, dense.T @ delta[rows]) for rows, columns, dense in self._kept()]
        if len(each) == 1:
            return each[0]
        if not each:
            return np.zeros(0, np.int64), np.zeros((0, delta.shape[1]), delta.dtype)
        at, where = np.unique(np.concatenate([c for c, _ in each]), return_inverse=True)
        total = np.zeros((len(at), delta.shape[1]), delta.dtype)
        np.add.at(total, where, np.concatenate([g for _, g in each]))
        return at, total


def matrix(batch: pa.RecordBatch, width: int) -> np.ndarray | Sparse:
    """The rows of a batch; dense where every row has all places."""
    lists = batch.column("idx")
    sizes = np.diff(lists.offsets.to_numpy())
    val = batch.column("val").flatten().to_numpy(zero_copy_only=False).astype(np.float32, copy=False)
    if len(sizes) and (sizes == width).all():
        return val.reshape(len(sizes), width)
    return Sparse(np.concatenate([[0], np.cumsum(sizes)]), lists.flatten().to_numpy(zero_copy_only=False), val)


def loader(width: int):
    def load(got: list[pa.RecordBatch], size: int) -> list:
        out = []
        for b in got:
            x, y = matrix(b, width), b.column("y").to_numpy(zero_copy_only=False)
            out += [(x[i : i + size], y[i : i + size]) for i in range(0, len(y), size)]
        return out

    return load


def softmax(z: np.ndarray) -> np.ndarray:
    e = np.exp(z - z.max(-1, keepdims=True))
    return e / e.sum(-1, keepdims=True)


def network(width: int, hidden: tuple[int, ...], seed: int, classes: int = len(TAGS)) -> dict:
    rng, sizes = np.random.default_rng(seed), [width, *hidden, classes]
    out = {}
    for i, (a, b) in enumerate(zip(sizes[:-1], sizes[1:], strict=True)):
        out[f"w{i}"] = rng.normal(0, np.sqrt(2 / min(a, 400)), (a, b)).astype(np.float32) * (1 if hidden else 0)
        out[f"b{i}"] = np.zeros(b, np.float32)
    return out


def forward(w: dict, x) -> list:
    out, n = [x], len(w) // 2
    for i in range(n):
        z = out[-1] @ w[f"w{i}"] + w[f"b{i}"]
        out.append(np.maximum(z, 0) if i < n - 1 else softmax(z))
    return out


def _first(x, delta: np.ndarray, w: np.ndarray, penalty: float):
    """Gradient of the weights that x meets; the penalty of a sparse row counts when it has the feature."""
    if isinstance(x, Sparse):
        at, g = x.back(delta)
        return at, g + penalty * w[at]
    return x.T @ delta + penalty * w


def cross_entropy(penalty: float, weights: np.ndarray | None = None):
    """Loss and gradient of a network with ReLU layers (or none) and a softmax; weights are of the tags."""

    def gradient(w: dict, batch, rng) -> tuple[float, dict]:
        x, y = batch
        layers, n, grads = forward(w, x), len(w) // 2, {}
        p = layers[-1]
        own = np.ones(len(y)) if weights is None else weights[y]
        delta = p.copy()
        delta[np.arange(len(y)), y] -= 1
        delta *= (own / len(y)).astype(delta.dtype)[:, None]
        for i in range(n - 1, -1, -1):
            grads[f"w{i}"] = _first(layers[i], delta, w[f"w{i}"], penalty)
            grads[f"b{i}"] = delta.sum(0)
            if i:
                delta = (delta @ w[f"w{i}"].T) * (layers[i] > 0)
        return float(-(own * np.log(np.maximum(p[np.arange(len(y)), y], 1e-12))).mean()), grads

    return gradient


def hinge(penalty: float, weights: np.ndarray | None = None, classes: int = len(TAGS)):
    """Squared hinge loss of all pairs of tags at once; a row counts in the pairs of its own tag."""
    sign = np.zeros((classes, len(pairs(classes))), np.float32)
    for j, (a, b) in enumerate(pairs(classes)):
        sign[a, j], sign[b, j] = 1, -1

    def gradient(w: dict, batch, rng) -> tuple[float, dict]:
        x, y = batch
        s = sign[y]
        own = np.ones((len(y), 1), np.float32) if weights is None else weights[y][:, None].astype(np.float32)
        short = np.maximum(0, 1 - s * (x @ w["w"] + w["b"])) * (s != 0)
        delta = -2 * own * short * s / len(y)
        return float((own * short**2).sum() / len(y)), {"w": _first(x, delta, w["w"], penalty), "b": delta.sum(0)}

    return gradient


def newton_sums(a: np.ndarray, b: np.ndarray, margin: np.ndarray, sign: np.ndarray, targets: np.ndarray) -> np.ndarray:
    """(5, pairs): sums over rows that a Newton step of each pair needs; sign (rows, pairs) is 0 where a row does not count, targets are those of -1 and 1."""
    t = np.where(sign > 0, targets[1], targets[0])
    p = 1 / (1 + np.exp(np.clip(a * margin + b, -30, 30)))
    own = sign != 0
    d, h = (t - p) * own, np.maximum(p * (1 - p), 1e-9) * own
    return np.stack([(d * margin).sum(0), d.sum(0), (h * margin**2).sum(0), (h * margin).sum(0), h.sum(0)])


def sigmoids(plus: np.ndarray, minus: np.ndarray, sums, steps: int = 60) -> np.ndarray:
    """(pairs, 2): a, b of 1 / (1 + exp(a * margin + b)), by Newton steps on smoothed targets; sums(a, b, targets) gives newton_sums() of all rows."""
    targets = np.stack([1 / (minus + 2), (plus + 1) / (plus + 2)])
    a, b = -np.ones(len(plus)), np.log((minus + 1) / (plus + 1))
    left = np.ones(len(plus), bool)
    for _ in range(steps):
        ga, gb, haa, hab, hbb = sums(a, b, targets)
        haa, hbb = haa + 1e-6, hbb + 1e-6
        det = haa * hbb - hab * hab
        left &= np.abs(det) >= 1e-12
        det = np.where(left, det, 1)
        da, db = -(hbb * ga - hab * gb) / det, -(haa * gb - hab * ga) / det
        a, b = np.where(left, a + np.clip(da, -5, 5), a), np.where(left, b + np.clip(db, -5, 5), b)
        left &= np.abs(da) + np.abs(db) >= 1e-7
        if not left.any():
            break
    return np.stack([a, b], axis=1)


def platt(margin: np.ndarray, y: np.ndarray, steps: int = 60) -> tuple[float, float]:
    """a, b of one pair, whose rows are in one place."""
    sign = np.where(y > 0, 1, -1)[:, None]
    count = lambda x: np.array([float((sign == x).sum())])
    a, b = sigmoids(count(1), count(-1), lambda a, b, t: newton_sums(a, b, margin[:, None], sign, t), steps)[0]
    return float(a), float(b)


def couple(r: np.ndarray, steps: int = 60) -> np.ndarray:
    """Class probabilities (rows) from pairwise ones r[:, i, j] = P(i | i or j): the minimum of
    sum (r_ji p_i - r_ij p_j)^2, by cyclic updates."""
    n, k, _ = r.shape
    q = np.zeros((n, k, k))
    for i in range(k):
        for j in range(k):
            q[:, i, j] = (r[:, :, i] ** 2).sum(1) - r[:, i, i] ** 2 if i == j else -r[:, j, i] * r[:, i, j]
    p = np.full((n, k), 1 / k)
    for _ in range(steps):
        for i in range(k):
            qp = np.einsum("nij,nj->ni", q, p)
            pqp = (p * qp).sum(1)
            step = (pqp - qp[:, i]) / q[:, i, i]
            p[:, i] += step
            p /= (1 + step)[:, None]
    return p


class Tagger:
    """A fitted estimator; probabilities(x) is computed where the rows are."""

    def __init__(self, kind: str, weights: dict, sigmoids=None, classes: int = len(TAGS)):
        self.kind, self.weights, self.sigmoids, self.classes = kind, weights, sigmoids, classes

    def probabilities(self, x: np.ndarray) -> np.ndarray:
        if self.kind != "svm":
            return forward(self.weights, x)[-1]
        margin = x @ self.weights["w"] + self.weights["b"]
        r = np.full((len(x), self.classes, self.classes), 0.5)
        for j, (a, b) in enumerate(pairs(self.classes)):
            s = self.sigmoids[j]
            p = np.clip(1 / (1 + np.exp(np.clip(s[0] * margin[:, j] + s[1], -30, 30))), 1e-7, 1 - 1e-7)
            r[:, a, b], r[:, b, a] = p, 1 - p
        return couple(r)


#: Words of a tag below which its calibration sees all of them.
RARE = 50
#: Rates, rounds and epochs of each kind. A round is so many epochs in each partition; the network stops at the published 300 epochs at the latest.
SETTINGS = {"svm": (0.01, 6, ((4, 128), (2, 64))), "lr": (0.02, 6, ((4, 128), (2, 64))), "mlp": (0.002, 30, ((6, 128), (4, 64)))}


def tag_weights(rows: DataFrame, classes: int = len(TAGS)) -> np.ndarray:
    """Weights under which all tags that occur count alike."""
    found = {r["y"]: r["count"] for r in rows.groupBy("y").count().collect()}
    total, kinds = sum(found.values()), max(1, len(found))
    return np.array([total / (kinds * found[i]) if found.get(i) else 0.0 for i in range(classes)])


def fit(kind: str, rows: DataFrame, width: int, hidden: tuple[int, ...] = (150, 100, 50), rounds: int | None = None, seed: int = 1, balanced: bool = False, parts: int | None = None, classes: int = len(TAGS)) -> Tagger:
    """kind is svm, lr or mlp; the network has the published hidden sizes, seed and longest training. All end when the loss no longer falls."""
    n = max(1, rows.count())
    rate, most, schedule = SETTINGS[kind]
    weigh = tag_weights(rows, classes) if balanced else None
    how = {"rounds": most if rounds is None else rounds, "rate": rate, "schedule": schedule, "seed": seed, "parts": parts, "tol": 1e-3}
    if kind == "lr":
        return Tagger(kind, training.fit(rows, loader(width), cross_entropy(1.0 / n, weigh), network(width, (), seed, classes), **how), classes=classes)
    if kind == "mlp":
        return Tagger(kind, training.fit(rows, loader(width), cross_entropy(1e-4, weigh), network(width, hidden, seed, classes), **how), classes=classes)
    two = pairs(classes)
    zero = {"w": np.zeros((width, len(two)), np.float32), "b": np.zeros(len(two), np.float32)}
    draw = F.pmod(F.xxhash64("word"), F.lit(1 << 30))
    fifth = (1 << 30) // 5
    weights = training.fit(rows.filter(draw >= fifth), loader(width), hinge(1.0 / n, weigh, classes), zero, **how)
    sent = rows.sparkSession.sparkContext.broadcast(weights)

    def margins(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            m = (matrix(b, width) @ sent.value["w"] + sent.value["b"]).astype(np.float64)
            lists = pa.ListArray.from_arrays(pa.array(np.arange(len(m) + 1, dtype=np.int32) * len(two)), pa.array(m.ravel()))
            yield pa.RecordBatch.from_arrays([b.column("y"), lists], names=["y", "m"])

    # of tags with so few words that hardly any are held back, all are seen: a sigmoid without one side says nothing
    rare = [r["y"] for r in rows.groupBy("y").count().collect() if r["count"] < RARE]
    seen = cut_lineage(rows.filter((draw < fifth) | F.col("y").isin(rare)).mapInArrow(margins, "y int, m array<double>"), "margins")
    found = {r["y"]: r["count"] for r in seen.groupBy("y").count().collect()}
    plus, minus = (np.array([float(found.get(pair[side], 0)) for pair in two]) for side in (0, 1))
    fitted = sigmoids(plus, minus, lambda a, b, t: _summed(seen, two, a, b, t))
    discard(seen)
    return Tagger(kind, weights, [(float(a), float(b)) for a, b in fitted], classes)


def _summed(rows: DataFrame, two: list[tuple[int, int]], a: np.ndarray, b: np.ndarray, targets: np.ndarray) -> np.ndarray:
    """newton_sums() of all rows (y, m), added up in tasks: the driver gets a few numbers of each."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros((5, len(two)))
        for batch in batches:
            y, m = batch.column("y").to_numpy()[:, None], batch.column("m").flatten().to_numpy().reshape(-1, len(two))
            sign = np.equal(y, [x for x, _ in two]).astype(np.int8) - np.equal(y, [x for _, x in two])
            total += newton_sums(a, b, m, sign, targets)
        yield pa.RecordBatch.from_arrays([pa.array([total.ravel().tolist()], pa.list_(pa.float64()))], names=["s"])

    return np.sum([np.array(s) for s in rows.mapInArrow(run, "s array<double>").toArrow()["s"].to_pylist()], axis=0).reshape(5, len(two))


def predict(taggers: list[Tagger], rows: DataFrame, width: int, mode: str = "soft", weights: list[float] | None = None, names: tuple[str, ...] = TAGS) -> DataFrame:
    """word, gold, pred, probs: the mean of the taggers' probabilities, or their most frequent tag; ties by tag order."""
    share = np.array(weights or [1.0] * len(taggers))
    share = share / share.sum()
    sent = rows.sparkSession.sparkContext.broadcast(taggers)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            x = matrix(b, width)
            each = [t.probabilities(x) for t in sent.value]
            if mode == "hard":
                each = [np.eye(len(names))[p.argmax(1)] for p in each]
            mean = sum(w * p for w, p in zip(share, each, strict=True))
            pred = [names[i] for i in mean.round(9).argmax(1)]
            gold = [names[i] for i in b.column("y").to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column("word"), pa.array(gold, pa.string()), pa.array(pred, pa.string()), pa.array(mean.astype(float).tolist(), pa.list_(pa.float64()))], names=["word", "gold", "pred", "probs"])

    return rows.mapInArrow(run, "word string, gold string, pred string, probs array<double>")
