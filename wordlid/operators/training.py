"""Training by rounds of local steps and averaging.

Rows are dealt evenly over partitions by a hash of the row. In each round the weights go to all partitions, each partition takes its own Adam
steps over its rows in small batches, and what comes back is averaged, weighted by rows, in a tree of tasks, so the driver
reads a few sets of weights whatever the number of partitions. Rounds are jobs, rows stay where they are. Rounds end when the loss no longer
falls by `tol`, or after `rounds`.
"""

from __future__ import annotations

import io
import math
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from wordlid.io import bound_batches, cut_lineage, discard

#: Rows of a partition, at the least, and sets of weights that are averaged together.
ROWS_EACH, FAN = 1000, 8


def packed(weights: dict[str, np.ndarray]) -> bytes:
    out = io.BytesIO()
    np.savez(out, **weights)
    return out.getvalue()


def unpacked(data: bytes) -> dict[str, np.ndarray]:
    with np.load(io.BytesIO(data)) as z:
        return {k: z[k] for k in z.files}


class Adam:
    """Adam whose state lives as long as a partition's training. A gradient may be (rows, values): only these rows of the weights move."""

    def __init__(self, weights: dict, rates: dict[str, float] | None = None):
        self.m = {k: np.zeros_like(v) for k, v in weights.items()}
        self.v = {k: np.zeros_like(x) for k, x in weights.items()}
        self.rates, self.t = rates or {}, 0

    def step(self, weights: dict, grads: dict, rate: float) -> None:
        self.t += 1
        for k, g in grads.items():
            at, g = g if isinstance(g, tuple) else (slice(None), g)
            m, v = self.m[k], self.v[k]
            m[at] += 0.1 * (g - m[at])
            v[at] += 0.001 * (g * g - v[at])
            weights[k][at] -= rate * self.rates.get(k, 1.0) * (m[at] / (1 - 0.9**self.t)) / (np.sqrt(v[at] / (1 - 0.999**self.t)) + 1e-8)


def slanted(step: int, steps: int, cut: float = 0.1, ratio: float = 32.0) -> float:
    """Share of the rate at a step: up to the whole at a share `cut` of all steps, then down to 1 / ratio."""
    top = max(1, math.floor(steps * cut))
    p = step / top if step < top else 1 - (step - top) / max(1.0, top * (1 / cut - 1))
    return (1 + max(0.0, p) * (ratio - 1)) / ratio


def train_part(weights: dict, gradient: Callable, load: Callable, schedule, rate: float, seed: int, average: bool = False, slant: bool = False) -> tuple[dict, float]:
    """Adam over the batches of one partition, schedule lists (epochs, batch size); with average, the mean of the weights over the steps is
    returned, with slant, the rate rises and falls. Also the mean loss of the last epoch."""
    weights = {k: v.copy() for k, v in weights.items()}
    adam, rng, loss, t = Adam(weights, getattr(gradient, "rates", None)), np.random.default_rng(seed), 0.0, 0
    mean = {k: np.zeros_like(x) for k, x in weights.items()} if average else None
    loaded = [(epochs, load(size)) for epochs, size in schedule]
    steps = sum(epochs * len(batches) for epochs, batches in loaded)
    for epochs, batches in loaded:
        for _ in range(epochs):
            total = 0.0
            for i in rng.permutation(len(batches)):
                one, grads = gradient(weights, batches[i], rng)
                adam.step(weights, grads, rate * (slanted(t, steps) if slant else 1.0))
                total, t = total + one, t + 1
                if average:
                    for k in mean:
                        mean[k] += (weights[k] - mean[k]) / t
            loss = total / max(1, len(batches))
    return (mean if average and t else weights), float(loss)


def _sum(parts: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Weighted sums of the sets of weights of a partition, one at a time."""
    n, loss, total = 0.0, 0.0, None
    for b in parts:
        for k in range(b.num_rows):
            own, add = b.column("n")[k].as_py(), unpacked(b.column("w")[k].as_buffer())
            n, loss = n + own, loss + own * b.column("loss")[k].as_py()
            total = {x: w * own for x, w in add.items()} if total is None else {x: total[x] + w * own for x, w in add.items()}
    if total is not None:
        yield pa.RecordBatch.from_arrays([pa.array([n]), pa.array([loss / n]), pa.array([packed({x: w / n for x, w in total.items()})], pa.binary())], names=["n", "loss", "w"])


SHAPE = "n double, loss double, w binary"


def dealt(rows: DataFrame, rows_each: int = ROWS_EACH, parts: int | None = None) -> tuple[DataFrame, int]:
    """rows, evenly over partitions by a hash of the whole row, written once; and the number of partitions."""
    first = cut_lineage(rows, "train")
    if parts is None:
        parts = max(1, math.ceil(first.count() / rows_each))
    return first.repartition(parts, F.xxhash64(*first.columns)), parts


def fit(rows: DataFrame, load: Callable, gradient: Callable, weights: dict, rounds: int = 3, rate: float = 0.003, schedule: tuple[tuple[int, int], ...] = ((4, 128), (4, 64)), seed: int = 1, average: bool = False, slant: bool = False, tol: float = 1e-4, parts: int | None = None, rows_each: int = ROWS_EACH) -> dict:
    """load(list of record batches, batch size) gives a partition's batches."""
    spark = rows.sparkSession
    bound_batches(spark)
    source, parts = dealt(rows, rows_each, parts)
    data = cut_lineage(source, "train")
    last = math.inf
    for r in range(rounds):
        sent = spark.sparkContext.broadcast(packed(weights))

        def run(batches: Iterator[pa.RecordBatch], sent=sent, r=r) -> Iterator[pa.RecordBatch]:
            got = [b for b in batches if b.num_rows]
            if got:
                own, loss = train_part(unpacked(sent.value), gradient, lambda size: load(got, size), schedule, rate / (1 + r), seed + r, average, slant)
                yield pa.RecordBatch.from_arrays([pa.array([float(sum(b.num_rows for b in got))]), pa.array([loss]), pa.array([packed(own)], pa.binary())], names=["n", "loss", "w"])

        back, left = cut_lineage(data.mapInArrow(run, SHAPE), "weights"), parts
        while left > FAN:
            left = math.ceil(left / FAN)
            less = cut_lineage(back.repartition(left).mapInArrow(_sum, SHAPE), "weights")
            discard(back)
            back = less
        got = list(_sum(iter(back.toArrow().to_batches())))
        discard(back)
        sent.destroy()
        if not got:
            break
        weights, loss = unpacked(got[0].column("w")[0].as_buffer()), got[0].column("loss")[0].as_py()
        if last - loss < tol:
            break
        last = loss
    discard(data)
    return weights
