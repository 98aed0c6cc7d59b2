"""Shards by minimax contiguous partition.

Equal texts are one atomic group: all their rows go to one shard. Groups stand in the order of the 64-bit hash of their
text. The smallest capacity at which the ordered groups fit the shards is found by binary search with a greedy check, and
the groups are cut under it, each cut as near to an equal share of what is left as the capacity allows. A group that
fills the capacity by itself has a shard to itself, and what lies before, between and behind such groups
is partitioned in the same way.

The driver sees cells, not groups: ranges of hashes with the bytes and the number of their groups, of 2**16 to begin with. A
greedy check may end a shard anywhere in a cell of several groups, which gives a lower bound of the capacity; the cells in which it
does so are split 2**12 ways, until no shard ends inside a cell. The bound is then attained by whole groups, so it is the least
capacity of the groups themselves. What is split at a time depends on the number of shards, not on that of the groups.

Nulls: a null text counts as empty (size 16, CRC 0) and groups with empty texts; rows with
a null doc_id are placed like others and have the last slots of their shard. Repeated rows each get a slot. An empty table gives
an empty result. Extra columns are ignored, whatever their names.
"""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from wordlid.io import cut_lineage, small_table

UNIT_BITS, STEP_BITS = 16, 12
SLOT_PARTS = 1024


class Cells:
    """Ranges of hashes in ascending order: first hash, leading bits that are fixed, bytes, number of groups."""

    def __init__(self, low, bits, size, many):
        order = np.argsort(low, kind="stable")
        self.low, self.bits, self.size, self.many = (np.asarray(x, np.int64)[order] for x in (low, bits, size, many))
        self.prefix = np.concatenate([[0], np.cumsum(self.size)])

    def split(self, at: np.ndarray, parts: Cells) -> Cells:
        """The cells with those at `at` replaced by their parts."""
        stay = np.ones(len(self.low), bool)
        stay[at] = False
        return Cells(*(np.concatenate([a[stay], b]) for a, b in zip((self.low, self.bits, self.size, self.many), (parts.low, parts.bits, parts.size, parts.many), strict=True)))


def greedy_cuts(cells: Cells, begin: int, end: int, capacity: int, most: int) -> list[int] | None:
    """Bytes before the second shard, the third, ... when cells [begin, end) are filled greedily; None if more than `most`
    shards are needed. A shard may end inside a cell of several groups."""
    at, out, stop = int(cells.prefix[begin]), [], int(cells.prefix[end])
    if most < 1:
        return None
    while stop - at > capacity:
        if len(out) + 1 >= most:
            return None
        limit = at + capacity
        i = int(np.searchsorted(cells.prefix, limit, side="right")) - 1
        if cells.many[i] == 1:
            limit = int(cells.prefix[i])
        if limit <= at:
            return None
        out.append(at := limit)
    return out


def smallest_capacity(cells: Cells, runs: list[tuple[int, int]], shards: int) -> tuple[int, list[list[int]]]:
    """The least capacity at which the runs of cells fit the shards, none shared by two runs, and the greedy cuts under it."""

    def fits(capacity: int) -> list[list[int]] | None:
        out, left = [], shards
        for a, b in runs:
            cuts = greedy_cuts(cells, a, b, capacity, left)
            if cuts is None:
                return None
            left -= len(cuts) + 1
            out.append(cuts)
        return out

    total = sum(int(cells.prefix[b] - cells.prefix[a]) for a, b in runs)
    low, high = -(-total // shards), max([1, *(int(cells.prefix[b] - cells.prefix[a]) for a, b in runs)])
    low = min(low, high)
    while low < high:
        middle = (low + high) // 2
        if fits(middle) is None:
            low = middle + 1
        else:
            high = middle
    return low, fits(low)


def even_cuts(prefix: np.ndarray, capacity: int, shards: int, greedy: list[int]) -> list[int]:
    """First cell of shards 1, 2, ...: none is over the capacity, all are near an equal share. `greedy` has the cells at which a
    greedy filling cuts, which are the latest that leave the rest feasible where whole cells do not say so."""
    n = len(prefix) - 1
    latest = [*greedy, *[n] * (shards - 1 - len(greedy))]
    earliest = [n]
    for _ in range(shards - 1):
        earliest.append(int(np.searchsorted(prefix, prefix[earliest[-1]] - capacity, side="left")))
    cuts, start = [], 0
    for j, left in enumerate(range(shards - 1, 0, -1)):
        goal = prefix[start] + (prefix[-1] - prefix[start]) / (left + 1)
        at = int(np.searchsorted(prefix, goal, side="left"))
        if at > 0 and goal - prefix[at - 1] < prefix[min(at, n)] - goal:
            at -= 1
        furthest = int(np.searchsorted(prefix, prefix[start] + capacity, side="right")) - 1
        start = max(start, min(earliest[left], latest[j]), min(at, furthest))
        cuts.append(start)
    return cuts


def plan_shards(cells: Cells, shards: int, refine: Callable[[Cells, np.ndarray], Cells]) -> tuple[list[int], Cells]:
    """First cell of shards 1, 2, ... and the cells that they refer to; refine(cells, at) gives the parts of some cells."""
    alone: list[int] = []  # first hashes of the groups that have a shard to themselves
    while True:
        edges = np.searchsorted(cells.low, np.array(sorted(alone), np.int64))
        starts, ends = [0, *(e + 1 for e in edges)], [*edges, len(cells.low)]
        runs = [(int(a), int(b)) for a, b in zip(starts, ends, strict=True) if a < b]
        if not runs:
            return sorted({*map(int, edges)} - {0}), cells
        capacity, cuts = smallest_capacity(cells, runs, shards - len(alone))
        open_: set[int] = set()
        for each in cuts:
            doubt = 0
            for at in each:
                i = int(np.searchsorted(cells.prefix, at, side="right")) - 1
                if cells.prefix[i] != at:
                    doubt += int(cells.size[i])
                if doubt:  # this cut and those behind it move by no more than the cells that were cut
                    low, high = (int(np.searchsorted(cells.prefix, x, side="right")) - 1 for x in (max(0, at - doubt), min(int(cells.prefix[-1]) - 1, at + doubt)))
                    open_ |= {k for k in range(low, high + 1) if cells.many[k] > 1}
        if open_:
            at = np.array(sorted(open_))
            cells = cells.split(at, refine(cells, at))
            continue
        full = [int(cells.low[i]) for a, b in runs for i in range(a, b) if cells.many[i] == 1 and cells.size[i] == capacity] if int(cells.size.max()) >= capacity else []
        if full and sum(b - a for a, b in runs) > len(full):
            alone += full
            continue
        break
    many = [len(c) + 1 for c in cuts]
    weight = [int(cells.prefix[b] - cells.prefix[a]) for a, b in runs]
    for _ in range(shards - len(alone) - sum(many)):
        k = max(range(len(runs)), key=lambda k: weight[k] / many[k])
        many[k] += 1
    out = []
    for (a, b), greedy, k in zip(runs, cuts, many, strict=True):
        prefix = cells.prefix[a : b + 1] - cells.prefix[a]
        places = [int(np.searchsorted(cells.prefix, c)) - a for c in greedy]
        out += [a, *(a + c for c in even_cuts(prefix, capacity, k, places))]
    return sorted([*out, *map(int, edges)])[1:], cells


def _cells(groups: DataFrame, bits: int) -> Cells:
    """Cells of groups (grp, size) by their leading bits; the driver gets one row for each."""
    shift = 64 - bits
    got = groups.groupBy(F.shiftright("grp", shift).alias("c")).agg(F.sum("size").alias("s"), F.count("*").alias("n")).toArrow()
    low = got["c"].to_numpy() << shift
    return Cells(low, np.full(len(low), bits), got["s"].to_numpy(), got["n"].to_numpy())


def shard_documents(docs: DataFrame, shards: int = 40) -> DataFrame:
    """doc_id, size, text_crc32, shard, slot: slots of a shard run from 0 without a gap."""
    spark = docs.sparkSession
    text = F.coalesce(F.col("text"), F.lit(""))
    rows = cut_lineage(
        docs.select("doc_id", (F.octet_length(text) + 16).cast("long").alias("size"), F.crc32(text).alias("text_crc32"), F.xxhash64(text).alias("grp"), F.monotonically_increasing_id().alias("row")),
        "shard-rows",
    )
    groups = cut_lineage(rows.groupBy("grp").agg(F.sum("size").alias("size")), "shard-groups")

    def refine(cells: Cells, at: np.ndarray) -> Cells:
        found = []
        for bits in np.unique(cells.bits[at]):
            low = cells.low[at][cells.bits[at] == bits]
            picked = small_table(spark, c=pa.array(low >> (64 - int(bits)), pa.int64()))
            inside = groups.join(F.broadcast(picked), F.shiftright("grp", 64 - int(bits)) == F.col("c"), "left_semi")
            found.append(_cells(inside, min(64, int(bits) + STEP_BITS)))
        return Cells(*(np.concatenate([getattr(f, k) for f in found]) for k in ("low", "bits", "size", "many")))

    cuts, cells = plan_shards(_cells(groups, UNIT_BITS), shards, refine)
    shard = F.lit(0)
    for cut in cuts:
        if cut < len(cells.low):
            shard = shard + (F.col("grp") >= F.lit(int(cells.low[cut]))).cast("int")
    # rows without a doc_id may be many that are alike, so they are dealt by their place in the table
    part = F.when(F.col("doc_id").isNull(), SLOT_PARTS + F.col("row") % SLOT_PARTS).otherwise(F.pmod(F.xxhash64("doc_id", "text_crc32"), F.lit(SLOT_PARTS)))
    placed = rows.select("doc_id", "size", "text_crc32", "row", shard.cast("int").alias("shard"), part.alias("part"))
    before = Window.partitionBy("shard").orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    starts = placed.groupBy("shard", "part").count().select("shard", "part", F.coalesce(F.sum("count").over(before), F.lit(0)).alias("start"))
    inside = Window.partitionBy("shard", "part").orderBy("doc_id", "text_crc32", "size", "row")
    # at most 2 * shards * SLOT_PARTS rows, whatever the input: safe to broadcast
    return placed.join(F.broadcast(starts), ["shard", "part"]).select(
        "doc_id", "size", "text_crc32", "shard", (F.col("start") + F.row_number().over(inside) - 1).cast("long").alias("slot")
    )
