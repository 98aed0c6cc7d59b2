"""Mixing sources to target weights by Sainte-Lague apportionment.

Each source's documents, in a seeded order, are one stream of words that is cut into blocks
of equal size. Blocks are allotted to sources by highest quotients; the allotment is house-monotone, so
the integer quota of each source in each output shard is the difference of two allotments and never negative. A source picks
its blocks systematically: every block floor(q/n) times, and q mod n blocks once more, at
even steps from a seeded phase; the picks fill the source's quotas shard by shard. How many words a document gives, and to which shards,
is then a difference of two values of one closed formula, so no block is ever listed.

Nulls: a null source is a source of its own, last in order; a null text has no words. A
document without words takes 0; a source without words has target 0. Rows with a null or repeated doc_id and repeated rows are rows
like any other. An empty table gives an empty result; extra columns are ignored, whatever their names.
"""

from __future__ import annotations

import heapq
import math
from collections.abc import Sequence
from itertools import accumulate

import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from wordlid.io import cut_lineage, small_table
from wordlid.llm.hot import unused

ORDER_PARTS = 1024
#: Output shards that quotas are dealt to.
SHARDS = 40
#: Sources up to which their table, of known size, is broadcast.
MOST_SENT = 100_000


def capped_targets(sizes: Sequence[int], weights: Sequence[float], total: float, cap: float = 2.0) -> list[float]:
    """Shares of total by weight; none over cap times its size, the excess reshared by weight."""
    out, open_, left = [0.0] * len(sizes), list(range(len(sizes))), float(total)
    while open_ and left > 0:
        weight = sum(weights[i] for i in open_)
        full = [i for i in open_ if left * weights[i] / weight >= cap * sizes[i]]
        if not full:
            for i in open_:
                out[i] = left * weights[i] / weight
            break
        for i in full:
            out[i] = cap * sizes[i]
        left -= sum(out[i] for i in full)
        open_ = [i for i in open_ if i not in set(full)]
    return out


def sainte_lague(votes: Sequence[float], seats: int) -> list[int]:
    """Seats by highest quotients v/1, v/3, v/5, ...; ties go to the earlier entry."""
    total = sum(votes)
    if total <= 0:
        return [0] * len(votes)
    out = [math.floor(v * seats / total + 0.5) if v > 0 else 0 for v in votes]
    spare = seats - sum(out)
    sign = 1 if spare > 0 else -1
    score = lambda i: -votes[i] / (2 * out[i] + 1) if sign > 0 else (votes[i] / (2 * out[i] - 1) if out[i] else math.inf)
    heap = [(score(i), sign * i) for i in range(len(votes)) if votes[i] > 0]
    heapq.heapify(heap)
    for _ in range(abs(spare)):
        _, i = heapq.heappop(heap)
        out[i * sign] += sign
        heapq.heappush(heap, (score(i * sign), i))
    return out


def shard_quotas(votes: Sequence[float], seats: int, shards: int) -> list[list[int]]:
    """For each shard, the blocks of each source; the shards' sizes are at most one block apart."""
    ends = [sainte_lague(votes, seats * (i + 1) // shards) for i in range(shards)]
    return [[b - a for a, b in zip(low, high, strict=True)] for low, high in zip([[0] * len(votes), *ends], ends, strict=False)]


def _plan(spark, found: list, weights: Sequence[float], share: float, cap: float, block: int, shards: int, seed: int) -> DataFrame:
    """A row for each source: target, blocks n, how often each is picked (base, and more of them once more from a phase), and the
    number of picks after each shard. The driver holds this one row for each source."""
    found = sorted(found, key=lambda r: (r["source"] is None, r["source"] or ""))
    sizes = [r["size"] for r in found]
    targets = capped_targets(sizes, [weights[i % len(weights)] for i in range(len(found))], share * sum(sizes), cap)
    quotas = shard_quotas(targets, round(sum(targets) / block), shards)
    plan = []
    for i, (r, goal) in enumerate(zip(found, targets, strict=True)):
        n = max(1, -(-r["size"] // block))
        most = int(cap * n)
        ends = [min(most, e) for e in accumulate(q[i] for q in quotas)]
        plan.append((r["source"], r["size"], goal, n, ends[-1] // n, ends[-1] % n, (seed * 2654435761 + i * 40503) % n, ends))
    kinds = {"source": pa.string(), "source_size": pa.int64(), "target": pa.float64(), **dict.fromkeys(("n", "base", "more", "phase"), pa.int64()), "ends": pa.list_(pa.int64())}
    out = small_table(spark, **{c: pa.array([r[i] for r in plan], t) for i, (c, t) in enumerate(kinds.items())})
    return F.broadcast(out) if len(plan) <= MOST_SENT else out


def _dealt(docs: DataFrame, keep: dict, weights: Sequence[float], share: float, cap: float, block: int, shards: int, seed: int) -> DataFrame:
    """The columns in keep, and of each row: its source's, taken, first_shard, last_shard, times (that the whole document is taken)."""
    words = F.coalesce(F.regexp_count("text", F.lit(r"[^\x20\x09-\x0D]+")), F.lit(0)).cast("long")
    rows = cut_lineage(docs.select(*[c.alias(k) for k, c in keep.items()], "doc_id", "source", words.alias("size"), F.xxhash64(F.lit(seed), "doc_id", F.crc32("text")).alias("key")), "mix-rows")
    sources = _plan(docs.sparkSession, rows.groupBy("source").agg(F.sum("size").alias("size")).collect(), weights, share, cap, block, shards, seed)
    rows = rows.withColumn("part", F.pmod("key", F.lit(ORDER_PARTS))).withColumn("full", (F.col("size") > 0).cast("long"))
    upto = Window.partitionBy("source").orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    before = lambda c, w: F.coalesce(F.sum(c).over(w), F.lit(0))
    starts = rows.groupBy("source", "part").agg(F.sum("size").alias("s"), F.sum("full").alias("f")).select(F.col("source").alias("_source"), F.col("part").alias("_part"), before("s", upto).alias("s0"), before("f", upto).alias("f0"))
    inside = Window.partitionBy("source", "part").orderBy("key", "doc_id", "size").rowsBetween(Window.unboundedPreceding, -1)
    at = rows.withColumn("s1", before("size", inside)).withColumn("f1", before("full", inside))
    at = at.join(starts, at["source"].eqNullSafe(starts["_source"]) & (at["part"] == starts["_part"])).withColumn("from", F.col("s0") + F.col("s1")).withColumn("at", F.col("f0") + F.col("f1"))
    named = sources.withColumnRenamed("source", "_name")
    at = at.join(named, at["source"].eqNullSafe(named["_name"])).withColumn("to", F.col("from") + F.col("size"))
    more = lambda i: F.expr(f"(cast({i} as decimal(18,0)) * more + phase) div n")
    picks = lambda b: F.expr(f"base * ({b})") + more(f"({b})")
    upto_word = lambda p: block * picks(f"{p} div {block}") + F.expr(f"{p} % {block}") * (picks(f"{p} div {block} + 1") - picks(f"{p} div {block}"))
    taken = (upto_word("`to`") - upto_word("`from`")).cast("long")
    shard = lambda pick: F.when(F.col("taken") > 0, F.size(F.filter("ends", lambda e: e <= pick))).cast("int")
    times = F.when(F.col("size") > 0, F.col("base") + more("(`at` + 1)") - more("`at`")).otherwise(0).cast("long")
    at = at.withColumns({"taken": taken, "times": times, "pick1": picks(f"`from` div {block}").cast("long"), "pick2": (picks(f"(`to` - 1) div {block} + 1") - 1).cast("long")})
    return at.select(*keep, "doc_id", "source", "size", "source_size", "target", "taken", shard(F.col("pick1")).alias("first_shard"), shard(F.col("pick2")).alias("last_shard"), "times")


def mix(docs: DataFrame, weights: Sequence[float] = (3, 1, 2), share: float = 1.5, cap: float = 2.0, block: int = 16, shards: int = SHARDS, seed: int = 42) -> DataFrame:
    """doc_id, source, size, source_size, target, taken (words that the mix takes of each document) and the first and last output
    shard that they go to."""
    return _dealt(docs, {}, weights, share, cap, block, shards, seed).drop("times")


def mixed_documents(docs: DataFrame, weights: Sequence[float] = (3, 1, 2), share: float = 1.5, cap: float = 2.0, block: int = 16, seed: int = 42) -> DataFrame:
    """docs as the mix takes them, whole: each source's documents floor(q/n) times, and q mod n of n of them once more by the same
    systematic pick. Rows are told apart by all their columns, as doc_id may be null or repeated."""
    a, b, times, many, copy = unused(docs, "_a", "_b", "_times", "_rows", "_copy")
    plain = [F.col(f"`{f.name}`") for f in docs.schema.fields if f.dataType.typeName() != "map"]
    hashes = {a: F.xxhash64(*plain), b: F.xxhash64(F.lit(seed), *plain)}
    dealt = _dealt(docs, hashes, weights, share, cap, block, 1, seed)
    taken = cut_lineage(dealt.groupBy(a, b).agg(F.sum("times").alias(times), F.count("*").alias(many)).filter(F.col(times) > 0), "taken")
    marked = docs.withColumns(hashes)
    out = marked.join(taken.filter(F.col(many) == 1), [a, b])
    repeated = taken.filter(F.col(many) > 1)
    if not repeated.isEmpty():
        out = out.unionByName(marked.join(repeated, [a, b]).dropDuplicates([a, b]))
    return out.withColumn(copy, F.explode(F.sequence(F.lit(1).cast("long"), F.col(times)))).select(*[F.col(f"`{c}`") for c in docs.columns])
