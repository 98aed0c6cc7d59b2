"""Chat formatting with cumulative-snapshot collapse, in DataFrame functions only.

A log often holds one conversation many times, each snapshot with a few turns more. For each turn a rolling hash
of all turns up to it is kept: the XOR of 128-bit hashes of (place, role, text), which has prefix sums. A
conversation whose whole hash is the hash of a shorter prefix of another, or of an equal one with a smaller conv_id, is
dropped by an anti-join; what is left is rendered. Prefix sums are taken in blocks of turns, so a very
long conversation is not one task's work before it is rendered, and hashes are made distinct before they are joined, so a very common
first turn is one row.

Nulls: a turn number that is null comes first; a null role or text counts as empty; rows with the same conv_id and turn follow each other by role and text;
rows with a null conv_id are one conversation. An empty table gives an empty result; extra columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from wordlid.io import cut_lineage

BLOCK = 256


def prefix_hashes(turns: DataFrame) -> DataFrame:
    """conv_id, place (from 1), a and b: hashes of the turns up to this one."""
    base = turns.select("conv_id", F.coalesce("turn", F.lit(-1)).cast("long").alias("turn"), F.coalesce("role", F.lit("")).alias("role"), F.xxhash64(F.coalesce("role", F.lit("")), F.coalesce("text", F.lit(""))).alias("x"), F.xxhash64(F.lit(77), F.coalesce("text", F.lit("")), F.coalesce("role", F.lit(""))).alias("y"))
    base = cut_lineage(base.withColumn("block", F.floor(F.col("turn") / BLOCK)), "turns")
    inside = Window.partitionBy("conv_id", "block").orderBy("turn", "role", "x", "y")
    before = Window.partitionBy("conv_id").orderBy("block").rowsBetween(Window.unboundedPreceding, -1)
    starts = base.groupBy("conv_id", "block").count().select(F.col("conv_id").alias("_conv"), F.col("block").alias("_block"), F.coalesce(F.sum("count").over(before), F.lit(0)).alias("start"))
    same = F.col("conv_id").eqNullSafe(F.col("_conv")) & F.col("block").eqNullSafe(F.col("_block"))
    placed = base.withColumn("n", F.row_number().over(inside)).join(starts, same).withColumn("place", F.col("n") + F.col("start"))
    keyed = placed.select("conv_id", "block", "place", F.xxhash64("place", "x").alias("x"), F.xxhash64("place", "y").alias("y"))
    local = Window.partitionBy("conv_id", "block").orderBy("place")
    sums = keyed.groupBy("conv_id", "block").agg(F.bit_xor("x").alias("x"), F.bit_xor("y").alias("y"))
    offsets = sums.select(F.col("conv_id").alias("_conv"), F.col("block").alias("_block"), *[F.coalesce(F.bit_xor(c).over(before), F.lit(0)).alias(f"_{c}") for c in ("x", "y")])
    return keyed.withColumns({"a": F.bit_xor("x").over(local), "b": F.bit_xor("y").over(local)}).join(offsets, same).select("conv_id", "place", F.col("a").bitwiseXOR(F.col("_x")).alias("a"), F.col("b").bitwiseXOR(F.col("_y")).alias("b"))


def maximal_conversations(turns: DataFrame) -> DataFrame:
    """conv_id, n_turns, copies of the conversations that no longer one begins with."""
    hashes = cut_lineage(prefix_hashes(turns), "prefixes")
    last = hashes.groupBy("conv_id").agg(F.max("place").alias("n_turns"))
    whole = hashes.join(last.withColumnRenamed("conv_id", "_c"), F.col("conv_id").eqNullSafe(F.col("_c")) & (F.col("place") == F.col("n_turns"))).select("conv_id", "n_turns", "a", "b")
    distinct = whole.groupBy("n_turns", "a", "b").agg(F.min("conv_id").alias("conv_id"), F.count("*").alias("copies"))
    inner = hashes.join(last.withColumnRenamed("conv_id", "_c"), F.col("conv_id").eqNullSafe(F.col("_c")) & (F.col("place") < F.col("n_turns"))).select(F.col("place").alias("n_turns"), "a", "b").distinct()
    return distinct.join(inner, ["n_turns", "a", "b"], "left_anti").select("conv_id", "n_turns", "copies")


def collapse(turns: DataFrame, head: str = "<|", tail: str = "|>\n", stop: str = "\n") -> DataFrame:
    """conv_id, n_turns, copies, rendered: one row for each maximal conversation."""
    kept = maximal_conversations(turns)
    mine = turns.select("conv_id", F.coalesce("turn", F.lit(-1)).cast("long").alias("turn"), F.coalesce("role", F.lit("")).alias("role"), F.coalesce("text", F.lit("")).alias("text"))
    mine = mine.join(kept.withColumnRenamed("conv_id", "_c"), F.col("conv_id").eqNullSafe(F.col("_c")))
    ordered = F.array_sort(F.collect_list(F.struct("turn", "role", F.xxhash64("role", "text").alias("x"), "text")))
    rendered = F.array_join(F.transform(ordered, lambda t: F.concat(F.lit(head), t["role"], F.lit(tail), t["text"], F.lit(stop))), "")
    return mine.groupBy("conv_id", "n_turns", "copies").agg(rendered.alias("rendered"))
