"""Exact duplicates by content-defined chunk recipes, in DataFrame functions only.

Every text is normalised (a run of white space becomes one space) and cut where its own
characters say so, so that texts share the chunks of a passage they share. A chunk's
identifier is a 64-bit hash; one aggregation over all chunks verifies that each identifier
stands for one SHA-256 digest. Where one stands for more, the digests are the identifiers instead.
Documents are equal when their ordered identifier lists are equal, so what is shuffled is
a few bytes a chunk: a text is read once, where it lies, and never moved. Lists that more than a thousandth of all
documents have are dealt over several tasks.

Nulls: a null text counts as empty; empty texts are equal to each other. A row with a null doc_id stays
only if its whole group has none. Rows repeated with the same doc_id count in group_size and one of
them stays. An empty table gives an empty result; extra columns are ignored, whatever their names.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from wordlid.io import cut_lineage
from wordlid.llm.hot import sent_if_few, spread_join, unused


def normalised(text="text"):
    """Each run of [\\x20\\x09-\\x0D] as one space; single spaces are left as they are."""
    return F.regexp_replace(F.coalesce(F.col(text), F.lit("")), r"[\x09-\x0D][\x20\x09-\x0D]*|\x20[\x20\x09-\x0D]+", " ")


def chunk_pattern(least: int, most: int, ends: str) -> str:
    """A chunk ends at the first space after `least` characters that follows one of `ends`, or after `most`."""
    return rf"(?s).{{{least},{most}}}?(?:(?<=[{ends}]\x20)|\z)|.{{1,{most}}}"


def recipes(docs: DataFrame, least: int = 256, most: int = 4096, ends: str = "aeionrst") -> DataFrame:
    """row, doc_id, text_sha256, chunks (ordered; each with its hash and its SHA-256)."""
    base = docs.select("doc_id", normalised().alias("norm"))
    return base.select(
        F.monotonically_increasing_id().alias("row"),
        "doc_id",
        F.sha2("norm", 256).alias("text_sha256"),
        F.transform(
            F.regexp_extract_all("norm", F.lit(chunk_pattern(least, most, ends)), F.lit(0)),
            lambda c: F.struct(F.xxhash64(c).alias("h"), F.unhex(F.sha2(c, 256)).alias("d")),
        ).alias("chunks"),
    )


def ambiguous(chunks: DataFrame) -> DataFrame:
    """Identifiers under which chunks with different digests go."""
    return chunks.groupBy("h").agg(F.min("d").alias("low"), F.max("d").alias("high")).filter("low <> high").select("h")


def exact_duplicates(docs: DataFrame, identifier=None) -> DataFrame:
    """doc_id, keep_id, group_size, kept, text_sha256, one row for each row of docs. `identifier` maps a chunk's hash to what names it."""
    rows = cut_lineage(recipes(docs), "recipes")
    if identifier is not None:
        rows = rows.withColumn("chunks", F.transform("chunks", lambda c: F.struct(identifier(c["h"]).alias("h"), c["d"].alias("d"))))
    sure = ambiguous(rows.select(F.explode("chunks").alias("c")).select("c.*")).isEmpty()
    named = rows.select("row", "doc_id", "text_sha256", F.transform("chunks", lambda c: c["h" if sure else "d"]).alias("recipe"))
    first = F.min(F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", "row")).alias("first")
    groups = cut_lineage(named.groupBy("recipe").agg(first, F.count("*").alias("n")).filter("n > 1"), "groups")
    return spread_join(named, groups, "recipe", groups.select("recipe", "n"), rows.count(), "left").select(
        "doc_id",
        F.when(F.col("n").isNull(), F.col("doc_id")).otherwise(F.col("first.doc_id")).alias("keep_id"),
        F.coalesce("n", F.lit(1)).cast("long").alias("group_size"),
        (F.col("n").isNull() | (F.col("row") == F.col("first.row"))).alias("kept"),
        "text_sha256",
    )


def drop_exact_duplicates(docs: DataFrame) -> DataFrame:
    """The rows of docs that stay, with all their columns. Rows are told apart by doc_id and text together, as doc_id may be null or repeated."""
    doc, text, sha, other = unused(docs, "_doc", "_text", "_sha", "_other")
    dropped = exact_duplicates(docs).filter("group_size > 1 and not kept")
    found = cut_lineage(dropped.select(F.col("doc_id").alias(doc), F.col("text_sha256").alias(text), (~F.col("doc_id").eqNullSafe(F.col("keep_id"))).alias(other)).distinct(), "exact-groups")
    hashed = docs.withColumn(sha, F.sha2(normalised(), 256))
    same = F.col("doc_id").eqNullSafe(F.col(doc)) & (F.col(sha) == F.col(text))
    # without a shuffle of the texts where the rows that go, counted first, are few
    out = hashed.join(sent_if_few(found.filter(F.col(other))), same, "left_anti")
    repeated = found.filter(~F.col(other))
    if repeated.isEmpty():
        return out.drop(sha)
    one = out.join(repeated, same, "left_semi").dropDuplicates(["doc_id", sha])
    return out.join(repeated, same, "left_anti").unionByName(one).drop(sha)
