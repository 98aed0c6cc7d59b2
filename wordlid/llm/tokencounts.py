"""Token counts as an exact length histogram.

Documents are aggregated by encoded length; suffix sums over the lengths then answer, for every context limit at once,
how many documents reach it and how many tokens are left when each document is cut there. Suffix sums are taken inside blocks of lengths and over the blocks'
totals, so no window holds more than a block.

Nulls: a null or empty text has length 0 and its documents count under length 0. Repeated rows count each. An empty table gives
an empty histogram; extra columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from wordlid.io import cut_lineage
from wordlid.llm.bpe import token_counts

BLOCK = 256


def histogram(lengths: DataFrame, column: str = "n_tokens") -> DataFrame:
    """For each length that occurs: documents and tokens of that length, of that length and more, the
    tokens of the whole table with every document cut to that length, and the share of documents that are no longer: the p-quantile is the
    first length whose share is p or more."""
    counts = lengths.groupBy(F.col(column).alias("n_tokens")).agg(F.count("*").alias("docs")).withColumn("block", F.expr(f"n_tokens div {BLOCK}"))
    counts = cut_lineage(counts, "lengths")  # read several times below; texts are encoded once
    later = Window.orderBy(F.desc("block")).rowsBetween(Window.unboundedPreceding, -1)
    totals = counts.groupBy("block").agg(F.sum("docs").alias("d"), F.sum(F.col("docs") * F.col("n_tokens")).alias("t"))
    above = totals.select(F.col("block").alias("_block"), F.coalesce(F.sum("d").over(later), F.lit(0)).alias("d_above"), F.coalesce(F.sum("t").over(later), F.lit(0)).alias("t_above"), F.lit(1).alias("one"))
    whole = totals.agg(F.sum("t").alias("all_tokens"), F.sum("d").alias("all_docs"))
    inside = Window.partitionBy("block").orderBy(F.desc("n_tokens"))
    joined = counts.join(above, F.col("block") == F.col("_block")).join(F.broadcast(whole.withColumn("_one", F.lit(1))), F.col("one") == F.col("_one"))  # one row
    ge = joined.select(
        "n_tokens", "docs", (F.col("docs") * F.col("n_tokens")).alias("tokens"),
        (F.sum("docs").over(inside) + F.col("d_above")).alias("docs_ge"),
        (F.sum(F.col("docs") * F.col("n_tokens")).over(inside) + F.col("t_above")).alias("tokens_ge"), "all_tokens", "all_docs",
    )
    return ge.select("n_tokens", "docs", "tokens", "docs_ge", "tokens_ge", (F.col("all_tokens") - F.col("tokens_ge") + F.col("docs_ge") * F.col("n_tokens")).alias("truncated_tokens"), ((F.col("all_docs") - F.col("docs_ge") + F.col("docs")) / F.col("all_docs")).alias("share_le"))


def quantile(hist: DataFrame, share: float) -> int | None:
    """The least length that at least this share of the documents does not exceed."""
    total = hist.agg(F.max("docs_ge")).first()[0]
    if not total:
        return None
    covered = total - F.col("docs_ge") + F.col("docs")
    return hist.filter(covered >= share * total).agg(F.min("n_tokens")).first()[0]


def truncated_total(hist: DataFrame, limit: int) -> int:
    """Tokens of all documents when each is cut to limit."""
    r = hist.agg(F.sum("tokens").alias("t"), F.sum(F.when(F.col("n_tokens") > limit, F.col("docs") * (F.col("n_tokens") - limit)).otherwise(0)).alias("over")).first()
    return (r["t"] or 0) - (r["over"] or 0)


def token_histogram(docs: DataFrame, path: str) -> DataFrame:
    """The histogram of the documents' lengths under the tokenizer in path."""
    return histogram(token_counts(docs, path))
