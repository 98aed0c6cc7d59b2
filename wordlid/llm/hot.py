"""Joins on keys of which a few may hold a large share of the rows."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: A key is hot if it has more than one of so many rows. There are fewer hot keys than this, whatever the input.
SHARE = 1000


#: Narrow rows (ids, hashes, digests) that may be sent to every executor.
MOST_SENT = 1_000_000


def sent_if_few(table: DataFrame) -> DataFrame:
    """table, to be broadcast if it is found to have no more than MOST_SENT rows."""
    return F.broadcast(table) if table.count() <= MOST_SENT else table


def spread_join(rows: DataFrame, table: DataFrame, key: str, counts: DataFrame, total: int, how: str = "inner") -> DataFrame:
    """rows joined with table on key, the rows of hot keys dealt over many tasks.

    counts (key, n) says how many rows have a key, total how many rows there are. The rows of a hot key get salts, as
    many as it has thousandths of all rows, and its rows of the table one copy for each. Only the hot keys are broadcast.
    Without a hot key the plan is the same, and every salt 0.
    """
    n = F.col("n") * SHARE
    hot = counts.filter(n > total).select(key, F.ceil(n / F.lit(max(total, 1))).cast("int").alias("_salts")).toArrow()
    hot = F.broadcast(rows.sparkSession.createDataFrame(hot))
    salted = rows.join(hot, key, "left").withColumn("_salt", F.when(F.col("_salts").isNull(), 0).otherwise(F.pmod(F.xxhash64(*rows.columns), "_salts").cast("int")))
    copied = table.join(hot, key, "left").withColumn("_salt", F.explode(F.sequence(F.lit(0), F.coalesce("_salts", F.lit(1)) - 1)))
    return salted.drop("_salts").join(copied.drop("_salts"), [key, "_salt"], how).drop("_salt")


def unused(docs: DataFrame, *names: str) -> list[str]:
    """Column names that docs does not have, whatever the case."""
    taken = {c.lower() for c in docs.columns}
    out = []
    for name in names:
        while name.lower() in taken:
            name += "_"
        taken.add(name.lower())
        out.append(name)
    return out
