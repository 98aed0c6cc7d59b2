"""Confusion, per-tag and averaged scores; the zero cases are zero."""

from __future__ import annotations

from collections.abc import Callable

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from wordlid.io import small_table
from wordlid.operators.corpus import TAGS


def grid(spark) -> DataFrame:
    tags = F.explode(F.array(*map(F.lit, TAGS)))
    return spark.range(1).select(tags.alias("gold")).select("gold", tags.alias("pred"))  # 36 rows


def confusion(pred: DataFrame) -> DataFrame:
    counts = pred.groupBy("gold", "pred").agg(F.count("*").alias("n"))
    return grid(pred.sparkSession).join(F.broadcast(counts), ["gold", "pred"], "left").select("gold", "pred", F.coalesce("n", F.lit(0)).alias("n"))


def per_tag(conf: DataFrame) -> DataFrame:
    tags = F.explode(F.array(F.struct(F.col("gold").alias("tag"), F.lit(0).alias("g")), F.struct(F.col("pred").alias("tag"), F.lit(1).alias("g"))))
    rows = conf.select(tags.alias("x"), "n", (F.col("gold") == F.col("pred")).alias("hit")).select("x.tag", "x.g", "n", "hit")
    sums = rows.groupBy("tag").agg(F.sum(F.when(F.col("g") == 0, F.col("n")).otherwise(0)).alias("gold_n"), F.sum(F.when(F.col("g") == 1, F.col("n")).otherwise(0)).alias("pred_n"), F.sum(F.when((F.col("g") == 0) & F.col("hit"), F.col("n")).otherwise(0)).alias("hits"))
    ratio = lambda a, b: F.when(F.col(b) > 0, F.col(a) / F.col(b)).otherwise(F.lit(0.0))
    pr = sums.select("tag", "gold_n", ratio("hits", "pred_n").alias("precision"), ratio("hits", "gold_n").alias("recall"))
    f1 = F.when(F.col("precision") + F.col("recall") > 0, 2 * F.col("precision") * F.col("recall") / (F.col("precision") + F.col("recall"))).otherwise(0.0)
    return pr.select("tag", F.col("gold_n").alias("support"), F.round("precision", 6).alias("precision"), F.round("recall", 6).alias("recall"), F.round(f1, 6).alias("f1"))


def f1_pivot(scores: DataFrame) -> DataFrame:
    """A row for each model, a column for each tag."""
    return scores.groupBy("model").pivot("tag", list(TAGS)).agg(F.max("f1"))


def macro(scores: DataFrame) -> DataFrame:
    """Plain means over the tags: macro F1 is the mean of the F1s."""
    return scores.agg(*[F.round(F.avg(c), 5).alias(f"macro_{c}") for c in ("precision", "recall", "f1")])


def averages(conf: DataFrame) -> DataFrame:
    scores = per_tag(conf)
    weighted = scores.agg(*[F.round(F.sum(F.col(c) * F.col("support")) / F.sum("support"), 5).alias(f"weighted_{c}") for c in ("precision", "recall", "f1")])
    right = conf.agg(F.round(F.sum(F.when(F.col("gold") == F.col("pred"), F.col("n")).otherwise(0)) / F.sum("n"), 5).alias("accuracy"))
    return weighted.crossJoin(right)  # one row each


def kappa(a: DataFrame) -> DataFrame:
    """Cohen's kappa of the columns gold and pred of a confusion table."""
    n = a.agg(F.sum("n").alias("t"), F.sum(F.when(F.col("gold") == F.col("pred"), F.col("n")).otherwise(0)).alias("same"))
    g = a.groupBy(F.col("gold").alias("tag")).agg(F.sum("n").alias("g"))
    p = a.groupBy(F.col("pred").alias("tag")).agg(F.sum("n").alias("p"))
    chance = g.join(p, "tag").agg(F.sum(F.col("g") * F.col("p")).alias("c"))
    po, pe = F.col("same") / F.col("t"), F.col("c") / (F.col("t") * F.col("t"))
    return n.crossJoin(chance).select(F.round((po - pe) / (1 - pe), 5).alias("kappa"))


def stage_list(spark: SparkSession) -> list:
    """The stages that the application has run, from Spark's own status store; it needs no web page."""
    jvm, gateway = spark.sparkContext._jvm, spark.sparkContext._gateway
    found = spark.sparkContext._jsc.sc().statusStore().stageList(None, False, False, gateway.new_array(jvm.double, 0), jvm.java.util.ArrayList())
    return [found.apply(i) for i in range(found.size())]


def cost_report(spark: SparkSession, run: Callable, parameters: dict[str, int] | None = None) -> DataFrame:
    """kind, name, tasks, seconds (of tasks), rows_read, shuffle_bytes, spilled_bytes of each stage that run() needed; and given numbers of parameters."""
    before = {s.stageId() for s in stage_list(spark)}
    run()
    rows = [("stage", f"{s.stageId()}: {s.name()}", s.numCompleteTasks(), s.executorRunTime() / 1000, s.inputRecords() + s.shuffleReadRecords(), s.shuffleWriteBytes(), s.memoryBytesSpilled() + s.diskBytesSpilled()) for s in stage_list(spark) if s.stageId() not in before]
    rows += [("parameters", k, v, None, None, None, None) for k, v in (parameters or {}).items()]
    kinds = {"kind": pa.string(), "name": pa.string(), "tasks": pa.int64(), "seconds": pa.float64(), "rows_read": pa.int64(), "shuffle_bytes": pa.int64(), "spilled_bytes": pa.int64()}
    return small_table(spark, **{c: pa.array([r[i] for r in rows], t) for i, (c, t) in enumerate(kinds.items())})
