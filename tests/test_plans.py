"""What the plans of some queries look like: pruned scans, pushed filters, no shuffle or Python where none is needed."""

import os
import re

import pytest
from pyspark.sql import functions as F

from wordlid import registry
from wordlid.operators import corpus as C

DIR = "/root/testdata/sf0.001"
pytestmark = pytest.mark.skipif(not os.path.isdir(DIR), reason="the tables are not here")


def plan(df):
    return df._jdf.queryExecution().explainString(df.sparkSession._jvm.org.apache.spark.sql.execution.ExplainMode.fromString("formatted"))


def test_listed_sources_reach_the_scan(spark):
    text = plan(registry.QUERIES["op_semi_sources"](spark, DIR))
    assert re.search(r"PushedFilters: \[.*In\(source, \[src1,src3,src5\]\)", text)
    assert "ReadSchema: struct<doc_id:bigint,source:string>" in text and "Exchange" not in text


def test_only_needed_columns_are_read(spark):
    assert "n_chars" not in plan(registry.QUERIES["w1_collect"](spark, DIR))
    text = plan(registry.QUERIES["op_revenue_by_nation"](spark, DIR))
    assert "ReadSchema: struct<l_suppkey:bigint,l_extendedprice:double,l_discount:double>" in text or "l_quantity" not in text


def test_counts_are_combined_before_the_shuffle(spark):
    docs = spark.read.parquet(f"{DIR}/documents.parquet")
    text = plan(C.word_types(C.to_tokens(C.to_sentences(docs))))
    assert text.count("HashAggregate") >= 2 and text.count("Exchange hashpartitioning") <= 1 + text.count("ReusedExchange") + 1
    assert "partial_count" in text and "Python" not in text


def test_features_are_made_without_python(spark):
    from wordlid.functions import text as T

    words = spark.range(3).select(F.concat(F.lit("wort"), "id").alias("word"), F.array(F.lit("wo"), F.lit("rt")).alias("pieces"))
    text = plan(words.select(F.explode(T.families(F.col("word"), F.col("pieces")))))
    assert "Python" not in text and "Exchange" not in text


def test_a_group_is_not_one_task(spark):
    """The words with the smallest MD5 of each tag: no window is over a tag's words, only over prefixes of one."""
    rows = spark.range(1000).select(F.col("id").cast("string").alias("word"), (F.col("id") % 2).cast("string").alias("tag"))
    text = plan(C.smallest(rows, F.lit(7)))
    windows = re.findall(r"Arguments: \[(?:row_number|.*sum).*?\], \[([^\]]*)\]", text)
    assert all("_p" in w or "_n" in text for w in windows)
    assert not re.search(r"row_number\(\)[^\n]*windowspecdefinition\(tag#\d+, _h", text)
