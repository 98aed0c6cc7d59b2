"""Streaming queries; each is run over the given table and has the same result as its batch SQL."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from wordlid.operators import corpus as C
from wordlid.plans.common import TYP, types
from wordlid.streaming.runner import event_stream, run, stream

Q: dict = {}
S: dict = {}


def query(name: str, sql: str | None = None):
    def put(f):
        Q[name] = f
        if sql:
            S[name] = sql
        return f

    return put


def _windows(spark, d, *size):
    e = event_stream(spark, d).withWatermark("ts", "2 hours")
    out = e.groupBy(F.window("ts", *size), "event_type").agg(F.count("*").alias("n"), F.round(F.sum("value"), 4).alias("total"))
    rows = run(out.select(F.unix_seconds("window.start").alias("win"), "event_type", "n", "total"), "update", ["win", "event_type"])
    return rows


@query("st_tumbling", "SELECT epoch(date_trunc('hour', ts))::BIGINT AS win, event_type, count(*) AS n, round(sum(value), 4) AS total FROM events GROUP BY 1, 2")
def tumbling(spark, d):
    return _windows(spark, d, "1 hour")


@query("st_sliding", "WITH s AS (SELECT event_type, value, unnest([epoch(ts)::BIGINT // 1800 * 1800, epoch(ts)::BIGINT // 1800 * 1800 - 1800]) AS win FROM (SELECT event_type, value, to_timestamp(floor(epoch(ts))) AS ts FROM events)) SELECT win, event_type, count(*) AS n, round(sum(value), 4) AS total FROM s GROUP BY 1, 2")
def sliding(spark, d):
    return _windows(spark, d, "1 hour", "30 minutes")


@query("st_session", "WITH l AS (SELECT *, CASE WHEN ts < lag(ts) OVER w + INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS new FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)), g AS (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS s FROM l) SELECT user_id, floor(epoch(min(ts)))::BIGINT AS first_s, count(*) AS n FROM g GROUP BY user_id, s HAVING epoch_ms(max(ts)) + 1800000 <= (SELECT epoch_ms(max(ts)) - 7200000 FROM events)")
def session(spark, d):
    """Sessions that the watermark has closed; each is written once, and its state goes."""
    e = event_stream(spark, d).withWatermark("ts", "2 hours")
    out = e.groupBy(F.session_window("ts", "30 minutes"), "user_id").agg(F.count("*").alias("n"))
    return run(out.select("user_id", F.unix_seconds("session_window.start").alias("first_s"), "n"))


@query("st_dedup", "SELECT DISTINCT event_id, user_id FROM events")
def dedup(spark, d):
    e = event_stream(spark, d)
    return run(e.union(e).withWatermark("ts", "2 hours").dropDuplicatesWithinWatermark(["event_id"]).select("event_id", "user_id"))


@query("st_static_join", f"WITH {TYP} SELECT tag, count(*) AS n FROM tok JOIN base USING (word) GROUP BY tag")
def static_join(spark, d, head_types=2000):
    """Online tagging: the comment stream meets a broadcast table of the most frequent types, and what that misses, all others."""
    base = C.base_tags(types(spark, d))
    head = base.orderBy(F.desc("n"), "word").limit(head_types).select("word", F.col("tag").alias("h"))
    tail = base.select(F.col("word").alias("rest"), "tag")
    tokens = C.to_tokens(C.to_sentences(stream(spark, d, "documents"))).join(F.broadcast(head), "word", "left")
    missed = F.when(F.col("h").isNull(), F.col("word"))
    every = tokens.withColumn("missed", missed).join(tail, F.col("missed") == F.col("rest"), "left")
    return run(every.groupBy(F.coalesce("h", "tag").alias("tag")).agg(F.count("*").alias("n")), "update", ["tag"])


@query("st_interval_join", "SELECT a.event_id AS click, b.event_id AS buy FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'click' AND b.event_type = 'purchase' AND b.ts BETWEEN a.ts AND a.ts + INTERVAL 2 HOUR")
def interval_join(spark, d):
    e = event_stream(spark, d).withWatermark("ts", "2 hours")
    a = e.filter("event_type = 'click'").select(F.col("event_id").alias("click"), F.col("user_id").alias("u"), F.col("ts").alias("t"))
    b = e.filter("event_type = 'purchase'").select(F.col("event_id").alias("buy"), "user_id", "ts")
    return run(a.join(b, F.expr("u = user_id and ts between t and t + interval 2 hours")).select("click", "buy"))


@query("st_stateful_drift", "SELECT user_id, count(*) AS n, count(DISTINCT event_type) AS kinds FROM events GROUP BY user_id")
def stateful_drift(spark, d):
    """For each user how many events and kinds of event have been seen, kept in state of a bounded size."""

    def step(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        n, kinds = state.get if state.exists else (0, "")
        seen = set(kinds.split("\n")) - {""}
        for b in batches:
            n += len(b)
            seen |= set(b["event_type"])
        state.update((n, "\n".join(sorted(seen))))
        yield pd.DataFrame({"user_id": [key[0]], "n": [n], "kinds": [len(seen)]})

    out = event_stream(spark, d).select("user_id", "event_type").groupBy("user_id").applyInPandasWithState(step, "user_id long, n long, kinds long", "n long, kinds string", "update", GroupStateTimeout.NoTimeout)
    return run(out, "update", ["user_id"])


@query("st_late_rows", "SELECT user_id, count(*) FILTER (ts < high - INTERVAL 2 HOUR) AS late, count(*) AS n FROM (SELECT user_id, ts, max(ts) OVER (PARTITION BY user_id ORDER BY event_id) AS high FROM events) GROUP BY user_id")
def late_rows(spark, d):
    """How many rows a watermark of two hours would drop for each user if they came one at a time; the state is the latest time and two counts."""

    def step(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        high, late, n = state.get if state.exists else (0, 0, 0)
        rows = pd.concat(list(batches)).sort_values("event_id")
        times = rows["us"].to_numpy()
        highs = np.maximum.accumulate(np.append(high, times))[1:]
        late, n, high = late + int((times < highs - 7_200_000_000).sum()), n + len(rows), int(highs[-1])
        state.update((high, late, n))
        yield pd.DataFrame({"user_id": [key[0]], "late": [late], "n": [n]})

    e = event_stream(spark, d).select("user_id", "event_id", F.unix_micros("ts").alias("us"))
    out = e.groupBy("user_id").applyInPandasWithState(step, "user_id long, late long, n long", "high long, late long, n long", "update", GroupStateTimeout.NoTimeout)
    return run(out, "update", ["user_id"])
