"""Structured Streaming over reward events, replayed from files with availableNow."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pairlab.operators.workloads_rl import EV
from pairlab.registry import query
from pairlab.sources.tables import shared_path


def stream(spark, d: str, files_a_batch: int = 0) -> DataFrame:
    """events as a stream, event time as timestamp (UTC session); d holds events.parquet or several files events*.parquet."""
    path = f"{d}/events*.parquet"
    schema = spark.read.parquet(path).schema
    options = {"maxFilesPerTrigger": files_a_batch} if files_a_batch else {}
    # a file source wants a folder
    raw = spark.readStream.schema(schema).option("pathGlobFilter", "*.parquet").options(**options).parquet(path)
    return raw.withColumn("time", F.col("ts").cast("timestamp")).withWatermark("time", "10 minutes")


def drain(df: DataFrame, name: str, mode: str = "append", path: str | None = None) -> DataFrame:
    """Runs a stream over all that is there and returns what it wrote, from the shared folder. With the path of an earlier run it
    goes on from that run's checkpoint; a batch that is repeated overwrites its own files."""
    spark = df.sparkSession
    path = path or shared_path(spark, name)

    def put(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/data/batch={number}")

    q = df.writeStream.outputMode(mode).option("checkpointLocation", f"{path}/state").trigger(availableNow=True).foreachBatch(put).start()
    q.awaitTermination()
    if q.exception():
        raise q.exception()
    out = spark.read.schema(df.schema).parquet(f"{path}/data/*")
    out.late_rows = sum(int(s["numRowsDroppedByWatermark"]) for p in q.recentProgress for s in p["stateOperators"])
    return out


def with_late_rows(out: DataFrame) -> DataFrame:
    """The result of a drained stream with n_late, the rows that came behind the watermark and count in no window."""
    return out.withColumn("n_late", F.lit(getattr(out, "late_rows", 0)).cast("long"))


#: append mode gives what has ended before the watermark
MARK = "(SELECT max(ts) - INTERVAL 10 MINUTE FROM events)"


@query("stream_tumbling", "SELECT CAST(epoch(date_trunc('hour', ts)) AS BIGINT) AS start, count(*) AS n, round(sum(value), 4) AS total FROM events GROUP BY 1")
def stream_tumbling(spark, d):
    out = stream(spark, d).groupBy(F.window("time", "1 hour")).agg(F.count("*").alias("n"), F.round(F.sum("value"), 4).alias("total"))
    return drain(out, "tumbling", "update").groupBy("window").agg(F.max_by("n", "n").alias("n"), F.max_by("total", "n").alias("total")).select(F.unix_timestamp("window.start").alias("start"), "n", "total")


@query("stream_sliding", f"WITH w AS (SELECT date_trunc('hour', ts) - to_hours(CAST(i AS INTEGER)) AS s, event_type FROM events, range(0, 6) r(i)) SELECT CAST(epoch(s) AS BIGINT) AS start, count(*) AS n, count(*) FILTER (event_type = 'purchase') AS hits FROM w GROUP BY s HAVING s + INTERVAL 6 HOUR <= {MARK}")
def stream_sliding(spark, d):
    out = stream(spark, d).groupBy(F.window("time", "6 hours", "1 hour")).agg(F.count("*").alias("n"), F.count_if(F.col("event_type") == "purchase").alias("hits"))
    return drain(out, "sliding", "append").select(F.unix_timestamp("window.start").alias("start"), "n", "hits")


@query("stream_session", f"WITH g AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) <= INTERVAL 2 HOUR THEN 0 ELSE 1 END AS fresh FROM events), s AS (SELECT user_id, ts, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM g) SELECT user_id, CAST(floor(epoch(min(ts))) AS BIGINT) AS start, count(*) AS n FROM s GROUP BY user_id, k HAVING max(ts) + INTERVAL 2 HOUR <= {MARK}")
def stream_session(spark, d):
    out = stream(spark, d).groupBy("user_id", F.session_window("time", "2 hours")).agg(F.count("*").alias("n"))
    return drain(out, "session", "append").select("user_id", F.unix_timestamp("session_window.start").alias("start"), "n")


@query("stream_dedup", "SELECT count(*) AS n, count(DISTINCT event_id) AS n_ids FROM events")
def stream_dedup(spark, d):
    return drain(stream(spark, d).dropDuplicatesWithinWatermark(["event_id"]).select("event_id"), "dedup").agg(F.count("*").alias("n"), F.count_distinct("event_id").alias("n_ids"))


@query("stream_static", "SELECT event_id, c_mktsegment AS segment FROM events JOIN customer ON c_custkey = user_id")
def stream_static(spark, d):
    c = spark.read.parquet(f"{d}/customer.parquet").select(F.col("c_custkey").alias("user_id"), F.col("c_mktsegment").alias("segment"))
    return drain(stream(spark, d).join(c, "user_id").select("event_id", "segment"), "static")


@query("stream_join_verdict", "SELECT a.event_id FROM events a JOIN events b ON a.event_id = b.event_id WHERE b.value > 50")
def stream_join_verdict(spark, d):
    a = stream(spark, d).select("event_id", "time")
    b = stream(spark, d).filter("value > 50").select(F.col("event_id").alias("other"), F.col("time").alias("judged"))
    return drain(a.join(b, F.expr("event_id = other AND judged BETWEEN time - interval 1 minute AND time + interval 1 minute")).select("event_id"), "joined")


@query("stream_group_advantage", f"WITH {EV}, g AS (SELECT query_id, iteration, avg(reward) AS m, stddev_pop(reward) AS s, min(reward) = max(reward) AS dead FROM ev GROUP BY ALL HAVING count(*) = 8) SELECT query_id, CAST(iteration AS BIGINT) AS iteration, event_id, round(CASE WHEN dead THEN 0 ELSE (reward - m) / s END, 6) AS advantage FROM ev JOIN g USING (query_id, iteration)")
def stream_group_advantage(spark, d):
    out = drain(group_advantages(stream(spark, d), None), "advantage")
    return out.select("query_id", "iteration", "event_id", "advantage")


def group_advantages(events: DataFrame, wait: str | None) -> DataFrame:
    """Advantages of each user's events in eights, emitted when a group is complete; the state holds seven rewards at most.

    With wait (a number of milliseconds of event time), a group that has not filled up that long after its last event is emitted with
    what it has, incomplete = true, and the next event begins a new one."""
    import pandas as pd
    from pyspark.sql.streaming.state import GroupStateTimeout

    def group(key, done, ids, rewards, incomplete):
        s = pd.Series(rewards)
        dead = s.min() == s.max()
        a = [0.0] * len(ids) if dead else list((s - s.mean()) / s.std(ddof=0))
        return pd.DataFrame({"query_id": key[0], "iteration": done, "event_id": ids, "advantage": [round(x, 6) for x in a], "incomplete": incomplete})

    def step(key, frames, state):
        ids, rewards, done = state.get if state.exists else ([], [], 0)
        ids, rewards = list(ids), list(rewards)
        out = []
        if state.hasTimedOut:
            if ids:
                out.append(group(key, done, ids, rewards, True))
            ids, rewards, done = [], [], done + bool(ids)
        else:
            rows = pd.concat(list(frames)).sort_values(["time", "event_id"])
            for event, kind in zip(rows["event_id"], rows["event_type"]):
                ids.append(int(event))
                rewards.append(1.0 if kind in ("purchase", "signup") else -1.0)
                if len(ids) == 8:
                    out.append(group(key, done, ids, rewards, False))
                    ids, rewards, done = [], [], done + 1
            if wait and ids:
                last = int(rows["time"].max().timestamp() * 1000)
                state.setTimeoutTimestamp(max(last, state.getCurrentWatermarkMs()) + int(wait))
        state.update((ids, rewards, done))
        yield pd.concat(out) if out else pd.DataFrame({"query_id": [], "iteration": [], "event_id": [], "advantage": [], "incomplete": []})

    timeout = GroupStateTimeout.EventTimeTimeout if wait else GroupStateTimeout.NoTimeout
    schema = "query_id long, iteration long, event_id long, advantage double, incomplete boolean"
    return events.select("user_id", "event_id", "event_type", "time").groupBy("user_id").applyInPandasWithState(step, schema, "ids array<long>, rewards array<double>, done long", "append", timeout)
