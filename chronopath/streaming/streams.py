"""Streaming pipelines over the events: windows, late data, repeats, enrichment, edge lifetimes and answers per batch.

Each registered query replays the events table as a file stream until it is used
up, writes to a stored table and returns that; where a batch query gives the same
rows it is the SQL twin.
"""

from __future__ import annotations

import uuid

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from chronopath.functions.algebra import PathAlgebra
from chronopath.plans import incremental
from chronopath.plans.fixpoint import solve_full
from chronopath.sources.graphs import table
from chronopath.storage import shared_dir, store


def event_stream(spark, sf_dir: str) -> DataFrame:
    schema = table(spark, sf_dir, "events").schema
    return spark.readStream.schema(schema).parquet(f"{sf_dir}/event[s].parquet").withColumn("ts", F.col("ts").cast("timestamp"))


def run_to_table(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Run a stream until its source is used up; the rows of the sink as a table."""
    spark = stream.sparkSession
    path = f"{shared_dir(spark)}/chronopath-stream-{uuid.uuid4().hex}"
    if mode == "append":
        writer = stream.writeStream.format("parquet").option("path", f"{path}/rows")
    else:  # each batch replaces the table before it; a repeated batch writes the same folder again
        writer = stream.writeStream.outputMode(mode).foreachBatch(lambda df, n: df.write.mode("overwrite").parquet(f"{path}/rows"))
    writer.option("checkpointLocation", f"{path}/log").trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(stream.schema).parquet(f"{path}/rows")


def stream_tumbling_edges(spark, sf_dir):
    windows = event_stream(spark, sf_dir).withWatermark("ts", "1 day").groupBy(F.window("ts", "1 day").alias("w"), "user_id").agg(F.count("*").alias("n"))
    return run_to_table(windows, "complete").select(F.col("w.start").cast("date").alias("day"), "user_id", "n")


def stream_sliding_edges(spark, sf_dir):
    windows = event_stream(spark, sf_dir).groupBy(F.window("ts", "2 days", "1 day").alias("w")).agg(F.count("*").alias("n"))
    return run_to_table(windows, "complete").select(F.col("w.start").cast("date").alias("first"), "n")


def stream_sessions(spark, sf_dir):
    sessions = event_stream(spark, sf_dir).withWatermark("ts", "40 days").groupBy(F.session_window("ts", "6 hours").alias("w"), "user_id").agg(F.count("*").alias("n"))
    return run_to_table(sessions, "complete").groupBy("user_id").agg(F.count("*").alias("sessions"), F.max("n").alias("longest"))


def stream_dedup(spark, sf_dir):
    kinds = event_stream(spark, sf_dir).select("user_id", "event_type", "ts").withWatermark("ts", "40 days").dropDuplicatesWithinWatermark(["user_id", "event_type"])
    return run_to_table(kinds.select("user_id", "event_type"))


def stream_enrich(spark, sf_dir):
    customer = table(spark, sf_dir, "customer").select(F.col("c_custkey").alias("user_id"), "c_mktsegment")
    return run_to_table(event_stream(spark, sf_dir).join(customer, "user_id").select("event_id", "c_mktsegment"))


def stream_pairs(spark, sf_dir):
    """Stream-stream join: a purchase within an hour after a click of the same user."""
    e = event_stream(spark, sf_dir).select("event_id", "user_id", "event_type", "ts")
    a = e.where("event_type = 'click'").select("user_id", F.col("event_id").alias("x"), F.col("ts").alias("at")).withWatermark("at", "2 hours")
    b = e.where("event_type = 'purchase'").select(F.col("user_id").alias("buyer"), F.col("event_id").alias("y"), F.col("ts").alias("bought")).withWatermark("bought", "2 hours")
    return run_to_table(a.join(b, F.expr("user_id = buyer and bought > at and bought <= at + interval 1 hour")).select("x", "y"))


DAY_MS = 86_400_000


def _lives(gap: int):
    """Lives of a key over its batches; state: first and last day of each open life.

    A life is given out once the watermark is past the days that could still lengthen it, by a timer where no row comes."""

    def step(key, frames, state):
        spans = list(zip(*state.get)) if state.exists else []
        spans += [(d, d) for f in frames for d in set(f["day"].tolist())]
        merged: list[list[int]] = []
        for born, last in sorted(spans):
            if merged and born - merged[-1][1] <= gap:
                merged[-1][1] = max(merged[-1][1], last)
            else:
                merged.append([born, last])
        now = state.getCurrentWatermarkMs() // DAY_MS
        closed, still = [x for x in merged if x[1] + gap < now], [x for x in merged if x[1] + gap >= now]
        if still:
            state.update(([b for b, _ in still], [e for _, e in still]))
            state.setTimeoutTimestamp((min(e for _, e in still) + gap + 1) * DAY_MS)
        elif state.exists:
            state.remove()
        yield pd.DataFrame({"user_id": [key[0]] * len(closed), "event_type": [key[1]] * len(closed), "first": [b for b, _ in closed], "last": [e for _, e in closed]})

    return step


def lifetimes(events: DataFrame, delay: str, gap: int = 3) -> DataFrame:
    """(user_id, event_type, born, died): a pair as an edge that lives while its events are at most ``gap`` days apart.

    ``born`` and ``died`` are dates. Events may come in any order within ``delay``; later ones are dropped, and so are
    those without a time. A life is given out when it can no longer grow, so those near the end stay open."""
    rows = events.select("user_id", "event_type", "ts", F.unix_date(F.col("ts").cast("date")).alias("day")).where("ts is not null").withWatermark("ts", delay)
    spans = rows.groupBy("user_id", "event_type").applyInPandasWithState(_lives(gap), "user_id long, event_type string, first int, last int", "first array<int>, last array<int>", "append", "EventTimeTimeout")
    return spans.select("user_id", "event_type", F.date_from_unix_date("first").alias("born"), F.date_from_unix_date(F.col("last") + 1).alias("died"))


def stream_lifetimes(spark, sf_dir):
    """Lives of (user, kind), as days since 2024. A row far after the last event ends the replay, so that every life closes."""
    mark = f"end-{uuid.uuid4().hex}"
    end = f"{shared_dir(spark)}/chronopath-{mark}"
    table(spark, sf_dir, "events").agg((F.max("ts").cast("timestamp") + F.expr("interval 100 days")).alias("ts")).select(F.lit(-1).cast("long").alias("user_id"), F.lit(mark).alias("event_type"), "ts").write.parquet(end)
    closing = spark.readStream.schema("user_id long, event_type string, ts timestamp").parquet(end)
    lives = run_to_table(lifetimes(event_stream(spark, sf_dir).select("user_id", "event_type", "ts").unionByName(closing), "40 days"))
    since = lambda c: F.datediff(c, F.lit("2024-01-01").cast("date")).alias(c)
    return lives.where(F.col("event_type") != mark).select("user_id", "event_type", since("born"), since("died"))


class IncrementalAnswer:
    """Values from a source over a stream of edge batches (step, op, src, dst, w); kept as tables under ``path``.

    A batch that runs again after a failure reads the state before it and writes the same folder."""

    def __init__(self, base: DataFrame, source: int, algebra: PathAlgebra, path: str):
        self.algebra, self.path, self.spark = algebra, path, base.sparkSession
        state = solve_full(base, source, algebra, track_parent=True)
        base.write.parquet(f"{path}/edges/-1")
        state.write.parquet(f"{path}/values/-1")
        self.last = -1

    def values(self, n: int | None = None) -> DataFrame:
        return self.spark.read.parquet(f"{self.path}/values/{self.last if n is None else n}")

    def __call__(self, batch: DataFrame, n: int) -> None:
        before, state = self.spark.read.parquet(f"{self.path}/edges/{n - 1}"), self.values(n - 1)
        deleted = batch.where("op = 'del'").select("src", "dst")
        after = store(before.join(deleted, ["src", "dst"], "left_anti").select("src", "dst", "w").unionByName(batch.where("op = 'add'").select("src", "dst", "w")))
        after.write.mode("overwrite").parquet(f"{self.path}/edges/{n}")
        incremental.apply_batch(state, before, after, batch, self.algebra).write.mode("overwrite").parquet(f"{self.path}/values/{n}")
        self.last = n


def run_incremental(base: DataFrame, steps: DataFrame, source: int, algebra: PathAlgebra) -> DataFrame:
    """Replay stored update batches, a file for each step, as a stream; values after the last one."""
    spark, path = base.sparkSession, f"{shared_dir(base.sparkSession)}/chronopath-answer-{uuid.uuid4().hex}"
    for r in steps.select("step").distinct().orderBy("step").collect():  # a number for each step
        steps.where(F.col("step") == r["step"]).coalesce(1).write.mode("append").parquet(f"{path}/updates")
    answer = IncrementalAnswer(base, source, algebra, path)
    stream = spark.readStream.schema(steps.schema).option("maxFilesPerTrigger", 1).parquet(f"{path}/updates")
    stream.writeStream.foreachBatch(answer).option("checkpointLocation", f"{path}/log").trigger(availableNow=True).start().awaitTermination()
    return answer.values().select("v", "val")


def queries() -> dict:
    return {f.__name__: f for f in (stream_tumbling_edges, stream_sliding_edges, stream_sessions, stream_dedup, stream_enrich, stream_pairs, stream_lifetimes)}


def oracle_sql() -> dict[str, str]:
    return {
        "stream_tumbling_edges": "SELECT ts::DATE AS day, user_id, count(*) AS n FROM events GROUP BY 1, 2",
        "stream_sliding_edges": "SELECT (ts::DATE - k::INTEGER) AS first, count(*) AS n FROM events, range(2) AS t(k) GROUP BY 1",
        "stream_sessions": "WITH m AS (SELECT user_id, ts, CASE WHEN ts < lag(ts) OVER w + INTERVAL 6 HOUR THEN 0 ELSE 1 END AS new FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)), s AS (SELECT user_id, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM m), c AS (SELECT user_id, k, count(*) AS n FROM s GROUP BY user_id, k) SELECT user_id, count(*) AS sessions, max(n) AS longest FROM c GROUP BY user_id",
        "stream_dedup": "SELECT DISTINCT user_id, event_type FROM events",
        "stream_enrich": "SELECT event_id, c_mktsegment FROM events JOIN customer ON c_custkey = user_id",
        "stream_pairs": "SELECT a.event_id AS x, b.event_id AS y FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'click' AND b.event_type = 'purchase' AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR",
        "stream_lifetimes": "WITH d AS (SELECT DISTINCT user_id, event_type, datediff('day', DATE '2024-01-01', ts::DATE)::INTEGER AS day FROM events), m AS (SELECT *, CASE WHEN day - lag(day) OVER w <= 3 THEN 0 ELSE 1 END AS new FROM d WINDOW w AS (PARTITION BY user_id, event_type ORDER BY day)), s AS (SELECT *, sum(new) OVER (PARTITION BY user_id, event_type ORDER BY day ROWS UNBOUNDED PRECEDING) AS k FROM m) SELECT user_id, event_type, min(day) AS born, max(day) + 1 AS died FROM s GROUP BY user_id, event_type, k",
    }
