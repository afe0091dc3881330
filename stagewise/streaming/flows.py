"""Structured Streaming around the filters: windows, dedup, probes, joins and the flush of runs."""

from __future__ import annotations

import functools
import json
import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.hashing import segment_col
from ..operators import applications as A
from ..operators import filters as X
from ..operators.online import online
from ..plans.storage import keep, shared_folder
from ..sources.tables import read_table, stream_table

OPERATORS: dict[str, tuple[Callable[[SparkSession, str], DataFrame], str | None]] = {}


def op(name: str, sql: str | None = None):
    def add(f):
        OPERATORS[f"stream_{name}"] = (f, sql)
        return f

    return add


def event_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The events as a file stream, with ``ts`` as an instant; the four files may come in any order."""
    df = read_table(spark, sf_dir, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    path = f"{shared_folder(spark)}/events_{uuid.uuid4().hex}"
    df.repartitionByRange(4, "ts").write.parquet(path)
    return stream_table(spark, path, df.schema, 1)


def whole_span(spark: SparkSession, sf_dir: str) -> str:
    """A watermark delay as long as all the events, so that none is late whatever the order of the files."""
    first, last = read_table(spark, sf_dir, "events", "ts").agg(F.min(F.unix_seconds(F.col("ts").cast("timestamp"))), F.max(F.unix_seconds(F.col("ts").cast("timestamp")))).first()
    return f"{(last or 0) - (first or 0) + 3600} seconds"


def drained(df: DataFrame, mode: str = "append") -> DataFrame:
    """Run a stream until its files are read, into Parquet, and give the rows back."""
    spark = df.sparkSession
    base = f"{shared_folder(spark)}/{uuid.uuid4().hex}"
    if mode == "append":
        df.writeStream.format("parquet").option("checkpointLocation", f"{base}/state").outputMode("append").trigger(availableNow=True).start(f"{base}/out").awaitTermination()
        return spark.read.schema(df.schema).parquet(f"{base}/out")

    def last(batch: DataFrame, n: int) -> None:
        batch.write.mode("overwrite").parquet(f"{base}/out")

    df.writeStream.foreachBatch(last).option("checkpointLocation", f"{base}/state").outputMode(mode).trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(df.schema).parquet(f"{base}/out")


@op("tumbling", "SELECT date_trunc('hour', ts) AS hour, event_type, count(*) AS n FROM events GROUP BY ALL")
def _tumbling(s, d):
    w = event_stream(s, d).withWatermark("ts", "1 hour").groupBy(F.window("ts", "1 hour"), "event_type").agg(F.count(F.lit(1)).alias("n"))
    return drained(w, "complete").select(F.col("window.start").cast("timestamp_ntz").alias("hour"), "event_type", "n")


@op("sliding", "SELECT start, count(*) AS n FROM (SELECT unnest([date_trunc('hour', ts), date_trunc('hour', ts) - INTERVAL 1 HOUR]) AS start FROM events) WHERE start IS NOT NULL GROUP BY start")
def _sliding(s, d):
    """Complete mode without a watermark: no row is late, and the last windows come out too."""
    w = event_stream(s, d).groupBy(F.window("ts", "2 hours", "1 hour")).agg(F.count(F.lit(1)).alias("n"))
    return drained(w, "complete").select(F.col("window.start").cast("timestamp_ntz").alias("start"), "n")


@op(
    "sessions",
    "WITH cut AS (SELECT user_id, ts, coalesce(ts >= lag(ts) OVER w + INTERVAL 30 MINUTE, true) AS opens FROM events WHERE ts IS NOT NULL WINDOW w AS (PARTITION BY user_id ORDER BY ts)), "
    "numbered AS (SELECT user_id, ts, count(*) FILTER (WHERE opens) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS i FROM cut) SELECT user_id, min(ts) AS start, count(*) AS n FROM numbered GROUP BY user_id, i",
)
def _sessions(s, d):
    """As for sliding; sessions drop late rows even in complete mode."""
    w = event_stream(s, d).groupBy(F.session_window("ts", "30 minutes").alias("w"), "user_id").agg(F.count(F.lit(1)).alias("n"))
    return drained(w, "complete").select("user_id", F.col("w.start").cast("timestamp_ntz").alias("start"), "n")


@op("dedup", "SELECT DISTINCT user_id, event_type FROM events")
def _dedup(s, d):
    return drained(event_stream(s, d).select("user_id", "event_type").dropDuplicates(["user_id", "event_type"]))


@op("dedup_within_watermark", "SELECT user_id, event_type, CAST(0 AS BIGINT) AS late FROM events WHERE user_id IS NOT NULL GROUP BY user_id, event_type")
def _dedup_within(s, d):
    """State of a pair is dropped once the watermark has passed it; the rows that came too late for it are counted by the engine."""
    rows = event_stream(s, d).withWatermark("ts", whole_span(s, d)).dropDuplicatesWithinWatermark(["user_id", "event_type"]).select("user_id", "event_type")
    base = f"{shared_folder(s)}/{uuid.uuid4().hex}"
    running = rows.writeStream.format("parquet").option("checkpointLocation", f"{base}/state").outputMode("append").trigger(availableNow=True).start(f"{base}/out")
    running.awaitTermination()
    late = sum(o["numRowsDroppedByWatermark"] for p in running.recentProgress for o in json.loads(p.json)["stateOperators"])
    return s.read.schema(rows.schema).parquet(f"{base}/out").where("user_id is not null").withColumn("late", F.lit(late).cast("long"))


@op("probe", "SELECT event_id, event_type = 'purchase' AS hit FROM events")
def _probe(s, d):
    """A stream probes a static filter: a stateless join with its segments."""
    df = read_table(s, d, "events", "event_id", "event_type")
    h = X.staged(df.withColumn("y", F.col("event_type") == "purchase"), ["event_id"], "y")
    return drained(h.probe(event_stream(s, d).select("event_id"), ["event_id"]))


@op("interval_join", "SELECT c.event_id AS click, p.event_id AS purchase FROM events c JOIN events p ON c.user_id = p.user_id AND c.event_type = 'click' AND p.event_type = 'purchase' AND p.ts >= c.ts AND p.ts <= c.ts + INTERVAL 1 HOUR")
def _interval(s, d):
    e, late = event_stream(s, d), whole_span(s, d)
    c = e.where("event_type = 'click'").select(F.col("event_id").alias("click"), F.col("user_id").alias("u"), F.col("ts").alias("tc")).withWatermark("tc", late)
    p = e.where("event_type = 'purchase'").select(F.col("event_id").alias("purchase"), F.col("user_id").alias("v"), F.col("ts").alias("tp")).withWatermark("tp", late)
    return drained(c.join(p, F.expr("u = v and tp >= tc and tp <= tc + interval 1 hour"))).select("click", "purchase")


@op("flush_per_batch", "SELECT count(*) AS keys, count(*) AS reads, CAST(0 AS BIGINT) AS wasted FROM events")
def _flush_per_batch(s, d):
    """Each micro-batch becomes a run with a filter of its own, and the filters of the earlier runs learn the new keys they would mistake."""
    runs, learnt = [], []

    def flush(batch: DataFrame, n: int) -> None:
        if batch.isEmpty():
            return
        run = keep(batch.select("event_id", F.lit(len(runs) + 1).alias("run")))
        for i, f in enumerate(learnt):
            learnt[i] = f.exclude(run, ["event_id"])
        learnt.append(online(run.withColumn("mine", F.lit(True)), ["event_id"], "mine", eps=1 / 64, room=1.0))
        runs.append(run)

    event_stream(s, d).writeStream.foreachBatch(flush).option("checkpointLocation", f"{shared_folder(s)}/{uuid.uuid4().hex}").trigger(availableNow=True).start().awaitTermination()
    rows = functools.reduce(DataFrame.unionByName, runs)
    # runs in order until the key is found; a filter's yes is a read
    asked, seen = rows.select("event_id", F.col("run").alias("home")), []
    for i, f in enumerate(learnt, 1):
        seen.append(f.probe(asked, ["event_id"]).where(F.col("hit") & (F.col("home") >= i)).select((F.col("home") == i).alias("mine")))
    reads = functools.reduce(DataFrame.unionByName, seen)
    return reads.agg(F.sum(F.col("mine").cast("long")).alias("keys"), F.count(F.lit(1)).alias("reads"), F.sum((~F.col("mine")).cast("long")).alias("wasted"))


@op("trained_predictor", "SELECT CAST(8 AS BIGINT) * count(*) AS answers, true AS late_errors_fewer FROM events")
def _streamed_training(s, d):
    """Online training in a stateful stream: a segment's layers are its state, its keys come eight times over, and each batch is answered before it is learnt."""
    import numpy as np
    import pandas as pd
    from pyspark.sql.streaming.state import GroupStateTimeout

    events = read_table(s, d, "events", "event_id", "event_type")
    path = f"{shared_folder(s)}/lessons_{uuid.uuid4().hex}"
    for _ in range(8):
        events.select(F.col("event_id").alias("k"), (F.col("event_type") == "purchase").alias("y")).coalesce(1).write.mode("append").parquet(path)
    sizes = events.agg(F.count(F.lit(1)).alias("u"), F.sum((F.col("event_type") == "purchase").cast("long")).alias("n")).first()
    parts = max(1, -(-sizes["u"] // X.SEGMENT_KEYS))
    n = max(1, (sizes["n"] or 0) // parts)
    lam = (sizes["u"] - (sizes["n"] or 0)) / max(1, sizes["n"] or 0)

    def learn(key, frames, state):
        layers = A.trained_layers(state.get[0] if state.exists else None, n, lam, 1 + 100_003 * int(key[0]))
        round_ = state.get[1] + 1 if state.exists else 1
        rows = pd.concat(list(frames)).sort_values("k", ignore_index=True)
        k, y, wrong = rows["k"].to_numpy(np.int64), rows["y"].to_numpy(bool), 0
        spots = layers.spots(k)
        for lo in range(0, len(k), A.TRAINING_BATCH):
            wrong += layers.teach([x[lo : lo + A.TRAINING_BATCH] for x in spots], y[lo : lo + A.TRAINING_BATCH])
        state.update((layers.dumps(), round_))
        yield pd.DataFrame({"seg": [int(key[0])], "round": [round_], "answers": [len(k)], "wrong": [wrong]})

    lessons = stream_table(s, path, s.read.parquet(path).schema, 1).withColumn("seg", segment_col(F.col("k"), parts))
    told = drained(lessons.groupBy("seg").applyInPandasWithState(learn, "seg int, round int, answers long, wrong long", "layers binary, round int", "append", GroupStateTimeout.NoTimeout))
    by = lambda c: F.sum(F.when(c, F.col("wrong")).otherwise(0))
    return told.agg(F.sum("answers").alias("answers"), (by(F.col("round") == 8) * 20 <= by(F.col("round") == 1)).alias("late_errors_fewer"))


@op("run_flush", "SELECT count(*) AS keys, CAST(0 AS BIGINT) AS wasted FROM events")
def _flush(s, d):
    """Each micro-batch becomes a run; the filter learns its keys, positive for that run and negative for the earlier ones."""
    runs: list[DataFrame] = []

    def flush(batch: DataFrame, n: int) -> None:
        if not batch.isEmpty():
            runs.append(keep(batch.select("event_id").withColumn("run", F.lit(len(runs) + 1))))

    event_stream(s, d).writeStream.foreachBatch(flush).option("checkpointLocation", f"{shared_folder(s)}/{uuid.uuid4().hex}").trigger(availableNow=True).start().awaitTermination()
    rows = runs[0]
    for r in runs[1:]:
        rows = rows.unionByName(r)
    return A.runs_get(rows, "event_id", rows, A.runs_filters(rows, "event_id")).agg(F.count(F.lit(1)).alias("keys"), F.sum("wasted").alias("wasted"))
