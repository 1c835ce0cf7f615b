"""Structured Streaming: enrichment, stateful routing and smoothing, windows. Each query runs a file stream to its end."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from adaptivejoin.sources.store import FileStore, build_store, shared_path, spooled
from adaptivejoin.tables import table

QUERIES: dict = {}
ORACLES: dict = {}


def query(name: str, sql: str | None = None):
    def add(f):
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return add


#: Micro-batches of a run.
FILES = 3


def stream(spark, folder: str, name: str, files: int = FILES) -> DataFrame:
    """The table as a stream of files, one a micro-batch, so that state is carried from batch to batch; its times become instants,
    which watermarks need."""
    schema = table(spark, folder, name).schema
    rows = spark.readStream.schema(schema).option("pathGlobFilter", "*.parquet").option("maxFilesPerTrigger", 1).parquet(_as_folder(spark, folder, name, files))
    return rows.withColumn("ts", F.col("ts").cast("timestamp")) if "ts" in schema.names else rows


def _as_folder(spark, folder: str, name: str, files: int) -> str:
    """A stream reads folders: the table is copied in files that follow the order of its key, written one after the other, since a
    stream takes files by age."""
    path = shared_path(spark, f"stream-{name}")
    rows = table(spark, folder, name)
    key = F.col(rows.columns[0])
    ends = rows.agg(F.min(key).alias("lo"), F.max(key).alias("hi")).first()
    width = ((ends["hi"] or 0) - (ends["lo"] or 0)) // files + 1
    for i in range(files):
        rows.where(F.floor((key - (ends["lo"] or 0)) / width) == i).coalesce(1).write.mode("append").parquet(path)
    return path


def finished(df: DataFrame, mode: str = "append") -> DataFrame:
    """Run to the end and read what was written. Append goes to files; update and complete replace the result by batch id."""
    spark = df.sparkSession
    out, state = shared_path(spark, "stream-out"), shared_path(spark, "stream-state")
    writer = df.writeStream.option("checkpointLocation", state).trigger(availableNow=True).outputMode(mode)
    if mode == "append":
        q = writer.format("parquet").start(out)
    else:
        q = writer.foreachBatch(lambda batch, no: batch.write.mode("overwrite").parquet(f"{out}/batch={no:06d}")).start()
    q.awaitTermination()
    if q.exception():
        raise q.exception()
    done = spark.read.schema(df.schema).parquet(out)
    if mode == "complete":
        last = spark.read.parquet(out).agg(F.max("batch")).first()[0]
        done = spark.read.parquet(f"{out}/batch={last:06d}")
    return done


@query("stream_enrich", "SELECT event_id, c_mktsegment, n_name FROM events JOIN customer ON user_id = c_custkey JOIN nation ON c_nationkey = n_nationkey")
def stream_enrich(spark, folder):
    """A stream joined with stored relations, batch by batch, without state."""
    c, n = table(spark, folder, "customer"), table(spark, folder, "nation")
    rows = stream(spark, folder, "events").join(c, F.col("user_id") == F.col("c_custkey")).join(n, F.col("c_nationkey") == F.col("n_nationkey"))
    return finished(rows.select("event_id", "c_mktsegment", "n_name"))


THRESHOLD = 2


def route_key(key: tuple, parts: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
    """Routes of one key in one lane; its count is the state."""
    n = state.get[0] if state.exists else 0
    for part in parts:
        part = part.sort_values(["ts", "event_id"])
        count = n + 1 + np.arange(len(part))
        n += len(part)
        yield pd.DataFrame({"event_id": part["event_id"].to_numpy(), "route": np.where(count <= THRESHOLD, "ship", np.where(count == THRESHOLD + 1, "fetch", "local"))})
    state.update((n,))


@query("stream_route", "SELECT user_id, count(*) FILTER (c <= 2) AS ship, count(*) FILTER (c = 3) AS fetch, count(*) FILTER (c > 3) AS local FROM (SELECT user_id, row_number() OVER (PARTITION BY event_id % 4, user_id ORDER BY ts, event_id) AS c FROM events) GROUP BY user_id")
def stream_route(spark, folder):
    """The router over a stream: state by lane and key; the route counts are those of the batch trace."""
    rows = stream(spark, folder, "events").select((F.col("event_id") % 4).cast("int").alias("lane"), "user_id", "ts", "event_id")
    routed = rows.groupBy("lane", "user_id").applyInPandasWithState(route_key, "event_id long, route string", "n long", "append", "NoTimeout")
    n = lambda r: F.count_if(F.col("route") == r).alias(r)
    return finished(routed).join(table(spark, folder, "events").select("event_id", "user_id"), "event_id").groupBy("user_id").agg(n("ship"), n("fetch"), n("local"))


def _annotate_sql() -> str:
    from adaptivejoin.plans import applications as A

    return f"WITH {A._spots_sql('conversations', 'conv_id, turn')}, {A.MODELS}, {A._scored_sql('conv_id, turn')} SELECT conv_id, turn, pos, token, entity FROM ranked WHERE r = 1"


@query("stream_annotate", _annotate_sql())
def stream_annotate(spark, folder):
    """Messages annotated as they come; models are a stored relation."""
    from adaptivejoin.plans import applications as A

    ids = ("conv_id", "turn")
    rows = A.spots(spark, folder, stream(spark, folder, "conversations"), ids)
    return finished(A.scored(rows, spooled(A.models(spark, folder), "models"), ids).select(*ids, "pos", "token", "entity"))


LATE = "10 minutes"


@query("stream_tumbling", "SELECT time_bucket(INTERVAL 1 HOUR, ts) AS begins, count(*) AS n FROM events GROUP BY 1")
def stream_tumbling(spark, folder):
    rows = stream(spark, folder, "events").withWatermark("ts", LATE).groupBy(F.window("ts", "1 hour")).agg(F.count("*").alias("n"))
    return finished(rows, "complete").select(F.col("window.start").cast("timestamp_ntz").alias("begins"), "n")


@query("stream_sliding", "SELECT b AS begins, count(*) AS n FROM (SELECT unnest([time_bucket(INTERVAL 30 MINUTE, ts), time_bucket(INTERVAL 30 MINUTE, ts) - INTERVAL 30 MINUTE]) AS b FROM events) GROUP BY b")
def stream_sliding(spark, folder):
    rows = stream(spark, folder, "events").withWatermark("ts", LATE).groupBy(F.window("ts", "1 hour", "30 minutes")).agg(F.count("*").alias("n"))
    return finished(rows, "complete").select(F.col("window.start").cast("timestamp_ntz").alias("begins"), "n")


@query("stream_session", "WITH g AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 6 HOUR THEN 0 ELSE 1 END AS new FROM events), s AS (SELECT user_id, sum(new) OVER (PARTITION BY user_id ORDER BY ts) AS no FROM g) SELECT user_id, count(DISTINCT no) AS sessions, count(*) AS n FROM s GROUP BY user_id")
def stream_session(spark, folder):
    rows = stream(spark, folder, "events").withWatermark("ts", LATE).groupBy("user_id", F.session_window("ts", "6 hours")).agg(F.count("*").alias("n"))
    return finished(rows, "complete").groupBy("user_id").agg(F.count("*").alias("sessions"), F.sum("n").alias("n"))


@query("stream_dedup", "SELECT event_id FROM events")
def stream_dedup(spark, folder):
    """Every event arrives twice; ids are kept only as long as the watermark lets the other copy come."""
    rows = stream(spark, folder, "events").select("event_id", "ts")
    twice = rows.unionAll(stream(spark, folder, "events").select("event_id", "ts")).withWatermark("ts", "30 days")
    return finished(twice.dropDuplicatesWithinWatermark(["event_id"]).select("event_id"))


@query("stream_prefetch", "SELECT event_id, c_mktsegment FROM events JOIN customer ON user_id = c_custkey")
def stream_prefetch(spark, folder):
    """Store calls ahead of the rows of a stream."""
    from adaptivejoin.sources.prefetch import AccessMode, prefetch_map

    path = shared_path(spark, "store")
    build_store(table(spark, folder, "customer").select("c_custkey", "c_mktsegment"), "c_custkey", 4, path)
    rows = stream(spark, folder, "events").select("event_id", "user_id")
    apply = lambda r, v: {"event_id": r["event_id"], "c_mktsegment": v[0]} if v else None
    return finished(prefetch_map(rows, "user_id", lambda: FileStore(path, "c_custkey", 4, ("c_mktsegment",), 8), apply, "event_id long, c_mktsegment string", AccessMode("async", 128, 4)))


@query("stream_late_dropped")
def stream_late_dropped(spark, folder):
    """Windows that the watermark has closed, in append mode; rows that come after are not counted."""
    rows = stream(spark, folder, "events").withWatermark("ts", LATE).groupBy(F.window("ts", "1 hour")).agg(F.count("*").alias("n"))
    return finished(rows).select(F.col("window.start").cast("timestamp_ntz").alias("begins"), "n")


@query("op_stream_stream", "SELECT a.event_id, count(*) AS n FROM events a JOIN events u ON a.user_id = u.user_id AND u.event_type = 'purchase' AND a.event_type <> 'purchase' AND a.ts >= u.ts AND a.ts <= u.ts + INTERVAL 1 HOUR GROUP BY a.event_id")
def op_stream_stream(spark, folder):
    """Accesses shortly after an update of their key: two streams within an interval."""
    a = stream(spark, folder, "events").where("event_type != 'purchase'").withWatermark("ts", "30 days").alias("a")
    u = stream(spark, folder, "events").where("event_type = 'purchase'").select(F.col("user_id").alias("who"), F.col("ts").alias("at")).withWatermark("at", "30 days")
    joined = a.join(u, F.expr("user_id = who and ts >= at and ts <= at + interval 1 hour"))
    return finished(joined.select("event_id")).groupBy("event_id").agg(F.count("*").alias("n"))


@query("op_sink_idempotent", "SELECT user_id, count(*) AS n FROM events GROUP BY user_id")
def op_sink_idempotent(spark, folder):
    """A batch that is written twice, as after a lost driver, counts once: its folder is named after it and replaced."""
    out, state = shared_path(spark, "sink"), shared_path(spark, "sink-state")

    def write(batch: DataFrame, no: int) -> None:
        for _ in range(2):
            batch.select("event_id", "user_id").write.mode("overwrite").parquet(f"{out}/batch={no}")

    q = stream(spark, folder, "events").writeStream.foreachBatch(write).option("checkpointLocation", state).trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.read.parquet(out).groupBy("user_id").agg(F.count("*").alias("n"))


@query("op_stream_static", "SELECT event_id, c_mktsegment FROM events LEFT JOIN (SELECT * FROM customer WHERE c_acctbal > 0) ON user_id = c_custkey")
def op_stream_static(spark, folder):
    """An outer join with a selection of a stored relation; the stream's rows all stay."""
    c = table(spark, folder, "customer").where("c_acctbal > 0").select("c_custkey", "c_mktsegment")
    return finished(stream(spark, folder, "events").join(c, F.col("user_id") == F.col("c_custkey"), "left").select("event_id", "c_mktsegment"))


SCALE = 1024


def smooth_key(key: tuple, parts: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
    """Smoothed measurements of one key, alpha 1/2 in fixed point; the mean and how many it holds are the state."""
    n, mean = state.get if state.exists else (0, 100 * SCALE)
    for part in parts:
        for v in part.sort_values(["ts", "event_id"])["v"]:
            n, mean = n + 1, (int(v) * SCALE + mean) // 2
    state.update((n, mean))
    yield pd.DataFrame({"user_id": [key[0]], "n": [n], "smoothed": [mean]})


@query("op_stream_state", f"WITH x AS (SELECT user_id, list(CAST(floor(value * 100) AS BIGINT) ORDER BY ts, event_id) AS v FROM events GROUP BY user_id) SELECT user_id, list_reduce(list_prepend(CAST({100 * SCALE} AS BIGINT), v), lambda a, x: (x * {SCALE} + a) // 2) AS smoothed FROM x")
def op_stream_state(spark, folder):
    """Costs smoothed while they stream: state by key, carried over the batches; the last value of a key is that of one fold."""
    rows = stream(spark, folder, "events").select("user_id", "ts", "event_id", F.floor(F.col("value") * 100).cast("long").alias("v"))
    every = finished(rows.groupBy("user_id").applyInPandasWithState(smooth_key, "user_id long, n long, smoothed long", "n long, mean long", "append", "NoTimeout"))
    return every.groupBy("user_id").agg(F.max_by("smoothed", "n").alias("smoothed"))


@query("op_stream_modes", "SELECT event_type, count(*) AS n FROM events GROUP BY event_type")
def op_stream_modes(spark, folder):
    """Update mode: each batch writes the groups that it changed; the last value of a group counts."""
    rows = stream(spark, folder, "events").groupBy("event_type").agg(F.count("*").alias("n"))
    return finished(rows, "update").groupBy("event_type").agg(F.max("n").alias("n"))
