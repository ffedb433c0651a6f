"""Registered streaming queries: each streams the events table in time slices and must equal its batch form."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..model import ArrayQuery, Constraint, as_array, fit_spec
from ..operators import query as Q
from ..operators.append import append
from ..operators.tree import IndexConfig, build_index
from ..streaming import append as S
from .arrays import PART_CELLS, hour, load, where_sql


def sliced(spark: SparkSession, d: str, slices: int = 6, copies: int = 1) -> tuple[DataFrame, str, DataFrame]:
    """Events written in slices of hours, in order, every row `copies` times; the first slice stays a table."""
    events = load(spark, d, "events").withColumn("h", hour("ts"))
    top = events.agg(F.max("h")).first()[0] + 1
    path = S.fresh_folder(spark, "event-slices")
    first = events.where(F.col("h") < top // slices)
    for k in range(1, slices):
        part = events.where((F.col("h") >= top * k // slices) & (F.col("h") < top * (k + 1) // slices)).drop("h")
        for _ in range(copies - 1):
            part = part.unionAll(part)
        part.write.mode("append").parquet(path)
    return first, path, events.drop("h")


def stream_append_range(spark: SparkSession, d: str) -> DataFrame:
    """The index takes the later slices from a stream; a range query over it must see them all."""
    first, path, events = sliced(spark, d)
    to_cells = lambda rows: as_array(rows, {"user": F.col("user_id"), "hour": hour("ts")}, F.col("value"))
    cells = to_cells(first)
    spec = fit_spec(events.select(F.col("user_id").alias("user"), hour("ts").cast("long").alias("hour")), ["user", "hour"], (16, 16))
    # the domain's origin is known; its upper ends grow with the stream
    spec = type(spec)(tuple(type(x)(x.name, x.lo, min(x.hi, x.lo + 100)) if x.name == "hour" else x for x in spec.dims), "value", spec.chunk)
    seen = cells.where(F.col("hour") < spec.dims[1].hi)
    built = build_index(seen, spec, IndexConfig(fanout=(4, 4), part_cells=PART_CELLS))
    append(built, cells.where(F.col("hour") >= spec.dims[1].hi), batch=("first", 0))
    state = S.IndexedStream(spark, built.path, "later", to_cells)
    checkpoint = S.fresh_folder(spark, "stream-checkpoint")
    S.append_stream(S.event_stream(spark, path, events, files=2), state, checkpoint)
    state.take(events, 0)  # a batch that comes again, whatever it holds, changes nothing
    return Q.range_query(state.index, ArrayQuery({"user": Constraint.below(100)}, Constraint.between(10.0, 90.0)))


def stream_tumbling(spark: SparkSession, d: str) -> DataFrame:
    """Hourly windows by user from a stream with a watermark: all that are closed when it ends."""
    return _closed(spark, d, S.tumbling)


def stream_sliding(spark: SparkSession, d: str) -> DataFrame:
    """Windows of two hours, an hour apart, likewise."""
    return _closed(spark, d, S.sliding)


def _closed(spark: SparkSession, d: str, windows) -> DataFrame:
    first, path, events = sliced(spark, d)
    first.drop("h").write.mode("append").parquet(path)
    rows = windows(S.event_stream(spark, path, events, files=100_000)).select("window", "user_id", "vmax", "n")
    out = S.run_to_files(rows, S.fresh_folder(spark, "windows"), S.fresh_folder(spark, "stream-checkpoint"))
    return out.select(F.date_format("window.start", "yyyy-MM-dd HH").alias("hour"), "user_id", "vmax", "n")


def stream_bounds(spark: SparkSession, d: str) -> DataFrame:
    first, path, events = sliced(spark, d)
    first.drop("h").write.mode("append").parquet(path)
    return S.run_to_latest(S.chunk_bounds(S.event_stream(spark, path, events, files=8)), S.fresh_folder(spark, "bounds"), S.fresh_folder(spark, "stream-checkpoint"))


def sliding_cells(spark: SparkSession, d: str) -> DataFrame:
    rows = load(spark, d, "events").groupBy(F.window("ts", "2 hours", "1 hour").alias("w"), "user_id").agg(F.max("value").alias("vmax"))
    return rows.select(F.date_format("w.start", "yyyy-MM-dd HH").alias("hour"), "user_id", "vmax")


def session_cells(spark: SparkSession, d: str) -> DataFrame:
    return S.sessions(load(spark, d, "events")).select("user_id", "n", "vmax", F.date_format("session_window.start", "yyyy-MM-dd HH:mm:ss").alias("began"))


QUERIES = {"stream_append_range": stream_append_range, "stream_tumbling": stream_tumbling, "stream_sliding": stream_sliding, "stream_bounds": stream_bounds, "sliding_cells": sliding_cells, "session_cells": session_cells}
SQL = {
    "stream_append_range": where_sql("ae", '"user" < 100 AND value >= 10.0 AND value < 90.0'),
    "stream_tumbling": "SELECT strftime(date_trunc('hour', ts), '%Y-%m-%d %H') AS hour, user_id, max(value) AS vmax, count(*) AS n FROM events GROUP BY date_trunc('hour', ts), user_id HAVING date_trunc('hour', ts) + INTERVAL 1 HOUR <= (SELECT max(ts) - INTERVAL 1 HOUR FROM events)",
    "stream_sliding": "SELECT strftime(w, '%Y-%m-%d %H') AS hour, user_id, max(value) AS vmax, count(*) AS n FROM (SELECT date_trunc('hour', ts) - INTERVAL (k) HOUR AS w, user_id, value FROM events, (VALUES (0), (1)) v(k)) GROUP BY w, user_id HAVING w + INTERVAL 2 HOUR <= (SELECT max(ts) - INTERVAL 1 HOUR FROM events)",
    "stream_bounds": "SELECT user_id // 16 AS block, min(value) AS vmin, max(value) AS vmax, count(*) AS n FROM events GROUP BY 1",
    "sliding_cells": "SELECT strftime(date_trunc('hour', ts) - INTERVAL (k) HOUR, '%Y-%m-%d %H') AS hour, user_id, max(value) AS vmax FROM events, (VALUES (0), (1)) v(k) GROUP BY 1, 2",
    "session_cells": "WITH g AS (SELECT *, CASE WHEN ts < lag(ts) OVER w + INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS fresh FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)), s AS (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM g) SELECT user_id, count(*) AS n, max(value) AS vmax, strftime(min(ts), '%Y-%m-%d %H:%M:%S') AS began FROM s GROUP BY user_id, k",
}
