"""Registered streaming queries, over the events table read as a stream."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators import cells as C
from ..operators import stream as S
from ..session import cut, shared_folder, table
from ..sources import workloads as WL
from ..spec import SketchSpec
from ..streaming import ingest as I
from .graph import SPEC, cols, sql_cells

Q: dict = {}
SQL: dict = {}


def put(name: str, sql: str):
    def keep(f):
        Q[name], SQL[name] = f, sql
        return f

    return keep


def events(s, d) -> DataFrame:
    """The table's file as a stream: the folder is watched, and only this name in it."""
    raw = s.readStream.schema(table(s, d, "events").schema).option("pathGlobFilter", "events.parquet").parquet(d)
    return raw.withColumn("ts", F.col("ts").cast("timestamp"))


def _name() -> str:
    return f"bs_{uuid.uuid4().hex}"


W7E = f"SELECT u, v FROM ({WL.SQL_W7}) GROUP BY u, v HAVING sum(delta) = 1"


def _updates_folder(s, d, parts: int = 4) -> str:
    """The toggle stream as files, for a source that delivers it one file a batch."""
    path = shared_folder(s, "updates")
    WL.stream_w7(s, d).repartition(parts).write.parquet(path)
    return path


def _updates(s, source: str) -> DataFrame:
    return s.readStream.schema("seq long, u long, v long, delta int, w double").option("maxFilesPerTrigger", 1).parquet(source)


def _ingested(s, d) -> str:
    path = shared_folder(s, "cells")
    I.start_ingest(_updates(s, _updates_folder(s, d)), path, path + "-log", SPEC).awaitTermination()
    return path


put("stream_cells_equals_batch", sql_cells(W7E, SPEC))(lambda s, d: cols(I.snapshot(s, _ingested(s, d))))


@put("stream_replay_idempotent", sql_cells(W7E, SPEC))
def _replay(s, d):
    path = shared_folder(s, "cells")
    for _ in range(2):  # the same batch twice
        I.write_batch(WL.stream_w7(s, d), 0, path, SPEC)
    return cols(I.snapshot(s, path))


@put("stream_compacted", sql_cells(W7E, SPEC))
def _compacted(s, d):
    """The first two batches summed in one folder, and the later ones as they came."""
    path, target = _ingested(s, d), shared_folder(s, "compacted")
    I.compact(s, path, target, 1)
    return cols(I.snapshot(s, path, compacted=target))


PANE = 250
#: Rows of a window as edges of an odd number of updates: what is left of them when pairs cancel.
W7W = f"SELECT u, v FROM ({WL.SQL_W7}) WHERE seq >= {PANE} AND seq < {4 * PANE} GROUP BY u, v HAVING count(*) % 2 = 1"


def _paned(s, d, source: str, delay: int | None = None) -> str:
    path = shared_folder(s, "panes")
    I.start_panes(_updates(s, source), path, path + "-log", SPEC, PANE, delay).awaitTermination()
    return path


@put("stream_pane_window", sql_cells(W7W, SPEC))
def _pane_window(s, d):
    """A sliding window of three panes as the XOR of their cells."""
    return cols(I.window_cells(s, _paned(s, d, _updates_folder(s, d)), 1, 3))


def _changes(s, d, how) -> DataFrame:
    path = shared_folder(s, "changes")
    I.start_changes(how(_updates(s, _updates_folder(s, d)), SPEC), path, path + "-log").awaitTermination()
    return cols(I.latest_cells(s, path))


put("stream_cell_state", sql_cells(W7E, SPEC))(lambda s, d: _changes(s, d, I.changed_cells))
put("stream_group_state", sql_cells(W7E, SPEC))(lambda s, d: _changes(s, d, I.changed_by_group))


@put("stream_xor_state", "SELECT user_id, bit_xor(event_id) AS x, count(*) AS n FROM events GROUP BY 1")
def _state(s, d):
    return I.drained(events(s, d).groupBy("user_id").agg(F.bit_xor("event_id").alias("x"), F.count(F.lit(1)).alias("n")), _name(), "complete")


@put("stream_tumbling", "SELECT strftime(time_bucket(INTERVAL 1 DAY, ts), '%Y-%m-%d') AS day, count(*) AS n FROM events GROUP BY 1")
def _tumbling(s, d):
    e = events(s, d).withWatermark("ts", "1 hour").groupBy(F.window("ts", "1 day")).agg(F.count(F.lit(1)).alias("n"))
    return I.drained(e.select(F.date_format("window.start", "yyyy-MM-dd").alias("day"), "n"), _name(), "complete")


@put("stream_sliding", "SELECT strftime(day, '%Y-%m-%d %H') AS start, count(*) AS n FROM (SELECT time_bucket(INTERVAL 12 HOUR, ts) - to_hours(12 * CAST(i AS INTEGER)) AS day FROM events, range(2) t(i)) GROUP BY 1")
def _sliding(s, d):
    e = events(s, d).withWatermark("ts", "1 hour").groupBy(F.window("ts", "1 day", "12 hours")).agg(F.count(F.lit(1)).alias("n"))
    return I.drained(e.select(F.date_format("window.start", "yyyy-MM-dd HH").alias("start"), "n"), _name(), "complete")


@put("stream_session", "SELECT user_id, count(*) AS sessions, CAST(max(n) AS BIGINT) AS longest FROM (SELECT user_id, k, count(*) AS n FROM (SELECT user_id, sum(f) OVER (PARTITION BY user_id ORDER BY ts) AS k FROM (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 6 HOUR THEN 0 ELSE 1 END AS f FROM events)) GROUP BY 1, 2) GROUP BY 1")
def _session(s, d):
    e = events(s, d).withWatermark("ts", "1 hour").groupBy("user_id", F.session_window("ts", "6 hours")).agg(F.count(F.lit(1)).alias("n"))
    return I.drained(e.select("user_id", "n"), _name(), "complete").groupBy("user_id").agg(F.count(F.lit(1)).alias("sessions"), F.max("n").alias("longest"))


@put("stream_static_join", "SELECT c_mktsegment, count(*) AS n FROM events JOIN customer ON user_id = c_custkey GROUP BY 1")
def _static(s, d):
    c = table(s, d, "customer").select("c_custkey", "c_mktsegment")
    return I.drained(events(s, d).join(c, F.col("user_id") == F.col("c_custkey")).groupBy("c_mktsegment").agg(F.count(F.lit(1)).alias("n")), _name(), "complete")


@put("stream_dedup", "SELECT count(*) AS n, count(DISTINCT event_id) AS ids FROM events")
def _dedup(s, d):
    e = events(s, d).withWatermark("ts", "60 days").dropDuplicatesWithinWatermark(["event_id"])
    path = shared_folder(s, "ids")
    return I.stored(e.select("event_id"), path, path + "-log").agg(F.count(F.lit(1)).alias("n"), F.countDistinct("event_id").alias("ids"))


DELAY = 100


@put("stream_late_counted", f"SELECT CAST((SELECT count(*) FROM events) AS BIGINT) AS sketched, CAST(count(*) AS BIGINT) AS late FROM events WHERE event_id % 2 = 1 AND event_id < (SELECT max(event_id) FROM events WHERE event_id % 2 = 0) - {DELAY}")
def _late(s, d):
    """Even numbers come first, odd ones a batch later: all rows are sketched, and those behind the allowed delay are counted."""
    source, stream = shared_folder(s, "updates"), cut(WL.stream_w7(s, d))
    for odd in (0, 1):
        stream.filter(F.col("seq") % 2 == odd).repartition(1).write.mode("append").parquet(source)  # one file a batch
    return I.late_counts(s, _paned(s, d, source, DELAY)).select(F.col("n").alias("sketched"), "late")
