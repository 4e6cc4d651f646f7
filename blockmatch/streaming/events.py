"""Streams over the events table: arriving points, trips, late rows, and their batch twins."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

SCHEMA = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def stream_events(spark: SparkSession, folder: str, per_trigger: int = 1, delay: str = "1 day") -> DataFrame:
    """A file stream of events Parquet with a fixed schema; times become instants, with the one watermark of all that follows."""
    rows = spark.readStream.schema(SCHEMA).option("maxFilesPerTrigger", per_trigger).parquet(folder)
    return rows.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", delay)


def once(events: DataFrame) -> DataFrame:
    """Each event once; on a stream, duplicates within the watermark are dropped and later rows are counted as late."""
    if events.isStreaming:
        return events.dropDuplicatesWithinWatermark(["event_id"])
    return events.dropDuplicates(["event_id"])


def poi_activity(events: DataFrame, width: str = "1 day", slide: str | None = None) -> DataFrame:
    """Arrivals by vertex (user_id), type and window; tumbling, or sliding if `slide` is given."""
    w = F.window("ts", width, slide) if slide else F.window("ts", width)
    rows = events.groupBy(w.alias("w"), "user_id", "event_type").agg(F.count("*").alias("cnt"))
    return rows.select(F.col("w.start").alias("start"), "user_id", "event_type", "cnt")


def trips(events: DataFrame, gap: str = "12 hours") -> DataFrame:
    """Sessions of a user with their first and last event."""
    rows = events.groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("cnt"), F.min_by("event_id", F.struct("ts", "event_id")).alias("first_event"), F.max_by("event_id", F.struct("ts", "event_id")).alias("last_event"))
    return rows.select("user_id", F.col("w.start").alias("start"), "cnt", "first_event", "last_event")


def views_then_purchases(events: DataFrame, within: str = "1 day") -> DataFrame:
    """Purchases up to a day after a view of the same user; a stream-stream interval join on streams."""
    v, p = (events.filter(F.col("event_type") == t).select(F.col("event_id").alias(f"{n}_id"), F.col("user_id").alias(f"{n}_user"), F.col("ts").alias(f"{n}_ts")) for t, n in (("view", "v"), ("purchase", "p")))
    near = (F.col("v_user") == F.col("p_user")) & (F.col("p_ts") >= F.col("v_ts")) & (F.col("p_ts") <= F.col("v_ts") + F.expr(f"interval {within}"))
    return v.join(p, near).select("v_id", "p_id", F.col("v_user").alias("user_id"))


def positions(events: DataFrame, n_vertices: int) -> DataFrame:
    """Add vid, the vertex at which an event takes place."""
    return events.withColumn("vid", F.pmod(F.col("event_id") * 7919 + F.col("user_id"), F.lit(n_vertices)))


def trip_segments(found: DataFrame, vertices: DataFrame) -> DataFrame:
    """user_id, start, x0, y0, x1, y1: a trip as the segment from its first to its last event's vertex; trips within one vertex are points.

    Vertices are numbered from 0 without gaps. A stream-static join on streams.
    """
    n = vertices.count()
    place = lambda c: F.pmod(F.col(c) * 7919 + F.col("user_id"), F.lit(n))
    ends = [vertices.select(F.col("vid").alias(f"v{k}"), F.col("x").alias(f"x{k}"), F.col("y").alias(f"y{k}")) for k in (0, 1)]
    rows = found.withColumns({"v0": place("first_event"), "v1": place("last_event")})
    return rows.join(ends[0], "v0").join(ends[1], "v1").select("user_id", "start", "x0", "y0", "x1", "y1")


def numbered(segments: DataFrame) -> DataFrame:
    """Add sid from 0 in order of user and start; for a micro-batch, whose rows pass one task."""
    return segments.withColumn("sid", (F.row_number().over(W.orderBy("user_id", "start")) - 1).cast("int"))


def current_interval(moves: DataFrame, intervals: DataFrame) -> DataFrame:
    """Moves (user_id, ts, sid, t) with the interval of their segment that holds t; the intervals are static."""
    rows = moves.join(intervals.select(F.col("sid").alias("_sid"), "ivl", "t_lo", "t_hi"), F.col("sid") == F.col("_sid"))
    last = (F.col("t") == 1) & (F.col("t_hi") >= 1 - 1e-9)
    return rows.filter((F.col("t_lo") <= F.col("t")) & ((F.col("t") < F.col("t_hi")) | last)).select("user_id", "ts", "sid", "t", F.col("ivl").cast("int").alias("ivl"))


CHANGE = "user_id long, ts timestamp, sid int, ivl int, was int"


def interval_changes(moves: DataFrame, forget: str = "7 days") -> DataFrame:
    """A row where a user's interval (user_id, ts, sid, ivl) differs from the one before; `was` is null at first.

    On a stream, the last interval of each user is state that is forgotten after a time
    without moves; rows of a micro-batch are taken in order of time. On a table: a window.
    """
    if not moves.isStreaming:
        w = W.partitionBy("user_id").orderBy("ts", "sid", "ivl")
        rows = moves.withColumns({"was": F.lag("ivl").over(w), "_s": F.lag("sid").over(w)})
        return rows.filter(F.col("was").isNull() | (F.col("was") != F.col("ivl")) | (F.col("_s") != F.col("sid"))).select("user_id", "ts", "sid", "ivl", "was")
    import pandas as pd
    from pyspark.sql.streaming.state import GroupStateTimeout

    days = int(pd.Timedelta(forget).total_seconds() * 1000)

    def run(key, batches, state):
        if state.hasTimedOut:
            state.remove()
            return
        sid, ivl = state.get if state.exists else (None, None)
        rows, out = pd.concat(list(batches)), []
        for r in rows.sort_values(["ts", "sid", "ivl"]).itertuples(index=False):
            if (r.sid, r.ivl) != (sid, ivl):
                out.append((key[0], r.ts, r.sid, r.ivl, ivl))
                sid, ivl = int(r.sid), int(r.ivl)
        state.update((sid, ivl))
        state.setTimeoutTimestamp(max(state.getCurrentWatermarkMs(), int(rows["ts"].max().timestamp() * 1000)) + days)
        frame = pd.DataFrame(out, columns=["user_id", "ts", "sid", "ivl", "was"])
        yield frame.astype({"was": "Int32"})

    return moves.select("user_id", "ts", "sid", "ivl").groupBy("user_id").applyInPandasWithState(run, CHANGE, "sid int, ivl int", "append", GroupStateTimeout.EventTimeTimeout)


def with_answers(changes: DataFrame, answers: DataFrame) -> DataFrame:
    """Changes of interval with the static answers of the new one."""
    return changes.join(answers.select("sid", "ivl", "rank", "home"), ["sid", "ivl"])


def run_to(stream: DataFrame, folder: str, checkpoint: str, mode: str = "append") -> int:
    """Run a stream over what is there into Parquet; a second run adds nothing (exactly once). Returns the rows dropped as late."""
    query = stream.writeStream.format("parquet").option("path", folder).option("checkpointLocation", checkpoint).outputMode(mode).trigger(availableNow=True).start()
    query.awaitTermination()
    return sum(op["numRowsDroppedByWatermark"] for p in query.recentProgress for op in p["stateOperators"])


def answer_trips(stream: DataFrame, answer: Callable[[DataFrame], DataFrame], folder: str, checkpoint: str) -> None:
    """Answer each micro-batch of segments with the batch plan; a batch's folder is overwritten when it runs again."""

    def each(batch: DataFrame, number: int) -> None:
        answer(batch).write.mode("overwrite").parquet(f"{folder}/batch={number}")

    stream.writeStream.foreachBatch(each).option("checkpointLocation", checkpoint).trigger(availableNow=True).start().awaitTermination()
