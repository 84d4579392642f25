"""Structured Streaming around the searches: a stream of events becomes segments, and meets a stored index.

The queries here run on what a source holds now (``availableNow``) and return the sink's table.
"""

from __future__ import annotations

import time
from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..functions import geometry
from ..operators import timebins
from ..plans import oracle_parts as sql
from ..plans.scenarios import EVENT_EPOCH, EVENT_Z, queries_of, segments
from ..session import shared_folder
from ..sources.tables import table


#: About how many events a file of the stand-in source holds.
FILE_ROWS = 2_000_000


def _files(spark: SparkSession, sf_dir: str, parts: int = 4) -> tuple[str, str]:
    """The events as several files, written one after the other in time order, and their schema: what a stream would find."""
    path = shared_folder(spark, "events")
    events = table(spark, sf_dir, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    lo, hi = events.agg(F.min(F.unix_micros("ts")), F.max(F.unix_micros("ts"))).first()
    if lo is None:
        events.write.parquet(path)
        return path, events.schema
    parts = max(parts, events.count() // FILE_ROWS + 1)
    step = (hi - lo) // parts + 1
    for i in range(parts):
        events.where(F.unix_micros("ts").between(lo + i * step, lo + (i + 1) * step - 1)).coalesce(1).write.mode("append").parquet(path)
        time.sleep(0.01)  # files are read in the order of their times
    return path, events.schema


def source(spark: SparkSession, sf_dir: str, per_trigger: int | None = None) -> DataFrame:
    path, schema = _files(spark, sf_dir)
    reader = spark.readStream.schema(schema)
    if per_trigger:
        reader = reader.option("maxFilesPerTrigger", per_trigger)
    return reader.parquet(path)


def drain(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Runs a stream over what there is and returns its result from shared storage.

    In complete mode each batch writes the whole result anew; the last one counts."""
    spark = stream.sparkSession
    out, mark = shared_folder(spark, "sink"), shared_folder(spark, "stream")
    if mode == "complete":
        last = []

        def keep(batch: DataFrame, number: int) -> None:
            batch.write.mode("overwrite").parquet(f"{out}/{number}")
            last[:] = [number]

        stream.writeStream.foreachBatch(keep).outputMode(mode).trigger(availableNow=True).option("checkpointLocation", mark).start().awaitTermination()
        return spark.read.schema(stream.schema).parquet(f"{out}/{last[0]}") if last else spark.createDataFrame([], stream.schema)
    stream.writeStream.format("parquet").outputMode(mode).trigger(availableNow=True).option("checkpointLocation", mark).start(out).awaitTermination()
    return spark.read.schema(stream.schema).parquet(out)


def points_of(events: DataFrame) -> DataFrame:
    code = F.create_map(*(F.lit(x) for kv in EVENT_Z.items() for x in kv))
    return events.select(
        F.col("user_id").alias("traj_id"), "ts", "event_id", ((F.unix_micros("ts") - EVENT_EPOCH) / F.lit(3600000000.0)).alias("t"), F.col("value").alias("x"), F.get_json_object("props", "$.k").cast("double").alias("y"), (25 * code[F.col("event_type")]).cast("double").alias("z")
    )


_SEG = "traj_id long, seg_id long, t0 double, x0 double, y0 double, z0 double, t1 double, x1 double, y1 double, z1 double"


def _link(key, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
    """Joins each user's new points, in time order, to the last one that was seen."""
    step, *last = state.get if state.exists else (0, None, None, None, None)
    points = pd.concat(list(batches)).sort_values(["t", "event_id"])
    rows = []
    for p in points[["t", "x", "y", "z"]].itertuples(index=False, name=None):
        if last[0] is not None:
            if p[0] > last[0]:
                rows.append((int(key[0]), step, *last, *p))
            step += 1
        last = p
    state.update((step, *map(float, last)))
    if rows:
        yield pd.DataFrame(rows, columns=[c.split()[0] for c in _SEG.split(", ")])


def stream_segments(points: DataFrame) -> DataFrame:
    """Segments as points arrive: the state is one point for each trajectory."""
    return points.groupBy("traj_id").applyInPandasWithState(_link, _SEG, "step long, t double, x double, y double, z double", "append", GroupStateTimeout.NoTimeout)


# ---- registered ----------------------------------------------------------------------------------------------


def st1_source(spark: SparkSession, sf_dir: str) -> DataFrame:
    return drain(source(spark, sf_dir).select("event_id", "user_id", "event_type"))


def st2_watermark(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Daily counts of all closed days.  The watermark holds back what could still change, and drops rows of days that
    are closed: the first week's events, which come a second time in a last file, change nothing."""
    path, schema = _files(spark, sf_dir)
    events = spark.read.schema(schema).parquet(path)
    events.where(F.col("ts") < events.agg(F.min("ts")).first()[0] + F.expr("INTERVAL 7 DAYS")).coalesce(1).write.mode("append").parquet(path)
    e = spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(path).withWatermark("ts", "1 day")
    return drain(e.groupBy(F.window("ts", "1 day")).agg(F.count(F.lit(1)).alias("n"))).select(F.col("window.start").cast("timestamp_ntz").alias("day"), "n")


def _windows(build: Callable[[DataFrame], DataFrame]) -> Callable[[SparkSession, str], DataFrame]:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        return drain(build(source(spark, sf_dir, 2)), "complete")

    return run


st3_tumbling = _windows(lambda e: e.groupBy(F.window("ts", "6 hours")).agg(F.count(F.lit(1)).alias("n")).select(F.col("window.start").cast("timestamp_ntz").alias("start"), "n"))
st3_sliding = _windows(lambda e: e.groupBy(F.window("ts", "12 hours", "6 hours")).agg(F.count(F.lit(1)).alias("n")).select(F.col("window.start").cast("timestamp_ntz").alias("start"), "n"))


def st3_session(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = source(spark, sf_dir).groupBy("user_id", F.session_window("ts", "4 hours")).agg(F.count(F.lit(1)).alias("n"))
    return drain(e, "complete").groupBy("user_id").agg(F.count(F.lit(1)).alias("sessions"), F.sum("n").alias("n"))


def st4_segments(spark: SparkSession, sf_dir: str) -> DataFrame:
    return drain(stream_segments(points_of(source(spark, sf_dir, 1))))


def st5_search(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Arriving segments meet a stored time-bin index, batch by batch."""
    d = segments(spark, sf_dir, "event")
    index = timebins.build(d, 1000)
    out = shared_folder(spark, "found")

    def meet(batch: DataFrame, _number: int) -> None:
        timebins.search(queries_of(batch, "event"), index, 10.0).write.mode("append").parquet(out)

    q = stream_segments(points_of(source(spark, sf_dir, 2))).writeStream.foreachBatch(meet).trigger(availableNow=True).option("checkpointLocation", shared_folder(spark, "stream")).start()
    q.awaitTermination()
    found = spark.read.schema("q_traj long, q_seg long, traj_id long, seg_id long, lo double, hi double").parquet(out)
    return found.withColumn("lo", geometry.rounded(F.col("lo"))).withColumn("hi", geometry.rounded(F.col("hi")))


def st6_interval_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Two streams: errors within an hour after a purchase of the same user."""
    a = source(spark, sf_dir).where("event_type = 'purchase'").select(F.col("user_id").alias("u"), F.col("ts").alias("bought"), F.col("event_id").alias("purchase")).withWatermark("bought", "2 hours")
    b = source(spark, sf_dir).where("event_type = 'error'").select("user_id", F.col("ts").alias("failed"), F.col("event_id").alias("error")).withWatermark("failed", "2 hours")
    met = a.join(b, F.expr("u = user_id AND failed >= bought AND failed <= bought + INTERVAL 1 HOUR"))
    return drain(met.select("purchase", "error"))


def st7_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A replayed source counts once: what comes again within the watermark is known, what comes later is late."""
    path, schema = _files(spark, sf_dir)
    spark.read.schema(schema).parquet(path).where("event_id % 3 = 0").write.mode("append").parquet(path)
    e = spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(path).withWatermark("ts", "2 days").dropDuplicatesWithinWatermark(["event_id"])
    return drain(e.select("event_id"))


def st8_restart(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A stream that is stopped and started again goes on where it was."""
    path, schema = _files(spark, sf_dir)
    out, mark = shared_folder(spark, "sink"), shared_folder(spark, "stream")
    for _ in range(2):
        q = spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(path).select("event_id").writeStream.format("parquet").trigger(availableNow=True).option("checkpointLocation", mark).start(out)
        q.awaitTermination()
    return spark.read.parquet(out)


def st1_rate(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A running source of one file a batch, stopped when all that there is is in the sink."""
    out, mark = shared_folder(spark, "sink"), shared_folder(spark, "stream")
    rows = source(spark, sf_dir, 1).select(F.col("event_id").alias("value"))
    q = rows.writeStream.format("parquet").option("checkpointLocation", mark).start(out)
    try:
        q.processAllAvailable()
    finally:
        q.stop()
    return spark.read.schema("value long").parquet(out)


def queries() -> dict:
    return {f"stream_{k}": f for k, f in globals().items() if k.startswith("st") and k[2:3].isdigit() and callable(f)}


def oracles() -> dict[str, str]:
    return {
        "stream_st1_rate": "SELECT event_id AS value FROM events",
        "stream_st1_source": "SELECT event_id, user_id, event_type FROM events",
        "stream_st2_watermark": "SELECT date_trunc('day', ts)::TIMESTAMP AS day, count(*) AS n FROM events WHERE date_trunc('day', ts) + INTERVAL 1 DAY <= (SELECT max(ts) FROM events) - INTERVAL 1 DAY GROUP BY 1",
        "stream_st3_tumbling": "SELECT time_bucket(INTERVAL 6 HOUR, ts, TIMESTAMP '1970-01-01') AS start, count(*) AS n FROM events GROUP BY 1",
        "stream_st3_sliding": "SELECT start, count(*) AS n FROM (SELECT time_bucket(INTERVAL 6 HOUR, ts, TIMESTAMP '1970-01-01') - k * INTERVAL 6 HOUR AS start FROM events, unnest(range(0, 2)) AS u(k)) GROUP BY 1",
        "stream_st3_session": """SELECT user_id, CAST(sum(fresh) AS BIGINT) AS sessions, count(*) AS n FROM (SELECT user_id, CASE WHEN epoch_us(ts) - epoch_us(lag(ts) OVER (PARTITION BY user_id ORDER BY ts)) <= 14400000000 THEN 0 ELSE 1 END AS fresh FROM events) GROUP BY 1""",
        "stream_st4_segments": f"WITH {sql.ctes('event')} SELECT * FROM d",
        "stream_st5_search": sql.search("event", 10.0),
        "stream_st6_interval_join": "SELECT a.event_id AS purchase, b.event_id AS error FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR WHERE a.event_type = 'purchase' AND b.event_type = 'error'",
        "stream_st7_dedup": "SELECT event_id FROM events",
        "stream_st8_restart": "SELECT event_id FROM events",
    }
