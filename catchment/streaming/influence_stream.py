"""Heat of client arrivals by time window, in batch and as a stream."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.metrics import distance
from ..operators.strips import label_totals
from ..plans.tables import materialize, shared_dir


MARKS = "newest long, late long, batch long"
SQUARES = "oid long, xl long, xh long, yl long, yh long, tile long, batch long"
#: Sides of a strip of a window; squares of arrivals are wide, so fewer strips hold each.
STRIP_EVENTS = 4096
HEAT = "window_start long, clients long, labels long, max_heat long, batch long"


def arrivals(events: DataFrame, facilities: DataFrame, with_facility: bool = False) -> DataFrame:
    """Events as clients (x: value in cents, y: minutes since 2024) with their L-infinity squares; a stream-static join.

    ``facilities`` is a small, checked table (at most 4,096 rows), sent to every task.
    """
    if facilities.limit(4097).count() > 4096:
        raise ValueError("too many facilities for a streaming join")
    places = F.broadcast(facilities.agg(F.sort_array(F.collect_list(F.struct("fid", "fx", "fy"))).alias("places")))
    minutes = F.expr("timestampdiff(MINUTE, timestamp_ntz'2024-01-01 00:00:00', cast(ts as timestamp_ntz))")
    rows = events.select(F.col("event_id").alias("oid"), F.col("ts").cast("timestamp").alias("ts"), F.round(F.col("value") * 100).cast("long").alias("x"), minutes.cast("long").alias("y")).join(places)
    near = F.array_min(F.transform("places", lambda p: F.struct(distance("linf", "x", "y", p["fx"], p["fy"]).alias("d"), p["fid"].alias("fid"))))
    rows = rows.withColumn("near", near).withColumns({"r": F.col("near.d"), "nn_fid": F.col("near.fid")}).drop("near", "places")
    own = ["nn_fid"] if with_facility else []
    return rows.select("oid", "ts", (F.col("x") - F.col("r")).alias("xl"), (F.col("x") + F.col("r")).alias("xh"), (F.col("y") - F.col("r")).alias("yl"), (F.col("y") + F.col("r")).alias("yh"), *own)


def with_windows(squares: DataFrame, size: str, slide: str | None = None, session: bool = False) -> DataFrame:
    """Squares with the start of each window they fall in (as ``tile``, epoch seconds); ``size`` is the gap of a session."""
    if not session:
        return squares.withColumn("tile", F.unix_timestamp(F.window("ts", size, slide or size)["start"]))
    # a session may hold any number of rows, so rows look theirs up by the hours that it spans
    second = F.unix_timestamp("ts")
    # rows of one tumbling window of the gap's size are of one session, so one row for each window meets the others in the sort of all sessions
    runs = squares.groupBy(F.window(F.timestamp_seconds(second), size)).agg(F.min(second).alias("begin"), F.max(second).alias("last"))
    # Spark joins what touches; a pause of the gap's size ends a session, so a run reaches a millisecond less far
    reach = F.expr(f"(unix_timestamp(timestamp_seconds(last) + interval {size}) - begin) * 1000 - 1")
    runs = runs.withColumn("gap", F.concat(reach, F.lit(" milliseconds")))
    spans = runs.groupBy(F.session_window(F.timestamp_seconds("begin"), F.col("gap")).alias("s")).agg(F.max("last").alias("last")).select(F.unix_timestamp("s.start").alias("tile"), "last")
    spans = materialize(spans, "sessions").withColumn("hour", F.explode(F.expr("sequence(tile div 3600, last div 3600)")))
    return squares.withColumn("at", second).withColumn("hour", F.expr("at div 3600")).join(spans, "hour").filter("at between tile and last").drop("at", "hour", "last")


def windowed_heat(squares: DataFrame) -> DataFrame:
    """(window_start, clients, labels, max_heat): the changed-interval sweep of every window's squares, windows and
    strips of them in parallel. Labels are counted, not made: they grow with the square of a window's rows."""
    counts = squares.groupBy("tile").agg(F.count("*").alias("clients"))
    real = materialize(squares.filter("xl < xh").groupBy("tile", "xl", "xh", "yl", "yh").agg(F.count("*").alias("n")), "windows")
    heat = label_totals(real, STRIP_EVENTS)
    return counts.join(heat, "tile", "left").select(F.col("tile").alias("window_start"), "clients", F.coalesce("labels", F.lit(0)).alias("labels"), F.coalesce("max_heat", F.lit(0)).alias("max_heat"))


class InfluenceStream:
    """A file stream of events kept as squares by window; each micro-batch recomputes the windows it touches.

    Rows older than the newest time seen before a batch less ``watermark_seconds`` are dropped and counted. Squares, heat and
    each batch's newest time and late rows lie under ``root`` in the shared folder, by batch: a batch that
    runs again after a failure writes its own folders anew, and a stream started again on the same root goes on where it was.
    """

    def __init__(self, spark, facilities: DataFrame, size: str, slide: str | None = None, watermark_seconds: int = 3600, root: str | None = None):
        self.spark, self.facilities, self.size, self.slide, self.delay = spark, facilities, size, slide, watermark_seconds
        self.root = root or f"{shared_dir(spark)}/influence-stream-{uuid.uuid4().hex}"

    def _read(self, name: str, schema: str, before: int | None = None) -> DataFrame:
        """A kept table with its batch; empty before the first one."""
        path = self.spark._jvm.org.apache.hadoop.fs.Path(f"{self.root}/{name}")
        if not path.getFileSystem(self.spark._jsc.hadoopConfiguration()).exists(path):
            return self.spark.createDataFrame([], schema)
        kept = self.spark.read.schema(schema).parquet(f"{self.root}/{name}")
        return kept if before is None else kept.filter(F.col("batch") < before)

    def _keep(self, rows: DataFrame, name: str, number: int) -> None:
        rows.write.mode("overwrite").parquet(f"{self.root}/{name}/batch={number}")

    def _batch(self, rows: DataFrame, number: int) -> None:
        newest = self._read("marks", MARKS, number).agg(F.max("newest")).first()[0]
        at = F.unix_timestamp(F.col("ts").cast("timestamp"))
        late = at < (newest - self.delay) if newest is not None else F.lit(False)
        told = rows.select(F.max(F.when(~late, at)).alias("newest"), F.coalesce(F.sum(late.cast("long")), F.lit(0)).alias("late"))
        self._keep(told, "marks", number)
        placed = with_windows(arrivals(rows.filter(~late), self.facilities), self.size, self.slide)
        self._keep(placed.drop("ts"), "squares", number)
        kept = self._read("squares", SQUARES)
        touched = kept.filter(F.col("batch") == number).select("tile").distinct()
        self._keep(windowed_heat(kept.join(touched, "tile", "left_semi").dropDuplicates(["tile", "oid"])), "heat", number)

    def heat(self) -> DataFrame:
        """(window_start, clients, labels, max_heat) as of the last batch that touched each window."""
        rows = self._read("heat", HEAT)
        return rows.groupBy("window_start").agg(F.max_by(F.struct("clients", "labels", "max_heat"), "batch").alias("h")).select("window_start", "h.*")

    def late(self) -> int:
        """How many rows came too late."""
        return self._read("marks", MARKS).agg(F.coalesce(F.sum("late"), F.lit(0))).first()[0]

    def run(self, path: str, schema, files_per_batch: int = 1) -> None:
        """Read all files there are, batch by batch, and stop."""
        source = self.spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_batch).parquet(path)
        query = source.writeStream.foreachBatch(self._batch).option("checkpointLocation", f"{self.root}/progress").trigger(availableNow=True).start()
        query.awaitTermination()


def facility_loads(events: DataFrame, facilities: DataFrame, keep_seconds: int = 86_400) -> DataFrame:
    """A stream's live clients by nearest facility: (fid, clients, newest), a row whenever a facility's load changes.

    ``events`` is a stream of (event_id, ts, value). State by facility holds a count for each hour, so it is bounded by the
    hours kept, not by clients; hours older than ``keep_seconds`` before the facility's newest event are dropped.
    """
    import pandas as pd

    placed = arrivals(events, facilities, with_facility=True).select("nn_fid", F.unix_timestamp("ts").alias("at"))

    def load(key, batches, state):
        hours, newest = (dict(zip(state.get[0], state.get[1])), state.get[2]) if state.exists else ({}, 0)
        for rows in batches:
            newest = max(newest, int(rows["at"].max()))
            for hour, count in (rows["at"] // 3600).value_counts().items():
                hours[int(hour)] = hours.get(int(hour), 0) + int(count)
        hours = {h: c for h, c in hours.items() if (h + 1) * 3600 > newest - keep_seconds}
        state.update((list(hours), list(hours.values()), newest))
        yield pd.DataFrame({"fid": [key[0]], "clients": [sum(hours.values())], "newest": [newest]})

    return placed.groupBy("nn_fid").applyInPandasWithState(load, "fid long, clients long, newest long", "hours array<long>, counts array<long>, newest long", "update", "NoTimeout")
