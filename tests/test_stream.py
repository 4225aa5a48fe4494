"""The stream keeps what the batch computes, and drops what comes too late."""

import random

import numpy as np
from pyspark.sql import functions as F

from catchment.sources import points
from catchment.streaming import influence_stream as stream

SF = "/root/testdata/sf0.001"


def test_stream_equals_batch(spark, tmp_path):
    events = spark.read.parquet(f"{SF}/events.parquet").orderBy("ts").limit(240).withColumn("part", F.ntile(3).over(__import__("pyspark").sql.Window.orderBy("ts")))
    _, f = points.sample(points.point_set(spark, SF, "evt"), 0, 8)
    source = tmp_path / "in"
    rows = events.persist()
    for k in (1, 2, 3):
        rows.filter(F.col("part") == k).drop("part").coalesce(1).write.mode("append").parquet(str(source))
    late = rows.filter("part = 1").orderBy("ts").limit(5).drop("part").withColumn("event_id", F.col("event_id") + 1_000_000)
    late.coalesce(1).write.mode("append").parquet(str(source))
    s = stream.InfluenceStream(spark, f, "1 day")
    s.run(str(source), spark.read.parquet(str(source)).schema)
    batch = stream.windowed_heat(stream.with_windows(stream.arrivals(rows.drop("part"), f), "1 day"))
    assert s.late() == 5
    assert {tuple(r) for r in s.heat().collect()} == {tuple(r) for r in batch.collect()}
    again = stream.InfluenceStream(spark, f, "1 day", root=s.root)
    again.run(str(source), spark.read.parquet(str(source)).schema)
    assert again.late() == 5 and again.heat().count() == batch.count()


def test_sessions(spark):
    rows = [(1, "2024-01-01 00:00:00", 1.0), (2, "2024-01-01 00:20:00", 2.0), (3, "2024-01-01 01:00:00", 3.0), (4, "2024-01-01 01:29:59", 3.5), (5, "2024-01-01 05:00:00", 4.0)]
    events = spark.createDataFrame(rows, "event_id long, ts string, value double").withColumn("ts", F.col("ts").cast("timestamp_ntz"))
    f = spark.createDataFrame([(1, 50, 10, 1)], points.FACILITIES)
    placed = stream.with_windows(stream.arrivals(events, f), "30 minutes", session=True)
    starts = {r["oid"]: r["tile"] for r in placed.collect()}
    assert len(set(starts.values())) == 3 and starts[1] == starts[2] and starts[3] == starts[4]


def test_sessions_of_many_rows(spark):
    """Sessions by their definition, a pause of exactly the gap included; what meets in one task are runs of rows, not rows."""
    rng = random.Random(1)
    for gap in (1, 60, 1800):
        at = sorted([rng.randrange(400_000) for _ in range(900)] + [500_000, 500_000 + gap, 600_000, 600_000 + gap - 1, 600_000 + 2 * gap - 2, 600_000 + 3 * gap - 2])
        rows = spark.createDataFrame(list(enumerate(at)), "oid long, s long").select("oid", F.timestamp_seconds("s").alias("ts"))
        got = {r["oid"]: r["tile"] for r in stream.with_windows(rows, f"{gap} seconds", session=True).collect()}
        want, start = {}, None
        for i, s in enumerate(at):
            start = s if i == 0 or s - at[i - 1] >= gap else start
            want[i] = start
        assert got == want


def test_facility_loads(spark, tmp_path):
    _, f = points.sample(points.point_set(spark, SF, "evt"), 0, 8)
    events = spark.read.parquet(f"{SF}/events.parquet").orderBy("ts").limit(120)
    events.coalesce(1).write.parquet(str(tmp_path / "in"))
    loads = stream.facility_loads(spark.readStream.schema(events.schema).parquet(str(tmp_path / "in")), f, keep_seconds=1 << 40)
    query = loads.writeStream.format("memory").queryName("loads").outputMode("update").option("checkpointLocation", str(tmp_path / "c")).trigger(availableNow=True).start()
    query.awaitTermination()
    placed = stream.arrivals(events, f, with_facility=True).groupBy("nn_fid").count()
    assert {(r["fid"], r["clients"]) for r in spark.table("loads").collect()} == {tuple(r) for r in placed.collect()}


def test_windowed_heat_counts_what_the_sweep_labels(spark):
    """Strips of a few sides, ties, touching and equal squares: the totals are those of the labels themselves."""
    from catchment.operators import strips, sweep

    rng = random.Random(5)
    rows = []
    for i in range(160):
        x, y, r = rng.randrange(40), rng.randrange(40), rng.randrange(1, 12)
        rows.append((i, i % 3, x - r, x + r, y - r, y + r, rng.randrange(1, 4)))
    real = spark.createDataFrame(rows, "oid long, tile long, xl long, xh long, yl long, yh long, n long").dropDuplicates(["tile", "xl", "xh", "yl", "yh"])
    pairs = sweep.changed_pairs(real, sweep.changed_intervals(real)).groupBy("tile").agg(F.count("*"), F.max("n"))
    want = {tuple(r) for r in pairs.collect()}
    assert {tuple(r) for r in strips.label_totals(real, 8).collect()} == want == {tuple(r) for r in strips.label_totals(real).collect()}


def test_windowed_heat_makes_no_labels(spark):
    """A window's labels grow with the square of its rows: 3,000 squares that all meet have millions, its plan has no row for them."""
    rng = random.Random(6)
    rows = [(i, 0, -rng.randrange(1, 10**6), rng.randrange(1, 10**6), -rng.randrange(1, 10**6), rng.randrange(1, 10**6)) for i in range(3_000)]
    found = stream.windowed_heat(spark.createDataFrame(rows, "oid long, tile long, xl long, xh long, yl long, yh long"))
    plan = found._jdf.queryExecution().optimizedPlan().toString()
    assert "MapInArrow" in plan and "Generate" not in plan
    assert found.first()["max_heat"] == 3_000 and found.first()["labels"] > 5_000_000


def test_squares_that_span_groups_are_not_dealt_to_them(spark):
    """Wide squares: what moves grows with the squares, and the totals are those of the labels whatever the groups."""
    from catchment.operators import strips, sweep

    rng = random.Random(9)
    rows = []
    for i in range(300):
        x, y, w, h = rng.randrange(60), rng.randrange(60), rng.randrange(1, 50), rng.randrange(1, 50)
        rows.append((i % 2, x - w, x + w, y - h, y + h, rng.randrange(1, 4)))
    real = spark.createDataFrame(rows, "tile long, xl long, xh long, yl long, yh long, n long").dropDuplicates(["tile", "xl", "xh", "yl", "yh"])
    pairs = sweep.changed_pairs(real, sweep.changed_intervals(real)).groupBy("tile").agg(F.count("*"), F.max("n"))
    want = {tuple(r) for r in pairs.collect()}
    for events, group in ((4, 4), (4, 32), (16, 64), (64, 64)):
        assert {tuple(r) for r in strips.label_totals(real, events, group).collect()} == want
    # 4,000 squares that all cross in 8,000 distinct sides: at most two groups and two ranges hold each, and an own side has one row of a profile
    cuts = strips.cuts_of(spark.createDataFrame([(0, -i, i, -i, i, 1) for i in range(1, 4_001)], "tile long, xl long, xh long, yl long, yh long, n long"), 256)
    assert len(cuts[0]) > 25
    import pyarrow as pa

    i = np.arange(1, 4_001)
    batch = pa.RecordBatch.from_arrays([pa.array(c) for c in (0 * i, -i, i, -i, i, 0 * i + 1)], names=["tile", "xl", "xh", "yl", "yh", "n"])
    dealt = sum(b.num_rows for b in strips._deal_ends(cuts)([batch]))
    sides = list(strips._deal_sides(cuts, cuts)([batch]))
    told = 0
    for strip in range(len(cuts[0]) + 1):
        held = [[b.column(c).to_numpy()[b.column("strip").to_numpy() == strip] for c in ("y", "span", "turn")] for b in sides]
        told += sum(b.num_rows for b in strips._profiles(cuts)(0, [np.concatenate(c) for c in zip(*held)], None, None))
    assert dealt <= 8_000 and sum(b.num_rows for b in sides) == 8_000 and told <= 16_000 + (len(cuts[0]) + 1) ** 2
