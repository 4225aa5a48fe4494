"""Nearest-neighbour circles, RNN sets of facilities and of query points."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.metrics import distance, reach, turned
from ..plans.tables import materialize

#: The most facilities that go to every task as one array; beyond it the tree of cells is used.
BROADCAST_FACILITIES = 1024
#: The tree's first level has at most 4**TOP cells; every later one cuts a cell into 4**STEP.
TOP, STEP = 3, 2


def spread(rows: DataFrame) -> DataFrame:
    """Rows over all cores, where a small table came in fewer parts than these: work on a row is much, its bytes are few."""
    cores = rows.sparkSession.sparkContext.defaultParallelism
    return rows.repartition(cores)


def _nearest_small(clients: DataFrame, facilities: DataFrame, metric: str) -> DataFrame:
    """Every client row against the array of all facilities: nothing is shuffled or sorted by client."""
    places = facilities.agg(F.sort_array(F.collect_list(F.struct("fid", "fx", "fy"))).alias("places"))
    near = F.array_min(F.transform("places", lambda p: F.struct(distance(metric, "x", "y", p["fx"], p["fy"]).alias("d"), p["fid"].alias("fid"))))
    met = spread(clients).join(F.broadcast(places), F.lit(True)).withColumn("b", near)
    return met.withColumns({"r": F.col("b.d"), "nn_fid": F.col("b.fid")}).drop("b", "places")


def _nearest_tree(clients: DataFrame, facilities: DataFrame, metric: str, mono: bool, top: int = TOP, step: int = STEP) -> DataFrame:
    """Clients descend a tree of cells over the facilities, as (oid, r, nn_fid).

    A cell shows two of its facilities, so each level gives a client a distance that is surely reached; it goes on
    into the cells that could hold something as near, and is done when none is left that holds several
    places. A client meets a few cells a level, however many facilities lie in one spot: crowded cells are cut
    further. With ``mono`` clients are the facilities and a point is not its own neighbour.
    """
    box = facilities.agg(F.min("fx"), F.min("fy"), F.greatest(F.max("fx") - F.min("fx"), F.max("fy") - F.min("fy"))).first()
    if box[0] is None:
        raise ValueError("no facilities")
    x0, y0, shift = box[0], box[1], max(0, int(box[2]).bit_length())
    places = facilities.groupBy("fx", "fy").agg(F.min("fid").alias("fid"), F.max("fid").alias("fid2"))
    place = F.struct("fid", "fid2", "fx", "fy")
    left, done, cut = None, None, min(top, shift)
    while True:
        shift -= cut
        at = lambda c, low: F.shiftright(F.col(c) - low, shift)  # noqa: E731, B023
        cells = places.groupBy(at("fx", x0).alias("gx"), at("fy", y0).alias("gy")).agg(F.count("*").alias("c"), F.min(place).alias("a"), F.max(place).alias("z"))
        if left is None:
            met = spread(clients.select("oid", "x", "y")).join(F.broadcast(cells), F.lit(True)).withColumn("best", F.lit(None).cast("struct<d:bigint,fid:bigint>"))
        else:
            kids = materialize(cells, "cells").withColumns({"px": F.shiftright("gx", cut), "py": F.shiftright("gy", cut)})
            asked = left.select("oid", "x", "y", "best", F.explode("front").alias("f")).select("oid", "x", "y", "best", F.col("f.gx").alias("px"), F.col("f.gy").alias("py"))
            met = asked.join(kids, ["px", "py"])
        own = lambda p: F.when((F.col(f"{p}.fid") != F.col("oid")) | (F.col(f"{p}.fid2") != F.col("oid")), F.struct(distance(metric, "x", "y", f"{p}.fx", f"{p}.fy").alias("d"), F.when(F.col(f"{p}.fid") != F.col("oid"), F.col(f"{p}.fid")).otherwise(F.col(f"{p}.fid2")).alias("fid")))
        seen = F.least(own("a"), own("z")) if mono else F.struct(distance(metric, "x", "y", "a.fx", "a.fy").alias("d"), F.col("a.fid").alias("fid"))
        low = lambda c, g, base: (F.col(g) * (1 << shift) + base, c)  # noqa: E731, B023
        gap = lambda c, g, base: F.greatest(F.lit(0).cast("long"), low(c, g, base)[0] - F.col(c), F.col(c) - low(c, g, base)[0] - ((1 << shift) - 1))  # noqa: E731, B023
        bound = reach(metric, gap("x", "gx", x0), gap("y", "gy", y0))
        met = met.select("oid", "x", "y", F.least("best", seen).alias("best"), F.when(F.col("c") > 1, F.struct(bound.alias("low"), "gx", "gy")).alias("kid"))
        state = met.groupBy("oid", "x", "y").agg(F.min("best").alias("best"), F.collect_list("kid").alias("front"))
        state = materialize(state.withColumn("front", F.filter("front", lambda k: F.col("best.d").isNull() | (k["low"] <= F.col("best.d")))), "nearest")
        found = state.filter("size(front) = 0 and best is not null").select("oid", F.col("best.d").alias("r"), F.col("best.fid").alias("nn_fid"))
        done = found if done is None else done.unionByName(found)
        left = state.filter("size(front) > 0")
        if not shift or left.isEmpty():
            return done
        cut = min(step, shift)


def nn_circles(clients: DataFrame, facilities: DataFrame, metric: str = "linf", strategy: str = "auto") -> DataFrame:
    """Circles of clients: oid, cx, cy, weight, grp, nn_fid, r (squared for L2), and the box xl, xh, yl, yh.

    For L1 centre and box are in turned coordinates. Ties go to the least facility id. ``auto`` sends up to
    ``BROADCAST_FACILITIES`` facilities (counted) to every task and descends a tree of cells beyond; no facility is an error.
    """
    if strategy == "auto":
        n = facilities.limit(BROADCAST_FACILITIES + 1).count()
        if not n:
            raise ValueError("no facilities")
        strategy = "broadcast" if n <= BROADCAST_FACILITIES else "lattice"
    if strategy == "broadcast":
        return boxes(_nearest_small(clients, facilities.select("fid", "fx", "fy"), metric), metric)
    found = _nearest_tree(clients, facilities.select("fid", "fx", "fy"), metric, False)
    return boxes(clients.join(found, "oid"), metric)


def nn_circles_mono(points: DataFrame, metric: str = "linf") -> DataFrame:
    """Circles when clients are the facilities: a point's nearest other point; points at one place get radius 0."""
    as_f = points.select(F.col("oid").alias("fid"), F.col("x").alias("fx"), F.col("y").alias("fy"))
    found = _nearest_tree(points, as_f, metric, True)
    return boxes(points.join(found, "oid"), metric)


def boxes(rows: DataFrame, metric: str) -> DataFrame:
    rows = turned(rows) if metric == "l1" else rows
    rows = rows.withColumnsRenamed({"x": "cx", "y": "cy"})
    if metric == "l2":
        return rows
    return rows.withColumns({"xl": F.col("cx") - F.col("r"), "xh": F.col("cx") + F.col("r"), "yl": F.col("cy") - F.col("r"), "yh": F.col("cy") + F.col("r")})


def canonical(circles: DataFrame) -> DataFrame:
    """Boxes of positive area, equal boxes as one: oid (least), members, n (how many), weight, box."""
    real = circles.filter((F.col("xl") < F.col("xh")) & (F.col("yl") < F.col("yh")))
    return real.groupBy("xl", "xh", "yl", "yh").agg(F.min("oid").alias("oid"), F.sort_array(F.collect_list("oid")).alias("members"), F.count("*").alias("n"), F.sum("weight").cast("long").alias("weight"))


def rnn_of_facilities(clients: DataFrame, facilities: DataFrame, circles: DataFrame, metric: str) -> DataFrame:
    """(fid, rnn): every facility at a client's least distance has that client; facilities without clients have an empty set.

    Such a facility lies on the border of the client's circle, so the two meet in a cell of the circle's size.
    """
    half = F.ceil(F.sqrt(F.col("r").cast("double"))).cast("long") + 1 if metric == "l2" else F.col("r")
    c = clients.select("oid", "x", "y").join(circles.select("oid", "r"), "oid").withColumn("half", half)
    around = {"xl": F.col("x") - F.col("half"), "xh": F.col("x") + F.col("half"), "yl": F.col("y") - F.col("half"), "yh": F.col("y") + F.col("half")}
    met = stabbed(facilities.select("fid", "fx", "fy"), c.withColumns(around), "fx", "fy").filter(distance(metric, "x", "y", "fx", "fy") == F.col("r"))
    sets = met.groupBy("fid").agg(F.sort_array(F.collect_list("oid")).alias("rnn"))
    return facilities.select("fid").join(sets, "fid", "left").select("fid", F.coalesce("rnn", F.array().cast("array<long>")).alias("rnn"))


def size_level(*extents):
    """The least e for which every extent is at most 2**e."""
    widest = F.greatest(*extents, F.lit(1)) if len(extents) > 1 else F.greatest(extents[0], F.lit(1))
    return F.length(F.bin(widest - 1)) - F.when(widest == 1, 1).otherwise(0)


def distinct_levels(rows: DataFrame, level) -> list[int]:
    """The size levels that occur, at most 64 numbers."""
    return sorted(r for r in rows.agg(F.collect_set(level.cast("int"))).first()[0])


def stabbed(points: DataFrame, boxes: DataFrame, x: str, y: str, own: tuple[str, ...] = ()) -> DataFrame:
    """Points joined with the closed boxes (xl, xh, yl, yh) that hold them; both with equal ``own`` columns.

    A box is put into the at most four cells of its own size that it meets, a point looks into one cell of each
    size that occurs; so neither very large nor crowded small boxes make a point meet many that miss it. Rows are far more
    than the tables that they come from, so neither side may be broadcast by the size of its table.
    """
    level = size_level(F.col("xh") - F.col("xl"), F.col("yh") - F.col("yl"))
    levels = distinct_levels(boxes, level)
    if not levels:
        return points.join(boxes.drop(*own), F.lit(False))
    cells = lambda lo, hi: F.explode(F.expr(f"sequence(shiftright({lo}, _e), shiftright({hi}, _e))"))
    dealt = boxes.withColumn("_e", level.cast("int")).withColumn("_gx", cells("xl", "xh")).withColumn("_gy", cells("yl", "yh"))
    asked = points.withColumn("_e", F.explode(F.array(*map(F.lit, levels)))).withColumns({"_gx": F.expr(f"shiftright({x}, _e)"), "_gy": F.expr(f"shiftright({y}, _e)")})
    return asked.hint("merge").join(dealt, [*own, "_e", "_gx", "_gy"]).filter(f"{x} between xl and xh and {y} between yl and yh").drop("_e", "_gx", "_gy")


def meeting(boxes: DataFrame, own: tuple[str, ...] = ()) -> DataFrame:
    """Pairs of closed boxes (oid, xl, xh, yl, yh, others) that meet, once each, columns prefixed a_ and b_, a_oid < b_oid.

    Two boxes meet in cells of the larger one's size, so a box is put into at most four cells for each size from its own on.
    """
    level = size_level(F.col("xh") - F.col("xl"), F.col("yh") - F.col("yl"))
    levels = distinct_levels(boxes, level)
    every = F.array(*map(F.lit, levels)) if levels else F.array().cast("array<int>")
    cells = lambda lo, hi: F.explode(F.expr(f"sequence(shiftright({lo}, _e), shiftright({hi}, _e))"))
    dealt = boxes.withColumn("_own", level.cast("int")).withColumn("_e", F.explode(F.filter(every, lambda e: e >= F.col("_own")))).withColumn("_gx", cells("xl", "xh")).withColumn("_gy", cells("yl", "yh"))
    key = [*own, "_e", "_gx", "_gy"]
    side = lambda p: dealt.select(*key, *[F.col(c).alias(f"{p}_{c}") for c in dealt.columns if c not in key])
    met = side("a").hint("merge").join(side("b"), key).filter("a_oid < b_oid and _e = greatest(a__own, b__own)")
    met = met.filter("a_xl <= b_xh and b_xl <= a_xh and a_yl <= b_yh and b_yl <= a_yh and _gx = shiftright(greatest(a_xl, b_xl), _e) and _gy = shiftright(greatest(a_yl, b_yl), _e)")
    return met.drop("_e", "_gx", "_gy", "a__own", "b__own")


def rnn_of_points(circles: DataFrame, queries: DataFrame, closed: bool = True) -> DataFrame:
    """(qid, rnn) by enclosure. ``closed`` counts the border."""
    met = stabbed(queries.select("qid", "x", "y"), circles.select("oid", "xl", "xh", "yl", "yh"), "x", "y")
    if not closed:
        met = met.filter("x > xl and x < xh and y > yl and y < yh")
    found = met.groupBy("qid").agg(F.sort_array(F.collect_list("oid")).alias("rnn"))
    return queries.select("qid").join(found, "qid", "left").select("qid", F.coalesce("rnn", F.array().cast("array<long>")).alias("rnn"))


def rnn_by_definition(clients: DataFrame, circles: DataFrame, queries: DataFrame, metric: str, most: int = 4096) -> DataFrame:
    """(qid, rnn) by the definition: clients no farther from the query than from their nearest facility.

    The reference for all other ways: all pairs of clients and distinct places of queries. At most ``most`` places go
    to every task at a time, so any number of them can be asked for; only time grows.
    """
    places = materialize(queries.select(F.col("x").alias("qx"), F.col("y").alias("qy")).distinct(), "places")
    parts = -(-places.count() // most)
    part = F.pmod(F.xxhash64("qx", "qy"), F.lit(max(1, parts)))
    c = spread(clients.select("oid", "x", "y").join(circles.select("oid", "r"), "oid"))
    met = None
    for i in range(max(1, parts)):
        near = c.join(F.broadcast(places.filter(part == i)), distance(metric, "x", "y", "qx", "qy") <= F.col("r")).select("qx", "qy", "oid")
        met = near if met is None else met.unionByName(near)
    found = met.groupBy("qx", "qy").agg(F.sort_array(F.collect_list("oid")).alias("rnn"))
    asked = queries.select("qid", F.col("x").alias("qx"), F.col("y").alias("qy"))
    return asked.join(found, ["qx", "qy"], "left").select("qid", F.coalesce("rnn", F.array().cast("array<long>")).alias("rnn"))


def set_text(column: str = "rnn"):
    return F.array_join(F.transform(column, lambda i: i.cast("string")), ",")
