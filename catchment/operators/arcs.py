"""Arc sweep for discs (L2).

Events are left and right extremes, crossings, and optionally centres; between two events arcs do not cross, so their
order at the middle of a slab is their order throughout it. Coordinates of events are rounded to 1e-6; whether discs cross is
decided on integers. All circles of one facility meet exactly there, so that point is taken as it is and the
other crossing is its mirror image; a vertex may thus lie on any number of circles.

Two ways lead to labels. ``label_arcs`` keeps the whole status of every slab and orders it, like a sweep line; it is
quadratic in rows. ``vertex_labels`` makes the same labels where they arise: right of an event point the arcs that meet
there follow each other by slope, then curvature, and the set below them is the point's depth less what ends or starts there.
So its rows are event points times the discs over them.

The integer test squares a difference of squared lengths: points must lie on a lattice of at most 20,000 units
(``rescaled``), which keeps it within 64 bits.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..plans.tables import materialize
from .circles import meeting, stabbed

MICRO = 1_000_000


def rescaled(points: DataFrame, x: str, y: str, extent: int, x0: int, y0: int, units: int = 20_000) -> DataFrame:
    """Points on the lattice 0..units by integer division; ``extent`` is the larger side of the whole set's box."""
    step = lambda c, low: F.expr(f"(({c} - {low}) * {units}) div {max(1, extent)}")
    return points.withColumns({x: step(x, x0), y: step(y, y0)})


def _own(d: DataFrame) -> list[str]:
    """The run that discs belong to, where several arrangements share a table."""
    return ["tile"] if "tile" in d.columns else []


def discs(circles: DataFrame, facilities: DataFrame) -> DataFrame:
    """Discs of positive radius, equal ones as one: oid (least), n, cx, cy, r2, nn_fid and its place fx, fy."""
    own = _own(circles)
    one = circles.filter("r > 0").groupBy(*own, "cx", "cy", F.col("r").alias("r2")).agg(F.min("oid").alias("oid"), F.count("*").alias("n"), F.sum("weight").cast("long").alias("weight"), F.min("nn_fid").alias("nn_fid"))
    return one.join(facilities.select(*own, F.col("fid").alias("nn_fid"), "fx", "fy"), [*own, "nn_fid"])


def _boxed(d: DataFrame) -> DataFrame:
    half = F.ceil(F.sqrt(F.col("r2").cast("double"))).cast("long")
    return d.withColumns({"xl": F.col("cx") - half, "xh": F.col("cx") + half, "yl": F.col("cy") - half, "yh": F.col("cy") + half})


def crossing_pairs(d: DataFrame) -> DataFrame:
    """Pairs of discs whose borders meet in two points, found through their boxes, decided on integers."""
    own = _own(d)
    met = meeting(_boxed(d.select(*own, "oid", "cx", "cy", "r2", "nn_fid", "fx", "fy")), tuple(own))
    met = met.withColumn("d2", F.expr("(a_cx - b_cx) * (a_cx - b_cx) + (a_cy - b_cy) * (a_cy - b_cy)"))
    return met.filter("d2 > 0 and (d2 - a_r2 - b_r2) * (d2 - a_r2 - b_r2) < 4 * a_r2 * b_r2")


def arc_vertices(d: DataFrame) -> DataFrame:
    """(vx, vy, oid) in millionths: every crossing point with every disc border through it."""
    own = _own(d)
    pairs = crossing_pairs(d)
    t = F.expr("((a_fx - a_cx) * (b_cx - a_cx) + (a_fy - a_cy) * (b_cy - a_cy)) / cast(d2 as double)")
    shared = F.array(F.struct(F.col("a_fx").cast("double").alias("x"), F.col("a_fy").cast("double").alias("y")), F.struct((2 * (F.col("a_cx") + t * (F.col("b_cx") - F.col("a_cx"))) - F.col("a_fx")).alias("x"), (2 * (F.col("a_cy") + t * (F.col("b_cy") - F.col("a_cy"))) - F.col("a_fy")).alias("y")))
    s = F.expr("(d2 + a_r2 - b_r2) / (2.0D * d2)")
    h = F.expr("sqrt(greatest(0.0D, 4.0D * a_r2 * d2 - (d2 + a_r2 - b_r2) * cast(d2 + a_r2 - b_r2 as double))) / (2.0D * d2)")
    root = lambda sign: F.struct((F.col("a_cx") + s * (F.col("b_cx") - F.col("a_cx")) + sign * h * (F.col("b_cy") - F.col("a_cy"))).alias("x"), (F.col("a_cy") + s * (F.col("b_cy") - F.col("a_cy")) - sign * h * (F.col("b_cx") - F.col("a_cx"))).alias("y"))
    points = F.when(F.col("a_nn_fid") == F.col("b_nn_fid"), shared).otherwise(F.array(root(1), root(-1)))
    rows = pairs.select(*own, F.explode(points).alias("p"), F.array("a_oid", "b_oid").alias("o"))
    micro = lambda c: F.round(F.col(c) * MICRO).cast("long")
    return rows.select(*own, micro("p.x").alias("vx"), micro("p.y").alias("vy"), F.explode("o").alias("oid")).distinct()


def left_extremes(d: DataFrame) -> DataFrame:
    """(vx, vy, oid) in millionths: where each disc begins."""
    return d.select(*_own(d), F.round((F.col("cx") - F.sqrt(F.col("r2").cast("double"))) * MICRO).cast("long").alias("vx"), (F.col("cy") * MICRO).alias("vy"), "oid")


def vertex_labels(d: DataFrame, vertices: DataFrame | None = None) -> DataFrame:
    """The labels of the arc sweep, made at its event points: (vx, vy, pos, n, weight), pos counting pairs upward.

    ``d`` is a written table (it is read several times). An event point is a left extreme or a crossing. A disc that begins there has two
    arcs to its right, one that ends there has none, any other one has one.
    """
    own = _own(d)
    at = [*own, "vx", "vy"]
    on = (arc_vertices(d) if vertices is None else vertices).select(*at, "oid").unionByName(left_extremes(d)).distinct()
    own_disc = d.select(*own, "oid", "cx", "cy", "r2", "n", "weight")
    on = on.join(own_disc, [*own, "oid"]).withColumns({"dx": F.col("vx") - F.col("cx") * MICRO, "dy": F.col("vy") - F.col("cy") * MICRO})
    rise = F.when(F.col("dy") != 0, F.col("dy"))
    slope = (-F.col("dx") / rise).alias("slope")
    bend = (-F.col("r2") / F.pow(rise / F.lit(float(MICRO)), F.lit(3.0))).alias("bend")
    arc = lambda a, b, up: F.struct(a.alias("slope"), b.alias("bend"), F.lit(up).alias("up"))
    ends = lambda sign: F.lit(sign * float("inf"))
    starts = F.array(arc(ends(-1), F.col("r2") * 0.0, -1), arc(ends(1), F.col("r2") * 0.0, 1))
    one = F.array(F.struct(slope, bend, F.when(F.col("dy") > 0, 1).otherwise(-1).alias("up")))
    arcs = on.withColumn("arcs", F.when(F.col("dy") != 0, one).when(F.col("dx") < 0, starts).otherwise(F.array().cast("array<struct<slope:double,bend:double,up:int>>")))
    passing = F.when((F.col("dy") > 0), 1).otherwise(0)
    here = arcs.groupBy(*at).agg(*[F.sum(F.col(m) * (passing - 1)).alias(f"{m}_less") for m in ("n", "weight")])
    spots = here.select(*at, F.expr(f"vx div {MICRO} - if(vx % {MICRO} < 0, 1, 0)").alias("qx"), F.expr(f"vy div {MICRO} - if(vy % {MICRO} < 0, 1, 0)").alias("qy"))
    grown = _boxed(own_disc).withColumns({"xl": F.col("xl") - 1, "yl": F.col("yl") - 1})
    near = F.expr(f"pow(vx / {float(MICRO)}D - cx, 2) + pow(vy / {float(MICRO)}D - cy, 2) < r2 + 3e-6D * sqrt(cast(r2 as double))")
    depth = stabbed(spots, grown.withColumnRenamed("oid", "over"), "qx", "qy", tuple(own)).filter(near).groupBy(*at).agg(*[F.sum(m).alias(f"{m}_over") for m in ("n", "weight")])
    each = arcs.select(*at, "oid", "n", "weight", F.explode("arcs").alias("arc")).select(*at, "oid", "n", "weight", "arc.*")
    order = Window.partitionBy(*at).orderBy("slope", "bend", "up", "oid")
    run = order.rowsBetween(Window.unboundedPreceding, 0)
    each = each.withColumns({f"{m}_run": F.sum(-F.col("up") * F.col(m)).over(run) for m in ("n", "weight")} | {"pos": F.row_number().over(order), "last": F.lead("oid").over(order).isNull()})
    found = each.filter("not last").join(here, at).join(depth, at)
    return found.select(*at, "pos", *[(F.col(f"{m}_over") + F.col(f"{m}_less") + F.col(f"{m}_run")).alias(m) for m in ("n", "weight")])


def arc_events(d: DataFrame, vertices: DataFrame, centre_events: bool = True) -> DataFrame:
    """(x, slab, x1) in millionths, in order; the last has no x1."""
    edge = lambda s: F.round((F.col("cx") + s * F.sqrt(F.col("r2").cast("double"))) * MICRO).cast("long")
    xs = d.select(F.explode(F.array(edge(-1), edge(1), *([F.col("cx") * MICRO] if centre_events else []))).alias("x"))
    xs = xs.unionByName(vertices.select(F.col("vx").alias("x"))).distinct()
    w = Window.partitionBy(F.lit(0)).orderBy("x")
    return xs.withColumns({"slab": F.row_number().over(w), "x1": F.lead("x").over(w)})


def arc_status(d: DataFrame, events: DataFrame, vertices: DataFrame | None = None) -> DataFrame:
    """(slab, x, x1, rank, oid, up, ys, yl, ym, n, weight): arcs of every slab from bottom to top by their height at its middle.

    ys and yl, an arc's least and largest height in the slab, are worked out anew for every slab from its two ends,
    where an arc that is cut at centres has them. Arcs that meet at an event have its height there.
    """
    edge = lambda s: F.round((F.col("cx") + s * F.sqrt(F.col("r2").cast("double"))) * MICRO).cast("long")
    marks = events.select("x", "slab")
    live = d.withColumns({"left": edge(-1), "right": edge(1)}).join(marks.select(F.col("x").alias("left"), F.col("slab").alias("first")), "left").join(marks.select(F.col("x").alias("right"), F.col("slab").alias("past")), "right")
    live = live.filter("first < past").withColumn("slab", F.explode(F.expr("sequence(first, past - 1)"))).join(events.filter("x1 is not null"), "slab")
    mid = F.expr(f"(x + x1) / {2.0 * MICRO}D")
    rise = F.sqrt(F.greatest(F.lit(0.0), F.col("r2") - F.pow(mid - F.col("cx"), 2)))
    arcs = live.withColumn("up", F.explode(F.array(F.lit(-1), F.lit(1)))).withColumn("ym", F.col("cy") + F.col("up") * rise)
    extremes = d.select(F.explode(F.array(edge(-1), edge(1))).alias("vx"), (F.col("cy") * MICRO).alias("vy"), "oid")
    ends = (extremes if vertices is None else vertices.select("vx", "vy", "oid").unionByName(extremes)).join(d.select("oid", "cy"), "oid")
    side = F.signum((F.col("vy") - F.col("cy") * MICRO).cast("double")).cast("int")
    ends = ends.withColumn("up", F.explode(F.when(side == 0, F.array(F.lit(-1), F.lit(1))).otherwise(F.array(side)))).groupBy("vx", "oid", "up").agg((F.max("vy") / float(MICRO)).alias("held"))
    for c, name in (("x", "h0"), ("x1", "h1")):
        free = F.col("cy") + F.col("up") * F.sqrt(F.greatest(F.lit(0.0), F.col("r2") - F.pow(F.col(c) / float(MICRO) - F.col("cx"), 2)))
        arcs = arcs.join(ends.withColumnRenamed("vx", c), [c, "oid", "up"], "left").withColumn(name, F.coalesce("held", free)).drop("held")
    arcs = arcs.withColumns({"ys": F.least("h0", "h1"), "yl": F.greatest("h0", "h1")})
    order = Window.partitionBy("slab").orderBy("ym", "up", "oid")
    return arcs.withColumn("rank", F.row_number().over(order)).select("slab", "x", "x1", "rank", "oid", "up", "ys", "yl", "ym", "n", "weight", F.round((F.col("cx") - F.sqrt(F.col("r2").cast("double"))) * MICRO).cast("long").alias("left"), "cy")


def order_mismatches(status: DataFrame) -> DataFrame:
    """(arcs, mismatches): arcs whose rank by least, then largest, then middle height is not their rank by middle height."""
    w = Window.partitionBy("slab").orderBy("ys", "yl", "ym", "up", "oid")
    return status.withColumn("other", F.row_number().over(w)).agg(F.count("*").alias("arcs"), F.coalesce(F.sum((F.col("other") != F.col("rank")).cast("long")), F.lit(0)).alias("mismatches"))


def label_arcs(d: DataFrame, changed_only: bool = True, centre_events: bool = True, vertices: DataFrame | None = None) -> DataFrame:
    """Labels of the arc sweep: (slab, x, x1, rank, y0, y1, n, weight); y0 and y1 are the arcs' heights at mid-slab.

    With ``changed_only`` just pairs within changed ranks: at a left extreme its own two arcs, at a crossing
    the arcs that meet there; right extremes and centres change nothing. Otherwise all pairs of all slabs.
    """
    vertices = materialize(arc_vertices(d), "vertices") if vertices is None else vertices
    events = materialize(arc_events(d, vertices, centre_events), "events")
    status = arc_status(d, events)
    w = Window.partitionBy("slab").orderBy("rank")
    run = w.rowsBetween(Window.unboundedPreceding, 0)
    pairs = status.withColumns({"heat_n": F.sum(-F.col("up") * F.col("n")).over(run), "heat_w": F.sum(-F.col("up") * F.col("weight")).over(run), "y1": F.lead("ym").over(w)}).filter("y1 is not null")
    pairs = pairs.select("slab", "x", "x1", "rank", F.col("ym").alias("y0"), "y1", F.col("heat_n").alias("n"), F.col("heat_w").alias("weight"))
    if not changed_only:
        return pairs
    own = status.filter("left = x").groupBy("slab", "oid").agg(F.min("rank").alias("lo"), F.max("rank").alias("hi")).select("slab", "lo", "hi")
    at = vertices.withColumnRenamed("vx", "x").join(status.select("slab", "x", "rank", "oid", "up", "cy", "left"), ["x", "oid"])
    on = at.filter((F.col("left") == F.col("x")) | (F.signum((F.col("vy") - F.col("cy") * MICRO).cast("double")) * F.col("up") >= 0))
    cross = on.groupBy("slab", "vy").agg(F.min("rank").alias("lo"), F.max("rank").alias("hi")).filter("lo < hi").select("slab", "lo", "hi")
    before = Window.partitionBy("slab").orderBy("lo", "hi")
    reach = F.max("hi").over(before.rowsBetween(Window.unboundedPreceding, -1))
    spans = own.unionByName(cross).withColumn("opens", F.when(reach.isNull() | (F.col("lo") > reach), 1).otherwise(0))
    spans = spans.withColumn("iv", F.sum("opens").over(before.rowsBetween(Window.unboundedPreceding, 0))).groupBy("slab", "iv").agg(F.min("lo").alias("lo"), F.max("hi").alias("hi"))
    return pairs.join(spans, "slab").filter("lo <= rank and rank < hi").drop("lo", "hi", "iv")


def arc_region_count(d: DataFrame, vertices: DataFrame | None = None) -> DataFrame:
    """n, vertices, c, r = c + 1 + sum(j - 1) and k = n + sum(j - 1) for j circles through a vertex, without a sweep."""
    from .components import components

    v = (arc_vertices(d) if vertices is None else vertices).groupBy("vx", "vy").agg(F.count("*").alias("j")).agg(F.count("*").alias("v"), F.coalesce(F.sum(F.col("j") - 1), F.lit(0)).alias("s"))
    known = components(crossing_pairs(d).select(F.col("a_oid").alias("u"), F.col("b_oid").alias("v")))
    parts = known.agg(F.count("*").alias("linked"), F.count_distinct("label").alias("groups"))
    every = d.agg(F.count("oid").alias("n")).join(F.broadcast(v)).join(F.broadcast(parts))
    c = F.col("n") - F.col("linked") + F.col("groups")
    return every.select("n", "v", c.alias("c"), (c + 1 + F.col("s")).alias("r"), (F.col("n") + F.col("s")).alias("k_expected"))


def raster_l2(d: DataFrame, box: tuple[int, int, int, int], width: int, height: int) -> DataFrame:
    """(px, py, heat) at pixel centres by the exact integer disc test: a disc gives the pixels of its box that it holds."""
    x0, x1, y0, y1 = box
    w, h = x1 - x0, y1 - y0
    half = F.ceil(F.sqrt(F.col("r2").cast("double"))).cast("long")
    px = lambda e: F.floor((e - x0) * F.lit(float(width)) / w).cast("long")
    py = lambda e: F.floor((e - y0) * F.lit(float(height)) / h).cast("long")
    bound = lambda lo, hi, top: F.sequence(F.greatest(lo, F.lit(0).cast("long")), F.greatest(F.least(hi, F.lit(top - 1).cast("long")), F.greatest(lo, F.lit(0).cast("long"))))
    cand = d.withColumn("px", F.explode(bound(px(F.col("cx") - half), px(F.col("cx") + half), width))).withColumn("py", F.explode(bound(py(F.col("cy") - half), py(F.col("cy") + half), height))).filter(f"px < {width} and py < {height}")
    qx = F.lit(2 * width * x0) + (2 * F.col("px") + 1) * w - F.col("cx") * (2 * width)
    qy = F.lit(2 * height * y0) + (2 * F.col("py") + 1) * h - F.col("cy") * (2 * height)
    wide = "decimal(38,0)"
    inside = (qx.cast(wide) * qx.cast(wide) * (height * height) + qy.cast(wide) * qy.cast(wide) * (width * width)) <= F.col("r2").cast(wide) * (4 * width * width * height * height)
    hot = cand.filter(inside).groupBy("px", "py").agg(F.sum("n").alias("heat"))
    pixels = d.sparkSession.range(width * height).select((F.col("id") % width).alias("px"), F.expr(f"id div {width}").alias("py"))
    return pixels.join(hot, ["px", "py"], "left").select("px", "py", F.coalesce("heat", F.lit(0)).alias("heat"))
