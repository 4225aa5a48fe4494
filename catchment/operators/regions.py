"""Region identity, region counts without a sweep, and the measures over regions."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..plans.tables import materialize
from .circles import meeting, stabbed
from .components import components
from .strips import EVENTS, face_parts, heat_counts
from .sweep import label_all_pairs

#: Node of the exterior.
EXTERIOR = -1


def signed_squares(squares: DataFrame) -> DataFrame:
    """Squares with two additive marks of their id, so that equal sums stand for equal sets (64 bits in all)."""
    return squares.withColumns({"s1": F.xxhash64("oid").bitwiseAND(0xFFFFFFFF), "s2": F.xxhash64("oid", F.lit(1)).bitwiseAND(0xFFFFFFFF)})


def subregions(squares: DataFrame, strips: int = 1) -> DataFrame:
    """Every rectangle of the full-slab sweep with its region: columns of the sweep and region_id.

    Rectangles of neighbouring slabs are one region where their open y ranges overlap and their sets are equal;
    empty ones that touch the space outside a neighbouring slab's status belong to the exterior.
    """
    measures = ("n", "weight", "s1", "s2")
    parts = label_all_pairs(signed_squares(squares), measures, strips)
    order = Window.partitionBy("tile", "slab").orderBy("y0")
    parts = materialize(parts.withColumn("node", F.expr("shiftleft(cast(tile as long), 50) + shiftleft(cast(slab as long), 25)") + F.row_number().over(order)), "subregions")
    left = parts.select(F.col("x1").alias("x"), "s1", "s2", "n", F.col("y0").alias("a0"), F.col("y1").alias("a1"), F.col("node").alias("u"))
    right = parts.select(F.col("x0").alias("x"), "s1", "s2", "n", F.col("y0").alias("b0"), F.col("y1").alias("b1"), F.col("node").alias("v"))
    same = left.join(right, ["x", "s1", "s2", "n"]).filter("a0 < b1 and b0 < a1").select("u", "v")
    reach = parts.groupBy("x0", "x1").agg(F.min("y0").alias("low"), F.max("y1").alias("high"))
    empty = parts.filter("n = 0").select("node", "x0", "x1", "y0", "y1")
    sides = empty.select("node", "y0", "y1", F.explode(F.array(F.struct(F.lit("x1").alias("at"), F.col("x0").alias("x")), F.struct(F.lit("x0").alias("at"), F.col("x1").alias("x")))).alias("s")).select("node", "y0", "y1", "s.*")
    ends = reach.select(F.lit("x1").alias("at"), F.col("x1").alias("x"), "low", "high").unionByName(reach.select(F.lit("x0").alias("at"), F.col("x0").alias("x"), "low", "high"))
    out = sides.join(ends, ["at", "x"], "left").filter("low is null or y0 < low or y1 > high").select(F.col("node").alias("u"), F.lit(EXTERIOR).cast("long").alias("v"))
    labels = components(same.unionByName(out))
    return parts.join(labels, "node", "left").withColumn("region_id", F.coalesce("label", "node")).drop("label")


def region_table(parts: DataFrame) -> DataFrame:
    """One row a region: region_id, n, weight, parts, and its least rectangle; the exterior is always there."""
    inner = parts.filter(F.col("region_id") != EXTERIOR).groupBy("region_id").agg(F.first("n").alias("n"), F.first("weight").alias("weight"), F.count("*").alias("parts"), F.min(F.struct("x0", "y0", "x1", "y1")).alias("at"))
    spark = parts.sparkSession
    outer = spark.range(1).select(F.lit(EXTERIOR).cast("long").alias("region_id"), F.lit(0).cast("long").alias("n"), F.lit(0).cast("long").alias("weight"))
    return inner.unionByName(outer, allowMissingColumns=True)


def label_by_faces(squares: DataFrame, events: int = EVENTS) -> DataFrame:
    """Exact-arrangement baseline: one interior point of each region (doubled lattice) and its enclosure query.

    Regions are put together inside x strips from pairs that stay over slabs, and over the strips' borders by their nodes; the
    point is the centre of the region's least slab rectangle. A strip holds all squares around its points.
    """
    parts = materialize(face_parts(squares, events), "faces")
    side = lambda kind, node: parts.filter(f"kind = {kind}").select(F.col("x0").alias("x"), F.col("y0").alias("y"), F.col("node").alias(node))
    known = components(side(1, "u").join(side(2, "v"), ["x", "y"]).select("u", "v"))
    named = parts.filter("kind = 0").join(known, "node", "left").withColumn("region_id", F.coalesce("label", "node")).filter(F.col("region_id") != EXTERIOR)
    least = named.groupBy("region_id").agg(F.min(F.struct("x0", "y0", "x1", "y1", "n")).alias("at"))
    return least.select("region_id", F.expr("at.x0 + at.x1").alias("qx"), F.expr("at.y0 + at.y1").alias("qy"), F.col("at.n").alias("n"))


def touch_edges(squares: DataFrame) -> DataFrame:
    """Pairs of squares whose borders share a point: closed boxes that meet, neither strictly inside the other."""
    met = meeting(squares.select("oid", "xl", "xh", "yl", "yh"))
    apart = "(a_xl < b_xl and b_xh < a_xh and a_yl < b_yl and b_yh < a_yh) or (b_xl < a_xl and a_xh < b_xh and b_yl < a_yl and a_yh < b_yh)"
    return met.filter(f"not ({apart})").select(F.col("a_oid").alias("u"), F.col("b_oid").alias("v"))


def euler_region_count(squares: DataFrame) -> DataFrame:
    """v, e, c and r = e - v + c + 1 from the crossings of sides alone; collinear sides count once."""
    flat = squares.select(F.explode(F.array("yl", "yh")).alias("y"), F.col("xl").alias("a"), F.col("xh").alias("b"))
    tall = squares.select(F.explode(F.array("xl", "xh")).alias("x"), F.col("yl").alias("a"), F.col("yh").alias("b"))
    width = max(1, int(squares.agg(F.avg(F.col("xh") - F.col("xl"))).first()[0] or 1))
    cell = lambda e: F.floor(e / F.lit(float(width))).cast("long")
    f = flat.distinct().withColumn("g", F.explode(F.sequence(cell(F.col("a")), cell(F.col("b"))))).withColumnsRenamed({"a": "fa", "b": "fb"})
    t = tall.distinct().withColumn("g", cell(F.col("x"))).withColumnsRenamed({"a": "ta", "b": "tb"})
    corners = materialize(f.join(t, "g").filter("x between fa and fb and y between ta and tb").select("x", "y").distinct(), "vertices")

    def edges(line: str, along: str, sides: DataFrame) -> DataFrame:
        w = Window.partitionBy(line).orderBy(along)
        gaps = corners.withColumn("next", F.lead(along).over(w)).filter("next is not null")
        s = sides.select(line, "a", "b").distinct()
        return gaps.join(s, line).filter(f"a <= {along} and b >= next").select(line, along).distinct()

    every = edges("y", "x", flat).agg(F.count("*").alias("e")).unionByName(edges("x", "y", tall).agg(F.count("*").alias("e"))).agg(F.sum("e").alias("e"))
    known = components(touch_edges(squares))
    parts = known.agg(F.count("*").alias("linked"), F.count_distinct("label").alias("groups"))
    out = corners.agg(F.count("*").alias("v")).join(F.broadcast(every)).join(F.broadcast(squares.agg(F.count("*").alias("n")))).join(F.broadcast(parts))
    out = out.withColumn("c", F.col("n") - F.col("linked") + F.col("groups"))
    return out.select("v", "e", "c", F.expr("e - v + c + 1").alias("r"))


def counts_by_heat(squares: DataFrame) -> DataFrame:
    """(heat, k, k_all, r): labels of both sweeps and regions, the exterior among those of heat 0, by heat; neither labels nor regions are made.

    A region's parts less their links over slab borders are one less its holes. The holes of all regions are the
    components of touching squares, each in the region that it lies in: the one left of and below its first corner.
    """
    swept = heat_counts(squares)
    known = components(touch_edges(squares))
    boxes = squares.select("oid", "xl", "xh", "yl", "yh", "n")
    first = boxes.join(known.withColumnRenamed("node", "oid"), "oid", "left").groupBy(F.coalesce("label", "oid").alias("hole")).agg(F.min(F.struct("xl", "yl")).alias("at"))
    at = materialize(first.select("hole", F.col("at.xl").alias("x"), F.col("at.yl").alias("y")), "holes")
    around = stabbed(at, boxes.drop("oid"), "x", "y").filter("xl < x and yl < y").groupBy("hole").agg(F.sum("n").alias("heat"))
    holes = at.select("hole").join(around, "hole", "left").groupBy(F.coalesce("heat", F.lit(0).cast("long")).alias("heat")).agg(F.count("*").alias("holes"))
    out = swept.join(holes, "heat", "full").select("heat", *[F.coalesce(c, F.lit(0).cast("long")).alias(c) for c in ("k", "k_all", "chi", "holes")])
    return materialize(out.select("heat", "k", "k_all", (F.col("chi") + F.col("holes")).alias("r")), "heats")


def region_count(squares: DataFrame) -> DataFrame:
    """r by the sweep, the exterior included."""
    return counts_by_heat(squares).agg(F.coalesce(F.sum("r"), F.lit(1)).alias("r"))


def cost_measures(squares: DataFrame) -> DataFrame:
    """One row: n, m, k_all, k, r, lambda_max, lambda_mean, sum_rnn, initial and merged intervals, events."""
    from .sweep import changed_intervals, initial_intervals

    heats = counts_by_heat(squares)
    regions = heats.filter("r > 0")
    r = regions.agg(F.sum("r").alias("r"), F.max("heat").alias("lambda_max"), F.sum(F.col("heat") * F.col("r")).alias("sum_rnn")).withColumn("lambda_mean", F.col("sum_rnn") / F.col("r"))
    counts = squares.agg(F.count("*").alias("n"), F.count_distinct("xl").alias("_a"))
    xs = squares.select(F.explode(F.array("xl", "xh")).alias("x")).agg(F.count_distinct("x").alias("events"))
    ys = squares.select(F.explode(F.array("yl", "yh")).alias("y")).agg(F.count_distinct("y").alias("ys"))
    k_all, k = heats.agg(F.sum("k_all").alias("k_all")), heats.agg(F.sum("k").alias("k"))
    merged = changed_intervals(squares).agg(F.count("*").alias("merged_intervals"))
    initial = initial_intervals(squares).agg(F.count("*").alias("initial_intervals"))
    out = counts.drop("_a")
    for one in (xs, ys, k_all, k, r, merged, initial):
        out = out.join(F.broadcast(one))
    return out.select("n", "events", ((F.col("events") - 1) * (F.col("ys") - 1)).alias("m"), "k_all", "k", "r", "lambda_max", "lambda_mean", "sum_rnn", "initial_intervals", "merged_intervals")
