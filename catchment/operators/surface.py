"""The labelled surface: point look-up, top regions, zoom, raster, colour classes."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .circles import stabbed


def _cell(width: int):
    return lambda e: F.floor(e / F.lit(float(width))).cast("long")


def heat_at(labels: DataFrame, points: DataFrame, measure: str = "n") -> DataFrame:
    """(qid, heat) of points by the full-slab rectangles, each taken half-open (left and lower sides included).

    A point outside every rectangle has heat 0. For closed sets at sides use ``rnn_of_points``.
    """
    width = max(1, int(labels.agg(F.avg(F.col("x1") - F.col("x0"))).first()[0] or 1)) * 4
    cell = _cell(width)
    parts = labels.withColumn("b", F.explode(F.sequence(cell(F.col("x0")), cell(F.col("x1")))))
    met = points.select("qid", "x", "y").withColumn("b", cell(F.col("x"))).join(parts, "b").filter("x0 <= x and x < x1 and y0 <= y and y < y1")
    found = met.groupBy("qid").agg(F.max(measure).alias("heat"))
    return points.select("qid").join(found, "qid", "left").select("qid", F.coalesce("heat", F.lit(0)).alias("heat"))


def heat_at_boxes(boxes: DataFrame, points: DataFrame, measure: str = "n") -> DataFrame:
    """``heat_at`` of an additive measure straight from the boxes (xl, xh, yl, yh), without any label; a place is looked up once."""
    places = points.select("x", "y").distinct()
    met = stabbed(places, boxes.select("xl", "xh", "yl", "yh", measure), "x", "y").filter("x < xh and y < yh")
    found = met.groupBy("x", "y").agg(F.sum(measure).alias("heat"))
    return points.select("qid", "x", "y").join(found, ["x", "y"], "left").select("qid", F.coalesce("heat", F.lit(0)).alias("heat"))


def top_labels(labels: DataFrame, k: int, measure: str = "n") -> DataFrame:
    """The k hottest labels in full order (heat, then place), with their rank; ties beyond k are cut."""
    order = [F.desc(measure), "x0", "y0", "x1", "y1"]
    top = labels.orderBy(*order).limit(k)
    return top.withColumn("rank", F.row_number().over(Window.partitionBy(F.lit(0)).orderBy(*order))).select("rank", F.col(measure).alias("heat"), "x0", "y0", "x1", "y1")


def hottest(labels: DataFrame, measure: str = "n") -> DataFrame:
    """Every label that reaches the maximum."""
    best = labels.agg(F.max(measure).alias("best"))
    return labels.join(F.broadcast(best), F.col(measure) == F.col("best")).drop("best")


def zoom(labels: DataFrame, box: tuple[int, int, int, int]) -> DataFrame:
    """Labels that meet the open box, clipped to it; the plain comparisons reach a Parquet scan."""
    x0, x1, y0, y1 = box
    met = labels.filter((F.col("x0") < x1) & (F.col("x1") > x0) & (F.col("y0") < y1) & (F.col("y1") > y0))
    return met.withColumns({"x0": F.greatest("x0", F.lit(x0)), "x1": F.least("x1", F.lit(x1)), "y0": F.greatest("y0", F.lit(y0)), "y1": F.least("y1", F.lit(y1))})


def heat_classes(labels: DataFrame, classes: int = 10, measure: str = "n") -> DataFrame:
    """Colour classes: the share of labels at or below each heat value, cut into equal steps. One row a heat value."""
    counts = labels.groupBy(measure).count()
    w = Window.partitionBy(F.lit(0)).orderBy(measure).rowsBetween(Window.unboundedPreceding, 0)
    total = counts.agg(F.sum("count").alias("total"))
    run = counts.withColumn("upto", F.sum("count").over(w)).join(F.broadcast(total))
    return run.select(F.col(measure).alias("heat"), F.col("count").alias("labels"), F.expr(f"cast(((upto - 1) * {classes}) div total as int)").alias("class"))


def _first_pixel(value, low: int, extent: int, cells: int):
    """The first pixel whose centre is at or above a coordinate."""
    num = (F.lit(low) - value) * (2 * cells) + extent
    floor = (num - F.pmod(num, F.lit(2 * extent))) / F.lit(2 * extent)
    return (-floor).cast("long")


def raster(labels: DataFrame, box: tuple[int, int, int, int], width: int, height: int, measure: str = "n") -> DataFrame:
    """(px, py, heat) of every pixel centre of the box: each rectangle (half-open) gives the pixels it holds."""
    x0, x1, y0, y1 = box
    clipped = lambda lo, hi: (F.greatest(lo, F.lit(0).cast("long")), hi)
    a, b = clipped(_first_pixel(F.col("x0"), x0, x1 - x0, width), F.least(_first_pixel(F.col("x1"), x0, x1 - x0, width), F.lit(width).cast("long")))
    c, d = clipped(_first_pixel(F.col("y0"), y0, y1 - y0, height), F.least(_first_pixel(F.col("y1"), y0, y1 - y0, height), F.lit(height).cast("long")))
    spans = labels.select(F.col(measure).alias("heat"), a.alias("pa"), b.alias("pb"), c.alias("pc"), d.alias("pd")).filter("heat <> 0 and pa < pb and pc < pd")
    hot = spans.withColumn("px", F.explode(F.expr("sequence(pa, pb - 1)"))).withColumn("py", F.explode(F.expr("sequence(pc, pd - 1)"))).select("px", "py", "heat")
    spark = labels.sparkSession
    all_pixels = spark.range(width * height).select((F.col("id") % width).alias("px"), F.expr(f"id div {width}").alias("py"))
    return all_pixels.join(hot, ["px", "py"], "left").select("px", "py", F.coalesce("heat", F.lit(0)).alias("heat"))


def box_sums(ranges: DataFrame, width: int, height: int, measure: str = "n") -> DataFrame:
    """(px, py, heat) of every cell of a width x height grid: the sums of the index ranges [pa, pb) x [pc, pd) that hold it.

    A range is four signed corners, so its size costs nothing; the corners are summed by cell, then along both axes.
    """
    corner = lambda x, y, s: F.struct(F.col(x).alias("px"), F.col(y).alias("py"), (s * F.col(measure)).alias("d"))
    four = F.array(corner("pa", "pc", 1), corner("pa", "pd", -1), corner("pb", "pc", -1), corner("pb", "pd", 1))
    real = ranges.filter("pa < pb and pc < pd")
    turns = real.select(F.explode(four).alias("c")).select("c.*").filter(f"px < {width} and py < {height}").groupBy("px", "py").agg(F.sum("d").alias("d"))
    spark = ranges.sparkSession
    cells = spark.range(width * height).select((F.col("id") % width).alias("px"), F.expr(f"id div {width}").alias("py")).join(turns, ["px", "py"], "left")
    along = lambda line, order: Window.partitionBy(line).orderBy(order).rowsBetween(Window.unboundedPreceding, 0)
    summed = cells.withColumn("s", F.sum(F.coalesce("d", F.lit(0))).over(along("py", "px")))
    return summed.select("px", "py", F.sum("s").over(along("px", "py")).cast("long").alias("heat"))


def pixel_ranges(boxes: DataFrame, box: tuple[int, int, int, int], width: int, height: int) -> DataFrame:
    """The boxes with the ranges pa..pb, pc..pd of pixels whose centres they hold (half-open)."""
    x0, x1, y0, y1 = box
    held = lambda c, low, extent, cells: F.least(F.greatest(_first_pixel(F.col(c), low, extent, cells), F.lit(0).cast("long")), F.lit(cells).cast("long"))
    return boxes.withColumns({"pa": held("xl", x0, x1 - x0, width), "pb": held("xh", x0, x1 - x0, width), "pc": held("yl", y0, y1 - y0, height), "pd": held("yh", y0, y1 - y0, height)})


def raster_boxes(boxes: DataFrame, box: tuple[int, int, int, int], width: int, height: int, measure: str = "n") -> DataFrame:
    """``raster`` of an additive measure straight from the boxes (xl, xh, yl, yh), without any label."""
    return box_sums(pixel_ranges(boxes, box, width, height), width, height, measure)


def register_rect_pixels(spark) -> None:
    """``rect_pixels(x0, x1, y0, y1, low_x, low_y, extent, cells)`` as a SQL table function: the pixels (px, py) of a square
    grid whose centres a half-open rectangle holds. For single shapes in SQL; whole tables go through ``raster_boxes``."""
    from pyspark.sql.functions import udtf

    @udtf(returnType="px bigint, py bigint")
    class RectPixels:
        def eval(self, x0: int, x1: int, y0: int, y1: int, low_x: int, low_y: int, extent: int, cells: int):
            first = lambda v, low: min(cells, max(0, -((2 * cells * (low - v) + extent) // (2 * extent))))
            for px in range(first(x0, low_x), first(x1, low_x)):
                for py in range(first(y0, low_y), first(y1, low_y)):
                    yield px, py

    spark.udtf.register("rect_pixels", RectPixels)
