"""Baselines on grids: side grid, exact faces with one point each, regular grid, superimposition."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .circles import spread
from .surface import box_sums, raster_boxes


class OverBudget(RuntimeError):
    """The plan would make more cell-square pairs than its budget; the message says how many."""


def _gaps(squares: DataFrame, low: str, high: str, a: str, b: str) -> DataFrame:
    sides = squares.select(F.explode(F.array(low, high)).alias(a)).distinct()
    return sides.withColumn(b, F.lead(a).over(Window.partitionBy(F.lit(0)).orderBy(a))).filter(f"{b} is not null")


def grid_cells(squares: DataFrame) -> DataFrame:
    """All cells between extended sides; the axes are 2n-row tables, the smaller one is sent to every task."""
    return _gaps(squares, "xl", "xh", "x0", "x1").join(F.broadcast(_gaps(squares, "yl", "yh", "y0", "y1")), F.lit(True))


def label_side_grid(squares: DataFrame, measures: tuple[str, ...] = ("n",), cells: int = 100_000_000, index: str = "column", widest: int = 65_536) -> DataFrame:
    """Side-grid baseline: an enclosure query at the centre of every cell (centres on the doubled lattice).

    ``index="column"`` compares a cell only with the squares over its x gap (equi-join by gap); ``"none"`` with all of
    them. Quadratic by nature: it refuses to start beyond ``cells`` cells, or ``widest`` squares, which bounds what is broadcast.
    """
    xs, ys = _gaps(squares, "xl", "xh", "x0", "x1"), _gaps(squares, "yl", "yh", "y0", "y1")
    n, m = squares.count(), xs.count() * ys.count()
    if m > cells or n > widest:
        raise OverBudget(f"{m} cells, {n} squares")
    grid = spread(xs).join(F.broadcast(ys), F.lit(True)).withColumn("qy", F.col("y0") + F.col("y1"))
    if index == "none":
        met = grid.join(F.broadcast(squares), F.expr("2 * xl < x0 + x1 and x0 + x1 < 2 * xh and 2 * yl < qy and qy < 2 * yh"), "left").withColumn("hit", F.col("xl").isNotNull())
    else:
        over = spread(xs).join(F.broadcast(squares), F.expr("xl <= x0 and x1 <= xh")).select("x0", "yl", "yh", *measures)
        met = grid.join(over, "x0", "left").withColumn("hit", F.expr("2 * yl < qy and qy < 2 * yh"))
    return met.groupBy("x0", "x1", "y0", "y1").agg(*[F.coalesce(F.sum(F.when(F.col("hit"), F.col(k))), F.lit(0)).cast("long").alias(k) for k in measures])


def superimpose(squares: DataFrame, measure: str = "n", additive: bool = True) -> DataFrame:
    """Overlay of the squares: four signed corners each, summed along x, then y. For additive measures only."""
    if not additive:
        raise ValueError("an overlay adds squares up; this measure is no sum over the set")
    corner = lambda x, y, s: F.struct(F.col(x).alias("x"), F.col(y).alias("y"), (s * F.col(measure)).alias("d"))
    corners = squares.select(F.explode(F.array(corner("xl", "yl", 1), corner("xl", "yh", -1), corner("xh", "yl", -1), corner("xh", "yh", 1))).alias("c")).select("c.*").groupBy("x", "y").agg(F.sum("d").alias("d"))
    cells = grid_cells(squares)
    along_x = Window.partitionBy("y").orderBy("x0").rowsBetween(Window.unboundedPreceding, 0)
    along_y = Window.partitionBy("x0").orderBy("y0").rowsBetween(Window.unboundedPreceding, 0)
    full = cells.join(corners.withColumnsRenamed({"x": "x0", "y": "y0"}), ["x0", "y0"], "left").withColumn("y", F.col("y0"))
    summed = full.withColumn("s", F.sum(F.coalesce("d", F.lit(0))).over(along_x)).withColumn(measure, F.sum("s").over(along_y).cast("long"))
    return summed.select("x0", "x1", "y0", "y1", measure)


def regular_grid(squares: DataFrame, box: tuple[int, int, int, int], cells: int) -> DataFrame:
    """cells x cells equal cells of the box: heat at the centre, how many squares' borders cross the open cell, and how far
    the heat at the centres of its four quarters is off in sum and at most.

    A cell with a crossing border lies in more than one region, so its one value is not exact. A square's cells are
    index ranges, so each count is a few signed corners a square.
    """
    x0, x1, y0, y1 = box
    w, h = x1 - x0, y1 - y0
    floor = lambda c, low, extent: F.floor((F.col(c) - low) * cells / F.lit(float(extent)))
    ceil = lambda c, low, extent: F.ceil((F.col(c) - low) * cells / F.lit(float(extent)))
    within = lambda e: F.least(F.greatest(e, F.lit(0).cast("long")), F.lit(cells).cast("long")).cast("long")
    one = squares.select("xl", "xh", "yl", "yh", F.lit(1).cast("long").alias("n"))
    met = one.withColumns({"pa": within(floor("xl", x0, w)), "pb": within(ceil("xh", x0, w)), "pc": within(floor("yl", y0, h)), "pd": within(ceil("yh", y0, h))})
    whole = one.withColumns({"pa": within(ceil("xl", x0, w)), "pb": within(floor("xh", x0, w)), "pc": within(ceil("yl", y0, h)), "pd": within(floor("yh", y0, h))})
    named = lambda df, name: df.select(F.col("px").alias("gx"), F.col("py").alias("gy"), F.col("heat").alias(name))
    centre = named(raster_boxes(squares, box, cells, cells), "heat")
    out = centre.join(named(box_sums(met, cells, cells), "met"), ["gx", "gy"]).join(named(box_sums(whole, cells, cells), "whole"), ["gx", "gy"])
    fine = raster_boxes(squares, box, 2 * cells, 2 * cells).select(F.expr("px div 2").alias("gx"), F.expr("py div 2").alias("gy"), F.col("heat").alias("fine"))
    off = fine.join(centre, ["gx", "gy"]).groupBy("gx", "gy").agg(F.sum(F.abs(F.col("fine") - F.col("heat"))).alias("off_sum"), F.max(F.abs(F.col("fine") - F.col("heat"))).alias("off_max"))
    return out.join(off, ["gx", "gy"]).select("gx", "gy", "heat", (F.col("met") - F.col("whole")).alias("crossing"), "off_sum", "off_max")
