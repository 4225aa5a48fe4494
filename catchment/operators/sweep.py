"""Sweeps over squares: events, line statuses, the full-slab sweep and the changed-interval sweep.

The plane is cut into x strips (``tile``). Cuts add slab borders but no event, so labels do not depend on them.
Nothing flows from slab to slab. The full-slab sweep deals a circle to every slab that it crosses by its border ranks
(no theta join). The changed-interval sweep never makes that incidence: its merged intervals meet the circles that
touch them in cells of their sizes, so its rows are those that its labels are made of.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .circles import canonical, distinct_levels, size_level

BOX = ("xl", "xh", "yl", "yh")


def strip_cuts(squares: DataFrame, strips: int) -> list[int]:
    """Interior cuts of the x axis by approximate percentiles of left sides; a handful of numbers."""
    if strips <= 1:
        return []
    at = [i / strips for i in range(1, strips)]
    found = squares.agg(F.percentile_approx("xl", at, 10_000)).first()[0] or []
    return sorted(set(found))


def tiled(squares: DataFrame, cuts: list[int] | None = None) -> DataFrame:
    """Squares once for each strip they reach (open overlap), with the part sxl..sxh of their width in it."""
    cuts = cuts or []
    if not cuts:
        return squares.withColumns({"tile": F.lit(0), "sxl": F.col("xl"), "sxh": F.col("xh")})
    edges = F.array(*[F.lit(c).cast("long") for c in cuts])
    first = F.size(F.filter(edges, lambda c: c <= F.col("xl")))
    last = F.size(F.filter(edges, lambda c: c < F.col("xh")))
    out = squares.withColumn("tile", F.explode(F.sequence(first, last)))
    low = F.when(F.col("tile") > 0, F.greatest(F.col("xl"), F.element_at(edges, F.greatest(F.col("tile"), F.lit(1))))).otherwise(F.col("xl"))
    high = F.when(F.col("tile") < len(cuts), F.least(F.col("xh"), F.element_at(edges, F.least(F.col("tile") + 1, F.lit(len(cuts)))))).otherwise(F.col("xh"))
    return out.withColumns({"sxl": low, "sxh": high})


def borders(tiles: DataFrame) -> DataFrame:
    """(tile, x, slab, x1): distinct slab borders of a strip in order; x1 is the next border (null for the last)."""
    sides = tiles.select("tile", F.explode(F.array("sxl", "sxh")).alias("x")).distinct()
    w = Window.partitionBy("tile").orderBy("x")
    return sides.withColumns({"slab": F.row_number().over(w) - 1, "x1": F.lead("x").over(w)})


def event_queue(squares: DataFrame) -> DataFrame:
    """(slab, x0, x1) of every slab between consecutive events, one strip."""
    return borders(tiled(squares)).filter("x1 is not null").select("slab", F.col("x").alias("x0"), "x1")


def alive(tiles: DataFrame, marks: DataFrame) -> DataFrame:
    """Each square with each slab that it crosses, by the ranks of its two borders."""
    low = marks.select("tile", F.col("x").alias("sxl"), F.col("slab").alias("first"))
    high = marks.select("tile", F.col("x").alias("sxh"), F.col("slab").alias("past"))
    ranked = tiles.join(low, ["tile", "sxl"]).join(high, ["tile", "sxh"])
    return ranked.withColumn("slab", F.explode(F.expr("sequence(first, past - 1)")))


def line_status(squares: DataFrame) -> DataFrame:
    """(slab, pos, y, oid, role) in the order of y, then lower sides first, then id."""
    tiles = tiled(squares)
    live = alive(tiles, borders(tiles))
    sides = live.select("tile", "slab", "oid", F.explode(F.array(F.struct(F.col("yl").alias("y"), F.lit("lower").alias("role")), F.struct(F.col("yh").alias("y"), F.lit("upper").alias("role")))).alias("s"))
    w = Window.partitionBy("tile", "slab").orderBy("s.y", "s.role", "oid")
    return sides.select("slab", F.row_number().over(w).alias("pos"), F.col("s.y").alias("y"), "oid", F.col("s.role").alias("role"))


def _pairs(elements: DataFrame, keys: list[str], measures: list[str], by: list[str] | None = None) -> DataFrame:
    """Valid pairs of the elements (keys, y, measures): sides at one y are summed first, so invalid pairs never arise.

    A row with null y is what lies below the first element. Rows move once, to their ``by`` columns (some of the keys).
    """
    at_y = elements.repartition(*(by or keys)).groupBy(*keys, "y").agg(*[F.sum(m).alias(m) for m in measures])
    w = Window.partitionBy(*keys).orderBy(F.asc_nulls_first("y"))
    run = w.rowsBetween(Window.unboundedPreceding, Window.currentRow)
    found = at_y.withColumns({m: F.sum(m).over(run) for m in measures} | {"y1": F.lead("y").over(w)})
    return found.filter("y is not null and y1 is not null").withColumnRenamed("y", "y0")


def _with_slab(pairs: DataFrame, marks: DataFrame) -> DataFrame:
    return pairs.join(marks.filter("x1 is not null").select("tile", "slab", F.col("x").alias("x0"), "x1"), ["tile", "slab"])


def _sides(live: DataFrame, keys: list[str], measures: list[str]):
    up = F.struct(F.col("yl").alias("y"), *[F.col(m) for m in measures])
    down = F.struct(F.col("yh").alias("y"), *[(-F.col(m)).alias(m) for m in measures])
    return live.select(*keys, F.explode(F.array(up, down)).alias("s")).select(*keys, "s.*")


def label_all_pairs(squares: DataFrame, measures: tuple[str, ...] = ("n",), strips: int = 1, extra: DataFrame | None = None) -> DataFrame:
    """Full-slab sweep, additive measures: every valid pair of every slab with its running sums; no set is made.

    ``extra`` boxes (same columns) add to the measures without being elements of their own.
    """
    tiles = tiled(squares, strip_cuts(squares, strips))
    marks = borders(tiles)
    live = alive(_plus(tiles, extra, squares, strips), marks)
    pairs = _pairs(_sides(live, ["tile", "slab"], list(measures)), ["tile", "slab"], list(measures))
    return _with_slab(pairs, marks).select("tile", "slab", "x0", "x1", "y0", "y1", *measures)


def _plus(tiles, extra, squares, strips):
    if extra is None:
        return tiles
    more = tiled(extra, strip_cuts(squares, strips))
    return tiles.unionByName(more, allowMissingColumns=True)


def initial_intervals(squares: DataFrame) -> DataFrame:
    """(x, lo, hi): two rows a square, at its left and right side."""
    own = ["tile"] if "tile" in squares.columns else []
    return squares.select(*own, F.explode(F.array("xl", "xh")).alias("x"), F.col("yl").alias("lo"), F.col("yh").alias("hi"))


def changed_intervals(squares: DataFrame, cuts: list[int] | None = None) -> DataFrame:
    """(tile, x, iv_id, lo, hi): merged closed intervals of each event; touching ones merge. An event lies in one strip.

    Squares that carry a ``tile`` of their own (a run, a window) keep it.
    """
    rows = initial_intervals(squares)
    rows = rows if "tile" in squares.columns else rows.withColumn("tile", _strip(cuts))
    before = Window.partitionBy("tile", "x").orderBy("lo", "hi")
    reach = F.max("hi").over(before.rowsBetween(Window.unboundedPreceding, -1))
    rows = rows.withColumn("opens", F.when(reach.isNull() | (F.col("lo") > reach), 1).otherwise(0))
    rows = rows.withColumn("iv_id", F.sum("opens").over(before.rowsBetween(Window.unboundedPreceding, Window.currentRow)))
    return rows.groupBy("tile", "x", "iv_id").agg(F.min("lo").alias("lo"), F.max("hi").alias("hi"))


def event_borders(squares: DataFrame, cuts: list[int] | None = None) -> DataFrame:
    """(tile, x, slab, x1) of every event: its slab's number in the strip and where that slab ends (null at the very end)."""
    own = ["tile"] if "tile" in squares.columns else []
    xs = squares.select(*own, F.explode(F.array("xl", "xh")).alias("x"))
    if cuts:
        xs = xs.unionByName(squares.sparkSession.createDataFrame([(c,) for c in cuts], "x long"))
    if not own:
        xs = xs.withColumn("tile", _strip(cuts))
    w = Window.partitionBy("tile").orderBy("x")
    marks = xs.distinct().withColumns({"slab": F.row_number().over(w) - 1, "x1": F.lead("x").over(w)})
    if cuts:
        ends = F.array(*[F.lit(c).cast("long") for c in cuts])
        marks = marks.withColumn("x1", F.coalesce("x1", F.get(ends, F.col("tile"))))
    return marks


def _strip(cuts: list[int] | None):
    return F.size(F.filter(F.array(*[F.lit(c).cast("long") for c in cuts]), lambda c: c <= F.col("x"))) if cuts else F.lit(0)


def _touched(boxes: DataFrame, intervals: DataFrame, columns: list[str]) -> DataFrame:
    """Boxes alive right after the event of an interval that touch it, once for each: (_e, _m, _gx, _gy), the
    interval's tile, x, iv_id, lo, hi, and yl, yh with ``columns`` of the box.

    Cells are as wide as the box's own size and as high as the larger of box and interval: a box lies in at most
    two by two of them for each height that occurs, an interval looks into at most two for each width.
    """
    level = size_level(F.col("xh") - F.col("xl"), F.col("yh") - F.col("yl"))
    tall = size_level(F.col("hi") - F.col("lo"))
    widths, heights = distinct_levels(boxes, level), distinct_levels(intervals, tall)
    own = ["tile"] if "tile" in boxes.columns else []
    numbers = lambda found: F.array(*[F.lit(e) for e in found]) if found else F.array().cast("array<int>")
    cells = lambda lo, hi, e: F.explode(F.expr(f"sequence(shiftright({lo}, {e}), shiftright({hi}, {e}))"))
    dealt = boxes.select(*own, "xl", "xh", "yl", "yh", *columns).withColumn("_e", level.cast("int"))
    dealt = dealt.withColumn("_m", F.explode(F.array_union(F.array("_e"), F.filter(numbers(heights), lambda m: m > F.col("_e")))))
    dealt = dealt.withColumn("_gx", cells("xl", "(xh - 1)", "_e")).withColumn("_gy", cells("yl", "yh", "_m"))
    asked = intervals.withColumn("_e", F.explode(numbers(widths))).withColumn("_m", F.greatest("_e", tall.cast("int")))
    asked = asked.withColumn("_gx", F.expr("shiftright(x, _e)")).withColumn("_gy", cells("lo", "hi", "_m"))
    met = asked.hint("merge").join(dealt, [*own, "_e", "_m", "_gx", "_gy"])
    return met.filter("xl <= x and x < xh and yl <= hi and yh >= lo and _gy = shiftright(greatest(yl, lo), _m)")


def _elements(touched: DataFrame, measures: list[str], keys: list[str]) -> DataFrame:
    """Sides inside the closed interval, and one row (null y) for what the boxes that start below it add, summed
    where they are met: what goes on is hardly more than the sides that labels lie between."""
    up = F.struct(F.when(F.col("yl") >= F.col("lo"), F.col("yl")).alias("y"), *[F.col(m) for m in measures])
    down = F.struct(F.col("yh").alias("y"), *[(-F.col(m)).alias(m) for m in measures])
    both = F.when(F.col("yh") <= F.col("hi"), F.array(up, down)).otherwise(F.array(up))
    cell = ["_e", "_m", "_gx", "_gy"]
    sides = touched.select(*keys, *cell, F.explode(both).alias("s")).select(*keys, *cell, "s.*")
    return sides.groupBy(*keys, *cell, "y").agg(*[F.sum(m).alias(m) for m in measures]).drop(*cell)


def changed_pairs(boxes: DataFrame, intervals: DataFrame, measures: tuple[str, ...] = ("n",)) -> DataFrame:
    """(tile, x, iv_id, y0, y1, measures): the pairs inside the intervals (of ``changed_intervals``) with their running sums."""
    keys = ["tile", "x", "iv_id"]
    elements = _elements(_touched(boxes, intervals, list(measures)), list(measures), keys)
    return _pairs(elements, keys, list(measures), ["tile", "x"])


def label_changed(squares: DataFrame, measures: tuple[str, ...] = ("n",), strips: int = 1, extra: DataFrame | None = None) -> DataFrame:
    """Changed-interval sweep, additive measures: only pairs inside the changed intervals of an event are labelled.

    ``extra`` boxes (same columns) add to the measures without being elements of their own.
    """
    cuts = strip_cuts(squares, strips)
    need = [*(["tile"] if "tile" in squares.columns else []), "xl", "xh", "yl", "yh", *measures]
    boxes = squares.select(need) if extra is None else squares.select(need).unionByName(extra.select(need))
    pairs = changed_pairs(boxes, changed_intervals(squares, cuts), measures)
    marks = event_borders(squares, cuts).filter("x1 is not null")
    return pairs.join(marks, ["tile", "x"]).select("tile", "slab", "iv_id", F.col("x").alias("x0"), "x1", "y0", "y1", *measures)


def base_sets(squares: DataFrame) -> DataFrame:
    """(x, iv_id, lo, hi, base): the set just below each changed interval of the slab after its event."""
    intervals = changed_intervals(squares)
    placed = intervals.join(event_borders(squares).filter("x1 is not null").select("tile", "x"), ["tile", "x"])
    below = _touched(squares, intervals, ["members"]).filter("yl < lo").select("tile", "x", "iv_id", F.explode("members").alias("oid"))
    sets = below.groupBy("tile", "x", "iv_id").agg(F.sort_array(F.collect_list("oid")).alias("base"))
    return placed.join(sets, ["tile", "x", "iv_id"], "left").select("x", "iv_id", "lo", "hi", F.coalesce("base", F.array().cast("array<long>")).alias("base"))


def _sets(labels: DataFrame, keys: list[str], live: DataFrame) -> DataFrame:
    inside = labels.select(*keys, "y0", "y1").join(live.select(*keys, "yl", "yh", "members"), keys).filter("yl <= y0 and yh >= y1")
    sets = inside.groupBy(*keys, "y0").agg(F.sort_array(F.flatten(F.collect_list("members"))).alias("rnn"))
    return labels.join(sets, [*keys, "y0"], "left").withColumn("rnn", F.coalesce("rnn", F.array().cast("array<long>")))


def label_changed_sets(squares: DataFrame, strips: int = 1) -> DataFrame:
    """Changed-interval sweep with the set of every label."""
    touched = _touched(squares, changed_intervals(squares, strip_cuts(squares, strips)), ["members"]).withColumnRenamed("x", "x0")
    return _sets(label_changed(squares, ("n",), strips), ["tile", "x0", "iv_id"], touched)


def label_all_sets(squares: DataFrame, strips: int = 1) -> DataFrame:
    """Full-slab sweep with the set of every valid pair."""
    tiles = tiled(squares, strip_cuts(squares, strips))
    live = alive(tiles, borders(tiles))
    return _sets(label_all_pairs(squares, ("n",), strips), ["tile", "slab"], live)


def incidence(labels_with_sets: DataFrame) -> DataFrame:
    """Sets as rows (x0, y0, oid): the layout for very large sets."""
    return labels_with_sets.select("x0", "y0", F.explode("rnn").alias("oid"))


def squares_of(circles: DataFrame) -> DataFrame:
    return canonical(circles)
