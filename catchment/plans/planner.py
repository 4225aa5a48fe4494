"""Which sweep to run, over how many strips: by what the measure needs and by costs estimated from side ranks."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators import sweep
from .tables import materialize

#: Events of a strip: what one task numbers in order.
PER_STRIP = 2_000_000


def prepared(squares: DataFrame) -> DataFrame:
    """The squares as a written table: a sweep reads them several times, and their count is then in the files' footers."""
    return materialize(squares, "squares")


def strips_for(squares: DataFrame, per_strip: int = PER_STRIP) -> int:
    return max(1, -(-2 * squares.count() // per_strip))


def estimates(squares: DataFrame) -> dict:
    """n, events, grid cells and square-slab incidences, without running a sweep."""
    marks = sweep.event_borders(squares)
    low = marks.select(F.col("x").alias("xl"), F.col("slab").alias("a"))
    high = marks.select(F.col("x").alias("xh"), F.col("slab").alias("b"))
    r = squares.join(low, "xl").join(high, "xh").agg(F.count("*"), F.sum(F.col("b") - F.col("a"))).first()
    events = marks.count()
    ys = squares.select(F.explode(F.array("yl", "yh")).alias("y")).distinct().count()
    return {"n": r[0], "events": events, "m": max(0, events - 1) * max(0, ys - 1), "incidences": r[1] or 0}


def choose(squares: DataFrame, additive: bool, whole_surface: bool = False, per_strip: int = PER_STRIP) -> dict:
    """The plan: algorithm, mode and number of strips, with the estimates that led to it."""
    algorithm = "full_slab" if whole_surface else "changed_interval"
    return {"algorithm": algorithm, "mode": "delta" if additive else "sets", "strips": strips_for(squares, per_strip), **estimates(squares)}


def labels(squares: DataFrame, measures: tuple[str, ...] = ("n",), additive: bool = True, whole_surface: bool = False, extra: DataFrame | None = None) -> DataFrame:
    """Labels of prepared squares by the sweep that fits: running sums for additive measures, sets for others, every
    pair of every slab only where the whole surface is asked for."""
    strips = strips_for(squares)
    if whole_surface:
        return sweep.label_all_pairs(squares, measures, strips, extra) if additive else sweep.label_all_sets(squares, strips)
    return sweep.label_changed(squares, measures, strips, extra) if additive else sweep.label_changed_sets(squares, strips)
