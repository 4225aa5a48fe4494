"""Experiment workloads: ratio and size sweeps over four point sets, all runs of a sweep in one plan.

A run is a tile: its squares share nothing with those of another run, so sweeps of any number of runs are the same
few shuffles.
"""

from __future__ import annotations

import time
from functools import reduce
from math import log

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.influence import capacity_served
from ..functions.metrics import distance
from ..operators.arcs import arc_vertices, discs, vertex_labels
from ..operators.circles import boxes, canonical, nn_circles, spread
from ..operators.grid import OverBudget, label_side_grid
from ..operators.prune import max_region_pruned
from ..operators.surface import raster_boxes, top_labels
from ..operators.sweep import changed_intervals, changed_pairs, event_borders, label_all_pairs, label_changed, label_changed_sets
from ..sources.points import in_order, point_set, sample
from .tables import materialize, release

SETS = ("ord", "evt", "uni", "zip")


def fitting(spark, sf_dir: str, runs: list[tuple[str, int, int]]) -> list[tuple[str, int, int]]:
    """Those of the runs (set, n, ratio) that their table has points for."""
    rows = {name: point_set(spark, sf_dir, name).count() for name in {s for s, _, _ in runs}}
    return [(s, n, ratio) for s, n, ratio in runs if n + max(1, n // ratio) <= rows[s]]


def run_points(spark, sf_dir: str, runs: list[tuple[str, int, int]]) -> tuple[DataFrame, DataFrame]:
    """Clients and facilities of all runs (set, n, ratio), the run number as ``tile``; each set is put in order once."""
    most: dict[str, int] = {}
    for name, n, ratio in runs:
        most[name] = max(most.get(name, 0), n + max(1, n // ratio))
    sets = [in_order(point_set(spark, sf_dir, name), m).withColumn("dataset", F.lit(name)) for name, m in most.items()]
    every = materialize(reduce(DataFrame.unionByName, sets), "points")
    table = spark.createDataFrame([(i, s, n, n + max(1, n // r)) for i, (s, n, r) in enumerate(runs)], "tile int, dataset string, n_c long, upto long")
    dealt = every.join(F.broadcast(table), "dataset")
    clients = dealt.filter("k <= n_c").select("tile", F.col("id").cast("long").alias("oid"), "x", "y", F.lit(1).cast("long").alias("weight"))
    return clients, dealt.filter("k > n_c and k <= upto").select("tile", F.col("id").cast("long").alias("fid"), F.col("x").alias("fx"), F.col("y").alias("fy"), F.lit(1).cast("long").alias("cap"))


def run_circles(clients: DataFrame, facilities: DataFrame, metric: str) -> DataFrame:
    """Circles of every run; a run's facilities, fewer than its clients, go to each of its clients as one array."""
    places = facilities.groupBy("tile").agg(F.sort_array(F.collect_list(F.struct("fid", "fx", "fy"))).alias("places"))
    near = F.array_min(F.transform("places", lambda p: F.struct(distance(metric, "x", "y", p["fx"], p["fy"]).alias("d"), p["fid"].alias("fid"))))
    met = spread(clients).join(F.broadcast(places), "tile").withColumn("b", near)
    return boxes(met.withColumns({"r": F.col("b.d"), "nn_fid": F.col("b.fid")}).drop("b", "places"), metric)


def canonical_runs(circles: DataFrame) -> DataFrame:
    """Squares of every run, equal ones as one."""
    return circles.filter("r > 0").groupBy("tile", "xl", "xh", "yl", "yh").agg(F.min("oid").alias("oid"), F.sort_array(F.collect_list("oid")).alias("members"), F.count("*").alias("n"))


def run_squares(spark, sf_dir: str, runs: list[tuple[str, int, int]], metric: str) -> DataFrame:
    """Canonical squares of the runs (set, n, ratio), the run number as ``tile``."""
    return canonical_runs(run_circles(*run_points(spark, sf_dir, runs), metric))


def run_discs(spark, sf_dir: str, runs: list[tuple[str, int, int]], units: int = 20_000) -> DataFrame:
    """Discs of the runs, each run's points on a lattice of 0..units by integer division."""
    clients, facilities = run_points(spark, sf_dir, runs)
    every = clients.select("tile", "x", "y").unionByName(facilities.select("tile", F.col("fx").alias("x"), F.col("fy").alias("y")))
    box = every.groupBy("tile").agg(F.min("x").alias("x0"), F.min("y").alias("y0"), F.greatest(F.max("x") - F.min("x"), F.max("y") - F.min("y"), F.lit(1)).alias("ext"))

    def rescaled(points: DataFrame, x: str, y: str) -> DataFrame:
        step = lambda c, low: F.expr(f"(({c} - {low}) * {units}) div ext")
        return points.join(F.broadcast(box), "tile").withColumns({x: step(x, "x0"), y: step(y, "y0")}).drop("x0", "y0", "ext")

    c, f = rescaled(clients, "x", "y"), materialize(rescaled(facilities, "fx", "fy"), "facilities")
    return materialize(discs(run_circles(c, f, "l2"), f), "discs")


def disc_table(spark, sf_dir: str, runs: list[tuple[str, int, int]]) -> DataFrame:
    """(dataset, ratio, n, k, max_heat) of the runs by the arc sweep at event points: labels made and the maximum region's heat."""
    d = run_discs(spark, sf_dir, runs)
    found = vertex_labels(d, materialize(arc_vertices(d), "vertices")).groupBy("tile").agg(F.count("*").alias("k"), F.max("n").alias("max_heat"))
    counts = d.groupBy("tile").agg(F.count("*").alias("n"))
    return named(spark, runs).join(counts, "tile").join(found, "tile").select("dataset", "ratio", "n", "k", "max_heat")


def named(spark, runs: list[tuple[str, int, int]]) -> DataFrame:
    return F.broadcast(spark.createDataFrame([(i, s, n, r) for i, (s, n, r) in enumerate(runs)], "tile int, dataset string, clients long, ratio int"))


def capacity_table(spark, sf_dir: str, runs: list[tuple[str, int, int]], metric: str, new_cap: int) -> DataFrame:
    """(dataset, ratio, n, k, max_size, max_served) of the runs: size and capacity measure side by side."""
    clients, facilities = run_points(spark, sf_dir, runs)
    facilities = facilities.withColumn("cap", F.pmod("fid", F.lit(7)) + 1)
    circles = materialize(run_circles(clients, facilities, metric), "circles")
    labels = capacity_served(label_changed_sets(materialize(canonical_runs(circles), "squares")), circles, facilities, new_cap)
    found = labels.groupBy("tile").agg(F.count("*").alias("k"), F.max("n").alias("max_size"), F.max("heat").alias("max_served"))
    counts = circles.filter("r > 0").groupBy("tile").agg(F.count_distinct("xl", "xh", "yl", "yh").alias("n"))
    return named(spark, runs).join(counts, "tile").join(found, "tile").select("dataset", "ratio", "n", "k", "max_size", "max_served")


def full_slab_count(squares: DataFrame, marks: DataFrame) -> DataFrame:
    """(tile, k_all): how many labels the full-slab sweep makes, without the incidence of squares and slabs.

    A slab has one pair less than heights with a side in it. So k_all is the number of slabs under the union of the squares
    with a side at a height, summed over heights, less the slabs under the union of all squares.
    """
    at = lambda c, name: marks.select("tile", F.col("x").alias(c), F.col("slab").alias(name))
    ranked = squares.select("tile", "xl", "xh", "yl", "yh").join(at("xl", "a"), ["tile", "xl"]).join(at("xh", "b"), ["tile", "xh"])

    def covered(rows: DataFrame, *keys: str) -> DataFrame:
        before = Window.partitionBy(*keys).orderBy("a", "b").rowsBetween(Window.unboundedPreceding, -1)
        upto = F.coalesce(F.max("b").over(before), F.lit(-1))
        return rows.withColumn("fresh", F.greatest(F.col("b") - F.greatest("a", upto), F.lit(0))).groupBy("tile").agg(F.sum("fresh").alias("slabs"))

    lines = ranked.select("tile", F.explode(F.array("yl", "yh")).alias("y"), "a", "b")
    every = covered(lines, "tile", "y").withColumnRenamed("slabs", "heights")
    return every.join(covered(ranked, "tile"), "tile").select("tile", (F.col("heights") - F.col("slabs")).alias("k_all"))


def sweep_counts(squares: DataFrame) -> DataFrame:
    """(tile, n, events, m, k_all, k, lambda_max) of every run; ``squares`` is a written table."""
    marks = event_borders(squares)
    part = changed_pairs(squares, changed_intervals(squares))
    side = squares.select("tile", "oid", F.explode(F.array("xl", "xh")).alias("x"), "yl", "yh")
    ys = squares.select("tile", F.explode(F.array("yl", "yh")).alias("y")).groupBy("tile").agg(F.count_distinct("y").alias("ys"))
    xs = side.groupBy("tile").agg(F.count_distinct("x").alias("events"), F.count_distinct("oid").alias("n"))
    out = xs.join(ys, "tile").join(full_slab_count(squares, marks), "tile").join(part.groupBy("tile").agg(F.count("*").alias("k"), F.max("n").alias("lambda_max")), "tile")
    return out.select("tile", "n", "events", ((F.col("events") - 1) * (F.col("ys") - 1)).alias("m"), "k_all", "k", "lambda_max")


def sweep_table(spark, sf_dir: str, runs: list[tuple[str, int, int]], metric: str) -> DataFrame:
    """Counts of the runs with their set and ratio."""
    squares = materialize(run_squares(spark, sf_dir, runs, metric), "squares")
    return named(spark, runs).join(sweep_counts(squares), "tile").drop("tile", "clients")


def timed(action) -> float:
    began = time.perf_counter()
    action()
    return time.perf_counter() - began


def race(spark, sf_dir: str, name: str, n: int, ratio: int, metric: str = "l1", cells: int = 30_000_000, algos: tuple[str, ...] = ("side_grid", "full_slab", "changed_interval")) -> list[dict]:
    """Seconds of the three sweeps on one sample (noop sink); a side grid of more than ``cells`` cells is not begun."""
    squares = materialize(canonical(nn_circles(*sample(point_set(spark, sf_dir, name), n, max(1, n // ratio)), metric)), "squares")
    make = {"side_grid": lambda: label_side_grid(squares, cells=cells), "full_slab": lambda: label_all_pairs(squares), "changed_interval": lambda: label_changed(squares)}
    out = []
    for algo in algos:
        row = {"dataset": name, "metric": metric, "n": n, "ratio": ratio, "algo": algo}
        try:
            out.append(row | {"seconds": round(timed(lambda: make[algo]().write.format("noop").mode("overwrite").save()), 3), "status": "done"})  # noqa: B023
        except OverBudget:
            out.append(row | {"seconds": None, "status": "over budget"})
    release(squares)
    return out


def race_l2(spark, sf_dir: str, name: str, n: int, ratio: int, cap: int = 200_000) -> list[dict]:
    """Seconds to the maximum region over discs: arc sweep against combination pruning, which may end aborted at ``cap`` nodes."""
    d = run_discs(spark, sf_dir, [(name, n, ratio)]).drop("tile")
    row = {"dataset": name, "metric": "l2", "n": n, "ratio": ratio}
    best: dict = {}
    swept = timed(lambda: best.update(max_heat=vertex_labels(d).agg(F.max("n")).first()[0]))
    pruned = timed(lambda: best.update(pruning=max_region_pruned(d, cap=cap)))
    return [row | {"algo": "arc_sweep", "seconds": round(swept, 3), "max_heat": best["max_heat"], "status": "done"}, row | {"algo": "combination_pruning", "seconds": round(pruned, 3), "max_heat": best["pruning"]["max_heat"], "status": best["pruning"]["status"]}]


def unfinished(races: list[dict]) -> dict[str, float]:
    """The share of each method's runs that were not finished."""
    out: dict[str, list[bool]] = {}
    for r in races:
        out.setdefault(r["algo"], []).append(r["status"] != "done")
    return {algo: round(sum(found) / len(found), 3) for algo, found in out.items()}


def slopes(races: list[dict]) -> dict[str, float]:
    """Growth of seconds with n for each method: the least-squares slope of log seconds over log n, finished runs only."""
    out = {}
    for algo in {r["algo"] for r in races}:
        spots = [(log(r["n"]), log(r["seconds"])) for r in races if r["algo"] == algo and r["status"] == "done"]
        mx, my = (sum(v) / max(1, len(spots)) for v in zip(*spots)) if spots else (0, 0)
        spread_x = sum((x - mx) ** 2 for x, _ in spots)
        if spread_x:
            out[algo] = round(sum((x - mx) * (y - my) for x, y in spots) / spread_x, 3)
    return out


def showcase_squares(spark, sf_dir: str, name: str, n: int = 20_000, metric: str = "linf") -> DataFrame:
    """Squares of the showcase map: n clients and 3 facilities to 10 of them, fewer where the table holds fewer points."""
    points = point_set(spark, sf_dir, name)
    n = min(n, points.count() * 10 // 13)
    return materialize(canonical(nn_circles(*sample(points, n, n * 3 // 10), metric)), "squares")


def showcase(spark, sf_dir: str, name: str, pixels: int) -> DataFrame:
    """The showcase map as a raster over the box of all its squares."""
    squares = showcase_squares(spark, sf_dir, name)
    return raster_boxes(squares, tuple(squares.agg(F.min("xl"), F.max("xh"), F.min("yl"), F.max("yh")).first()), pixels, pixels)


def showcase_top(spark, sf_dir: str, name: str, k: int = 4) -> DataFrame:
    """The hottest labels of the showcase map."""
    return top_labels(label_changed(showcase_squares(spark, sf_dir, name)), k)
