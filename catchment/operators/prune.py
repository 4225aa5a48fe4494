"""Combination pruning: the maximum region over discs by enumerating in/out choices, level by level.

A node fixes the choices of a root disc's first neighbours; it exists while some witness (a point in a face of the
root) agrees with all of them. Each level is one join with the next neighbour's memberships. With pruning, nodes whose
inside count plus remaining neighbours cannot beat the best are dropped. Exponential by nature: a frontier
beyond ``cap`` ends the run with status ``aborted``.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..plans.tables import materialize
from .arcs import MICRO, crossing_pairs, label_arcs
from .circles import stabbed


def witnesses(d: DataFrame) -> DataFrame:
    """(wid, oid): a mid-slab point inside every face that the arc sweep meets, with the discs that hold it."""
    spots = label_arcs(d, changed_only=True).select(F.xxhash64("slab", "rank").alias("wid"), F.expr(f"(x + x1) / {2.0 * MICRO}D").alias("wx"), F.expr("(y0 + y1) / 2").alias("wy"))
    spots = spots.withColumns({"qx": F.floor("wx").cast("long"), "qy": F.floor("wy").cast("long")})
    half = F.ceil(F.sqrt(F.col("r2").cast("double"))).cast("long")
    around = d.select("oid", "n", "cx", "cy", "r2", (F.col("cx") - half - 1).alias("xl"), (F.col("cx") + half).alias("xh"), (F.col("cy") - half - 1).alias("yl"), (F.col("cy") + half).alias("yh"))
    return materialize(stabbed(spots, around, "qx", "qy").filter("(wx - cx) * (wx - cx) + (wy - cy) * (wy - cy) < r2").select("wid", "oid", "n"), "witnesses")


def max_region_pruned(d: DataFrame, prune: bool = True, cap: int = 1_000_000) -> dict:
    """max_heat, enumerated and pruned node counts, levels and status."""
    held = witnesses(d)
    near = crossing_pairs(d).select(F.col("a_oid").alias("a"), F.col("b_oid").alias("b"))
    both = near.unionByName(near.select(F.col("b").alias("a"), F.col("a").alias("b")))
    inner = held.select(F.col("oid").alias("root"), "wid").join(held.select("wid", "oid", "n"), "wid").filter("root <> oid")
    around = both.select(F.col("a").alias("root"), F.col("b").alias("oid")).unionByName(inner.select("root", "oid")).distinct()
    sizes = Window.partitionBy("root")
    around = materialize(around.withColumns({"depth": F.row_number().over(sizes.orderBy("oid")), "degree": F.count("*").over(sizes)}), "neighbours")
    rest = materialize(around.join(d.select("oid", "n"), "oid").withColumn("left", F.coalesce(F.sum("n").over(sizes.orderBy(F.desc("depth")).rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))).select("root", "depth", "left", "oid", F.col("n").alias("gain")), "left")
    front = held.select(F.col("oid").alias("root"), "wid", F.col("n").alias("inside")).withColumn("node", F.xxhash64("root"))
    best = front.agg(F.max("inside")).first()[0] or 0
    depth, enumerated, pruned, status = 0, front.select("node").distinct().count(), 0, "done"
    levels = around.agg(F.max("depth")).first()[0] or 0
    member = held.select("wid", "oid", F.lit(1).alias("in"))
    while depth < levels:
        depth += 1
        step = front.join(rest.filter(F.col("depth") == depth).drop("depth"), "root").join(member, ["wid", "oid"], "left")
        step = step.select("root", "wid", F.xxhash64("node", F.coalesce("in", F.lit(0))).alias("node"), (F.col("inside") + F.when(F.col("in") == 1, F.col("gain")).otherwise(0)).alias("inside"), "left")
        step = materialize(step, "front")
        counts = step.agg(F.count_distinct("node"), F.max("inside"), F.count("*")).first()
        if not counts[2]:
            break
        enumerated += counts[0]
        best = max(best, counts[1])
        kept = step.filter(F.col("inside") + F.col("left") > best) if prune else step
        if prune:
            pruned += counts[0] - kept.select("node").distinct().count()
        if counts[0] > cap:
            status = "aborted"
            break
        front = kept.drop("left")
    return {"max_heat": best, "enumerated": enumerated, "pruned": pruned, "levels": depth, "status": status}
