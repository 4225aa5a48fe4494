"""Influence measures: additive ones as box weights, others as functions of a label's set.

Every measure has a value on the empty set: 0, or for capacity the total served without the new facility.
"""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def edge_boxes(circles: DataFrame, edges: DataFrame) -> DataFrame:
    """A box for each compatible pair (a, b): the overlap of their squares, where both are in the set.

    So connected pairs are additive: the sweep sums ``pairs`` over these boxes like any weight.
    """
    one = circles.select(F.col("oid").alias("a"), *[F.col(c).alias(f"a_{c}") for c in ("xl", "xh", "yl", "yh")])
    two = circles.select(F.col("oid").alias("b"), *[F.col(c).alias(f"b_{c}") for c in ("xl", "xh", "yl", "yh")])
    both = edges.select("a", "b").join(one, "a").join(two, "b")
    box = {c: (F.greatest if c.endswith("l") else F.least)(f"a_{c}", f"b_{c}") for c in ("xl", "xh", "yl", "yh")}
    return both.select(*[e.alias(c) for c, e in box.items()], F.lit(0).cast("long").alias("n"), F.lit(0).cast("long").alias("weight"), F.lit(1).cast("long").alias("pairs")).filter("xl < xh and yl < yh")


def _place(labels: DataFrame) -> list[str]:
    """What tells labels apart: the lower left corner, and the run or strip where there are several."""
    return [*(["tile"] if "tile" in labels.columns else []), "x0", "y0"]


def capacity_served(labels: DataFrame, circles: DataFrame, facilities: DataFrame, new_cap: int) -> DataFrame:
    """Clients served after opening at a label's place: each facility serves up to its capacity of those it keeps,
    the new one up to ``new_cap`` of its set. The measure's formula is our own choice.

    Where ``circles`` carry a ``tile`` (a run), labels and facilities do too, and each run is a market of its own.
    """
    own = ["tile"] if "tile" in circles.columns else []
    place = _place(labels)
    total = circles.groupBy(*own, F.col("nn_fid").alias("fid")).agg(F.count("*").alias("had"))
    caps = facilities.select(*own, "fid", "cap").join(total, [*own, "fid"], "left").select(*own, "fid", "cap", F.coalesce("had", F.lit(0)).alias("had"))
    served = caps.groupBy(*own).agg(F.coalesce(F.sum(F.least("cap", "had")), F.lit(0)).alias("served"))
    lost = labels.select(*place, F.explode("rnn").alias("oid")).join(circles.select(*own, "oid", F.col("nn_fid").alias("fid")), [*own, "oid"]).groupBy(*place, "fid").agg(F.count("*").alias("c"))
    change = lost.join(caps, [*own, "fid"]).groupBy(*place).agg(F.sum(F.least("cap", F.col("had") - F.col("c")) - F.least("cap", "had")).alias("change"))
    out = labels.join(change, place, "left")
    out = out.join(F.broadcast(served), own) if own else out.join(F.broadcast(served), F.lit(True))
    return out.withColumn("heat", (F.col("served") + F.coalesce("change", F.lit(0)) + F.least(F.lit(new_cap), F.size("rnn"))).cast("long")).drop("change", "served")


def group_measures(labels: DataFrame, clients: DataFrame) -> DataFrame:
    """same_group_pairs and distinct_groups of every label's set."""
    place = _place(labels)
    counts = labels.select(*place, F.explode("rnn").alias("oid")).join(clients.select("oid", "grp"), "oid").groupBy(*place, "grp").agg(F.count("*").alias("c"))
    sums = counts.groupBy(*place).agg(F.sum(F.expr("c * (c - 1) div 2")).alias("same_group_pairs"), F.count("*").alias("distinct_groups"))
    out = labels.join(sums, place, "left")
    return out.withColumns({c: F.coalesce(c, F.lit(0)).cast("long") for c in ("same_group_pairs", "distinct_groups")})


def near_edges(clients: DataFrame, column: str, most: int) -> DataFrame:
    """(a, b), a < b: clients of one group whose ``column`` differs by at most ``most``; a band join by lattice steps."""
    step = lambda shift: (F.floor(F.col(column) / F.lit(float(most + 1))) + shift).cast("long")
    left = clients.select(F.col("oid").alias("a"), "grp", F.col(column).alias("va"), F.explode(F.array(step(-1), step(0), step(1))).alias("s"))
    right = clients.select(F.col("oid").alias("b"), "grp", F.col(column).alias("vb"), step(0).alias("s"))
    return left.join(right, ["grp", "s"]).filter((F.col("a") < F.col("b")) & (F.abs(F.col("va") - F.col("vb")) <= most)).select("a", "b")


def by_expression(labels: DataFrame, expression: str) -> DataFrame:
    """Any SQL expression of ``rnn``, as heat."""
    return labels.withColumn("heat", F.expr(expression).cast("double"))


def by_function(labels: DataFrame, fn) -> DataFrame:
    """Any Python function of the set, as heat. It is called once a label, so the calls are the rows of the result."""

    @F.pandas_udf("double")
    def measure(sets: pd.Series) -> pd.Series:
        return pd.Series([float(fn(list(s))) for s in sets], dtype="float64")

    return labels.withColumn("heat", measure("rnn"))


def by_group_function(members: DataFrame, keys: list[str], fn) -> DataFrame:
    """(keys, heat): a Python function of a set given as rows (keys, oid), as a grouped aggregate."""

    @F.pandas_udf("double")
    def measure(oids: pd.Series) -> float:
        return float(fn(oids.tolist()))

    return members.groupBy(*keys).agg(measure("oid").alias("heat"))
