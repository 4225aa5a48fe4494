"""Connected components of an edge table by star contraction."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.tables import materialize


def components(edges: DataFrame, rounds: int = 60) -> DataFrame:
    """(node, label) for every node of the (u, v) edges; the label is the component's least node.

    Each round sends every node's neighbours to the least of them, first upward, then downward, and is written out;
    it stops once a round changes nothing. Nothing is collected but a count and a checksum.
    """

    def mark(df):
        r = df.agg(F.count("*"), F.sum(F.xxhash64("u", "v").bitwiseAND(0x7FFFFFFF))).first()
        return r[0], r[1]

    def lowered(df, low):
        return df.join(low, "u")

    now = materialize(edges.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).filter("u <> v").distinct(), "edges")
    state = mark(now)
    for _ in range(rounds):
        if not state[0]:
            break
        both = now.unionByName(now.select(F.col("v").alias("u"), F.col("u").alias("v")))
        up = lowered(both, both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))).filter("v > u")
        wide = up.select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()
        low = wide.groupBy("u").agg(F.min("v").alias("m"))
        down = lowered(wide, low).filter("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v"))
        now = materialize(down.unionByName(low.select("u", F.col("m").alias("v"))).distinct(), "edges")
        seen, state = state, mark(now)
        if seen == state:
            break
    else:
        raise RuntimeError("the components did not settle")
    return now.select(F.col("u").alias("node"), F.col("v").alias("label")).unionByName(now.select(F.col("v").alias("node"), F.col("v").alias("label")).distinct())
