"""Synthetic arrangements with known counts."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def _boxes(df: DataFrame) -> DataFrame:
    return df.select(F.col("oid").cast("long"), *[F.col(c).cast("long") for c in ("xl", "xh", "yl", "yh")], F.lit(1).cast("long").alias("weight"))


def diagonal_squares(spark: SparkSession, n: int) -> DataFrame:
    """n squares of side 2n centred at (2i, 2i) (doubled, to stay on integers): every one meets every other."""
    i = F.col("id") * 2
    return _boxes(spark.range(1, n + 1).select(F.col("id").alias("oid"), (i - n).alias("xl"), (i + n).alias("xh"), (i - n).alias("yl"), (i + n).alias("yh")))


def disjoint_squares(spark: SparkSession, n: int) -> DataFrame:
    i = F.col("id") * 10
    return _boxes(spark.range(n).select(F.col("id").alias("oid"), i.alias("xl"), (i + 4).alias("xh"), i.alias("yl"), (i + 4).alias("yh")))


def distinctness_squares(spark: SparkSession, values: list[int]) -> DataFrame:
    """Squares between (a1, a1) and every other (a, a): as many regions as values iff all are distinct."""
    first = values[0]
    rows = [(i + 2, min(first, a), max(first, a)) for i, a in enumerate(values[1:])]
    df = spark.createDataFrame(rows, "oid long, lo long, hi long")
    return _boxes(df.select("oid", F.col("lo").alias("xl"), F.col("hi").alias("xh"), F.col("lo").alias("yl"), F.col("hi").alias("yh")))


def comb_squares(spark: SparkSession, teeth: int) -> DataFrame:
    """A wide square that starts over a comb of small ones: one region gets several labels at one event."""
    i = F.col("id") * 5
    small = spark.range(1, teeth + 1).select(F.col("id").alias("oid"), F.lit(9).alias("xl"), F.lit(11).alias("xh"), (i - 1).alias("yl"), (i + 1).alias("yh"))
    big = spark.range(1).select(F.lit(0).alias("oid"), F.lit(10).alias("xl"), F.lit(40).alias("xh"), F.lit(0).alias("yl"), F.lit(5 * teeth + 5).alias("yh"))
    return _boxes(big.unionByName(small))
