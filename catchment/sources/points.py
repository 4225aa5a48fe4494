"""Point sets on the given tables, their experiment samples, and file sources and sinks.

Coordinates are LONG on an integer lattice, so every comparison of sides is exact.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

CLIENTS = T.StructType([T.StructField("oid", T.LongType()), T.StructField("x", T.LongType()), T.StructField("y", T.LongType()), T.StructField("weight", T.LongType()), T.StructField("grp", T.StringType())])
FACILITIES = T.StructType([T.StructField("fid", T.LongType()), T.StructField("fx", T.LongType()), T.StructField("fy", T.LongType()), T.StructField("cap", T.LongType())])


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def md5_int(column: str, first: int, digits: int):
    """Hex digits of the md5 of a key, as an integer (``first`` counts from 1)."""
    return F.conv(F.substring(F.md5(F.col(column).cast("string").cast("binary")), first, digits), 16, 10).cast("long")


def cents(column: str):
    return F.round(F.col(column) * 100).cast("long")


def market_clients(spark, sf_dir) -> DataFrame:
    """Every customer: balance by a hashed lattice coordinate; weight = number of orders, grp = nation."""
    orders = table(spark, sf_dir, "orders").groupBy(F.col("o_custkey").alias("oid")).agg(F.count("*").alias("n"))
    who = table(spark, sf_dir, "customer").select(F.col("c_custkey").alias("oid"), cents("c_acctbal").alias("x"), md5_int("c_custkey", 14, 5).alias("y"), F.col("c_nationkey").cast("string").alias("grp"))
    return who.join(orders, "oid", "left").select("oid", "x", "y", F.coalesce("n", F.lit(0)).cast("long").alias("weight"), "grp")


def market_facilities(spark, sf_dir) -> DataFrame:
    """Every supplier on the same lattice; capacity from its nation number."""
    return table(spark, sf_dir, "supplier").select(F.col("s_suppkey").alias("fid"), cents("s_acctbal").alias("fx"), md5_int("s_suppkey", 14, 5).alias("fy"), (F.col("s_nationkey") + 5).cast("long").alias("cap"))


def part_queries(spark, sf_dir) -> DataFrame:
    """Every part as a query location on the market lattice."""
    return table(spark, sf_dir, "part").select(F.col("p_partkey").alias("qid"), (F.col("p_size") * 20000 - 50000).cast("long").alias("x"), (cents("p_retailprice") * 5).alias("y"))


def _uniform(spark, sf_dir):
    return table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("id"), md5_int("o_orderkey", 9, 5).alias("x"), md5_int("o_orderkey", 14, 5).alias("y"))


def _skewed(column: str):
    return F.floor(F.lit(1048576.0) * F.pow(F.col(column) / F.lit(1048576.0), F.lit(1.25))).cast("long")


def point_set(spark, sf_dir: str, name: str) -> DataFrame:
    """(id, x, y) of a named set: ord, evt, uni, zip, emb, part or star."""
    if name == "ord":
        return table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("id"), cents("o_totalprice").alias("x"), (F.datediff("o_orderdate", F.lit("1995-01-01").cast("date")) * 20000).cast("long").alias("y"))
    if name == "evt":
        minutes = F.expr("timestampdiff(MINUTE, timestamp_ntz'2024-01-01 00:00:00', cast(ts as timestamp_ntz))")
        return table(spark, sf_dir, "events").select(F.col("event_id").alias("id"), cents("value").alias("x"), minutes.cast("long").alias("y"))
    if name == "uni":
        return _uniform(spark, sf_dir)
    if name == "zip":
        return _uniform(spark, sf_dir).select("id", _skewed("x").alias("x"), _skewed("y").alias("y"))
    if name == "emb":
        return table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("id"), *[F.round(F.get("embedding", F.lit(i)).cast("double") * 1e6).cast("long").alias(c) for i, c in ((0, "x"), (1, "y"))])
    if name == "part":
        return table(spark, sf_dir, "part").select(F.col("p_partkey").alias("id"), (F.col("p_size") * 200).cast("long").alias("x"), cents("p_retailprice").alias("y"))
    if name == "star":
        price = table(spark, sf_dir, "orders").groupBy(F.col("o_custkey").alias("id")).agg(F.expr("sum(cast(round(o_totalprice * 100) as long)) div count(*)").alias("y"))
        return table(spark, sf_dir, "customer").select(F.col("c_custkey").alias("id"), (cents("c_acctbal") * 40).alias("x")).join(price, "id")
    raise ValueError(f"no point set {name!r}")


def in_order(points: DataFrame, most: int) -> DataFrame:
    """(id, x, y, k): the first ``most`` points in md5 order, k counting them from 1. One task numbers that bounded sample."""
    ordered = points.select("id", "x", "y", md5_int("id", 1, 8).alias("h")).orderBy("h", "id").limit(most)
    return ordered.withColumn("k", F.row_number().over(Window.partitionBy(F.lit(0)).orderBy("h", "id"))).drop("h")


def sample(points: DataFrame, n: int, n_f: int) -> tuple[DataFrame, DataFrame]:
    """The experiments' uniform sample: in md5 order the first n points are clients, the next n_f facilities."""
    rows = in_order(points, n + n_f)
    one = F.lit(1).cast("long")
    clients = rows.filter(F.col("k") <= n).select(F.col("id").cast("long").alias("oid"), "x", "y", one.alias("weight"), F.lit("0").alias("grp"))
    return clients, rows.filter(F.col("k") > n).select(F.col("id").cast("long").alias("fid"), F.col("x").alias("fx"), F.col("y").alias("fy"), one.alias("cap"))


def read_points(spark, path: str, kind: str, fmt: str = "parquet", **options) -> DataFrame:
    """Clients or facilities from Parquet, CSV or JSON with the fixed schema, checked by ``validated``."""
    schema = {"clients": CLIENTS, "facilities": FACILITIES}[kind]
    return validated(spark.read.schema(schema).options(**options).format(fmt).load(path), kind)


def validated(points: DataFrame, kind: str) -> DataFrame:
    """The points; a row with a null id or coordinate raises when it is reached."""
    keys = {"clients": ("oid", "x", "y"), "facilities": ("fid", "fx", "fy")}[kind]
    bad = F.lit(False)
    for k in keys:
        bad = bad | F.col(k).isNull()
    return points.withColumn(keys[0], F.when(bad, F.raise_error(F.lit(f"{kind}: null id or coordinate"))).otherwise(F.col(keys[0])))


def write_labels(labels: DataFrame, path: str) -> None:
    """Parquet by tile, rows in x order inside a file, so that a zoom prunes tiles and row groups."""
    labels.repartition("tile").sortWithinPartitions("tile", "x0", "y0").write.partitionBy("tile").parquet(path)


def polygons(labels: DataFrame, metric: str = "linf") -> DataFrame:
    """GeoJSON-like features of label rectangles (corners turned back for L1)."""
    corner = lambda a, b: F.array((F.col(a) + F.col(b)) / 2, (F.col(b) - F.col(a)) / 2) if metric == "l1" else F.array(F.col(a).cast("double"), F.col(b).cast("double"))
    ring = F.array(*[corner(a, b) for a, b in (("x0", "y0"), ("x1", "y0"), ("x1", "y1"), ("x0", "y1"), ("x0", "y0"))])
    shape = F.struct(F.lit("Polygon").alias("type"), F.array(ring).alias("coordinates"))
    return labels.select(F.to_json(F.struct(F.lit("Feature").alias("type"), shape.alias("geometry"), F.struct("heat").alias("properties"))).alias("feature"))
