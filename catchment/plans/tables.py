"""Written intermediate tables in the folder that the cluster shares."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share, as the session names it.

    Only a session that runs in one process (local master) gets a folder of its own where none is named; on a
    cluster that would lose data, so it is an error there.
    """
    root = spark.conf.get("spark.checkpoint.dir", None)
    if not root:
        context = spark.sparkContext
        held = context._jsc.sc().getCheckpointDir()
        if held.isDefined():
            root = held.get()
        elif context.master.startswith("local") and not context.master.startswith("local-cluster"):
            root = "file://" + tempfile.mkdtemp(prefix="catchment-")
            context.setCheckpointDir(root)
        else:
            raise ValueError("spark.checkpoint.dir names no folder that driver and executors share")
    return root.rstrip("/") if "://" in root else "file://" + root.rstrip("/")


def materialize(df: DataFrame, name: str, **options) -> DataFrame:
    """Write a table into the shared folder and read it again: lineage ends, a lost executor costs a reread.

    ``options`` are the writer's. The path of the table is kept on the frame for ``release``.
    """
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/catchment-{name}-{uuid.uuid4().hex}"
    df.write.options(**options).parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out._catchment_path = path
    return out


def release(*tables: DataFrame) -> None:
    """Drop tables of ``materialize`` that nothing lazy reads any more."""
    for df in tables:
        path = getattr(df, "_catchment_path", None)
        if path:
            spark = df.sparkSession
            p = spark._jvm.org.apache.hadoop.fs.Path(path)
            p.getFileSystem(spark._jsc.hadoopConfiguration()).delete(p, True)
