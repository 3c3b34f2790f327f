"""Tables written between steps: Parquet in the folder all executors share, scanned with pruning and pushdown."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_dir(spark: SparkSession) -> str:
    """This application's folder under ``spark.checkpoint.dir``; it goes when the application ends.

    Where the session names no folder, a temporary one of this machine serves a local master; a cluster needs a shared one.
    """
    sc = spark.sparkContext
    named = sc.getConf().get("spark.checkpoint.dir") or sc.getCheckpointDir()
    if not named:
        if not (sc.master == "local" or sc.master.startswith("local[")):
            raise RuntimeError("set spark.checkpoint.dir to a folder that driver and executors share")
        sc.setCheckpointDir(tempfile.mkdtemp(prefix="graphdelta-"))
        named = sc.getCheckpointDir()
    folder = f"{named.rstrip('/')}/graphdelta-{sc.applicationId}"
    path = sc._jvm.org.apache.hadoop.fs.Path(folder)
    path.getFileSystem(sc._jsc.hadoopConfiguration()).deleteOnExit(path)
    return folder


def cut(df: DataFrame, name: str = "table") -> DataFrame:
    """The rows as a Parquet table: plans do not grow, scans prune columns and push filters, a lost executor re-reads."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)
