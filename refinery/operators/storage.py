"""Tables written once and read back: they cut lineage and survive lost executors."""

from __future__ import annotations

import gc
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def shared_dir(spark: SparkSession) -> str:
    """The folder that the cluster names in spark.checkpoint.dir, which all executors share. On a cluster without one this raises: a folder of one machine
    would lose what other executors write. In local mode the warehouse's folder serves."""
    path = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if not path:
        if not spark.sparkContext.master.startswith("local") or spark.sparkContext.master.startswith("local-cluster"):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        path = f"{spark.conf.get('spark.sql.warehouse.dir').rstrip('/')}-shared"
    return path.rstrip("/")


def materialize(df: DataFrame, name: str, root: str | None = None) -> DataFrame:
    path = f"{root or shared_dir(df.sparkSession)}/table-{name}-{uuid.uuid4().hex}"
    df.write.option("compression", "zstd").parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def few(df: DataFrame, most: int = 100_000) -> DataFrame:
    """A table that is broadcast below a counted bound, so that what it is joined to stays where it is; else left to a join by shuffle."""
    return F.broadcast(df) if df.limit(most + 1).count() <= most else df


def release(spark: SparkSession) -> None:
    """Spark deletes a shuffle's files when its frames are collected as garbage, which a driver of few objects puts off; after a pass nothing asks for them."""
    gc.collect()
    spark._jvm.System.gc()


def remove(df: DataFrame) -> None:
    spark = df.sparkSession
    for path in {f.rsplit("/", 1)[0] for f in df.inputFiles()}:
        if "/table-" in path:
            p = spark._jvm.org.apache.hadoop.fs.Path(path)
            p.getFileSystem(spark._jsc.hadoopConfiguration()).delete(p, True)
