"""Reading the given tables, and writing intermediate ones where all executors see them."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from signpart import schemas

#: Where one process is driver and executor and the session names no folder, as in tests; a cluster must name one.
_ONE_MACHINE = "/tmp/checkpoints/signpart"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.schema(schemas.TABLES[name]).parquet(f"{sf_dir}/{name}.parquet")


def shared_folder(spark: SparkSession) -> str:
    base = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if not base:
        master = spark.sparkContext.master
        if master != "local" and not master.startswith("local["):
            raise ValueError("spark.checkpoint.dir names no folder that driver and executors share; set it when the session is made")
        base = _ONE_MACHINE
    return f"{base.rstrip('/')}/signpart-{uuid.uuid4().hex}"


def written(df: DataFrame, path: str | None = None) -> DataFrame:
    """Writes df to the shared folder and reads it again: the lineage ends there, and lost executors cost nothing."""
    spark, path = df.sparkSession, path or shared_folder(df.sparkSession)
    df.write.mode("overwrite").parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def remove(spark: SparkSession, path: str) -> None:
    target = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    target.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(target, True)


def at_most(df: DataFrame, limit: int) -> bool:
    """Whether df has at most ``limit`` rows; looks no further."""
    return df.limit(limit + 1).agg(F.count(F.lit(1))).first()[0] <= limit


def sized_broadcast(df: DataFrame, limit: int) -> DataFrame:
    """A broadcast hint if df, a written table, has at most ``limit`` rows; else df, to be joined by shuffle."""
    return F.broadcast(df) if at_most(df, limit) else df
