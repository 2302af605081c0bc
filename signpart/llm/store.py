"""Tables shared between executors, and reading the input tables."""

from __future__ import annotations

import uuid
from collections.abc import Iterator
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Where one process is driver and executor and the session names no folder, as in tests; a cluster must name one.
_ONE_MACHINE = "/tmp/checkpoints/signpart"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_folder(spark: SparkSession) -> str:
    """A new folder that all executors and the driver see, below the session's ``spark.checkpoint.dir``."""
    base = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if not base:
        master = spark.sparkContext.master
        if master != "local" and not master.startswith("local["):
            raise ValueError("spark.checkpoint.dir names no folder that driver and executors share; set it when the session is made")
        base = _ONE_MACHINE
    return f"{base.rstrip('/')}/signpart-{uuid.uuid4().hex}"


#: Run-time setting that lets a query's shuffle files go as soon as the query has ended.
_CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


@contextmanager
def freed_shuffles(spark: SparkSession) -> Iterator[None]:
    """Queries that end inside leave no shuffle files; a lost file of a running one is made again as ever."""
    before = spark.conf.get(_CLEANUP)
    spark.conf.set(_CLEANUP, "true")
    try:
        yield
    finally:
        spark.conf.set(_CLEANUP, before)


def written(df: DataFrame, folder: str | None = None) -> DataFrame:
    """Write to the shared folder and read again: cuts the lineage, and lost executors cost nothing."""
    spark = df.sparkSession
    path = folder or shared_folder(spark)
    with freed_shuffles(spark):
        df.write.mode("overwrite").parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def _file_system(spark: SparkSession, path: str):
    target = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    return target.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()), target


def remove(spark: SparkSession, path: str) -> None:
    files, target = _file_system(spark, path)
    files.delete(target, True)


def exists(spark: SparkSession, path: str) -> bool:
    files, target = _file_system(spark, path)
    return files.exists(target)


def shuffle_partitions(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions", "200"))


def small_enough(df: DataFrame, limit: int) -> bool:
    """Whether df has at most ``limit`` rows; looks no further than that."""
    return df.limit(limit + 1).agg(F.count(F.lit(1))).first()[0] <= limit


#: Bytes that a table may have in an executor's memory to be sent to all of them.
BROADCAST_BYTES = 32 << 20
#: Bytes that a row of a few longs takes in a broadcast table, with its place in the hash map.
ROW_BYTES = 64


def broadcast_if_small(df: DataFrame, row_bytes: int = ROW_BYTES, most: int | None = None) -> DataFrame:
    """df, marked to be sent to all executors if its rows take at most ``most`` bytes; df should be a written table."""
    most = BROADCAST_BYTES if most is None else most
    return F.broadcast(df) if small_enough(df, most // row_bytes) else df


def free_names(df: DataFrame, *names: str) -> list[str]:
    """Names for helper columns, made unlike all columns of df in any case."""
    taken, out = {c.lower() for c in df.columns}, []
    for name in names:
        while name.lower() in taken:
            name += "_"
        taken.add(name.lower())
        out.append(name)
    return out
