"""Reading the given tables and keeping intermediate ones."""

from __future__ import annotations

import os
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession

from ..schemas import GIVEN, checked

#: A setting of the session: whether a query's shuffle files go when it ends.
_CLEAN = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
_local: str | None = None


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    workers_import(spark)
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return checked(df, GIVEN[name], name) if name in GIVEN else df


def workers_import(spark: SparkSession) -> None:
    """Lets Python workers import this library, wherever the session was started."""
    root = os.path.dirname(os.path.dirname(os.path.dirname(os.path.abspath(__file__))))
    env = spark.sparkContext.environment
    if root not in env.get("PYTHONPATH", "").split(os.pathsep):
        env["PYTHONPATH"] = os.pathsep.join(x for x in (root, env.get("PYTHONPATH", "")) if x)


def file_system(spark: SparkSession, path: str):
    """Hadoop's file system of a path, and the path."""
    where = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    return where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()), where


def stamp(spark: SparkSession, sf_dir: str) -> int:
    """Changes when a table of the folder does: a hash of names, sizes and times."""
    fs, where = file_system(spark, sf_dir)
    return hash(tuple(sorted((x.getPath().getName(), x.getLen(), x.getModificationTime()) for x in fs.listStatus(where))))


def new_path(spark: SparkSession, tag: str) -> str:
    """A path in the shared folder that no other call has; what is there goes when the driver's JVM ends."""
    path = f"{shared_root(spark)}/unicat-core/{uuid.uuid4().hex}-{tag}"
    fs, where = file_system(spark, path)
    fs.deleteOnExit(where)
    return path


def shared_root(spark: SparkSession) -> str:
    """The folder that the driver and all executors share: spark.checkpoint.dir. A local session without it gets its own."""
    global _local
    given = spark.conf.get("spark.checkpoint.dir", None)
    if given:
        return given.rstrip("/")
    if not spark.sparkContext.master.startswith("local["):
        raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    if _local is None:
        _local = tempfile.mkdtemp(prefix="unicat-shared-")
    return f"file://{_local}"


def keep(df: DataFrame, tag: str) -> DataFrame:
    """Writes a table to the shared folder and reads it again, which cuts lineage and outlives lost executors. The files of
    the shuffles behind it go as soon as it is written."""
    spark, path = df.sparkSession, new_path(df.sparkSession, tag)
    before = spark.conf.get(_CLEAN, "false")
    spark.conf.set(_CLEAN, "true")
    try:
        df.write.parquet(path)
    finally:
        spark.conf.set(_CLEAN, before)
    return spark.read.schema(df.schema).parquet(path)
