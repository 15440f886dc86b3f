"""Helpers that the training-data operators share: scratch tables, worker paths, skew-aware joins."""

from __future__ import annotations

import os
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

UPPER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"
LOWER = "abcdefghijklmnopqrstuvwxyz"
#: A join key is heavy when it holds more than one row in HEAVY_SHARE, so no more than HEAVY_SHARE keys can be heavy.
HEAVY_SHARE = 10_000
HEAVY_LEAST = 1_000
BATCH_ROWS = 1_000

_local_scratch: str | None = None


def ascii_lower(col):
    """Lower-cases A-Z alone; every other code point stays."""
    return F.translate(col, UPPER, LOWER)


def prepare(spark: SparkSession) -> SparkSession:
    """Lets Python workers import this library, wherever the session was started, and keeps Arrow batches small."""
    root = os.path.dirname(os.path.dirname(os.path.dirname(os.path.abspath(__file__))))
    env = spark.sparkContext.environment
    if root not in env.get("PYTHONPATH", "").split(os.pathsep):
        env["PYTHONPATH"] = os.pathsep.join(x for x in (root, env.get("PYTHONPATH", "")) if x)
    # Whole texts go to Python: fewer of them at a time keep a worker's memory small.
    if int(spark.conf.get("spark.sql.execution.arrow.maxRecordsPerBatch")) > BATCH_ROWS:
        spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", str(BATCH_ROWS))
    return spark


def scratch_root(spark: SparkSession) -> str:
    """The shared folder for intermediate tables: spark.checkpoint.dir; only a local session without it gets a folder of its own."""
    global _local_scratch
    given = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if given:
        return given.rstrip("/")
    if not spark.sparkContext.master.startswith("local["):
        raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    if _local_scratch is None:
        _local_scratch = tempfile.mkdtemp(prefix="unicat-scratch-")
    return f"file://{_local_scratch}"


def _delete_at_end(spark: SparkSession, path: str) -> None:
    """Intermediate tables go when the driver's JVM ends; results that are still read from them need them until then."""
    jvm = spark.sparkContext._jvm
    where = jvm.org.apache.hadoop.fs.Path(path)
    where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).deleteOnExit(where)


def aside(df: DataFrame) -> tuple[DataFrame, dict[str, str]]:
    """df with its columns that start with __, as the operators' own do, under other names, and new name -> old name."""
    names: dict[str, str] = {}
    for c in df.columns:
        if c.startswith("__"):
            new = f"in{c}"
            while new in df.columns or new in names:
                new = f"in{new}"
            names[new] = c
    return df.withColumnsRenamed({old: new for new, old in names.items()}), names


def named(col: str, names: dict[str, str]) -> str:
    """What a column of the caller is called while its names are set aside."""
    return next((new for new, old in names.items() if old == col), col)


def back(df: DataFrame, names: dict[str, str]) -> DataFrame:
    """The caller's names again, but for those that a column of the operator has now: these stay as in__..."""
    own = {c.lower() for c in df.columns}
    return df.withColumnsRenamed({new: old for new, old in names.items() if old.lower() not in own})


#: A setting of the session: whether a query's shuffle files go when it ends, instead of when the driver collects garbage.
_CLEAN = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


def materialise(df: DataFrame, tag: str) -> DataFrame:
    """Writes a table to the shared folder and reads it again: cuts lineage and survives lost executors. The shuffles behind
    it are not needed again, so their files are removed when the table is written."""
    spark = df.sparkSession
    path = f"{scratch_root(spark)}/unicat/{uuid.uuid4().hex}-{tag}"
    _delete_at_end(spark, path)
    before = spark.conf.get(_CLEAN, "false")
    spark.conf.set(_CLEAN, "true")
    try:
        df.write.parquet(path)
    finally:
        spark.conf.set(_CLEAN, before)
    return spark.read.schema(df.schema).parquet(path)


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    prepare(spark)
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def split_heavy(keys: DataFrame, rows_col: str):
    """(heavy, light) of a materialised table with one row a key; heavy is None or at most HEAVY_SHARE rows, so it can be broadcast."""
    total = keys.agg(F.sum(rows_col)).first()[0] or 0
    limit = max(HEAVY_LEAST, total // HEAVY_SHARE)
    if keys.where(F.col(rows_col) > limit).limit(1).count() == 0:
        return None, keys
    return keys.where(F.col(rows_col) > limit), keys.where(F.col(rows_col) <= limit)


def join_keys(rows: DataFrame, keys: DataFrame, on: list[str], rows_col: str) -> DataFrame:
    """Inner join of many rows with a materialised table of distinct keys. Heavy keys go to a broadcast of at most
    HEAVY_SHARE rows; the others, of which none holds more than one row in HEAVY_SHARE, are shuffled."""
    heavy, light = split_heavy(keys, rows_col)
    out = rows.join(light, on)
    return out if heavy is None else out.unionByName(rows.join(F.broadcast(heavy), on))


def trim() -> None:
    """Gives a worker's freed memory back to the system; workers outlive their tasks."""
    import ctypes
    import gc

    import pyarrow as pa

    gc.collect()
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL("libc.so.6").malloc_trim(0)
    except (OSError, AttributeError):  # not glibc
        return
