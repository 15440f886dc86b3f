"""Sources and sinks around the methods: exchange formats, partitioned and bucketed tables, images, rasters made on the
fly, and saved solutions."""

from __future__ import annotations

import hashlib
import re

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition
from pyspark.sql.functions import pandas_udf

from .rasters import DIRECTIONS, PLANTED_SIDE
from .tables import file_system

FORMATS = ("csv", "json", "orc", "parquet")


def save_as(df: DataFrame, path: str, fmt: str) -> None:
    """A flat table in an exchange format."""
    w = df.write.mode("overwrite")
    (w.option("header", "true") if fmt == "csv" else w).format(fmt).save(path)


def load_as(spark: SparkSession, path: str, fmt: str, schema) -> DataFrame:
    r = spark.read.schema(schema)
    return (r.option("header", "true") if fmt == "csv" else r).format(fmt).load(path)


def save_lines(df: DataFrame, path: str, column: str) -> None:
    """One column as text files, a row a line: white space within is a blank."""
    df.select(F.regexp_replace(F.coalesce(F.col(column).cast("string"), F.lit("")), r"\s+", " ").alias("value")).write.mode("overwrite").text(path)


def save_responses(resp: DataFrame, path: str) -> None:
    """Responses in folders by word type, so that a reader of one type reads its files only."""
    resp.write.mode("overwrite").partitionBy("wtype").parquet(path)


def save_bucketed(df: DataFrame, name: str, key: str, buckets: int) -> DataFrame:
    """A managed table in buckets by a key, sorted in them: joins and sums by the key need no shuffle."""
    df.write.mode("overwrite").bucketBy(buckets, key).sortBy(key).format("parquet").saveAsTable(name)
    return df.sparkSession.table(name)


def save_solution(path: str, **tables: DataFrame) -> None:
    """labels, models, trace and what else a solution has, a table each."""
    for name, df in tables.items():
        df.write.mode("overwrite").parquet(f"{path}/{name}")


def load_solution(spark: SparkSession, path: str) -> dict[str, DataFrame]:
    fs, where = file_system(spark, path)
    return {x.getPath().getName(): spark.read.parquet(f"{path}/{x.getPath().getName()}") for x in fs.listStatus(where) if x.isDirectory()}


def to_pgm(px, width: int) -> bytes:
    """A grey raster as a binary PGM image, intensities rounded and cut to 0..255."""
    v = np.clip(np.rint(np.asarray(px, float)), 0, 255).astype(np.uint8)
    return b"P5\n%d %d\n255\n" % (width, len(v) // width) + v.tobytes()


def from_netpbm(raw: bytes) -> tuple[int, int, np.ndarray] | None:
    """(width, height, grey intensities 0..255) of a PGM (binary or plain) or binary PPM image, with comments and either depth; else None."""
    if raw[:2] == b"P2":
        return _from_plain(raw)
    m = re.match(rb"P([56])((?:\s+|#[^\n]*\n)+)(\d+)((?:\s+|#[^\n]*\n)+)(\d+)((?:\s+|#[^\n]*\n)+)(\d+)\s", raw)
    if m is None:
        return None
    w, h, top, channels = int(m[3]), int(m[5]), int(m[7]), 1 if m[1] == b"5" else 3
    v = np.frombuffer(raw[m.end() :], np.uint8 if top < 256 else ">u2")
    if len(v) < w * h * channels:
        return None
    v = v[: w * h * channels].reshape(-1, channels).astype(float) * (255 / top)
    return w, h, (v[:, 0] if channels == 1 else v @ np.array([0.299, 0.587, 0.114]))


def _from_plain(raw: bytes) -> tuple[int, int, np.ndarray] | None:
    """As from_netpbm, of a grey image whose numbers are written out."""
    try:
        n = np.array(re.sub(rb"#[^\n]*", b"", raw[2:]).split(), np.int64)
    except ValueError:
        return None
    if len(n) < 3 or n[2] < 1 or len(n) < 3 + n[0] * n[1]:
        return None
    return int(n[0]), int(n[1]), n[3 : 3 + n[0] * n[1]] * (255 / n[2])


@pandas_udf(T.StructType([T.StructField("w", T.IntegerType()), T.StructField("h", T.IntegerType()), T.StructField("px", T.ArrayType(T.DoubleType()))]))
def decode_image(raw: pd.Series) -> pd.DataFrame:
    rows = [from_netpbm(x) or (None, None, None) for x in raw]
    return pd.DataFrame({"w": pd.array([r[0] for r in rows], "Int32"), "h": pd.array([r[1] for r in rows], "Int32"), "px": [r[2] for r in rows]})


def read_images(spark: SparkSession, path: str) -> DataFrame:
    """path, w, h, px of every readable image under a path; others have null w, h and px."""
    files = spark.read.format("binaryFile").load(path).select("path", "content")
    return files.select("path", decode_image("content").alias("i")).select("path", "i.w", "i.h", "i.px")


class _Label(InputPartition):
    def __init__(self, label: int):
        self.label = label


class _RasterReader(DataSourceReader):
    def __init__(self, labels: list[int], side: int):
        self.labels, self.side = labels, side

    def partitions(self):
        return [_Label(k) for k in self.labels]

    def read(self, partition):
        k = partition.label
        for y in range(self.side):
            for x in range(self.side):
                if 0 <= k < len(DIRECTIONS):
                    a, b = DIRECTIONS[k]
                    up = (a * x + b * y + 128) // 4 % 2 == 0
                else:
                    up = int(hashlib.md5(f"{k - 5}|{x % 5}|{y % 5}".encode()).hexdigest()[0], 16) % 2 == 1
                yield k, x, y, 178.0 if up else 78.0


class CarrierRasters(DataSource):
    """The carriers of the planted rasters without noise, a partition a label: spark.read.format("unicat_carriers"). Option
    labels: how many from 0 on; or only: which, joined by commas."""

    @classmethod
    def name(cls) -> str:
        return "unicat_carriers"

    def schema(self) -> str:
        return "label int, x int, y int, v double"

    def reader(self, schema) -> DataSourceReader:
        only = self.options.get("only")
        labels = range(int(self.options.get("labels", 10))) if only is None else [int(k) for k in only.split(",") if k]
        return _RasterReader(list(labels), int(self.options.get("side", PLANTED_SIDE)))
