"""Items as rasters: long pixel rows (item_id, x, y, v), from embeddings (raw or planted), text and event streams."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .tables import table

PLANTED_SIDE = 32
RAW_SIDE = 8
TEXT_SIDE = 16
SIGMA = 40.0
#: Directions of the five structural carriers (a, b): stripes where a*x + b*y changes parity.
DIRECTIONS = ((1, 0), (0, 1), (1, 1), (1, -1), (2, 1))


def raw_embedding(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The 64 floats of an embedding as 8 by 8 pixels, 128 + 320 * value. A negative control: it carries no signal."""
    e = table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("item_id"), F.posexplode("embedding").alias("i", "f"))
    return e.select("item_id", (F.col("i") % RAW_SIDE).alias("x"), F.floor(F.col("i") / RAW_SIDE).cast("int").alias("y"), (128 + 320 * F.col("f").cast("double")).alias("v"))


def planted(spark: SparkSession, sf_dir: str, sigma: float = SIGMA) -> DataFrame:
    """32 by 32 pixels with a carrier that depends on the label, and the embedding as noise of strength sigma."""
    e = table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("item_id"), "label", "embedding")
    xs = F.sequence(F.lit(0), F.lit(PLANTED_SIDE - 1))
    p = e.select("item_id", "label", "embedding", F.explode(xs).alias("y")).select("*", F.explode(xs).alias("x"))
    stripes = [F.when(F.col("label") == k, F.floor((a * F.col("x") + b * F.col("y") + 128) / 4) % 2 == 0) for k, (a, b) in enumerate(DIRECTIONS)]
    digit = F.conv(F.substring(F.md5(F.concat_ws("|", (F.col("label") - 5).cast("string"), (F.col("x") % 5).cast("string"), (F.col("y") % 5).cast("string"))), 1, 1), 16, 10).cast("int")
    up = F.coalesce(*stripes, digit % 2 == 1)
    noise = F.element_at("embedding", ((7 * F.col("x") + 13 * F.col("y") + 3 * F.col("x") * F.col("y")) % 64 + 1).cast("int")).cast("double")
    return p.select("item_id", "x", "y", (128 + F.when(up, 50).otherwise(-50) + F.lit(sigma * 8) * noise).alias("v"))


PLANTED_SQL = f"""
planted AS (
  SELECT vec_id AS item_id, x, y, 128 + CASE WHEN up THEN 50 ELSE -50 END + {SIGMA * 8} * embedding[((7*x + 13*y + 3*x*y) % 64 + 1)::INT]::DOUBLE AS v
  FROM (SELECT vec_id, label, embedding, x::INT AS x, y::INT AS y,
    CASE label {" ".join(f"WHEN {k} THEN (({a}*x + {b}*y + 128) // 4) % 2 = 0" for k, (a, b) in enumerate(DIRECTIONS))}
      ELSE ('0x' || substr(md5((label - 5)::VARCHAR || '|' || (x % 5)::VARCHAR || '|' || (y % 5)::VARCHAR), 1, 1))::INT % 2 = 1 END AS up
    FROM embeddings, range(0, {PLANTED_SIDE}) AS a(x), range(0, {PLANTED_SIDE}) AS b(y))
)"""


def text_raster(df: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """All code points of a text, 16 a row, as intensities; code points over 255 count as 255."""
    chars = F.filter(F.split(F.coalesce(F.col(text_col), F.lit("")), ""), lambda c: c != "")
    e = df.select(F.col(id_col).alias("item_id"), F.posexplode(chars).alias("i", "c"))
    return e.select("item_id", (F.col("i") % TEXT_SIDE).alias("x"), F.floor(F.col("i") / TEXT_SIDE).cast("int").alias("y"), F.least(F.lit(255), F.ascii("c")).cast("double").alias("v"))


def event_raster(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Users as rasters of hours (x) by weekdays (y): how many events a user has in each."""
    e = table(spark, sf_dir, "events")
    # Rows of the raster: the seven weekdays, so that a habit is a pattern in it.
    return e.groupBy(F.col("user_id").alias("item_id"), F.hour("ts").alias("x"), F.weekday("ts").alias("y")).agg(F.count(F.lit(1)).cast("double").alias("v"))


def as_arrays(pixels: DataFrame, side: int) -> DataFrame:
    """item_id and px, the pixels of a side by side raster in row order."""
    ordered = F.array_sort(F.collect_list(F.struct((F.col("y") * side + F.col("x")).alias("i"), "v")))
    return pixels.groupBy("item_id").agg(F.transform(ordered, lambda s: s["v"]).alias("px"))
