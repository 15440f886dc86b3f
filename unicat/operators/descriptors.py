"""Patch descriptors of rasters: gradients, orientation histograms, centre-symmetric codes, at three scales.

Rasters are arrays in row order (item_id, px) of side * side values; one row holds an item, so no operator here shuffles.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

PATCH, CELLS, ANGLES, CODES = 8, 2, 8, 16


def _at(px: Column, x: Column, y: Column, side: int) -> Column:
    """The pixel at (x, y), with the border repeated beyond it."""
    inside = lambda v: F.least(F.lit(side - 1), F.greatest(F.lit(0), v))
    return px[(inside(y) * side + inside(x)).cast("int")]


def pixels(rasters: DataFrame, side: int) -> DataFrame:
    """item_id, x, y and px for each pixel."""
    i = F.explode(F.sequence(F.lit(0), F.lit(side * side - 1))).alias("i")
    return rasters.select("item_id", "px", i).select("item_id", "px", (F.col("i") % side).alias("x"), F.floor(F.col("i") / side).cast("int").alias("y"))


def gradients(rasters: DataFrame, side: int) -> DataFrame:
    """item_id, x, y, gx, gy: central differences."""
    p, x, y = F.col("px"), F.col("x"), F.col("y")
    return pixels(rasters, side).select("item_id", "x", "y", (_at(p, x + 1, y, side) - _at(p, x - 1, y, side)).alias("gx"), (_at(p, x, y + 1, side) - _at(p, x, y - 1, side)).alias("gy"))


def octant(gx: Column, gy: Column) -> Column:
    """The angle of a gradient among eight, by comparisons alone, so that every engine agrees."""
    steep = F.abs(gy) > F.abs(gx)
    return F.when(gy >= 0, F.when(gx > 0, F.when(steep, 1).otherwise(0)).otherwise(F.when(steep, 2).otherwise(3))).otherwise(F.when(gx <= 0, F.when(steep, 5).otherwise(4)).otherwise(F.when(steep, 6).otherwise(7)))


OCTANT_SQL = "CASE WHEN gy >= 0 THEN CASE WHEN gx > 0 THEN CASE WHEN abs(gy) > abs(gx) THEN 1 ELSE 0 END ELSE CASE WHEN abs(gy) > abs(gx) THEN 2 ELSE 3 END END ELSE CASE WHEN gx <= 0 THEN CASE WHEN abs(gy) > abs(gx) THEN 5 ELSE 4 END ELSE CASE WHEN abs(gy) > abs(gx) THEN 6 ELSE 7 END END END"


def centre_symmetric_codes(rasters: DataFrame, side: int, threshold: float = 1.0, radius: int = 1) -> DataFrame:
    """item_id, x, y, code 0..15: bit i is set if a neighbour exceeds the opposite one by more than the threshold."""
    p, x, y = F.col("px"), F.col("x"), F.col("y")
    ring = ((1, 0), (1, 1), (0, 1), (-1, 1))
    bits = [F.when(_at(p, x + radius * dx, y + radius * dy, side) - _at(p, x - radius * dx, y - radius * dy, side) > threshold, 1 << i).otherwise(0) for i, (dx, dy) in enumerate(ring)]
    return pixels(rasters, side).select("item_id", "x", "y", sum(bits[1:], bits[0]).alias("code"))


def halved(rasters: DataFrame, side: int) -> DataFrame:
    """Half the resolution: means of two by two pixels."""
    p, half = F.col("px"), side // 2

    def mean(i):
        x, y = (i % half) * 2, F.floor(i / half).cast("int") * 2
        return (p[y * side + x] + p[y * side + x + 1] + p[(y + 1) * side + x] + p[(y + 1) * side + x + 1]) / 4

    return rasters.select("item_id", F.transform(F.sequence(F.lit(0), F.lit(half * half - 1)), mean).alias("px"))


def _patched(rows: DataFrame, side: int, scale: int, patch: int) -> DataFrame:
    across = side // patch
    cell = patch // CELLS
    return rows.select(
        "item_id", F.lit(scale).alias("scale"), (F.floor(F.col("y") / patch) * across + F.floor(F.col("x") / patch)).cast("int").alias("patch"),
        (F.floor((F.col("y") % patch) / cell) * CELLS + F.floor((F.col("x") % patch) / cell)).cast("int").alias("cell"), *[c for c in rows.columns if c not in ("item_id", "x", "y")],
    )


def structural(rasters: DataFrame, side: int, scale: int = 0, patch: int = PATCH, weight: str = "magnitude", norm: str = "l1") -> DataFrame:
    """item_id, scale, patch, bin (cell * 8 + angle), v: orientation histograms (32 bins) of magnitudes or counts, each patch
    summing to one (l1), of length one (l2) or as it is (none)."""
    size = F.sqrt(F.col("gx") * F.col("gx") + F.col("gy") * F.col("gy")) if weight == "magnitude" else F.lit(1.0)
    g = _patched(gradients(rasters, side), side, scale, patch).where("gx <> 0 or gy <> 0")
    h = g.groupBy("item_id", "scale", "patch", (F.col("cell") * ANGLES + octant(F.col("gx"), F.col("gy"))).alias("bin")).agg(F.sum(size).alias("m"))
    return _shares(h, norm)


def texture(rasters: DataFrame, side: int, scale: int = 0, patch: int = PATCH, threshold: float = 1.0) -> DataFrame:
    """item_id, scale, patch, bin (cell * 16 + code), v: histograms of codes, each patch summing to one (64 bins)."""
    c = _patched(centre_symmetric_codes(rasters, side, threshold), side, scale, patch)
    return _shares(c.groupBy("item_id", "scale", "patch", (F.col("cell") * CODES + F.col("code")).alias("bin")).agg(F.count(F.lit(1)).cast("double").alias("m")))


def _shares(h: DataFrame, norm: str = "l1") -> DataFrame:
    if norm == "none":
        return h.withColumnRenamed("m", "v")
    size = F.sum("m") if norm == "l1" else F.sqrt(F.sum(F.col("m") * F.col("m")))
    total = h.groupBy("item_id", "scale", "patch").agg(size.alias("total"))
    return h.join(total, ["item_id", "scale", "patch"]).select("item_id", "scale", "patch", "bin", (F.col("m") / F.col("total")).alias("v"))


def pyramid(rasters: DataFrame, side: int, kind: str = "S", scales: int = 3, patch: int = PATCH) -> DataFrame:
    """Descriptors at several scales; each scale has half the resolution of the one before."""
    out, r = None, rasters
    for scale in range(scales):
        if side < patch:
            break
        d = (structural if kind == "S" else texture)(r, side, scale, patch)
        out = d if out is None else out.unionByName(d)
        r, side = halved(r, side), side // 2
    return out


def blocks(patches: DataFrame, side: int, patch: int = PATCH) -> DataFrame:
    """Adds block, one row for each block that a patch lies in: 0 is the whole item; 1 to 4 are the quarters at the finest
    scale and 5 to 8 those at the next."""
    across = F.greatest(F.lit(1), F.floor(F.lit(side // patch) / F.pow(F.lit(2), F.col("scale"))).cast("int"))
    x, y = F.col("patch") % across, F.floor(F.col("patch") / across)
    quarter = (F.when(2 * y >= across, 2).otherwise(0) + F.when(2 * x >= across, 1).otherwise(0)).cast("int")
    own = F.when(F.col("scale") == 0, F.array(F.lit(0), 1 + quarter)).when(F.col("scale") == 1, F.array(F.lit(0), 5 + quarter)).otherwise(F.array(F.lit(0)))
    return patches.withColumn("block", F.explode(own))


def global_gradient(rasters: DataFrame, side: int, grid: int = 4) -> DataFrame:
    """item_id, bin (cell of the grid * 8 + angle), v: gradient energy of the whole item."""
    cell = side // grid
    g = gradients(rasters, side)
    at = (F.floor(F.col("y") / cell) * grid + F.floor(F.col("x") / cell)).cast("int")
    return g.groupBy("item_id", (at * ANGLES + octant(F.col("gx"), F.col("gy"))).alias("bin")).agg(F.sum(F.col("gx") * F.col("gx") + F.col("gy") * F.col("gy")).alias("v"))


def dense_gradient(rasters: DataFrame, side: int, patch: int = 16, grid: int = 4) -> DataFrame:
    """item_id, patch, bin (128: a four by four grid of eight angles), v: gradient magnitudes."""
    across, cell = side // patch, patch // grid
    g = gradients(rasters, side)
    x, y = F.col("x"), F.col("y")
    at = (F.floor((y % patch) / cell) * grid + F.floor((x % patch) / cell)).cast("int")
    return g.groupBy("item_id", (F.floor(y / patch) * across + F.floor(x / patch)).cast("int").alias("patch"), (at * ANGLES + octant(F.col("gx"), F.col("gy"))).alias("bin")).agg(F.sum(F.sqrt(F.col("gx") * F.col("gx") + F.col("gy") * F.col("gy"))).alias("v"))
