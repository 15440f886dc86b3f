"""Functions that users call on columns: divergences of word maps, codes of rasters, clustering measures, patches."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.functions import pandas_udf, udtf


def sym_kl(a: Column, b: Column, dims: int, eps: float = 1e-2) -> Column:
    """The symmetric divergence of two maps of feature -> response over dims features, smoothed by eps."""

    def total(m):
        return F.aggregate(F.map_values(m), F.lit(0.0), lambda t, x: t + x) + eps * dims

    za, zb = total(a), total(b)

    def terms(_, x, y):
        p, q = (F.coalesce(x, F.lit(0.0)) + eps) / za, (F.coalesce(y, F.lit(0.0)) + eps) / zb
        return (p - q) * F.log(p / q)

    held = F.map_zip_with(a, b, terms)
    rest = (eps / za - eps / zb) * F.log(zb / za) * (dims - F.size(held))  # features that neither has
    return F.greatest(F.lit(0.0), F.aggregate(F.map_values(held), F.lit(0.0), lambda t, x: t + x) + rest)


def register_sql(spark: SparkSession) -> None:
    """SQL functions unicat_kl_term(p, q) and unicat_edge(j, tau), without Python in their plans, and the table function unicat_patches."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION unicat_kl_term(p DOUBLE, q DOUBLE) RETURNS DOUBLE RETURN (p - q) * ln(p / q)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION unicat_edge(j DOUBLE, tau DOUBLE) RETURNS DOUBLE RETURN least(0.999999999D, exp(-tau * j))")
    spark.udtf.register("unicat_patches", Patches)


def ring_codes(px: np.ndarray, side: int, radius: float = 1.0, threshold: float = 1.0, interpolate: bool = False) -> np.ndarray:
    """Codes 0..15 of every pixel of rasters (rows of side * side values). interpolate takes the diagonal neighbours on the
    circle of the radius by bilinear interpolation, else they are the pixels at whole steps of it. The border is repeated."""
    v = px.reshape(-1, side, side)
    step = np.arange(side)

    def at(dx: float, dy: float) -> np.ndarray:
        x, y = np.clip(step + dx, 0, side - 1), np.clip(step + dy, 0, side - 1)
        x0, y0 = np.floor(x).astype(int), np.floor(y).astype(int)
        x1, y1, fx, fy = np.minimum(x0 + 1, side - 1), np.minimum(y0 + 1, side - 1), (x - x0)[None, None, :], (y - y0)[None, :, None]
        top = v[:, y0][:, :, x0] * (1 - fx) + v[:, y0][:, :, x1] * fx
        return top * (1 - fy) + (v[:, y1][:, :, x0] * (1 - fx) + v[:, y1][:, :, x1] * fx) * fy

    d = radius / np.sqrt(2) if interpolate else radius
    out = np.zeros(v.shape, np.int64)
    for i, (dx, dy) in enumerate(((radius, 0), (d, d), (0, radius), (-d, d))):
        out |= (at(dx, dy) - at(-dx, -dy) > threshold).astype(np.int64) << i
    return out.reshape(len(v), -1)


def cs_codes(side: int, radius: float = 1.0, threshold: float = 1.0, interpolate: bool = False):
    """An Arrow function of px (array of side * side values) to the array of its codes."""

    @pandas_udf(T.ArrayType(T.IntegerType()))
    def codes(px: pd.Series) -> pd.Series:
        return pd.Series(list(ring_codes(np.stack(px.to_numpy()).astype(float), side, radius, threshold, interpolate).astype(np.int32))) if len(px) else pd.Series([], dtype=object)

    return codes


def _table(cat: pd.Series, truth: pd.Series) -> np.ndarray:
    return pd.crosstab(cat, truth).to_numpy()


@pandas_udf(T.DoubleType())
def purity(cat: pd.Series, truth: pd.Series) -> float:
    """Share of rows that have the most frequent truth of their category; for tables that fit a task (else measures.purity)."""
    return float(_table(cat, truth).max(axis=1).sum() / len(cat)) if len(cat) else float("nan")


@pandas_udf(T.DoubleType())
def cond_entropy(cat: pd.Series, truth: pd.Series) -> float:
    """H(truth | category) in nats; for tables that fit a task (else measures.conditional_entropy)."""
    n = _table(cat, truth).astype(float)
    size = np.broadcast_to(n.sum(axis=1, keepdims=True), n.shape)
    return float((n[n > 0] * np.log(size[n > 0] / n[n > 0])).sum() / n.sum()) if len(cat) else float("nan")


@udtf(returnType=T.StructType([*(T.StructField(c, T.IntegerType()) for c in ("patch", "x", "y")), T.StructField("v", T.DoubleType())]))
class Patches:
    """The pixels of all patches of a raster: patches of a size every stride pixels; strides under the size overlap."""

    def eval(self, px, w: int, h: int, size: int, stride: int):
        across = (w - size) // stride + 1
        for j in range((h - size) // stride + 1):
            for i in range(across):
                for y in range(size):
                    for x in range(size):
                        yield j * across + i, x, y, float(px[(j * stride + y) * w + i * stride + x])
