"""Queries of the compared methods, and the tables of purity and conditional entropy over all of them."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..operators import baselines as ba
from ..operators import descriptors as de
from ..operators import text_words as tw
from ..operators import vocabulary as vo
from ..registry import query
from ..rng import u01_sql
from . import raster_queries as ra
from . import text_queries as q

VEC = q.TEXT + ", rv AS (SELECT item_id, feat AS bin, round(r, 6) AS v FROM resp)"


@query("b01_kmeans_sql", VEC + "," + vo.lloyd_sql("rv", "item_id", 4, 3, u01_sql("42", "item_id")) + " SELECT item_id, coalesce(word, -1)::INT AS cat FROM items LEFT JOIN a3 USING (item_id)")
def b01(spark, sf_dir):
    return ba.with_wordless(ba.kmeans_items(q.responses(spark, sf_dir), 4, 3), q.items(spark, sf_dir))


G = ra.OCT + ", gg AS (SELECT item_id, ((y // 8) * 4 + x // 8) * 8 + o AS bin, sum(gx * gx + gy * gy) AS e FROM oct GROUP BY ALL), gv AS (SELECT item_id, bin, round(e / sum(e) OVER (PARTITION BY item_id), 6) AS v FROM gg)"


def global_vectors(spark, sf_dir):
    from pyspark.sql import Window

    g = de.global_gradient(ra.planted(spark, sf_dir), ra.SIDE)
    return q.held(spark, sf_dir, "global", lambda: g.select("item_id", F.col("bin").alias("feat"), F.round(F.col("v") / F.sum("v").over(Window.partitionBy("item_id")), 6).alias("r")))


@query("b02_kmeans_global", G + "," + vo.lloyd_sql("gv", "item_id", 10, 2, u01_sql("42", "item_id")) + " SELECT item_id, word::INT AS cat FROM a2")
def b02(spark, sf_dir):
    return ba.kmeans_items(global_vectors(spark, sf_dir), 10, 2)


def _plsa_sql(k: int, rounds: int) -> str:
    out = q.TEXT + f""",
z AS (SELECT z FROM range({k}) AS t(z)),
w0 AS (SELECT feat, z, w / sum(w) OVER (PARTITION BY z) AS w FROM (SELECT feat, z, 0.5 + {u01_sql("42", "'w'", "feat", "z")} AS w FROM (SELECT DISTINCT feat FROM cnt_s), z)),
p0 AS (SELECT item_id, z, d / sum(d) OVER (PARTITION BY item_id) AS d FROM (SELECT item_id, z, 0.5 + {u01_sql("42", "'d'", "item_id", "z")} AS d FROM (SELECT DISTINCT item_id FROM cnt_s), z))"""
    for i in range(rounds):
        out += f""",
e{i} AS (SELECT item_id, feat, z, n * w * d / sum(w * d) OVER (PARTITION BY item_id, feat) AS m FROM cnt_s JOIN w{i} USING (feat) JOIN p{i} USING (item_id, z)),
w{i + 1} AS (SELECT feat, z, w / sum(w) OVER (PARTITION BY z) AS w FROM (SELECT feat, z, sum(m) AS w FROM e{i} GROUP BY ALL)),
p{i + 1} AS (SELECT item_id, z, d / sum(d) OVER (PARTITION BY item_id) AS d FROM (SELECT item_id, z, sum(m) AS d FROM e{i} GROUP BY ALL))"""
    return out + f" SELECT item_id, coalesce(z, -1)::INT AS cat FROM items LEFT JOIN (SELECT item_id, arg_max(z, (round(d, 9), -z)) AS z FROM p{rounds} GROUP BY item_id) USING (item_id)"


def token_counts(spark, sf_dir):
    def make():
        i = q.items(spark, sf_dir)
        return tw.token_counts(i, tw.token_dictionary(i))

    return q.held(spark, sf_dir, "counts", make)


@query("b03_plsa_rounds", _plsa_sql(4, 2))
def b03(spark, sf_dir):
    return ba.with_wordless(ba.plsa(token_counts(spark, sf_dir), 4, 2), q.items(spark, sf_dir))


@query("b04_lda")
def b04(spark, sf_dir):
    return ba.with_wordless(ba.lda(token_counts(spark, sf_dir), 4), q.items(spark, sf_dir))


@query("b05_affinity_propagation")
def b05(spark, sf_dir):
    s = q.edges(spark, sf_dir).select("s", "t", F.round(F.log("q"), 9).alias("v"))
    return ba.with_wordless(ba.affinity_propagation(s, -2.0, 8), q.items(spark, sf_dir))
