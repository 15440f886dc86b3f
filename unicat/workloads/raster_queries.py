"""Queries of the raster operators on planted and raw rasters, with their DuckDB twins."""

from __future__ import annotations

import re

from pyspark.sql import functions as F

from ..operators import descriptors as de
from ..operators import text_words as tw
from ..operators import vocabulary as vo
from ..registry import query
from ..rng import u01_sql
from ..sources import rasters
from ..sources.tables import table
from . import text_queries as q
from .text_queries import held, rounded

SIDE = rasters.PLANTED_SIDE
P = "WITH " + rasters.PLANTED_SQL
#: The eight neighbours of every pixel with the border repeated, by windows along rows and then along columns.
NEAR = P.replace("planted AS (", "planted AS MATERIALIZED (") + """, nb AS (
  SELECT *, coalesce(lag(v) OVER w, v) AS l, coalesce(lead(v) OVER w, v) AS r FROM planted WINDOW w AS (PARTITION BY item_id, y ORDER BY x)
), nc AS (
  SELECT *, coalesce(lag(v) OVER w, v) AS u, coalesce(lead(v) OVER w, v) AS d, coalesce(lag(l) OVER w, l) AS ul, coalesce(lead(l) OVER w, l) AS dl, coalesce(lag(r) OVER w, r) AS ur, coalesce(lead(r) OVER w, r) AS dr
  FROM nb WINDOW w AS (PARTITION BY item_id, x ORDER BY y))"""
GRAD = NEAR + ", grad AS (SELECT item_id, x, y, r - l AS gx, d - u AS gy FROM nc)"
OCT = GRAD + f", oct AS (SELECT *, {de.OCTANT_SQL} AS o FROM grad)"
CODE = NEAR + """, codes AS (SELECT item_id, x, y, (CASE WHEN r - l > 1 THEN 1 ELSE 0 END) + (CASE WHEN dr - ul > 1 THEN 2 ELSE 0 END)
  + (CASE WHEN d - u > 1 THEN 4 ELSE 0 END) + (CASE WHEN dl - ur > 1 THEN 8 ELSE 0 END) AS code FROM nc)"""
PATCHED = "(y // 8) * 4 + x // 8 AS patch, ((y % 8) // 4) * 2 + (x % 8) // 4 AS cell"
STRUCT = OCT + f""", sm AS (SELECT item_id, patch, cell * 8 + o AS bin, sum(sqrt(gx * gx + gy * gy)) AS m FROM (SELECT *, {PATCHED} FROM oct WHERE gx <> 0 OR gy <> 0) GROUP BY ALL),
struct_h AS (SELECT item_id, patch, bin, m / sum(m) OVER (PARTITION BY item_id, patch) AS v FROM sm)"""
TEXTURE = CODE + f""", tm AS (SELECT item_id, patch, cell * 16 + code AS bin, count(*)::DOUBLE AS m FROM (SELECT *, {PATCHED} FROM codes) GROUP BY ALL),
text_h AS (SELECT item_id, patch, bin, m / sum(m) OVER (PARTITION BY item_id, patch) AS v FROM tm)"""


#: Token counts over nine blocks: the whole, quarters by all tokens, quarters by every second one.
TEXT_BLOCKS = q.TEXT + """, words_in AS (SELECT item_id, regexp_extract_all(lower(text), '[\\p{L}]+') AS ws FROM items),
wp AS (SELECT item_id, len(ws) AS size, unnest(ws) AS w, unnest(range(len(ws))) AS i FROM words_in),
bc AS (SELECT item_id, block, feat, count(*) AS n FROM (SELECT item_id, feat, unnest(CASE WHEN i % 2 = 0 THEN [0, 1 + i * 4 // size, 5 + i * 4 // size] ELSE [0, 1 + i * 4 // size] END) AS block FROM wp JOIN dict USING (w)) GROUP BY ALL)"""


def _scale_sql(src: str, side: int, mark: str) -> str:
    """The CTEs from neighbours to structural histograms for another raster table and side, under marked names."""
    tail = STRUCT[len(P) :].replace("(y // 8) * 4 + x // 8", f"(y // 8) * {side // 8} + x // 8")
    tail = re.sub(r"\b(nb|nc|grad|oct|sm|struct_h)\b", rf"\g<1>{mark}", tail[tail.index("nb AS (") :])
    return re.sub(r"\bplanted\b", src, tail)


#: Structural histograms of three scales: struct_h, struct_h1, struct_h2.
PYRAMID = (
    STRUCT
    + ", half1 AS (SELECT item_id, (x // 2)::INT AS x, (y // 2)::INT AS y, sum(v) / 4 AS v FROM planted GROUP BY item_id, x // 2, y // 2), "
    + _scale_sql("half1", 16, "1")
    + ", half2 AS (SELECT item_id, (x // 2)::INT AS x, (y // 2)::INT AS y, sum(v) / 4 AS v FROM half1 GROUP BY item_id, x // 2, y // 2), "
    + _scale_sql("half2", 8, "2")
    + ", every AS (SELECT 0 AS scale, * FROM struct_h UNION ALL SELECT 1, * FROM struct_h1 UNION ALL SELECT 2, * FROM struct_h2)"
)


def planted(spark, sf_dir):
    return held(spark, sf_dir, "planted", lambda: rasters.as_arrays(rasters.planted(spark, sf_dir), SIDE))


@query("r01_raster_embedding", "SELECT vec_id AS item_id, (i % 8)::INT AS x, (i // 8)::INT AS y, round(128 + 320 * f::DOUBLE, 6) AS v FROM (SELECT vec_id, unnest(embedding) AS f, unnest(range(64)) AS i FROM embeddings)")
def r01(spark, sf_dir):
    return rounded(rasters.raw_embedding(spark, sf_dir), "v")


@query("r01_raster_planted", P + " SELECT item_id, x, y, round(v, 6) AS v FROM planted")
def r01_planted(spark, sf_dir):
    return rounded(rasters.planted(spark, sf_dir), "v")


@query("r01_raster_text", "SELECT item_id, (i % 16)::INT AS x, (i // 16)::INT AS y, least(255, c)::DOUBLE AS v FROM (SELECT doc_id AS item_id, unnest(c) AS c, unnest(range(len(c))) AS i FROM (SELECT doc_id, [unicode(c) FOR c IN regexp_extract_all(text, '(?s).')] AS c FROM documents))")
def r01_text(spark, sf_dir):
    return rasters.text_raster(table(spark, sf_dir, "documents"), "doc_id", "text")


@query("r01_raster_events", "SELECT user_id AS item_id, hour(ts)::INT AS x, (isodow(ts) - 1)::INT AS y, count(*)::DOUBLE AS v FROM events GROUP BY ALL")
def r01_events(spark, sf_dir):
    return rasters.event_raster(spark, sf_dir)


@query("r02_gradients", GRAD + " SELECT item_id, x, y, round(gx, 6) AS gx, round(gy, 6) AS gy FROM grad")
def r02(spark, sf_dir):
    return rounded(de.gradients(planted(spark, sf_dir), SIDE), "gx", "gy")


@query("r03_octants", OCT + " SELECT item_id, o, count(*) AS n FROM oct GROUP BY ALL")
def r03(spark, sf_dir):
    return de.gradients(planted(spark, sf_dir), SIDE).groupBy("item_id", de.octant(F.col("gx"), F.col("gy")).alias("o")).agg(F.count(F.lit(1)).alias("n"))


@query("r04_structural_hist", STRUCT + " SELECT item_id, patch::INT AS patch, bin::INT AS bin, round(v, 6) AS v FROM struct_h")
def r04(spark, sf_dir):
    return rounded(de.structural(planted(spark, sf_dir), SIDE).select("item_id", "patch", "bin", "v"), "v")


@query("r05_cs_codes", CODE + " SELECT item_id, x, y, code::INT AS code FROM codes")
def r05(spark, sf_dir):
    return de.centre_symmetric_codes(planted(spark, sf_dir), SIDE)


@query("r06_strength_map", CODE + " SELECT code::INT AS code, count(*) AS n FROM codes GROUP BY code")
def r06(spark, sf_dir):
    return de.centre_symmetric_codes(planted(spark, sf_dir), SIDE).groupBy("code").agg(F.count(F.lit(1)).alias("n"))


@query("r07_texture_hist", TEXTURE + " SELECT item_id, patch::INT AS patch, bin::INT AS bin, round(v, 6) AS v FROM text_h")
def r07(spark, sf_dir):
    return rounded(de.texture(planted(spark, sf_dir), SIDE).select("item_id", "patch", "bin", "v"), "v")


@query("r08_patch_pyramid", PYRAMID + " SELECT scale::INT AS scale, patch::INT AS patch, count(DISTINCT item_id) AS items, count(*) AS bins FROM every GROUP BY ALL")
def r08(spark, sf_dir):
    return de.pyramid(planted(spark, sf_dir), SIDE).groupBy("scale", "patch").agg(F.countDistinct("item_id").alias("items"), F.count(F.lit(1)).alias("bins"))


@query("r13_blocks", PYRAMID + """, b AS (SELECT scale, patch, unnest(CASE scale WHEN 0 THEN [0, 1 + 2 * (patch // 8) + (patch % 4) // 2] WHEN 1 THEN [0, 5 + patch] ELSE [0] END) AS block FROM (SELECT DISTINCT scale, patch FROM every))
  SELECT block::INT AS block, scale::INT AS scale, count(DISTINCT patch) AS patches FROM b GROUP BY ALL""")
def r13(spark, sf_dir):
    p = de.pyramid(planted(spark, sf_dir), SIDE).select("item_id", "scale", "patch").distinct()
    return de.blocks(p, SIDE).groupBy("block", "scale").agg(F.countDistinct("patch").alias("patches"))


@query("r19_global_gradient", OCT + " SELECT item_id, ((y // 8) * 4 + x // 8) * 8 + o AS bin, round(sum(gx * gx + gy * gy), 4) AS v FROM oct GROUP BY ALL")
def r19(spark, sf_dir):
    g = de.global_gradient(planted(spark, sf_dir), SIDE)
    return g.select("item_id", "bin", F.round("v", 4).alias("v"))


@query("r20_dense_gradient", OCT + " SELECT item_id, (y // 16) * 2 + x // 16 AS patch, (((y % 16) // 4) * 4 + (x % 16) // 4) * 8 + o AS bin, round(sum(sqrt(gx * gx + gy * gy)), 4) AS v FROM oct GROUP BY ALL")
def r20(spark, sf_dir):
    return de.dense_gradient(planted(spark, sf_dir), SIDE).withColumn("v", F.round("v", 4))


def patch_vectors(spark, sf_dir, kind: str):
    """key (item * 100 + patch), bin, v of the finest scale."""
    d = de.structural(planted(spark, sf_dir), SIDE) if kind == "S" else de.texture(planted(spark, sf_dir), SIDE)
    return held(spark, sf_dir, f"patches-{kind}", lambda: d.select((F.col("item_id") * 100 + F.col("patch")).alias("key"), "bin", F.round("v", 6).alias("v")))


VEC = STRUCT + ", vec AS (SELECT item_id * 100 + patch AS key, bin, round(v, 6) AS v FROM struct_h)"
WORDS = VEC + "," + vo.lloyd_sql("vec", "key", 12, 3, u01_sql("42", "key"))


@query("r09_patch_sample", VEC + f" SELECT key FROM (SELECT DISTINCT key FROM vec) ORDER BY {u01_sql('42', 'key')}, key LIMIT 200")
def r09(spark, sf_dir):
    return vo.sample_keys(patch_vectors(spark, sf_dir, "S"), "key", 200)


def dictionary(spark, sf_dir):
    return held(spark, sf_dir, "dictionary", lambda: vo.lloyd(patch_vectors(spark, sf_dir, "S"), "key", 12, 3))


@query("r10_dictionary_sql", WORDS + " SELECT word::INT AS word, bin::INT AS bin, c FROM c3")
def r10(spark, sf_dir):
    return dictionary(spark, sf_dir).select("word", "bin", "c")


@query("r11_word_match", WORDS + " SELECT key, word::INT AS word FROM a3")
def r11(spark, sf_dir):
    return vo.nearest_word(patch_vectors(spark, sf_dir, "S"), dictionary(spark, sf_dir), "key")


@query("r12_word_match_eps", WORDS + " SELECT key, word::INT AS word FROM d3 WHERE d <= 0.02")
def r12(spark, sf_dir):
    return vo.words_within(patch_vectors(spark, sf_dir, "S"), dictionary(spark, sf_dir), "key", 0.02)


@query("r10_dictionary_ml")
def r10_ml(spark, sf_dir):
    """The same words by the library's k-means with its parallel initialisation."""
    from pyspark.ml.clustering import KMeans
    from pyspark.ml.functions import array_to_vector

    v = patch_vectors(spark, sf_dir, "T")
    at = v.groupBy("key").agg(F.map_from_entries(F.collect_list(F.struct("bin", "v"))).alias("m"))
    dense = at.select("key", array_to_vector(F.transform(F.sequence(F.lit(0), F.lit(63)), lambda i: F.coalesce(F.col("m")[i], F.lit(0.0)))).alias("features"))
    model = KMeans(k=12, seed=1, maxIter=10).fit(dense)
    return model.transform(dense).groupBy(F.col("prediction").alias("word")).agg(F.count(F.lit(1)).alias("n"))


_NINE = """, at_w AS (SELECT key // 100 AS item_id, key % 100 AS patch, word FROM a3), bl AS (SELECT item_id, word, unnest([0, 1 + 2 * (patch // 8) + (patch % 4) // 2]) AS block FROM at_w)
SELECT item_id::BIGINT AS item_id, (block * 12 + word)::INT AS feat, 'S' AS wtype, round(2 / (1 + exp(-count(*) / 2.0)) - 1, 6) AS r FROM bl GROUP BY item_id, block, word"""


@query("r15_planted_vectors", WORDS + _NINE)
def r15(spark, sf_dir):
    """Responses over the whole and the quarters of the finest scale, with the twelve words of r10."""
    m = vo.nearest_word(patch_vectors(spark, sf_dir, "S"), dictionary(spark, sf_dir), "key")
    at = m.select(F.floor(F.col("key") / 100).alias("item_id"), F.lit(0).alias("scale"), (F.col("key") % 100).cast("int").alias("patch"), "word")
    n = de.blocks(at, SIDE).groupBy("item_id", "block", "word").agg(F.count(F.lit(1)).alias("n"))
    return n.select("item_id", (F.col("block") * 12 + F.col("word")).cast("int").alias("feat"), F.lit("S").alias("wtype"), F.round(tw.saturate(F.col("n")), 6).alias("r"))


@query("r15_nine_blocks")
def r15_nine(spark, sf_dir):
    """The whole representation: nine blocks over three scales, 500 words of each type by matrix products; what it holds."""
    from .item_sets import planted_responses

    r = held(spark, sf_dir, "planted-500", lambda: planted_responses(spark, sf_dir, 500))
    return r.groupBy("wtype").agg(F.count(F.lit(1)).alias("nnz"), F.countDistinct("item_id").alias("items"), F.countDistinct("feat").alias("used_features"), F.countDistinct(F.floor(F.col("feat") % 4500 / 500)).alias("blocks"))


@query("r13_text_blocks", TEXT_BLOCKS + " SELECT item_id, block::INT AS block, feat::INT AS feat, n FROM bc")
def r13_text(spark, sf_dir):
    """Token counts of texts over nine blocks."""
    items = q.items(spark, sf_dir)
    return tw.block_counts(items, tw.token_dictionary(items))


@query("r04_structural_variants", OCT + f""", sv AS (SELECT item_id, patch, cell * 8 + o AS bin, count(*)::DOUBLE AS m FROM (SELECT *, {PATCHED} FROM oct WHERE gx <> 0 OR gy <> 0) GROUP BY ALL)
SELECT item_id, patch::INT AS patch, bin::INT AS bin, round(m / sqrt(sum(m * m) OVER (PARTITION BY item_id, patch)), 6) AS v FROM sv""")
def r04_variants(spark, sf_dir):
    """Histograms of counts instead of magnitudes, each patch of length one."""
    return rounded(de.structural(planted(spark, sf_dir), SIDE, weight="count", norm="l2").select("item_id", "patch", "bin", "v"), "v")
