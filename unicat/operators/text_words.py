"""Words of text items: frequent tokens (structural, type S) and centre-symmetric codes of characters (texture, type T).

Both become sparse responses (item_id, feat, wtype, r) with 0 < r < 1; absent words have no row.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window

TOKENS = 200
#: A token in more than this share of the items says too little.
MOST_ITEMS = 0.3
CODES, QUARTERS = 16, 4
TEXTURE = CODES * QUARTERS
SATURATION = 2.0


def saturate(n: Column, kind: str = "zero_sigmoid", s: float = SATURATION) -> Column:
    """The response to n matches. zero_sigmoid is 0 at 0; logistic is 1/2 there; linear_clip grows up to s matches."""
    n = n.cast("double")
    if kind == "zero_sigmoid":
        return 2 / (1 + F.exp(-n / s)) - 1
    if kind == "logistic":
        return 1 / (1 + F.exp(-n / s))
    return F.least(F.lit(1.0), n / s)


def tokens(items: DataFrame) -> DataFrame:
    """item_id, w: the letter sequences of each text, lower-cased, one row for each occurrence."""
    return spread(items).select("item_id", F.explode(F.regexp_extract_all(F.lower("text"), F.lit(r"(\p{L}+)"), F.lit(1))).alias("w"))


def token_dictionary(items: DataFrame, m: int = TOKENS, most: float = MOST_ITEMS) -> DataFrame:
    """w, feat: the m tokens in most items, among those in at most a share of them; ties by token."""
    n = items.select("item_id").distinct().count()
    held = tokens(items).groupBy("w", "item_id").count().groupBy("w").agg(F.count(F.lit(1)).alias("d")).where(F.col("d") <= most * n)
    top = held.orderBy(F.desc("d"), "w").limit(m)
    return top.select("w", (F.row_number().over(Window.orderBy(F.desc("d"), "w")) - 1).alias("feat"))


def token_counts(items: DataFrame, dictionary: DataFrame) -> DataFrame:
    """item_id, feat, n. The dictionary has m rows, so it is broadcast."""
    return tokens(items).join(F.broadcast(dictionary), "w").groupBy("item_id", "feat").agg(F.count(F.lit(1)).alias("n"))


def spread(items: DataFrame) -> DataFrame:
    """A table of few partitions, such as one small file, dealt over all cores; a larger one stays as it is."""
    cores = items.sparkSession.sparkContext.defaultParallelism
    return items.repartition(4 * cores, "item_id") if items.rdd.getNumPartitions() <= 2 * cores else items


def codes_of(text: str) -> np.ndarray:
    """Counts by quarter of the text and code. The code of a place compares the four code points before it with the four
    after it, nearest first: bit i is set if the one before is greater by more than one."""
    p = np.frombuffer(text.encode("utf-32-le"), np.int32)
    n = len(p)
    code = np.zeros(n - 8, np.int64)
    for k in range(4):
        code |= (p[3 - k : n - 5 - k] - p[5 + k : n - 3 + k] > 1).astype(np.int64) << k
    return np.bincount(np.arange(4, n - 4) * QUARTERS // n * CODES + code, minlength=TEXTURE)


def texture_counts(items: DataFrame) -> DataFrame:
    """item_id, feat (code, then quarter of the text), n, by shifted arrays of code points; a text's counts leave its task
    added up. Texts of fewer than nine code points have none."""

    def run(batches):
        for b in batches:
            for i, x in zip(b.column(0).to_pylist(), b.column(1), strict=True):
                text = x.as_py()
                if text is not None and len(text) >= 9:
                    n = codes_of(text)
                    at = np.flatnonzero(n)
                    yield pa.RecordBatch.from_arrays([pa.array([i] * len(at), pa.int64()), pa.array(at.astype(np.int32)), pa.array(n[at])], ["item_id", "feat", "n"])

    rows = spread(items.select(F.col("item_id").cast("long"), "text")).mapInArrow(run, "item_id long, feat int, n long")
    return rows.groupBy("item_id", "feat").agg(F.sum("n").alias("n"))


def text_responses(items: DataFrame, m: int = TOKENS, types: tuple[str, ...] = ("S", "T"), s: float = SATURATION, dictionary: DataFrame | None = None) -> DataFrame:
    """item_id, feat, wtype, r. The dictionary is made from the items unless a frozen one is given. Texture counts are scaled to a mean of one a word first, else they would measure length."""
    out = None
    if "S" in types:
        out = token_counts(items, token_dictionary(items, m) if dictionary is None else dictionary).select("item_id", F.col("feat").cast("int").alias("feat"), F.lit("S").alias("wtype"), saturate(F.col("n"), s=s).alias("r"))
    if "T" in types:
        counts = texture_counts(items)
        share = F.col("n") * TEXTURE / F.sum("n").over(Window.partitionBy("item_id"))
        t = counts.select("item_id", (F.col("feat") + m).cast("int").alias("feat"), F.lit("T").alias("wtype"), saturate(share, s=s).alias("r"))
        out = t if out is None else out.unionByName(t)
    return out


def block_counts(items: DataFrame, dictionary: DataFrame) -> DataFrame:
    """item_id, block, feat, n over nine blocks of a text, as a raster has: the whole, its quarters at the finest scale (all
    tokens), and its quarters at the next (every second token)."""
    words = F.regexp_extract_all(F.lower("text"), F.lit(r"(\p{L}+)"), F.lit(1))
    rows = spread(items).select("item_id", words.alias("all")).select("item_id", F.size("all").alias("size"), F.posexplode("all").alias("i", "w"))
    quarter = F.floor(F.col("i") * 4 / F.col("size")).cast("int")
    found = rows.join(F.broadcast(dictionary), "w").select("item_id", "feat", F.explode(F.when(F.col("i") % 2 == 0, F.array(F.lit(0), 1 + quarter, 5 + quarter)).otherwise(F.array(F.lit(0), 1 + quarter))).alias("block"))
    return found.groupBy("item_id", "block", "feat").agg(F.count(F.lit(1)).alias("n"))


def block_responses(items: DataFrame, m: int = TOKENS, types: tuple[str, ...] = ("S", "T"), s: float = SATURATION) -> DataFrame:
    """As text_responses(), with the tokens over nine blocks: feat is block * m + word, and texture follows from 9 * m."""
    out = text_responses(items, m, ("T",), s).withColumn("feat", (F.col("feat") + 8 * m).cast("int")) if "T" in types else None
    if "S" in types:
        counts = block_counts(items, token_dictionary(items, m))
        r = counts.select("item_id", (F.col("block") * m + F.col("feat")).cast("int").alias("feat"), F.lit("S").alias("wtype"), saturate(F.col("n"), s=s).alias("r"))
        out = r if out is None else out.unionByName(r)
    return out


#: The same as DuckDB CTEs over a table items(item_id, text): tok, dict, cnt_s, cnt_t, resp.
def text_sql(items: str, m: int = TOKENS) -> str:
    return rf"""
items AS ({items}),
tok AS (SELECT item_id, unnest(regexp_extract_all(lower(text), '[\p{{L}}]+')) AS w FROM items),
dict AS (SELECT w, row_number() OVER (ORDER BY d DESC, w) - 1 AS feat FROM (SELECT w, count(DISTINCT item_id) AS d FROM tok GROUP BY w)
  WHERE d <= {MOST_ITEMS} * (SELECT count(DISTINCT item_id) FROM items) ORDER BY d DESC, w LIMIT {m}),
cnt_s AS (SELECT item_id, feat, count(*) AS n FROM tok JOIN dict USING (w) GROUP BY item_id, feat),
chars AS (SELECT item_id, [unicode(c) FOR c IN regexp_extract_all(text, '(?s).')] AS p FROM items),
places AS (SELECT item_id, p, len(p) AS size, unnest(range(4, len(p) - 4)) AS i FROM chars WHERE len(p) >= 9),
cnt_t AS (SELECT item_id, (i * {QUARTERS}) // size * {CODES} + (CASE WHEN p[i] - p[i+2] > 1 THEN 1 ELSE 0 END) + (CASE WHEN p[i-1] - p[i+3] > 1 THEN 2 ELSE 0 END)
    + (CASE WHEN p[i-2] - p[i+4] > 1 THEN 4 ELSE 0 END) + (CASE WHEN p[i-3] - p[i+5] > 1 THEN 8 ELSE 0 END) AS feat, count(*) AS n FROM places GROUP BY 1, 2),
resp AS (
  SELECT item_id, feat, 'S' AS wtype, 2 / (1 + exp(-n / {SATURATION})) - 1 AS r FROM cnt_s
  UNION ALL SELECT item_id, feat + {m}, 'T', 2 / (1 + exp(-(n * {TEXTURE} / sum(n) OVER (PARTITION BY item_id)) / {SATURATION})) - 1 FROM cnt_t
)"""
