"""Visual words: k-means over patch descriptors, and matching of patches to words.

Vectors are long rows (key, bin, v) with zeros left out. Centroids are k rows of at most 128 numbers and are broadcast.
match() and learned() are for dictionaries of hundreds of words: each patch is one row and meets all words in a matrix
product of its batch, so nothing of patches times words is shuffled. The other forms are plain joins, which SQL can repeat.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window

from ..rng import u01
from ..sources.tables import keep


def sample_keys(vectors: DataFrame, key: str, n: int, seed: int = 42) -> DataFrame:
    """The n keys with the lowest keyed numbers: the same sample on any partitioning."""
    return vectors.select(key).distinct().orderBy(u01(seed, F.col(key)), key).limit(n)


def distances(vectors: DataFrame, centroids: DataFrame, key: str) -> DataFrame:
    """key, word, d: squared distances by norms and shared bins; every key meets every word."""
    vn = vectors.groupBy(key).agg(F.sum(F.col("v") * F.col("v")).alias("vn"))
    cn = centroids.groupBy("word").agg(F.sum(F.col("c") * F.col("c")).alias("cn"))
    dot = vectors.join(F.broadcast(centroids), "bin").groupBy(key, "word").agg(F.sum(F.col("v") * F.col("c")).alias("dot"))
    every = vn.crossJoin(F.broadcast(cn))
    return every.join(dot, [key, "word"], "left").select(key, "word", F.round(F.col("vn") + F.col("cn") - 2 * F.coalesce("dot", F.lit(0.0)), 9).alias("d"))


def nearest_word(vectors: DataFrame, centroids: DataFrame, key: str) -> DataFrame:
    """key, word: the nearest one, ties to the lower word."""
    return distances(vectors, centroids, key).groupBy(key).agg(F.min_by("word", F.struct("d", "word")).alias("word"))


def words_within(vectors: DataFrame, centroids: DataFrame, key: str, eps: float) -> DataFrame:
    """key, word: every word within a squared distance, so none or many."""
    return distances(vectors, centroids, key).where(F.col("d") <= eps).select(key, "word")


def lloyd(vectors: DataFrame, key: str, k: int, rounds: int, seed: int = 42) -> DataFrame:
    """word, bin, c after some rounds from k keyed keys. v and c have six places, and means are taken in whole millionths, so
    that one halfway between two centroids doesn't depend on the order of sums. A word that loses all its keys keeps its centroid."""
    first = sample_keys(vectors, key, k, seed)
    first = first.withColumn("word", F.row_number().over(Window.orderBy(u01(seed, F.col(key)), key)) - 1)
    centroids = keep(vectors.join(F.broadcast(first), key).select("word", "bin", F.round("v", 6).alias("c")), "centroids")
    for _ in range(rounds):
        at = nearest_word(vectors, centroids, key)
        sizes = at.groupBy("word").agg(F.count(F.lit(1)).alias("n"))
        sums = vectors.join(at, key).groupBy("word", "bin").agg(F.sum(F.round(F.col("v") * 1e6).cast("long")).alias("total"))
        mean = F.signum("total") * F.expr("(2 * abs(total) + n) div (2 * n)") / 1e6
        new = sums.join(F.broadcast(sizes), "word").select("word", "bin", mean.alias("c"))
        kept = centroids.join(F.broadcast(sizes.select("word")), "word", "left_anti")
        centroids = keep(new.unionByName(kept), "centroids")
    return centroids


def dense(vectors: DataFrame, key: str, dims: int) -> DataFrame:
    """key, x: one array of all bins for each key."""
    held = F.map_from_entries(F.collect_list(F.struct("bin", "v")))
    m = vectors.groupBy(key).agg(held.alias("m"))
    return m.select(F.col(key).cast("long").alias(key), F.transform(F.sequence(F.lit(0), F.lit(dims - 1)), lambda i: F.coalesce(F.col("m")[i], F.lit(0.0))).alias("x"))


def learned(vectors: DataFrame, key: str, k: int, dims: int, rounds: int = 10, seed: int = 42) -> np.ndarray:
    """Centroids (k by dims) by rounds over all vectors: each task sums its vectors by nearest word, and k rows of sums and
    counts come to the driver. Starts from k keyed vectors; a word that loses all keeps its centroid."""
    rows = keep(dense(vectors, key, dims), "dense-vectors")
    first = rows.join(F.broadcast(sample_keys(rows, key, k, seed)), key, "left_semi").orderBy(key).toArrow()
    words = np.array(first.column(1).to_pylist(), float).reshape(-1, dims)
    sc = vectors.sparkSession.sparkContext
    for _ in range(rounds if len(words) else 0):
        held = sc.broadcast(words)

        def add(batches, held=held):
            total = np.zeros((len(held.value), dims + 1))
            for b in batches:
                x = b.column(1).flatten().to_numpy().reshape(-1, dims)
                np.add.at(total, _nearest(x, held.value), np.column_stack([x, np.ones(len(x))]))
            at = np.flatnonzero(total[:, -1])
            yield pa.RecordBatch.from_arrays([pa.array(at), pa.array(total[at].tolist(), pa.list_(pa.float64()))], ["word", "total"])

        sums = rows.mapInArrow(add, "word long, total array<double>").groupBy("word").agg(*[F.sum(F.col("total")[i]).alias(f"x{i}") for i in range(dims + 1)]).toArrow()
        new = words.copy()
        if sums.num_rows:
            x = np.column_stack([sums.column(i + 1).to_numpy() for i in range(dims + 1)])
            new[sums.column(0).to_numpy()] = np.round(x[:, :-1] / x[:, -1:], 6)
        if np.array_equal(new, words):
            break
        words = new
    return words


def _nearest(x: np.ndarray, words: np.ndarray) -> np.ndarray:
    """The nearest word of each vector, ties to the lower word."""
    return np.argmin(np.round((words * words).sum(axis=1)[None, :] - 2 * x @ words.T, 9), axis=1)


def match(vectors: DataFrame, words: np.ndarray, key: str, dims: int) -> DataFrame:
    """key, word: the nearest one."""
    held = vectors.sparkSession.sparkContext.broadcast(words)

    def run(batches):
        for b in batches:
            x = b.column(1).flatten().to_numpy().reshape(-1, dims)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(_nearest(x, held.value) if len(held.value) else np.zeros(len(x), np.int64))], [key, "word"])

    return dense(vectors, key, dims).mapInArrow(run, f"{key} long, word long")


def lloyd_sql(vectors: str, key: str, k: int, rounds: int, draw: str) -> str:
    """DuckDB CTEs c0 .. c<rounds> over a CTE with (key, bin, v); draw is the keyed number of a key."""
    out = f"""
lk AS (SELECT {key}, row_number() OVER (ORDER BY {draw}, {key}) - 1 AS word FROM (SELECT DISTINCT {key} FROM {vectors}) ORDER BY {draw}, {key} LIMIT {k}),
c0 AS (SELECT word, bin, round(v, 6) AS c FROM {vectors} JOIN lk USING ({key})),
vn AS (SELECT {key}, sum(v * v) AS vn FROM {vectors} GROUP BY {key})"""
    for i in range(rounds + 1):
        out += f""",
d{i} AS (SELECT {key}, word, round(vn + cn - 2 * coalesce(dot, 0), 9) AS d FROM vn CROSS JOIN (SELECT word, sum(c * c) AS cn FROM c{i} GROUP BY word)
  LEFT JOIN (SELECT {key}, word, sum(v * c) AS dot FROM {vectors} JOIN c{i} USING (bin) GROUP BY ALL) USING ({key}, word)),
a{i} AS (SELECT {key}, arg_min(word, (d, word)) AS word FROM d{i} GROUP BY {key})"""
        if i < rounds:
            out += f""",
c{i + 1} AS (SELECT word, bin, round(total / n, 6) AS c FROM (SELECT word, bin, sum(v) AS total FROM {vectors} JOIN a{i} USING ({key}) GROUP BY ALL) JOIN (SELECT word, count(*) AS n FROM a{i} GROUP BY word) USING (word)
  UNION ALL SELECT word, bin, c FROM c{i} WHERE word NOT IN (SELECT word FROM a{i}))"""
    return out
