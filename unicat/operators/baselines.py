"""The methods that the sampler is compared with: k-means, pLSA, LDA, affinity propagation.

k-means and pLSA are rounds of joins and aggregates; affinity propagation works on the edges of a sparse similarity
graph; LDA is the library's. Starting values are keyed numbers.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window

from ..rng import u01
from ..sources.tables import keep
from . import vocabulary


#: The category of items that have no word: no method here can place them, so they are one of their own.
WORDLESS = -1


def with_wordless(assigned: DataFrame, items: DataFrame) -> DataFrame:
    """item_id, cat of all items."""
    return items.select("item_id").join(assigned.select("item_id", "cat"), "item_id", "left").select("item_id", F.coalesce("cat", F.lit(WORDLESS)).alias("cat"))


def kmeans_items(resp: DataFrame, k: int, rounds: int, seed: int = 42) -> DataFrame:
    """item_id, cat."""
    v = resp.select("item_id", F.col("feat").alias("bin"), F.round("r", 6).alias("v"))
    words = vocabulary.lloyd(v, "item_id", k, rounds, seed)
    return vocabulary.nearest_word(v, words, "item_id").withColumnRenamed("word", "cat")


def plsa(counts: DataFrame, k: int, rounds: int, seed: int = 42) -> DataFrame:
    """item_id, cat (the most likely topic) from counts (item_id, feat, n), by expectation maximisation."""
    topics = F.explode(F.sequence(F.lit(0), F.lit(k - 1))).alias("z")
    pw = counts.select("feat").distinct().select("feat", topics).withColumn("w", 0.5 + u01(seed, "w", F.col("feat"), F.col("z")))
    pd = counts.select("item_id").distinct().select("item_id", topics).withColumn("d", 0.5 + u01(seed, "d", F.col("item_id"), F.col("z")))
    pw = keep(pw.join(pw.groupBy("z").agg(F.sum("w").alias("t")), "z").select("feat", "z", (F.col("w") / F.col("t")).alias("w")), "plsa-w")
    pd = keep(pd.join(pd.groupBy("item_id").agg(F.sum("d").alias("t")), "item_id").select("item_id", "z", (F.col("d") / F.col("t")).alias("d")), "plsa-d")
    for _ in range(rounds):
        # A count's topics meet in its own row, so no window or second shuffle is needed for the share.
        wz = pw.groupBy("feat").agg(F.map_from_entries(F.collect_list(F.struct("z", "w"))).alias("mw"))
        dz = pd.groupBy("item_id").agg(F.map_from_entries(F.collect_list(F.struct("z", "d"))).alias("md"))
        both = counts.join(F.broadcast(wz), "feat").join(dz, "item_id")
        raw = F.transform(F.sequence(F.lit(0), F.lit(k - 1)), lambda z: F.col("mw")[z] * F.col("md")[z])
        e = both.select("item_id", "feat", "n", raw.alias("p")).withColumn("t", F.aggregate("p", F.lit(0.0), lambda a, x: a + x))
        e = e.select("item_id", "feat", F.posexplode(F.transform("p", lambda x: F.col("n") * x / F.col("t"))).alias("z", "m"))
        w, d = e.groupBy("feat", "z").agg(F.sum("m").alias("w")), e.groupBy("item_id", "z").agg(F.sum("m").alias("d"))
        pw = keep(w.join(F.broadcast(w.groupBy("z").agg(F.sum("w").alias("t"))), "z").select("feat", "z", (F.col("w") / F.col("t")).alias("w")), "plsa-w")
        pd = keep(d.join(d.groupBy("item_id").agg(F.sum("d").alias("t")), "item_id").select("item_id", "z", (F.col("d") / F.col("t")).alias("d")), "plsa-d")
    return pd.groupBy("item_id").agg(F.max_by("z", F.struct(F.round("d", 9).alias("d"), (-F.col("z")).alias("minus"))).alias("cat"))


def count_vectors(counts: DataFrame) -> DataFrame:
    """item_id, features: the counts (item_id, feat, n) of each item as a sparse vector over the features in order."""
    from pyspark.ml.linalg import Vectors, VectorUDT

    feats = [r.feat for r in counts.select("feat").distinct().orderBy("feat").collect()]
    place = {f: i for i, f in enumerate(feats)}
    sparse = F.udf(lambda own: Vectors.sparse(len(place), {place[x.feat]: float(x.n) for x in own}), VectorUDT())
    per = counts.groupBy("item_id", "feat").agg(F.sum("n").alias("n"))
    return per.groupBy("item_id").agg(sparse(F.sort_array(F.collect_list(F.struct("feat", "n")))).alias("features"))


def lda(counts: DataFrame, k: int, rounds: int = 20, optimizer: str = "online", seed: int = 1) -> DataFrame:
    """item_id, cat by the library's LDA over sparse vectors."""
    from pyspark.ml.clustering import LDA
    from pyspark.ml.functions import vector_to_array

    vectors = count_vectors(counts)
    topics = LDA(k=k, maxIter=rounds, optimizer=optimizer, seed=seed).fit(vectors).transform(vectors)
    d = vector_to_array("topicDistribution")
    return topics.select("item_id", (F.array_position(d, F.array_max(d)) - 1).cast("int").alias("cat"))


def affinity_propagation(similar: DataFrame, preference: float, rounds: int, damping: float = 0.5) -> DataFrame:
    """item_id, cat (its exemplar): messages along a sparse table of similarities (s, t, v), both directions counted, and
    each item's preference for itself."""
    ends = similar.select(F.col("s").alias("i"), F.col("t").alias("k"), "v").unionByName(similar.select(F.col("t").alias("i"), F.col("s").alias("k"), "v"))
    own = ends.select("i").distinct().select("i", F.col("i").alias("k"), F.lit(preference).alias("v"))
    m = keep(ends.unionByName(own).select("i", "k", "v", F.lit(0.0).alias("r"), F.lit(0.0).alias("a")), "ap")
    for _ in range(rounds):
        w = Window.partitionBy("i").orderBy(F.desc("av"), "k")
        top = m.withColumn("av", F.round(F.col("v") + F.col("a"), 9)).withColumn("n", F.row_number().over(w)).where("n <= 2").groupBy("i").agg(F.max(F.when(F.col("n") == 1, F.col("av"))).alias("a1"), F.max(F.when(F.col("n") == 1, F.col("k"))).alias("k1"), F.max(F.when(F.col("n") == 2, F.col("av"))).alias("a2"))
        new_r = F.col("v") - F.when(F.col("k") == F.col("k1"), F.coalesce("a2", F.lit(0.0))).otherwise(F.col("a1"))
        m = m.join(top, "i").select("i", "k", "v", F.round(damping * F.col("r") + (1 - damping) * new_r, 9).alias("r"), "a")
        plus = m.groupBy("k").agg(F.sum(F.when(F.col("i") != F.col("k"), F.greatest(F.lit(0.0), "r")).otherwise(0.0)).alias("plus"), F.max(F.when(F.col("i") == F.col("k"), F.col("r"))).alias("rk"))
        new_a = F.when(F.col("i") == F.col("k"), F.col("plus")).otherwise(F.least(F.lit(0.0), F.col("rk") + F.col("plus") - F.greatest(F.lit(0.0), "r")))
        m = keep(m.join(plus, "k").select("i", "k", "v", "r", F.round(damping * F.col("a") + (1 - damping) * new_a, 9).alias("a")), "ap")
    exemplars = m.where("i = k and r + a > 0").select(F.col("k").alias("e"))
    near = m.join(exemplars, F.col("k") == F.col("e"), "left_semi").withColumn("u", F.when(F.col("i") == F.col("k"), float("inf")).otherwise(F.col("v")))
    best = near.groupBy("i").agg(F.max_by("k", F.struct("u", (-F.col("k")).alias("minus"))).alias("cat"))
    return m.select("i").distinct().join(best, "i", "left").select(F.col("i").alias("item_id"), F.coalesce("cat", "i").alias("cat"))


def affinity_to(similar: DataFrame, categories: int, rounds: int = 40, damping: float = 0.7, tries: int = 8) -> DataFrame:
    """Affinity propagation with the preference for which it finds a number of categories, or comes nearest to it, by
    bisection between the least similarity times as many as there are items, and the greatest."""
    low, high, n = similar.agg(F.min("v"), F.max("v"), F.count(F.lit(1))).first()
    if not n:
        return affinity_propagation(similar, 0.0, 1, damping)
    low, best = 50 * low, None
    for _ in range(tries):
        middle = (low + high) / 2
        got = keep(affinity_propagation(similar, middle, rounds, damping), "ap-try")
        k = got.agg(F.countDistinct("cat")).first()[0]
        if best is None or abs(k - categories) < best[0]:
            best = abs(k - categories), got
        if k == categories:
            break
        low, high = (middle, high) if k < categories else (low, middle)
    return best[1]


def affinity_matrix(v: np.ndarray, preference: float, rounds: int = 150, damping: float = 0.7) -> np.ndarray:
    """The exemplar of each item from a whole matrix of similarities: the same messages as affinity_propagation()."""
    n = len(v)
    s = v.copy()
    np.fill_diagonal(s, preference)
    r, a, at = np.zeros((n, n)), np.zeros((n, n)), np.arange(n)
    for _ in range(rounds):
        x = a + s
        first = x.argmax(axis=1)
        top = x[at, first]
        x[at, first] = -np.inf
        second = x.max(axis=1)
        new = s - top[:, None]
        new[at, first] = s[at, first] - second
        r = damping * r + (1 - damping) * new
        plus = np.maximum(r, 0)
        plus[at, at] = 0
        total = plus.sum(axis=0)
        new = np.minimum(0, (r[at, at] + total)[None, :] - plus)
        new[at, at] = total
        a = damping * a + (1 - damping) * new
    own = np.flatnonzero(np.diag(r + a) > 0)
    if not len(own):
        return at
    out = own[s[:, own].argmax(axis=1)]
    out[own] = own
    return out


def affinity_local(pairs: DataFrame, items: DataFrame, categories: int, most: int = 5_000, tries: int = 14) -> DataFrame:
    """item_id, cat by affinity propagation on the whole similarity -j of all pairs, with the preference for the number of
    categories found by bisection. For at most so many items; larger sets take affinity_to() on a sparse graph."""
    ids = np.sort(items.select("item_id").distinct().limit(most + 1).toArrow().column(0).to_numpy())
    if len(ids) > most:
        raise ValueError(f"more than {most} items: use affinity_to() on a sparse graph")
    p = pairs.select("s", "t", "j").toArrow()
    s, t, j = (p.column(i).to_numpy() for i in range(3))
    v = np.full((len(ids), len(ids)), -float(j.max()) if len(j) else -1.0)  # items without a shared word are the farthest apart
    s, t = np.searchsorted(ids, s), np.searchsorted(ids, t)
    v[s, t] = v[t, s] = -j
    # A little keyed noise, without which equal items swing for ever.
    v += 1e-9 * np.random.default_rng(1).random(v.shape)
    far = max(1e-9, -float(v.min()))
    low, high, best = -400 * far, -1e-3 * far, None
    for _ in range(tries):
        middle = -float(np.sqrt(low * high))  # bisection of the order of magnitude
        found = affinity_matrix(v, middle)
        k = len(np.unique(found))
        if best is None or abs(k - categories) < best[0]:
            best = abs(k - categories), found
        if k == categories:
            break
        low, high = (middle, high) if k < categories else (low, middle)
    return items.sparkSession.createDataFrame([(int(i), int(ids[c])) for i, c in zip(ids, best[1], strict=True)], "item_id long, cat long")
