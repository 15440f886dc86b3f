"""Accuracy and cost measures over (item_id, truth, cat) and over traces of the sampler."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window


def contingency(assigned: DataFrame) -> DataFrame:
    """cat, truth, n."""
    return assigned.groupBy("cat", "truth").agg(F.count(F.lit(1)).alias("n"))


def purity(assigned: DataFrame) -> DataFrame:
    per = contingency(assigned).groupBy("cat").agg(F.max("n").alias("top"), F.sum("n").alias("n"))
    return per.agg((F.sum("top") / F.sum("n")).alias("purity"))


def conditional_entropy(assigned: DataFrame, base: float = math.e) -> DataFrame:
    """H(truth | category); natural logarithms by default."""
    c = contingency(assigned).withColumn("of", F.sum("n").over(Window.partitionBy("cat")))
    return c.agg((F.sum(F.col("n") * F.log(F.col("of") / F.col("n"))) / F.sum("n") / math.log(base)).alias("cond_entropy"))


def inferred_k(runs: DataFrame) -> DataFrame:
    """run, k: the number of categories of each run."""
    return runs.groupBy("run").agg(F.countDistinct("cat").alias("k"))


def majority(assigned: DataFrame) -> DataFrame:
    """cat, truth (the most frequent one; ties to the first by name), n, precision."""
    c = contingency(assigned).withColumn("size", F.sum("n").over(Window.partitionBy("cat")))
    w = Window.partitionBy("cat").orderBy(F.desc("n"), "truth")
    return c.withColumn("rank", F.row_number().over(w)).where("rank = 1").select("cat", "truth", "n", (F.col("n") / F.col("size")).alias("precision"))


def normalised_information(assigned: DataFrame) -> DataFrame:
    """Entropies of truth and category, their mutual information, and NMI by the arithmetic mean."""
    c = contingency(assigned)
    total = c.agg(F.sum("n").alias("total"))
    x = c.groupBy("truth").agg(F.sum("n").alias("nx"))
    y = c.groupBy("cat").agg(F.sum("n").alias("ny"))
    hx = x.crossJoin(F.broadcast(total)).agg(F.sum(-F.col("nx") / F.col("total") * F.log(F.col("nx") / F.col("total"))).alias("h_truth"))
    hy = y.crossJoin(F.broadcast(total)).agg(F.sum(-F.col("ny") / F.col("total") * F.log(F.col("ny") / F.col("total"))).alias("h_cat"))
    mi = c.join(x, "truth").join(y, "cat").crossJoin(F.broadcast(total)).agg(F.sum(F.col("n") / F.col("total") * F.log(F.col("n") * F.col("total") / (F.col("nx") * F.col("ny")))).alias("mutual"))
    return hx.crossJoin(hy).crossJoin(mi).select("h_truth", "h_cat", "mutual", (2 * F.col("mutual") / (F.col("h_truth") + F.col("h_cat"))).alias("nmi"))


def average_precision(scored: DataFrame) -> DataFrame:
    """One-vs-rest average precision of each truth: scored has item_id, truth, cat_truth (what its category stands for) and
    score; items of a predicted truth are ranked by score."""
    w = Window.partitionBy("cat_truth").orderBy(F.desc("score"), "item_id")
    hit = F.when(F.col("truth") == F.col("cat_truth"), 1).otherwise(0)
    ranked = scored.withColumn("rank", F.row_number().over(w)).withColumn("hits", F.sum(hit).over(w.rowsBetween(Window.unboundedPreceding, 0))).withColumn("hit", hit)
    sizes = scored.groupBy(F.col("truth").alias("cat_truth")).agg(F.count(F.lit(1)).alias("n"))
    return ranked.groupBy("cat_truth").agg(F.sum(F.col("hit") * F.col("hits") / F.col("rank")).alias("total")).join(sizes, "cat_truth").select(F.col("cat_truth").alias("truth"), (F.col("total") / F.col("n")).alias("average_precision"))


def convergence_step(trace: DataFrame, delta: float = 0.05) -> DataFrame:
    """chain, first step whose best energy so far is within delta of the way from the start to the chain's best."""
    w = Window.partitionBy("chain").orderBy("step")
    run = trace.withColumn("best", F.min("energy").over(w.rowsBetween(Window.unboundedPreceding, 0))).withColumn("start", F.first("energy").over(w)).withColumn("last", F.min("energy").over(Window.partitionBy("chain")))
    near = run.where(F.col("best") <= F.col("last") + delta * (F.col("start") - F.col("last")))
    return near.groupBy("chain").agg(F.min("step").alias("step"))


def work(trace: DataFrame) -> DataFrame:
    """Counters of the cost model steps * categories * words: steps, mean categories, operations, accepted share, moved."""
    return trace.groupBy("chain").agg(
        F.count(F.lit(1)).alias("steps"), F.avg("k").alias("mean_k"), F.sum(F.col("k") * F.col("model_words")).alias("operations"), F.avg(F.col("accepted").cast("double")).alias("acceptance"), F.sum("n_moved").alias("moved")
    )
