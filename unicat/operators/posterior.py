"""Category models in closed form, and the energy of a partition from sufficient statistics.

A category of n items with mean responses E_f against reference means E_0 gets, for each chosen word,
lambda = ln[E_f (1 - E_0) / ((1 - E_f) E_0)], z = e^lambda E_0 + 1 - E_0 and gain = lambda E_f - ln z, which is the
Bernoulli divergence of E_f from E_0. Summed over its items, a category's log-likelihood is n times its gains, so the
energy needs only (n, sum of r) of each category and no item is read again.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window

CLIP = 1e-6


def clipped(e: Column, clip: float = CLIP) -> Column:
    return F.least(F.lit(1 - clip), F.greatest(F.lit(clip), e))


def category_stats(resp: DataFrame, labels: DataFrame) -> DataFrame:
    """cat, feat, wtype, total: summed responses."""
    return resp.join(labels, "item_id").groupBy("cat", "feat", "wtype").agg(F.sum("r").alias("total"))


def category_sizes(labels: DataFrame) -> DataFrame:
    return labels.groupBy("cat").agg(F.count(F.lit(1)).alias("n"))


def category_means(resp: DataFrame, labels: DataFrame) -> DataFrame:
    """cat, feat, wtype, e_f. Items without the word count as zeros: the sum is divided by the size of the category."""
    return category_stats(resp, labels).join(F.broadcast(category_sizes(labels)), "cat").select("cat", "feat", "wtype", "n", (F.col("total") / F.col("n")).alias("e_f"))


def reference_means(resp: DataFrame, items: int, sizes: dict[str, int], mode: str = "uniform") -> DataFrame:
    """feat, e_0 (background) or wtype, e_0 (uniform over the words of a type, half)."""
    if mode == "background":
        return resp.groupBy("feat").agg((F.sum("r") / items).alias("e_0"))
    words = F.create_map(*[x for t, m in sizes.items() for x in (F.lit(t), F.lit(m))])
    if mode == "half":
        return resp.select("wtype").distinct().withColumn("e_0", F.lit(0.5))
    return resp.groupBy("wtype").agg(F.sum("r").alias("total")).select("wtype", (F.col("total") / (items * words[F.col("wtype")])).alias("e_0"))


def word_weights(e_f: Column, e_0: Column, clip: float = CLIP) -> tuple[Column, Column, Column]:
    """(lambda, z, gain)."""
    f, o = clipped(e_f, clip), clipped(e_0, clip)
    lam = F.log(f * (1 - o) / ((1 - f) * o))
    z = F.exp(lam) * o + 1 - o
    return lam, z, lam * f - F.log(z)


def select_words(means: DataFrame, reference: DataFrame, words: int = 40, rule: str = "mean_gap") -> DataFrame:
    """The models: the words of greatest gap E_f - E_0 (or of greatest gain) of each category, with rank, lambda, z, gain."""
    on = "feat" if "feat" in reference.columns else "wtype"
    e = means.join(F.broadcast(reference), on)
    lam, z, gain = word_weights(F.col("e_f"), F.col("e_0"))
    e = e.select("cat", "feat", "wtype", "n", "e_f", "e_0", lam.alias("lambda"), z.alias("z"), gain.alias("gain"))
    by = F.col("e_f") - F.col("e_0") if rule == "mean_gap" else F.col("gain")
    w = Window.partitionBy("cat").orderBy(by.desc(), "feat")
    return e.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= words)


def pursue_sequential(resp: DataFrame, labels: DataFrame, reference: DataFrame, words: int = 5) -> DataFrame:
    """Pursuit without the independence assumption, for small tables: at each step the words are judged under the current
    model, by weighing the pooled items with its density (self-normalised importance weights), and the best is added.
    cat, rank, feat, gain."""
    items = resp.select("item_id").distinct()
    cats = category_sizes(labels).select("cat")
    target = category_means(resp, labels).select("cat", "feat", "wtype", "e_f")
    weights, chosen = items.crossJoin(F.broadcast(cats)).withColumn("logw", F.lit(0.0)), None
    for rank in range(1, words + 1):
        w = weights.withColumn("w", F.exp(F.col("logw") - F.max("logw").over(Window.partitionBy("cat"))))
        total = w.groupBy("cat").agg(F.sum("w").alias("total"))
        now = w.join(resp, "item_id").groupBy("cat", "feat").agg(F.sum(F.col("w") * F.col("r")).alias("m")).join(total, "cat").select("cat", "feat", (F.col("m") / F.col("total")).alias("e_now"))
        lam, z, gain = word_weights(F.col("e_f"), F.col("e_now"))
        scored = target.join(now, ["cat", "feat"]).select("cat", "feat", lam.alias("lambda"), gain.alias("gain"), (F.col("e_f") - F.col("e_now")).alias("gap")).where("gap > 0")
        if chosen is not None:
            scored = scored.join(chosen.select("cat", "feat"), ["cat", "feat"], "left_anti")
        best = scored.withColumn("n", F.row_number().over(Window.partitionBy("cat").orderBy(F.desc("gain"), "feat"))).where("n = 1").select("cat", F.lit(rank).alias("rank"), "feat", "lambda", "gain")
        chosen = best if chosen is None else chosen.unionByName(best)
        add = best.select("cat", "feat", "lambda").join(resp, "feat").select("cat", "item_id", (F.col("lambda") * F.col("r")).alias("add"))
        weights = weights.join(add, ["cat", "item_id"], "left").select("cat", "item_id", (F.col("logw") + F.coalesce("add", F.lit(0.0))).alias("logw"))
    return chosen


def item_loglik(resp: DataFrame, models: DataFrame, items: DataFrame | None = None) -> DataFrame:
    """item_id, cat, ll: log of the model over the initial model, for every item and category: as many rows as both make,
    which is what assignment and unfitness need while categories are few. items: all items, those without a word too."""
    base = models.groupBy("cat").agg(F.sum(-F.log("z")).alias("base"))
    hits = resp.join(F.broadcast(models.select("cat", "feat", "lambda")), "feat").groupBy("item_id", "cat").agg(F.sum(F.col("lambda") * F.col("r")).alias("score"))
    every = (resp if items is None else items).select("item_id").distinct().crossJoin(F.broadcast(base))
    return every.join(hits, ["item_id", "cat"], "left").select("item_id", "cat", (F.col("base") + F.coalesce("score", F.lit(0.0))).alias("ll"))


def category_loglik(models: DataFrame) -> DataFrame:
    """cat, n, ll = n times the summed gains."""
    return models.groupBy("cat").agg(F.first("n").alias("n"), (F.first("n") * F.sum("gain")).alias("ll"))


def energy(models: DataFrame, beta: float) -> DataFrame:
    """One row: k and energy = beta * k - log-likelihood."""
    c = category_loglik(models)
    return c.agg(F.count(F.lit(1)).alias("k"), (beta * F.count(F.lit(1)) - F.sum("ll")).alias("energy"))


#: DuckDB CTEs over resp and labels(item_id, cat): sizes, means, ref, models.
def model_sql(items: str, sizes: dict[str, int], words: int = 40, rule: str = "mean_gap", reference: str = "uniform") -> str:
    m = " ".join(f"WHEN '{t}' THEN {n}" for t, n in sizes.items())
    ref = {
        "uniform": f"SELECT wtype AS k, sum(r) / ({items} * CASE wtype {m} END) AS e_0 FROM resp GROUP BY wtype",
        "half": "SELECT DISTINCT wtype AS k, 0.5 AS e_0 FROM resp",
        "background": f"SELECT feat AS k, sum(r) / {items} AS e_0 FROM resp GROUP BY feat",
    }[reference]
    on = "feat" if reference == "background" else "wtype"
    clip = f"least(1 - {CLIP}, greatest({CLIP}, %s))"
    by = "e_f - e_0" if rule == "mean_gap" else "gain"
    return f"""
sizes AS (SELECT cat, count(*) AS n FROM labels_now GROUP BY cat),
means AS (SELECT cat, feat, wtype, n, total / n AS e_f FROM (SELECT cat, feat, wtype, sum(r) AS total FROM resp JOIN labels_now USING (item_id) GROUP BY ALL) JOIN sizes USING (cat)),
ref AS ({ref}),
lambdas AS (SELECT *, ln(f * (1 - o) / ((1 - f) * o)) AS lam FROM (SELECT means.*, e_0, {clip % 'e_f'} AS f, {clip % 'e_0'} AS o FROM means JOIN ref ON k = {on})),
gains AS (SELECT *, exp(lam) * o + 1 - o AS z, lam * f - ln(exp(lam) * o + 1 - o) AS gain FROM lambdas),
models AS (SELECT cat, feat, wtype, n, e_f, e_0, lam, z, gain, rank FROM (SELECT *, row_number() OVER (PARTITION BY cat ORDER BY {by} DESC, feat) AS rank FROM gains) WHERE rank <= {words})"""
