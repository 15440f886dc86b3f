"""Whole chains and the experiments: quality tables of all methods, numbers of categories, convergence, speed, sweeps."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators import baselines as ba
from ..operators import descriptors as de
from ..operators import measures, posterior, sampler
from ..operators import text_words as tw
from ..registry import query
from ..rng import u01
from ..sources import rasters
from ..sources.tables import table
from . import item_sets as sets
from . import text_queries as q
from .item_sets import chains, item_set, scored

SEEDS = list(range(1, 11))


def stacked(parts: list[DataFrame]) -> DataFrame:
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def steps_of(traces: DataFrame) -> DataFrame:
    return traces.where("step >= 0").select("chain", "step", "k", F.round("energy", 4).alias("energy"), "accepted", "n_moved", "n_atoms")


@query("entry_categories")
def entry(spark, sf_dir):
    """The flagship: categories of all documents by one composite-cut chain, with what they hold."""
    own = item_set(spark, sf_dir, "text")
    best = sampler.best_labels(chains(spark, own, [1])).join(own.items, "item_id")
    return measures.majority(best).select("cat", "truth", "n", F.round("precision", 6).alias("precision"))


for _move, _name in (("single", "i07_single_chain"), ("composite", "i11_composite_chain")):

    @query(_name)
    def chain(spark, sf_dir, move=_move):
        return steps_of(chains(spark, item_set(spark, sf_dir, "text"), [1], move=move)).drop("chain")


@query("i11_paper_fidelity")
def paper_chain(spark, sf_dir):
    return steps_of(chains(spark, item_set(spark, sf_dir, "text"), [1], fidelity="paper", scope="any")).drop("chain")


@query("i11_distributed_chain")
def distributed(spark, sf_dir):
    """Two composite steps by DataFrame jobs, beside the same steps of the local engine: both traces."""
    own = item_set(spark, sf_dir, "text")
    params = replace(own.params, seed=1, steps=2)
    trace, _ = sampler.distributed_chain(own.resp, own.edges, own.items, sets.reference(own), params, 2)
    far = spark.createDataFrame([(t[0], t[1], round(t[2], 4), bool(t[3]), int(t[5]), int(t[6])) for t in trace], "step int, k int, energy double, accepted boolean, n_moved long, n_atoms long")
    near = steps_of(chains(spark, own, [1], steps=2)).drop("chain")
    return far.withColumn("engine", F.lit("distributed")).unionByName(near.withColumn("engine", F.lit("local")))


@query("i01_initial_states")
def i01(spark, sf_dir):
    """Chains from each of the four kinds of start: where they begin and what they reach."""
    own, modes = item_set(spark, sf_dir, "text"), ["one", "components", "singletons", "random"]
    traces = sampler.run_chains(spark, own.resp, own.edges, own.dims, sets.reference(own), [replace(own.params, initial=mode, steps=150) for mode in modes], [1] * len(modes), own.items)
    reached = traces.where("step >= 0").groupBy("chain").agg(F.min_by("k", "step").alias("k_first"), F.round(F.min_by("energy", "step"), 4).alias("energy_first"), F.round(F.min("energy"), 4).alias("best"))
    return reached.select(F.element_at(F.array(*map(F.lit, modes)), (F.col("chain") + 1).cast("int")).alias("start"), "k_first", "energy_first", "best")


@query("i15_ten_chains")
def ten(spark, sf_dir):
    own = item_set(spark, sf_dir, "text")
    return scored(chains(spark, own, SEEDS), own.items, "composite")


@query("p13_best_state")
def p13(spark, sf_dir):
    rows = steps_of(chains(spark, item_set(spark, sf_dir, "text"), [1, 2]))
    return rows.groupBy("chain").agg(F.min_by("step", F.struct("energy", "step")).alias("step"), F.min("energy").alias("energy"))


# Quality tables


def row(assigned: DataFrame, own, name: str) -> DataFrame:
    """method, k, purity, cond_entropy over all items of the set."""
    a = ba.with_wordless(assigned, own.items).join(own.items, "item_id").select("item_id", "truth", "cat")
    p = measures.purity(a).crossJoin(measures.conditional_entropy(a)).crossJoin(a.agg(F.countDistinct("cat").alias("k")))
    return p.select(F.lit(own.name).alias("items"), F.lit(name).alias("method"), "k", F.round("purity", 4).alias("purity"), F.round("cond_entropy", 4).alias("cond_entropy"))


def counts(own) -> DataFrame:
    """Counts for the topic models from responses of both types: what the saturation of so many matches gives, back again."""
    n = F.round(-tw.SATURATION * F.log(2 / (F.least(F.col("r"), F.lit(1 - 1e-6)) + 1) - 1))
    return own.resp.select("item_id", "feat", F.greatest(F.lit(1.0), n).cast("long").alias("n"))


def global_vectors(spark, sf_dir) -> DataFrame:
    """Global gradient descriptors of planted rasters at three scales, as shares."""

    def make():
        px, out, side = q.held(spark, sf_dir, "planted", lambda: rasters.as_arrays(rasters.planted(spark, sf_dir), sets.SIDE)), None, sets.SIDE
        for scale in range(3):
            g = de.global_gradient(px, side).withColumn("feat", F.col("bin") + 128 * scale)
            out = g if out is None else out.unionByName(g)
            px, side = de.halved(px, side), side // 2
        total = out.groupBy("item_id").agg(F.sum("v").alias("total"))
        return out.join(total, "item_id").select("item_id", "feat", F.round(F.col("v") / F.col("total"), 6).alias("r"))

    return q.held(spark, sf_dir, "global-three", make)


def table_of(spark, sf_dir, name: str) -> DataFrame:
    """All methods on an item set. The compared methods get the true number of categories, the sampler does not."""
    own = item_set(spark, sf_dir, name)
    k = own.items.select("truth").distinct().count()
    rows = [row(ba.kmeans_items(own.resp, k, 6), own, "k-means")]
    if name in ("planted", "mixed"):
        g = global_vectors(spark, sf_dir)
        rows.append(row(ba.kmeans_items(g if name == "planted" else g.withColumn("item_id", F.col("item_id") + sets.RASTERS), k if name == "planted" else 10, 6), own, "k-means on global gradients"))
    c = q.held(spark, sf_dir, f"counts-{name}", lambda: counts(own))
    rows += [row(ba.plsa(c, k, 8), own, "pLSA"), row(ba.lda(c, k, 15), own, "LDA"), row(ba.affinity_local(own.pairs, own.items, k), own, "affinity propagation")]
    for types, label in ((("S", "T"), "sampler, both"), (("S",), "sampler, structural"), (("T",), "sampler, texture")):
        part = own if types == ("S", "T") else item_set(spark, sf_dir, name, types=types)
        rows.append(row(sampler.best_labels(chains(spark, part, [1])).select("item_id", "cat"), own, label))
    return stacked(rows)


for _set in ("text", "planted", "web", "mixed"):

    @query(f"w01_w02_{_set}")
    def w01(spark, sf_dir, name=_set):
        """Purity and conditional entropy of every method on an item set."""
        return table_of(spark, sf_dir, name)

    @query(f"w03_inferred_k_{_set}")
    def w03(spark, sf_dir, name=_set):
        """Inferred numbers of categories over ten runs, and their mean beside the true one."""
        own = item_set(spark, sf_dir, name)
        runs = scored(chains(spark, own, SEEDS, steps=200), own.items, name).select(F.col("method").alias("items"), "chain", "k")
        mean = runs.agg(F.avg("k").alias("mean_k")).crossJoin(own.items.agg(F.countDistinct("truth").alias("true_k")))
        return runs.crossJoin(F.broadcast(mean))


for _set in ("web", "planted"):

    @query(f"w04_top_words_{_set}")
    def w04(spark, sf_dir, name=_set):
        """The forty words of each found category with gains and types, and what the category stands for."""
        own = item_set(spark, sf_dir, name)
        labels = sampler.best_labels(chains(spark, own, [1])).select("item_id", F.col("cat").cast("long").alias("cat"))
        m = posterior.select_words(posterior.category_means(own.resp, labels), posterior.reference_means(own.resp, own.items.count(), own.sizes))
        stands = measures.majority(labels.join(own.items, "item_id")).select("cat", "truth")
        k = sets.WORDS
        words = tw.token_dictionary(sets.texts(spark, sf_dir, True), k).select("w", F.col("feat").alias("word")) if name == "web" else None
        m = m.withColumn("block", F.when((F.col("wtype") == "S") | F.lit(name == "planted"), F.floor(F.col("feat") % (9 * k) / k).cast("int"))).withColumn("word", F.when(F.col("block").isNotNull(), F.col("feat") % k).otherwise(F.col("feat") - 9 * k))
        if words is not None:
            m = m.join(F.broadcast(words), "word", "left").withColumn("w", F.when(F.col("wtype") == "S", F.col("w")))
        return m.join(F.broadcast(stands), "cat").select("cat", "truth", "rank", "wtype", "block", "word", F.col("w") if words is not None else F.lit(None).cast("string").alias("w"), F.round("gain", 6).alias("gain"))


@query("w05_convergence")
def w05(spark, sf_dir):
    """Best energy and steps to converge of both samplers, from the same start and seeds, on three item sets."""
    rows = []
    for name in ("text", "planted", "web"):
        own = item_set(spark, sf_dir, name)
        for move in ("single", "composite"):
            t = steps_of(chains(spark, own, [1, 2, 3], move=move, steps=250, patience=250))
            rows.append(measures.convergence_step(t).join(t.groupBy("chain").agg(F.min("energy").alias("best_energy")), "chain").select(F.lit(name).alias("items"), F.lit(move).alias("move"), "chain", "step", "best_energy"))
    return stacked(rows)


def _mix(items: DataFrame, categories: int, share: float) -> DataFrame:
    """Some of 16 categories, four languages and twelve refined labels of rasters, and a keyed share of their items."""
    label = F.when(F.col("truth").startswith("label-"), F.substring("truth", 7, 9).cast("int") + 10 * ((F.col("item_id") - sets.RASTERS) % 2))
    lang = F.when(F.col("truth").startswith("doc-"), F.col("truth"))
    refined = items.withColumn("truth", F.when(label < 12, F.concat(F.lit("label-"), label.cast("string"))).otherwise(lang)).where("truth is not null")
    names = sorted(r.truth for r in refined.select("truth").distinct().collect())[:categories]
    return refined.where(F.col("truth").isin(names) & (u01(42, "sample", F.col("item_id")) < share))


W6 = {"items": [(16, 0.25), (16, 0.5), (16, 0.75), (16, 1.0)], "categories": [(4, 1.0), (8, 0.6), (12, 0.45), (16, 0.35)], "both": [(4, 0.4), (8, 0.6), (12, 0.8), (16, 1.0)]}
for _kind, _cases in W6.items():

    @query(f"w06_steps_by_{_kind}")
    def w06(spark, sf_dir, kind=_kind, cases=_cases):
        """Steps to converge with growing items, categories, or both."""
        rows = []
        for categories, share in cases:
            own = item_set(spark, sf_dir, "mixed", 25, where=(f"{categories}-{share}", lambda i, c=categories, s=share: _mix(i, c, s)))
            t = steps_of(chains(spark, own, [1, 2], steps=250, patience=250))
            n = own.items.count()
            rows.append(measures.convergence_step(t).select(F.lit(categories).alias("categories"), F.lit(n).cast("long").alias("n_items"), "chain", "step"))
        return stacked(rows)


@query("w07_seconds_per_step")
def w07(spark, sf_dir):
    """Seconds per step of one chain alone, on three item sets."""
    rows = []
    for name in ("text", "planted", "web"):
        own = item_set(spark, sf_dir, name)
        for move in ("single", "composite"):
            t = chains(spark, own, [1], move=move, steps=150, patience=150)
            rows.append(t.where("step >= 0").agg(F.count(F.lit(1)).alias("steps"), F.max("seconds").alias("seconds_per_step")).select(F.lit(name).alias("items"), F.lit(move).alias("move"), "steps", "seconds_per_step"))
    return stacked(rows)


@query("m04_energy_trace")
def m04(spark, sf_dir):
    return steps_of(chains(spark, item_set(spark, sf_dir, "planted"), [1, 2])).select("chain", "step", "energy")


@query("m07_work")
def m07(spark, sf_dir):
    return measures.work(chains(spark, item_set(spark, sf_dir, "text"), [1, 2]).where("step > 0"))


@query("m08_space", q.TEXT + " SELECT wtype, count(*) AS nnz, count(DISTINCT feat)::BIGINT AS words, count(DISTINCT item_id)::BIGINT AS items FROM resp GROUP BY wtype")
def m08(spark, sf_dir):
    return q.responses(spark, sf_dir).groupBy("wtype").agg(F.count(F.lit(1)).alias("nnz"), F.countDistinct("feat").alias("words"), F.countDistinct("item_id").alias("items"))


@query("w08_vocabulary_sweep")
def w08(spark, sf_dir):
    """Purity and entropy on the mixed set with as many words of both types in each kind of item."""
    rows = []
    for k in (10, 25, 50):
        own = item_set(spark, sf_dir, "mixed", k)
        rows.append(scored(chains(spark, own, [1], steps=200), own.items, f"{k} words a type"))
    return stacked(rows)


@query("w09_word_types")
def w09(spark, sf_dir):
    rows = []
    for types in (("S", "T"), ("S",), ("T",)):
        own = item_set(spark, sf_dir, "text", types=types)
        rows.append(scored(chains(spark, own, [1]), own.items, "+".join(types)))
    return stacked(rows)


@query("w10_parameters")
def w10(spark, sf_dir):
    """How beta moves the number of categories and the measures; tau does in w10_tau."""
    own = item_set(spark, sf_dir, "text")
    return stacked([scored(chains(spark, own, [1], beta=b), own.items, f"beta-{b:g}") for b in (100.0, 300.0, 900.0)])


@query("w10_tau")
def w10_tau(spark, sf_dir):
    from ..operators import graph

    own = item_set(spark, sf_dir, "text")
    rows = []
    for tau in (0.2, 1.0, 2.0, 4.0):
        edges = graph.nearest_items(own.resp, own.dims, tau, own.params.q_min)
        part = replace(own, edges=q.held(spark, sf_dir, f"tau-{tau}", lambda edges=edges: edges))
        rows.append(scored(chains(spark, part, [1], steps=200), own.items, f"tau-{tau:g}"))
    return stacked(rows)


@query("w11_negative_control")
def w11(spark, sf_dir):
    """k-means and the sampler on raw embeddings, which carry no signal: purity near chance."""
    from ..operators import graph

    e = table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("item_id"), F.posexplode("embedding").alias("feat", "r")).withColumn("r", F.col("r").cast("double"))
    base = item_set(spark, sf_dir, "planted")
    # Positive parts as responses: 64 words of one type.
    resp = q.held(spark, sf_dir, "raw-resp", lambda: e.where("r > 0").select("item_id", "feat", F.lit("S").alias("wtype"), F.least(F.lit(0.99), 2 * F.col("r")).alias("r")))
    pairs = graph.symmetric_kl(resp, 64)
    edges = q.held(spark, sf_dir, "raw-edges", lambda: graph.nearest_items(resp, 64, 1.0))
    own = replace(base, name="raw", resp=resp, dims=64, sizes={"S": 64}, pairs=pairs, edges=edges)
    return stacked([row(ba.kmeans_items(e, 10, 5), own, "k-means"), row(sampler.best_labels(chains(spark, own, [1], steps=200)).select("item_id", "cat"), own, "sampler")])


@query("w12_copies_in_one_component", q.ON.replace(q.LABELS_SQL, "labels_now AS (SELECT item_id, 1 AS cat FROM items)") + """
SELECT count(*)::BIGINT AS n_groups, count(*) FILTER (parts = 1)::BIGINT AS together FROM (SELECT text, count(*) AS n, count(DISTINCT cp) AS parts FROM items JOIN cps USING (item_id) WHERE item_id IN (SELECT item_id FROM resp) GROUP BY text) WHERE n > 1""")
def w12(spark, sf_dir):
    """Groups of equal texts with words, and how many of them end whole in one component of a draw under one label."""
    from ..operators import graph

    items = q.items(spark, sf_dir)
    one = items.select("item_id", F.lit(1).alias("cat"))
    parts = graph.components(graph.draw_edges(q.edges(spark, sf_dir), one, 42, 0), one)
    known = items.join(q.responses(spark, sf_dir), "item_id", "left_semi").join(parts, "item_id")
    g = known.groupBy(F.sha2("text", 256).alias("text")).agg(F.count(F.lit(1)).alias("n"), F.countDistinct("cp").alias("parts")).where("n > 1")
    return g.agg(F.count(F.lit(1)).alias("n_groups"), F.count(F.when(F.col("parts") == 1, 1)).alias("together"))
