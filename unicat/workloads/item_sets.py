"""The four item sets of the experiments, each with nine-block responses, its graph and its truth, and chains over them.

text: documents by language. planted: rasters by label. web: documents and pages, by table and language. mixed: web and
planted together, which have words of their own each. A set's words are the same number of both types in each kind.
"""

from __future__ import annotations

from dataclasses import dataclass, replace

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators import descriptors as de
from ..operators import graph, posterior, sampler
from ..operators import text_words as tw
from ..operators import vocabulary as vo
from ..params import Params
from ..sources import rasters
from ..sources.tables import table
from .text_queries import held

SIDE = rasters.PLANTED_SIDE
BLOCKS = 9
WORDS = 50
#: Divergences of texts are a tenth of those of images, so tau is ten times the published 0.2 there.
SETTINGS = {"text": Params(tau=2.0, steps=400, patience=200), "web": Params(tau=2.0, steps=400, patience=200), "planted": Params(tau=1.0, beta=100.0, steps=400, patience=200), "mixed": Params(tau=1.5, beta=200.0, steps=400, patience=200)}
#: Ids of pages and of rasters follow those of documents.
PAGES, RASTERS = 10_000_000_000, 20_000_000_000


@dataclass
class ItemSet:
    name: str
    items: DataFrame  # item_id, truth
    resp: DataFrame  # item_id, feat, wtype, r
    dims: int
    sizes: dict  # features of a type
    edges: DataFrame
    pairs: DataFrame
    params: Params


def texts(spark, sf_dir, web: bool = False) -> DataFrame:
    """item_id, text, truth. web adds the pages without their tags, as categories of their own."""
    d = table(spark, sf_dir, "documents").select(F.col("doc_id").alias("item_id"), F.coalesce("text", F.lit("")).alias("text"), F.concat(F.lit("doc-"), F.coalesce("lang", F.lit("?"))).alias("truth"))
    if not web:
        return d
    bare = F.regexp_replace(F.regexp_replace(F.coalesce("html", F.lit("")), r"(?s)<(script|style)[^>]*>.*?</\1>", " "), r"<[^>]*>", " ")
    p = table(spark, sf_dir, "pages").select((F.col("page_id") + PAGES).alias("item_id"), F.trim(bare).alias("text"), F.concat(F.lit("page-"), F.regexp_extract(F.coalesce("html", F.lit("")), r'lang="(\w+)"', 1)).alias("truth"))
    return d.unionByName(p)


def patch_words(spark, sf_dir, kind: str, k: int) -> DataFrame:
    """item_id, scale, patch, word of planted rasters at three scales, by a dictionary of k words over all of them."""

    def make():
        px = held(spark, sf_dir, "planted", lambda: rasters.as_arrays(rasters.planted(spark, sf_dir), SIDE))
        v = de.pyramid(px, SIDE, kind)
        v = held(spark, sf_dir, f"pyramid-{kind}", lambda: v.select((F.col("item_id") * 1000 + F.col("scale") * 100 + F.col("patch")).alias("key"), "bin", F.round("v", 6).alias("v")))
        dims = 32 if kind == "S" else 64
        m = vo.match(v, vo.learned(v, "key", k, dims), "key", dims)
        return m.select(F.floor(F.col("key") / 1000).alias("item_id"), F.floor(F.col("key") % 1000 / 100).cast("int").alias("scale"), (F.col("key") % 100).cast("int").alias("patch"), "word")

    return held(spark, sf_dir, f"patch-words-{kind}-{k}", make)


def planted_responses(spark, sf_dir, k: int, types=("S", "T")) -> DataFrame:
    """item_id, feat, wtype, r over nine blocks of k words of each type."""
    out = None
    for kind in types:
        counts = de.blocks(patch_words(spark, sf_dir, kind, k), SIDE).groupBy("item_id", "block", "word").agg(F.count(F.lit(1)).alias("n"))
        shift = 0 if kind == "S" else BLOCKS * k
        r = counts.select("item_id", (F.col("block") * k + F.col("word") + shift).cast("int").alias("feat"), F.lit(kind).alias("wtype"), tw.saturate(F.col("n")).alias("r"))
        out = r if out is None else out.unionByName(r)
    return out


def responses(spark, sf_dir, name: str, k: int = WORDS, types=("S", "T")) -> tuple[DataFrame, DataFrame, int, dict]:
    """(items, responses, features, features of each type)."""
    rows = held(spark, sf_dir, "embeddings-truth", lambda: table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("item_id"), F.concat(F.lit("label-"), F.col("label").cast("string")).alias("truth")))
    if name == "planted":
        return rows, held(spark, sf_dir, f"planted-{k}-{types}", lambda: planted_responses(spark, sf_dir, k, types)), 2 * BLOCKS * k, {"S": BLOCKS * k, "T": BLOCKS * k}
    if name == "mixed":
        items, resp, dims, sizes = responses(spark, sf_dir, "web", k, types)
        more, r, d, own = responses(spark, sf_dir, "planted", k, types)
        both = resp.unionByName(r.select((F.col("item_id") + RASTERS).alias("item_id"), (F.col("feat") + dims).cast("int").alias("feat"), "wtype", "r"))
        return items.unionByName(more.withColumn("item_id", F.col("item_id") + RASTERS)), both, dims + d, {t: sizes[t] + own[t] for t in sizes}
    # Documents are read where they are; only the pages' texts without tags are worth a copy.
    items = texts(spark, sf_dir) if name == "text" else held(spark, sf_dir, f"texts-{name}", lambda: texts(spark, sf_dir, True))
    resp = held(spark, sf_dir, f"resp-{name}-{k}-{types}", lambda: tw.block_responses(items, k, types))
    return items.select("item_id", "truth"), resp, BLOCKS * k + tw.TEXTURE, {"S": BLOCKS * k, "T": tw.TEXTURE}


def item_set(spark, sf_dir, name: str, k: int = WORDS, types=("S", "T"), where=None) -> ItemSet:
    """where: a condition on items (item_id, truth) that a part of the set meets, and a name for it."""
    items, resp, dims, sizes = responses(spark, sf_dir, name, k, types)
    tag = f"{name}-{k}-{types}"
    if where is not None:
        tag += f"-{where[0]}"
        items = held(spark, sf_dir, f"part-items-{tag}", lambda: where[1](items))
        resp = held(spark, sf_dir, f"part-{tag}", lambda: resp.join(items, "item_id", "left_semi"))
    params = SETTINGS[name]
    blocks = held(spark, sf_dir, f"set-blocks-{tag}", lambda: graph.item_blocks(resp, dims))
    pairs = graph.symmetric_kl(resp, dims, blocks=blocks)
    edges = held(spark, sf_dir, f"set-edges-{tag}-{params.tau}", lambda: graph.nearest_items(resp, dims, params.tau, params.q_min, params.neighbours, params.knn_mode, blocks=blocks) if params.knn_mode != "capped" else graph.nearest(graph.edges_of(pairs, params.tau, params.q_min), params.neighbours, params.knn_mode))
    return ItemSet(name, items, resp, dims, sizes, edges, pairs, params)


def reference(own: ItemSet) -> np.ndarray:
    """E_0 of every feature: uniform over the words of a type, by the responses' own mean."""
    e = {r.wtype: r.e_0 for r in posterior.reference_means(own.resp, own.items.count(), own.sizes).collect()}
    out = np.full(own.dims, 0.01)
    for r in own.resp.select("feat", "wtype").distinct().collect():  # as many as features
        out[r.feat] = e[r.wtype]
    return out


def chains(spark, own: ItemSet, seeds: list[int], **changes) -> DataFrame:
    return sampler.run_chains(spark, own.resp, own.edges, own.dims, reference(own), replace(own.params, **changes), seeds, own.items)


def scored(traces: DataFrame, truth: DataFrame, name: str) -> DataFrame:
    """method, chain, k, purity, cond_entropy of the best state of each chain, over all items."""
    best = sampler.best_labels(traces).join(truth, "item_id")
    c = best.groupBy("chain", "cat", "truth").agg(F.count(F.lit(1)).alias("n"))
    size = c.groupBy("chain", "cat").agg(F.sum("n").alias("size"))
    per = c.join(size, ["chain", "cat"]).groupBy("chain", "cat").agg(F.max("n").alias("top"), F.sum("n").alias("n"), F.sum(F.col("n") * F.log(F.col("size") / F.col("n"))).alias("h"))
    return per.groupBy("chain").agg(F.count(F.lit(1)).alias("k"), F.round(F.sum("top") / F.sum("n"), 4).alias("purity"), F.round(F.sum("h") / F.sum("n"), 4).alias("cond_entropy")).select(F.lit(name).alias("method"), "chain", "k", "purity", "cond_entropy")
