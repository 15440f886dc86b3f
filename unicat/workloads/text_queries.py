"""Queries of the representation, graph, model and measure operators on the documents, with their DuckDB twins.

The fixed state of one-step queries: items are all documents, categories are the ranks of their languages, the dictionary
has TOKENS tokens and the texture codes, seed 42, step 0.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window

from ..operators import graph, measures, posterior
from ..operators import text_words as tw
from ..registry import query
from ..rng import u01, u01_sql
from ..sources.tables import keep, stamp, table

ITEMS = "SELECT doc_id AS item_id, coalesce(text, '') AS text FROM documents"
DIMS = tw.TOKENS + tw.TEXTURE
TYPES = {"S": tw.TOKENS, "T": tw.TEXTURE}
LABELS_SQL = "labels_now AS (SELECT doc_id AS item_id, (dense_rank() OVER (ORDER BY lang))::BIGINT AS cat FROM documents)"
TEXT = "WITH RECURSIVE " + tw.text_sql(ITEMS)
GRAPH = TEXT + "," + graph.graph_sql(DIMS)
N_SQL = "(SELECT count(*) FROM items)"


def items(spark, sf_dir) -> DataFrame:
    return table(spark, sf_dir, "documents").select(F.col("doc_id").alias("item_id"), F.coalesce("text", F.lit("")).alias("text"))


def languages(spark, sf_dir) -> DataFrame:
    d = table(spark, sf_dir, "documents")
    ranks = d.select("lang").distinct().withColumn("cat", F.dense_rank().over(Window.orderBy("lang")).cast("long"))
    return d.join(F.broadcast(ranks), d.lang.eqNullSafe(ranks.lang)).select(F.col("doc_id").alias("item_id"), "cat")


_held: dict[tuple, DataFrame] = {}


def held(spark, sf_dir: str, what: str, make) -> DataFrame:
    """A derived table that several queries use, written once for a session and state of the input's files."""
    key = (spark.sparkContext.applicationId, sf_dir, stamp(spark, sf_dir), what)
    if key not in _held:
        _held[key] = keep(make(), what)
    return _held[key]


def responses(spark, sf_dir) -> DataFrame:
    return held(spark, sf_dir, "responses", lambda: tw.text_responses(items(spark, sf_dir)))


def blocks(spark, sf_dir) -> DataFrame:
    return held(spark, sf_dir, "blocks", lambda: graph.item_blocks(responses(spark, sf_dir), DIMS))


def pairs(spark, sf_dir, **options) -> DataFrame:
    """All pairs, which are many times the input and so are never kept."""
    return graph.symmetric_kl(responses(spark, sf_dir), DIMS, blocks=blocks(spark, sf_dir), **options)


def near(spark, sf_dir, **options) -> DataFrame:
    return graph.nearest_items(responses(spark, sf_dir), DIMS, blocks=blocks(spark, sf_dir), **options)


def edges(spark, sf_dir) -> DataFrame:
    return held(spark, sf_dir, "edges", lambda: near(spark, sf_dir))


def models(spark, sf_dir, **options) -> DataFrame:
    resp, labels = responses(spark, sf_dir), languages(spark, sf_dir)
    n = labels.count()
    reference = posterior.reference_means(resp, n, TYPES, options.pop("reference", "uniform"))
    return posterior.select_words(posterior.category_means(resp, labels), reference, **options)


def rounded(df: DataFrame, *cols: str) -> DataFrame:
    return df.select(*[F.round(c, 6).alias(c) if c in cols else F.col(c) for c in df.columns])


@query("r18_text_dictionary", TEXT + " SELECT w, feat FROM dict")
def r18_dictionary(spark, sf_dir):
    return tw.token_dictionary(items(spark, sf_dir)).select("w", F.col("feat").cast("long").alias("feat"))


@query("r18_text_words", TEXT + " SELECT item_id, feat::BIGINT AS feat, n FROM cnt_s UNION ALL SELECT item_id, feat + 1000, n FROM cnt_t")
def r18_words(spark, sf_dir):
    i = items(spark, sf_dir)
    s = tw.token_counts(i, tw.token_dictionary(i)).select("item_id", F.col("feat").cast("long").alias("feat"), "n")
    return s.unionByName(tw.texture_counts(i).select("item_id", (F.col("feat") + 1000).cast("long").alias("feat"), "n"))


@query("r14_responses", TEXT + " SELECT item_id, feat::INT AS feat, wtype, round(r, 6) AS r FROM resp")
def r14_responses(spark, sf_dir):
    return rounded(tw.text_responses(items(spark, sf_dir)), "r")


@query("r14_saturation_variants", TEXT + " SELECT item_id, feat::INT AS feat, round(1 / (1 + exp(-n / 2.0)), 6) AS logistic, round(least(1, n / 2.0), 6) AS linear_clip FROM cnt_s")
def r14_variants(spark, sf_dir):
    i = items(spark, sf_dir)
    c = tw.token_counts(i, tw.token_dictionary(i))
    return c.select("item_id", F.col("feat").cast("int").alias("feat"), F.round(tw.saturate(F.col("n"), "logistic"), 6).alias("logistic"), F.round(tw.saturate(F.col("n"), "linear_clip"), 6).alias("linear_clip"))


@query("r15_item_vectors", TEXT + " SELECT item_id, count(*) AS nnz, round(sum(r), 6) AS total, min(feat)::INT AS first_feat, max(feat)::INT AS last_feat FROM resp GROUP BY item_id")
def r15_vectors(spark, sf_dir):
    r = responses(spark, sf_dir).groupBy("item_id").agg(F.map_from_entries(F.collect_list(F.struct("feat", "r"))).alias("v"))
    keys = F.map_keys("v")
    return r.select("item_id", F.size("v").cast("long").alias("nnz"), F.round(F.aggregate(F.map_values("v"), F.lit(0.0), lambda a, x: a + x), 6).alias("total"), F.array_min(keys).alias("first_feat"), F.array_max(keys).alias("last_feat"))


for _t, _name in (("S", "r16_only_s"), ("T", "r16_only_t")):

    @query(_name, TEXT + f" SELECT item_id, feat::INT AS feat, round(r, 6) AS r FROM resp WHERE wtype = '{_t}'")
    def r16(spark, sf_dir, t=_t):
        return rounded(responses(spark, sf_dir).where(F.col("wtype") == t).select("item_id", "feat", "r"), "r")


@query("g01_item_scalars", GRAPH + " SELECT item_id, round(z, 6) AS z, round(a, 6) AS a, round(h, 6) AS h FROM scal")
def g01(spark, sf_dir):
    return rounded(graph.item_scalars(responses(spark, sf_dir), DIMS), "z", "a", "h")


@query("g02_sym_kl_sparse", GRAPH + " SELECT s, t, round(j, 6) AS j FROM jp")
def g02_sparse(spark, sf_dir):
    return pairs(spark, sf_dir, places=6)


@query("g02_sym_kl_half", GRAPH + " SELECT s, t, round(j / 2, 6) AS j FROM jp")
def g02_half(spark, sf_dir):
    return pairs(spark, sf_dir, mode="half", places=6)


@query("g03_edge_prob", GRAPH + " SELECT s, t, round(least(1 - 1e-9, exp(-0.2 * j)), 6) AS q FROM jp")
def g03(spark, sf_dir):
    return graph.all_edges(responses(spark, sf_dir), DIMS, q_min=0.0, blocks=blocks(spark, sf_dir), places=6, cap=1.0)


@query("g05_weak_edges", GRAPH.replace("0.001", "0.4") + " SELECT s, t FROM weak")
def g05(spark, sf_dir):
    return graph.all_edges(responses(spark, sf_dir), DIMS, q_min=0.4, blocks=blocks(spark, sf_dir)).select("s", "t")


@query("g06_knn_union", GRAPH + " SELECT s, t, round(q, 6) AS q FROM edges")
def g06_union(spark, sf_dir):
    return rounded(edges(spark, sf_dir), "q")


@query("g06_knn_mutual", GRAPH + " SELECT s, t, round(q, 6) AS q FROM votes WHERE votes = 2")
def g06_mutual(spark, sf_dir):
    return rounded(near(spark, sf_dir, mode="mutual"), "q")


@query("g06_knn_capped")
def g06_capped(spark, sf_dir):
    return rounded(graph.nearest(edges(spark, sf_dir), mode="capped"), "q")


ON = GRAPH + "," + LABELS_SQL + f""",
ons AS (SELECT s, t, q, x.cat FROM edges JOIN labels_now x ON x.item_id = s JOIN labels_now y ON y.item_id = t WHERE x.cat = y.cat AND {u01_sql("42", "0", "'e'", "s", "t")} < q),
duo AS (SELECT s AS u, t AS v FROM ons UNION ALL SELECT t, s FROM ons),
reach(item_id, spot) AS (SELECT item_id, item_id FROM items UNION SELECT r.item_id, b.v FROM reach r JOIN duo b ON r.spot = b.u),
cps AS (SELECT item_id, min(spot) AS cp FROM reach GROUP BY item_id)"""


def draw(spark, sf_dir):
    return held(spark, sf_dir, "draw", lambda: graph.draw_edges(edges(spark, sf_dir), languages(spark, sf_dir), 42, 0))


def parts(spark, sf_dir):
    return held(spark, sf_dir, "parts", lambda: graph.components(draw(spark, sf_dir), languages(spark, sf_dir)))


@query("g07_edge_draw", ON + " SELECT s, t, cat FROM ons")
def g07(spark, sf_dir):
    return draw(spark, sf_dir).select("s", "t", "cat")


@query("g08_components", ON + " SELECT item_id, cp FROM cps")
def g08(spark, sf_dir):
    return parts(spark, sf_dir)


@query("g09_candidates_recall")
def g09(spark, sf_dir):
    """How much of the nearest-neighbour graph of all pairs each way of finding candidates keeps: neighbours of the items
    whose id is divisible by 100, and of all items."""
    n, own = languages(spark, sf_dir).count(), edges(spark, sf_dir)
    counts = graph.candidate_counts(graph.candidate_buckets(responses(spark, sf_dir)), own)
    queries = sum((F.col(c) % 100 == 0).cast("long") for c in "st")
    total = own.agg(F.count(F.lit(1)).alias("edges"), F.coalesce(F.sum(queries), F.lit(0)).alias("ends"))
    share = lambda hits, of: (F.col(hits) / F.nullif(F.col(of), F.lit(0))).alias
    names = spark.createDataFrame([("rare_words",), ("minhash",), ("both",)], "method string")
    counts = names.join(counts, "method", "left").fillna(0, ["candidates", "hits", "query_hits"])
    return counts.crossJoin(total).select("method", "candidates", F.lit(n * (n - 1) // 2).cast("long").alias("all_pairs"), share("query_hits", "ends")("recall_queries"), share("hits", "edges")("recall"))


@query("g09_pair_divergences", GRAPH + " SELECT s, t, round(j, 6) AS j FROM jp JOIN edges USING (s, t)")
def g09_pairs(spark, sf_dir):
    """The divergences of given pairs (those of the graph), by arrays instead of a join on words."""
    return rounded(graph.pair_divergences(responses(spark, sf_dir), edges(spark, sf_dir).select("s", "t"), DIMS), "j")


STATE = TEXT + "," + LABELS_SQL + ","


@query("p01_means", STATE + posterior.model_sql(N_SQL, TYPES) + " SELECT cat, feat::INT AS feat, n, round(e_f, 6) AS e_f FROM means")
def p01(spark, sf_dir):
    return rounded(posterior.category_means(responses(spark, sf_dir), languages(spark, sf_dir)).select("cat", "feat", "n", "e_f"), "e_f")


for _mode in ("uniform", "half", "background"):

    @query(f"p02_reference_{_mode}", STATE + posterior.model_sql(N_SQL, TYPES, reference=_mode) + " SELECT k::VARCHAR AS word, round(e_0, 6) AS e_0 FROM ref")
    def p02(spark, sf_dir, mode=_mode):
        resp = responses(spark, sf_dir)
        r = posterior.reference_means(resp, languages(spark, sf_dir).count(), TYPES, mode)
        return r.select(F.col(r.columns[0]).cast("string").alias("word"), F.round("e_0", 6).alias("e_0"))


for _rule, _name in (("mean_gap", "p03_mean_gap"), ("kl_gain", "p04_kl_gain")):

    @query(_name, STATE + posterior.model_sql(N_SQL, TYPES, rule=_rule) + " SELECT cat, rank::INT AS rank, feat::INT AS feat FROM models")
    def p03(spark, sf_dir, rule=_rule):
        return models(spark, sf_dir, rule=rule).select("cat", "rank", "feat")


@query("p05_sequential")
def p05(spark, sf_dir):
    resp, labels = responses(spark, sf_dir), languages(spark, sf_dir)
    return rounded(posterior.pursue_sequential(resp, labels, posterior.reference_means(resp, labels.count(), TYPES), 3), "lambda", "gain")


MODELS = STATE + posterior.model_sql(N_SQL, TYPES)


@query("p06_weights", MODELS + " SELECT cat, feat::INT AS feat, round(lam, 6) AS \"lambda\", round(z, 6) AS z, round(gain, 6) AS gain FROM models")
def p06(spark, sf_dir):
    return rounded(models(spark, sf_dir).select("cat", "feat", "lambda", "z", "gain"), "lambda", "z", "gain")


LL = MODELS + """,
base AS (SELECT cat, sum(-ln(z)) AS base FROM models GROUP BY cat),
hits AS (SELECT item_id, cat, sum(lam * r) AS score FROM resp JOIN models USING (feat) GROUP BY ALL),
ll AS (SELECT i.item_id, base.cat, base + coalesce(score, 0) AS ll FROM items i CROSS JOIN base LEFT JOIN hits ON hits.item_id = i.item_id AND hits.cat = base.cat)"""


@query("p07_loglik", LL + " SELECT item_id, cat, round(ll, 6) AS ll FROM ll")
def p07(spark, sf_dir):
    return rounded(posterior.item_loglik(responses(spark, sf_dir), models(spark, sf_dir), items(spark, sf_dir)), "ll")


@query("p08_category_ll", MODELS + " SELECT cat, n, round(n * sum(gain), 6) AS ll FROM models GROUP BY cat, n")
def p08(spark, sf_dir):
    return rounded(posterior.category_loglik(models(spark, sf_dir)), "ll")


@query("p09_prior", MODELS + " SELECT count(*) AS k, (-300.0 * count(*))::DOUBLE AS log_prior FROM sizes")
def p09(spark, sf_dir):
    return posterior.category_sizes(languages(spark, sf_dir)).agg(F.count(F.lit(1)).alias("k"), (-300.0 * F.count(F.lit(1))).alias("log_prior"))


@query("p10_energy", MODELS + " SELECT count(*) AS k, round(300.0 * count(*) - sum(ll), 6) AS energy FROM (SELECT n * sum(gain) AS ll FROM models GROUP BY cat, n)")
def p10(spark, sf_dir):
    return rounded(posterior.energy(models(spark, sf_dir), 300.0), "energy")


@query("p14_top_words", MODELS + " SELECT cat, rank::INT AS rank, wtype, coalesce(w, 'code ' || (models.feat - 200)) AS word, round(gain, 6) AS gain FROM models LEFT JOIN dict ON models.feat = dict.feat")
def p14(spark, sf_dir):
    words = tw.token_dictionary(items(spark, sf_dir))
    m = models(spark, sf_dir).join(F.broadcast(words), "feat", "left")
    return m.select("cat", "rank", "wtype", F.coalesce("w", F.concat(F.lit("code "), (F.col("feat") - tw.TOKENS).cast("string"))).alias("word"), F.round("gain", 6).alias("gain"))


# Measures, on a keyed guess: the language for seven in ten documents, else a keyed number.
GUESS_SQL = f"""WITH assigned AS (SELECT doc_id AS item_id, lang AS truth,
  CASE WHEN {u01_sql("7", "doc_id")} < 0.7 THEN dense_rank() OVER (ORDER BY lang) ELSE 1 + floor({u01_sql("8", "doc_id")} * 5) END::BIGINT AS cat FROM documents),
cont AS (SELECT cat, truth, count(*) AS n FROM assigned GROUP BY ALL)"""


def guess(spark, sf_dir) -> DataFrame:
    d = table(spark, sf_dir, "documents").select(F.col("doc_id").alias("item_id"), F.col("lang").alias("truth"))
    known = languages(spark, sf_dir).withColumnRenamed("cat", "right")
    cat = F.when(u01(7, F.col("item_id")) < 0.7, F.col("right")).otherwise((1 + F.floor(u01(8, F.col("item_id")) * 5)).cast("long"))
    return d.join(known, "item_id").select("item_id", "truth", cat.alias("cat"))


@query("m01_purity", GUESS_SQL + " SELECT round(sum(top)::DOUBLE / sum(n), 6) AS purity FROM (SELECT max(n) AS top, sum(n) AS n FROM cont GROUP BY cat)")
def m01(spark, sf_dir):
    return rounded(measures.purity(guess(spark, sf_dir)), "purity")


_H = "sum(n * ln(total / n)) / sum(n)"
for _base, _name in ((None, "m02_cond_entropy"), (2.0, "m02_cond_entropy_bits")):

    @query(_name, GUESS_SQL + f" SELECT round({_H}{' / ln(2)' if _base else ''}, 6) AS cond_entropy FROM (SELECT n, (sum(n) OVER (PARTITION BY cat))::DOUBLE AS total FROM cont)")
    def m02(spark, sf_dir, base=_base):
        a = guess(spark, sf_dir)
        return rounded(measures.conditional_entropy(a, base) if base else measures.conditional_entropy(a), "cond_entropy")


@query("m03_inferred_k", GUESS_SQL + f" SELECT run, count(DISTINCT c)::BIGINT AS k FROM (SELECT run, 1 + floor({u01_sql('run', 'item_id')} * (2 + run)) AS c FROM assigned, range(1, 11) AS r(run)) GROUP BY run")
def m03(spark, sf_dir):
    runs = guess(spark, sf_dir).crossJoin(F.broadcast(spark.range(1, 11).withColumnRenamed("id", "run")))
    return measures.inferred_k(runs.select("run", (1 + F.floor(u01(F.col("run"), F.col("item_id")) * (2 + F.col("run")))).alias("cat")))


@query("m12_contingency", GUESS_SQL + " SELECT cat, truth, sum(n)::BIGINT AS n FROM cont GROUP BY CUBE (cat, truth)")
def m12(spark, sf_dir):
    return guess(spark, sf_dir).cube("cat", "truth").agg(F.count(F.lit(1)).alias("n"))


@query("m12_majority", GUESS_SQL + " SELECT cat, truth, n, round(n::DOUBLE / size, 6) AS precision FROM (SELECT *, sum(n) OVER (PARTITION BY cat) AS size, row_number() OVER (PARTITION BY cat ORDER BY n DESC, truth) AS rk FROM cont) WHERE rk = 1")
def m12_majority(spark, sf_dir):
    return rounded(measures.majority(guess(spark, sf_dir)), "precision")


@query(
    "m11_nmi",
    GUESS_SQL
    + """, tot AS (SELECT sum(n)::DOUBLE AS total FROM cont), x AS (SELECT truth, sum(n)::DOUBLE AS nx FROM cont GROUP BY truth), y AS (SELECT cat, sum(n)::DOUBLE AS ny FROM cont GROUP BY cat),
hx AS (SELECT -sum(nx / total * ln(nx / total)) AS h FROM x, tot), hy AS (SELECT -sum(ny / total * ln(ny / total)) AS h FROM y, tot),
mi AS (SELECT sum(n / total * ln(n * total / (nx * ny))) AS v FROM cont JOIN x USING (truth) JOIN y USING (cat), tot)
SELECT round(hx.h, 6) AS h_truth, round(hy.h, 6) AS h_cat, round(v, 6) AS mutual, round(2 * v / (hx.h + hy.h), 6) AS nmi FROM hx, hy, mi""",
)
def m11(spark, sf_dir):
    return rounded(measures.normalised_information(guess(spark, sf_dir)), "h_truth", "h_cat", "mutual", "nmi")


@query(
    "m09_average_precision",
    GUESS_SQL
    + f""",
scored AS (SELECT item_id, truth, cat_truth, {u01_sql("9", "item_id")} AS score FROM assigned JOIN (SELECT cat, truth AS cat_truth FROM (SELECT *, row_number() OVER (PARTITION BY cat ORDER BY n DESC, truth) AS rk FROM cont) WHERE rk = 1) USING (cat)),
ranked AS (SELECT cat_truth, (truth = cat_truth)::INT AS hit, row_number() OVER w AS rk, sum((truth = cat_truth)::INT) OVER (PARTITION BY cat_truth ORDER BY score DESC, item_id ROWS UNBOUNDED PRECEDING) AS hits FROM scored WINDOW w AS (PARTITION BY cat_truth ORDER BY score DESC, item_id))
SELECT cat_truth AS truth, round(sum(hit * hits / rk) / (SELECT count(*) FROM scored s WHERE s.truth = ranked.cat_truth), 6) AS average_precision FROM ranked GROUP BY ranked.cat_truth""",
)
def m09(spark, sf_dir):
    a = guess(spark, sf_dir)
    scored = a.join(F.broadcast(measures.majority(a).select("cat", F.col("truth").alias("cat_truth"))), "cat").withColumn("score", u01(9, F.col("item_id")))
    return rounded(measures.average_precision(scored), "average_precision")
