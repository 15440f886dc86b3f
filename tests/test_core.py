"""Worked examples and invariants of the methods."""

import math

import numpy as np
from pyspark.sql import functions as F

from unicat.operators import graph, measures, posterior
from unicat.operators import text_words as tw
from unicat.rng import u01, u01_py


def test_keyed_draw(spark):
    assert u01_py(42, 1, 3, 5) == 0.5395387606695294
    assert spark.range(1).select(u01(42, 1, 3, 5).alias("u")).first().u == 0.5395387606695294


def test_responses(spark):
    rows = spark.createDataFrame([(n,) for n in (0, 1, 2, 5, 10)], "n int").select(F.round(tw.saturate(F.col("n")), 6).alias("r")).collect()
    assert [r.r for r in rows] == [0.0, 0.244919, 0.462117, 0.848284, 0.986614]


def test_divergence_and_edges(spark):
    resp = spark.createDataFrame([(1, 0, 0.8), (1, 1, 0.2), (2, 0, 0.7), (2, 2, 0.1), (3, 3, 0.9)], "item_id long, feat int, r double")
    dense = {(r.s, r.t): r.j for r in graph.symmetric_kl_dense(resp, 4).collect()}
    assert {k: round(v, 6) for k, v in dense.items()} == {(1, 2): 0.860720, (1, 3): 8.281743, (2, 3): 8.159328}
    sparse = {(r.s, r.t): r.j for r in graph.symmetric_kl(resp, 4).collect()}
    assert set(sparse) == {(1, 2)} and abs(sparse[1, 2] - dense[1, 2]) < 1e-9
    assert round(math.exp(-0.2 * sparse[1, 2]), 6) == 0.841858


def test_word_weight(spark):
    lam, z, gain = posterior.word_weights(F.lit(0.6), F.lit(0.1))
    r = spark.range(1).select(lam.alias("l"), z.alias("z"), gain.alias("g")).first()
    assert (round(r.l, 6), round(r.z, 6), round(r.g, 6)) == (2.602690, 2.25, 0.750684)


def test_measures(spark):
    a = spark.createDataFrame([(0, "a", 1), (1, "a", 1), (2, "b", 1), (3, "a", 2), (4, "b", 2), (5, "c", 2)], "item_id int, truth string, cat int")
    assert measures.purity(a).first().purity == 0.5
    assert round(measures.conditional_entropy(a).first().cond_entropy, 6) == 0.867563
    assert round(measures.conditional_entropy(a, 2).first().cond_entropy, 6) == 1.251629


def test_components_and_pruning(spark):
    e = spark.createDataFrame([(1, 2, 0.9), (2, 3, 0.8), (5, 6, 0.7), (1, 3, 0.6)], "s long, t long, q double")
    v = spark.range(1, 8).withColumnRenamed("id", "item_id")
    assert {r.item_id: r.cp for r in graph.components(e, v).collect()} == {1: 1, 2: 1, 3: 1, 4: 4, 5: 5, 6: 5, 7: 7}
    assert {(r.s, r.t) for r in graph.nearest(e, 1, "mutual").collect()} == {(1, 2), (5, 6)}
    assert {(r.s, r.t) for r in graph.nearest(e, 1, "union").collect()} == {(1, 2), (2, 3), (5, 6)}
    assert {(r.s, r.t) for r in graph.nearest(e, 1, "capped").collect()} == {(1, 2), (5, 6)}


def test_lda_reads_whole_counts(spark):
    from unicat.operators.baselines import count_vectors, lda

    rows = [(i, f, n) for i in range(20) for f, n in (((0, 3_000), (1, 40)) if i % 2 else ((2, 900), (1, 40)))]
    counts = spark.createDataFrame(rows, "item_id long, feat long, n long")
    got = {r.item_id: r.features.toArray().tolist() for r in count_vectors(counts).collect()}
    assert got == {i: [3000.0, 40.0, 0.0] if i % 2 else [0.0, 40.0, 900.0] for i in range(20)}
    assert lda(counts, 2, rounds=2).count() == 20


def test_centroids_do_not_depend_on_the_order_of_sums(spark):
    from unicat.operators import vocabulary

    # The mean is 0.4342035; sums of doubles come out below it in every order.
    v = spark.createDataFrame([(i, 0, x) for i, x in enumerate((0.423927, 0.43444, 0.697035, 0.181412))], "key long, bin int, v double")
    assert [r.c for r in vocabulary.lloyd(v, "key", 1, 1).collect()] == [0.434204]
    below = v.withColumn("v", -F.col("v"))
    assert [r.c for r in vocabulary.lloyd(below, "key", 1, 1).collect()] == [-0.434204]


def test_blocks_make_the_pairs_and_edges_of_the_join(spark, monkeypatch):
    rows = [(i, f, 0.0 if (i, f) == (4, 2) else 0.1 + (i * f) % 7 / 10) for i in range(57) for f in {i % 5, 2, 5 + i % 3} if i % 19 or f == 0]
    rows += [(100 + i, f, 0.5) for i in range(5) for f in (0, 1)] + [(200, 9, 0.3)]  # copies, and an item that shares nothing
    resp = spark.createDataFrame(rows, "item_id long, feat int, r double")
    joined = graph._symmetric_kl_by_join(resp, 10, 1e-2, "full", None)
    want = {(r.s, r.t): r.j for r in joined.collect()}
    monkeypatch.setattr(graph, "BLOCK_ITEMS", 9)
    monkeypatch.setattr(graph, "BLOCK_WORDS", 3)
    got = graph.symmetric_kl(resp, 10)
    assert "Exchange" not in got._jdf.queryExecution().executedPlan().toString()
    rows = got.collect()
    got = {(r.s, r.t): r.j for r in rows}
    assert len(rows) == len(got) and got.keys() == want.keys() and max(abs(got[p] - want[p]) for p in want) < 1e-9
    for mode in ("union", "mutual"):
        for k in (2, 6):
            far = sorted(graph.nearest(graph.edges_of(joined, 0.7, 0.01), k, mode).collect())
            assert sorted(graph.nearest_items(resp, 10, 0.7, 0.01, k, mode).collect()) == far
    assert graph.nearest_items(resp.limit(0), 10).count() == 0 and graph.symmetric_kl(resp.limit(0), 10).count() == 0
    for q_min in (0.01, 0.6):
        far = {(r.s, r.t): r.q for r in graph.edges_of(joined, 0.7, q_min).collect()}
        assert {(r.s, r.t): r.q for r in graph.all_edges(resp, 10, 0.7, q_min).collect()} == far


def test_nearest_by_single_precision_bounds(spark, monkeypatch):
    """Copies, and items whose divergences differ by less than single precision resolves: ties and order stay those of all pairs."""
    rng = np.random.default_rng(5)
    base = rng.uniform(0.1, 0.9, 12)
    rows = [(i, f, float(v)) for i in range(60) for f, v in enumerate(base if i % 3 == 0 else base + 1e-6 * rng.normal(size=12))]
    rows += [(i, f, float(rng.uniform(0.1, 0.9))) for i in range(60, 120) for f in rng.choice(12, 5, replace=False).tolist()]
    resp = spark.createDataFrame(rows, "item_id long, feat int, r double")
    sides = [graph._side(b, 0, "") for b in graph.item_blocks(resp, 12).toArrow().to_batches()]
    x = graph._Dense(sides[0], 12, 1e-2)
    j, _ = graph._compared(sides[0], sides[0], 1e-2)
    assert np.abs(x.u @ x.v.T + j).max() <= x.error(x) < 1e-3
    row, col = np.divmod(np.arange(j.size), len(j))
    assert np.allclose(x.exact(x, row, col)[0], j.ravel(), atol=1e-12)
    pairs = graph.edges_of(graph.symmetric_kl(resp, 12), 0.7, 0.01)
    monkeypatch.setattr(graph, "BLOCK_ITEMS", 25)
    for mode in ("union", "mutual"):
        assert sorted(graph.nearest_items(resp, 12, 0.7, 0.01, 3, mode).collect()) == sorted(graph.nearest(pairs, 3, mode).collect())


def test_blocks_meet_in_some_tasks_a_core_however_finely_they_are_split(spark):
    from unicat.operators import graph

    blocks = spark.range(0, 120, 1, 60).selectExpr("id as block")
    met = graph._met(blocks)
    assert met.rdd.getNumPartitions() <= 25 * spark.sparkContext.defaultParallelism  # 3,600 before
    pairs = {frozenset((r.x_block, r.y_block)) for r in met.collect()}
    assert len(pairs) == met.count() == 120 * 121 // 2


def test_the_set_of_documents_writes_no_copy_of_their_texts(spark, sf, monkeypatch):
    from unicat.workloads import item_sets

    made = []
    monkeypatch.setattr(item_sets, "held", lambda spark, sf_dir, what, make: made.append(what) or make())
    items, resp, *_ = item_sets.responses(spark, sf, "text")
    assert not [what for what in made if what.startswith("texts")] and items.columns == ["item_id", "truth"]
    assert items.count() == spark.read.parquet(f"{sf}/documents.parquet").count()
