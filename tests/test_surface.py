"""Measures on fixed traces, compared methods, images, schemas, late rows, plans, and empty or odd tables."""

import os
import shutil
import subprocess
import sys

import numpy as np
import pytest
from pyspark.sql import functions as F

from unicat.operators import baselines, graph, measures, posterior, vocabulary
from unicat.operators import text_words as tw
from unicat.plans import planner
from unicat.schemas import checked
from unicat.sources import io
from unicat.streaming import streams

TRACE = [(1, 0, 2, 100.0, True, 0), (1, 1, 2, 60.0, True, 5), (1, 2, 3, 20.0, True, 4), (1, 3, 3, 25.0, False, 0), (1, 4, 3, 18.0, True, 1), (2, 0, 1, 10.0, True, 0), (2, 1, 1, 10.0, False, 0)]


def test_convergence_and_work_of_a_fixed_trace(spark):
    t = spark.createDataFrame([(*x, 40) for x in TRACE], "chain long, step int, k int, energy double, accepted boolean, n_moved long, model_words int")
    assert {r.chain: r.step for r in measures.convergence_step(t).collect()} == {1: 2, 2: 0}
    w = {r.chain: r for r in measures.work(t).collect()}
    assert (w[1].steps, w[1].mean_k, w[1].operations, w[1].acceptance, w[1].moved) == (5, 2.6, 13 * 40, 0.8, 10)


def test_affinity_propagation_finds_the_wanted_number(spark):
    r = np.random.default_rng(1)
    at = np.concatenate([r.normal(c, 0.2, (8, 2)) for c in ((0, 0), (5, 0), (0, 5))])
    d = ((at[:, None] - at[None]) ** 2).sum(-1)
    rows = [(i, j, float(d[i, j])) for i in range(24) for j in range(i + 1, 24)]
    pairs, items = spark.createDataFrame(rows, "s long, t long, j double"), spark.range(24).withColumnRenamed("id", "item_id")
    got = {x.item_id: x.cat for x in baselines.affinity_local(pairs, items, 3).collect()}
    assert [len({got[i] for i in range(8 * c, 8 * c + 8)}) for c in range(3)] == [1, 1, 1] and len(set(got.values())) == 3
    assert len(np.unique(baselines.affinity_matrix(-d, -20.0))) == 3
    with pytest.raises(ValueError):
        baselines.affinity_local(pairs, items, 3, most=5)


def test_sequential_pursuit_starts_with_the_word_of_greatest_gain(spark):
    resp = spark.createDataFrame([(i, f, "S", r) for i in range(8) for f, r in ((0, 0.9 if i < 4 else 0.1), (1, 0.5), (2, 0.1 if i < 4 else 0.8))], "item_id long, feat int, wtype string, r double")
    labels = spark.range(8).select(F.col("id").alias("item_id"), (F.col("id") >= 4).cast("int").alias("cat"))
    got = {(r.cat, r["rank"]): r.feat for r in posterior.pursue_sequential(resp, labels, None, 1).collect()}
    assert got == {(0, 1): 0, (1, 1): 2}


def test_images_round_trip(spark, tmp_path):
    px = np.arange(48.0) * 5
    (tmp_path / "a.pgm").write_bytes(io.to_pgm(px, 8))
    (tmp_path / "b.ppm").write_bytes(b"P6\n# a comment\n2 1\n255\n" + bytes([255, 255, 255, 0, 0, 0]))
    (tmp_path / "c.txt").write_bytes(b"no image")
    got = {r.path[-5:]: r for r in io.read_images(spark, f"file://{tmp_path}").collect()}
    assert (got["a.pgm"].w, got["a.pgm"].h, got["a.pgm"].px) == (8, 6, np.minimum(px, 255).tolist())
    assert [round(x) for x in got["b.ppm"].px] == [255, 0] and got["c.txt"].w is None
    assert io.from_netpbm(b"P5\n9 9\n255\nshort") is None


def test_bucketed_tables_need_no_shuffle(spark):
    t = io.save_bucketed(spark.range(100).withColumn("v", F.lit(1)), "unicat_test_buckets", "id", 4)
    plan = t.groupBy("id").agg(F.sum("v"))._jdf.queryExecution().executedPlan().toString()
    assert "Exchange" not in plan
    spark.sql("DROP TABLE unicat_test_buckets")


def test_schemas_are_checked(spark):
    df = spark.createDataFrame([], "doc_id long, text string")
    assert checked(df, "doc_id bigint, text string", "documents") is df
    with pytest.raises(ValueError, match="lang string"):
        checked(df, "doc_id bigint, lang string", "documents")


def test_late_rows_are_dropped(spark):
    rows = [(1, "2024-01-01 00:10:00"), (2, "2024-01-01 09:00:00"), (3, "2024-01-01 09:30:00"), (4, "2024-01-01 00:20:00"), (5, "2024-01-01 20:00:00"), (6, "2024-01-01 09:45:00")]
    e = spark.createDataFrame([(i, t, 7, "click", 1.0) for i, t in rows], "event_id long, ts string, user_id long, event_type string, value double").withColumn("ts", F.to_timestamp("ts"))
    path = streams.new_path(spark, "late")
    for part in ("event_id <= 3", "event_id = 6", "event_id = 4", "event_id = 5"):
        e.where(part).coalesce(1).write.mode("append").parquet(path)
    stream = spark.readStream.schema(e.schema).option("maxFilesPerTrigger", 1).parquet(path)
    got = {str(r.start): r.n for r in streams.collected(streams.tumbling(stream, "1 hour"), "append").collect()}
    assert got["2024-01-01 00:00:00"] == 1 and got["2024-01-01 09:00:00"] == 3  # event 4 came after its window had closed


def test_candidates_drop_no_item_and_planner_counts(spark):
    resp = spark.createDataFrame([(i, f, "S", 0.5) for i in range(60) for f in (0, 1 + i % 3)], "item_id long, feat int, wtype string, r double")
    p = planner.plan(resp)
    assert (p.pairs, p.chain, p.shared_pairs) == ("all", "local", 60 * 59 // 2 + 3 * 190)
    assert planner.plan(resp, most_pairs=10).pairs == "candidates"
    found = graph.candidate_pairs(resp, "both", most_items=25, bands=4)
    assert found.select(F.explode(F.array("s", "t"))).distinct().count() == 60
    some = graph.symmetric_kl(resp, 4)
    both = graph.pair_divergences(resp, some.select("s", "t"), 4).withColumnRenamed("j", "k").join(some, ["s", "t"])
    assert both.count() == 1770 and both.where("abs(j - k) > 1e-9").count() == 0


def test_candidates_are_counted_without_being_written(spark, monkeypatch):
    rng = np.random.default_rng(3)
    resp = spark.createDataFrame([(i, f, "S", 0.5) for i in range(80) for f in {int(x) for x in rng.integers(0, 40, 4)}], "item_id long, feat int, wtype string, r double")
    edges = spark.createDataFrame([(int(s), int(s + d)) for s, d in zip(rng.integers(0, 60, 90), rng.integers(1, 20, 90))], "s long, t long").distinct()
    monkeypatch.setattr(graph, "BLOCK_ITEMS", 13)
    got = {r.method: r[1:] for r in graph.candidate_counts(graph.candidate_buckets(resp, "both", 10, 3), edges).collect()}
    for method in ("rare_words", "minhash", "both"):
        pairs = {tuple(r) for r in graph.candidate_pairs(resp, method, 10, 3).collect()}
        hits = [tuple(r) for r in edges.collect() if tuple(r) in pairs]
        assert got[method] == (len(pairs), len(hits), sum((s % 100 == 0) + (t % 100 == 0) for s, t in hits))


def test_words_by_matrix_products_are_the_nearest(spark):
    v = spark.createDataFrame([(i, b, float((i * 7 + b * 3) % 11)) for i in range(40) for b in range(4)], "key long, bin int, v double")
    words = vocabulary.learned(v, "key", 3, 4, rounds=5)
    x = np.array([[(i * 7 + b * 3) % 11 for b in range(4)] for i in range(40)], float)
    want = ((x[:, None] - words[None]) ** 2).sum(-1).round(9).argmin(1)
    assert {r.key: r.word for r in vocabulary.match(v, words, "key", 4).collect()} == dict(enumerate(want.tolist()))
    assert vocabulary.learned(v.limit(0), "key", 3, 4).shape == (0, 4)


def test_text_words_of_odd_texts(spark):
    rows = [(1, None), (2, ""), (3, "short"), (4, "a😀b" * 5), (5, "The cat sat on the mat."), (5, "The cat sat on the mat.")]
    items = spark.createDataFrame(rows, "item_id long, text string")
    n = {r.item_id: r.n for r in tw.texture_counts(items).groupBy("item_id").agg(F.sum("n").alias("n")).collect()}
    assert n == {4: 15 - 8, 5: 2 * (23 - 8)}
    assert tw.text_responses(items.limit(0)).count() == 0


def test_the_rest_works_without_the_corpus_operators(tmp_path):
    root = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))
    shutil.copytree(root, tmp_path / "r", ignore=shutil.ignore_patterns(".git", "llm", "corpus_pipeline.py", "__pycache__", ".pytest_cache"))
    code = "import __spark_entry__ as e; q = e.queries(); assert len(q) > 120 and not any(k.startswith('op') for k in q) and 'pipeline' not in q and set(e.oracle_sql()) <= set(q)"
    subprocess.run([sys.executable, "-c", code], cwd=tmp_path / "r", check=True, env={**os.environ, "PYTHONPATH": ""})


def test_a_side_that_is_too_large_is_not_broadcast(spark, sf, monkeypatch):
    from unicat import catalogue

    q04 = catalogue.QUERIES["q04_hint_broadcast"]
    plan = lambda df: df._jdf.queryExecution().executedPlan().toString()
    small = q04(spark, sf)
    assert "BroadcastHashJoin" in plan(small)
    monkeypatch.setattr(planner.broadcasts, "__defaults__", (10,))
    large = q04(spark, sf)
    assert "SortMergeJoin" in plan(large) and sorted(large.collect()) == sorted(small.collect())


@pytest.mark.parametrize("name", ["s06_carrier_source", "s07_images"])
def test_sources_carry_the_given_embeddings(spark, tmp_path, name):
    import duckdb

    from unicat import catalogue

    rows = [(i, [(i * 7 + k * 5) % 31 / 30 - 0.5 for k in range(64)], None if i == 3 else i % 8 - 1) for i in range(0, 240, 3)]
    spark.createDataFrame(rows, "vec_id long, embedding array<float>, label int").coalesce(1).write.parquet(f"file://{tmp_path}/embeddings.parquet")
    con = duckdb.connect()
    con.execute(f"CREATE VIEW embeddings AS SELECT * FROM read_parquet('{tmp_path}/embeddings.parquet/*.parquet')")
    want = con.execute(catalogue.SQL[name]).fetchall()
    got = [tuple(r) for r in catalogue.QUERIES[name](spark, f"file://{tmp_path}").collect()]
    assert len(want) > 0 and sorted(got) == sorted(want)


def test_plain_images():
    assert io.from_netpbm(b"P2\n# a comment\n2 1\n510\n510 0\n")[2].tolist() == [255.0, 0.0]
    assert io.from_netpbm(b"P2\n2 2\n255\n1 2 3") is None and io.from_netpbm(b"P2\nx") is None
