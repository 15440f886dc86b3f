"""Held-out accuracy of the co-trained classifier, and its defined cases."""

import random

import numpy as np
from pyspark.sql import functions as F

from unicat.llm import quality_classifier as qc

from .helpers import frame, odd_docs, prose


def corpus(n=900):
    r, rows, truth = random.Random(2), [], []
    for i in range(n):
        kind = r.choice(["good", "good", "noisy", "table", "toxic"])
        text = prose(i, r.randint(60, 160), 800).capitalize() + "."
        if kind == "noisy":
            text = " ".join(w + r.choice(["###", "$$$", "&&&"]) for w in text.split())
        if kind == "table":
            text = text.replace(" ", " | ")
        if kind == "toxic":
            text = text.replace(" ", " awful moron ", 2)
        rows.append((i, text, "en", f"src{0 if kind == 'good' and r.random() < 0.8 else r.randint(1, 5)}", len(text)))
        truth.append((i, int(kind not in ("noisy", "table")), int(kind == "toxic")))
    return rows, truth


def test_held_out_accuracy_and_use_of_both_views(spark):
    rows, truth = corpus()
    docs = frame(spark, rows)
    labels = spark.createDataFrame(truth[:450], "doc_id long, quality int, toxic int")
    model = qc.train(docs, labels)
    assert model[5] and model[5][0] > 0
    got = {r.doc_id: r for r in qc.score(docs, model).collect()}
    good = {i: q == 1 and t == 0 for i, q, t in truth}
    rest = range(450, 900)
    assert np.mean([got[i]["__kept"] == good[i] for i in rest]) > 0.93
    assert np.mean([got[i]["__kept"] for i in rest if good[i]]) > 0.97
    meta = [got[i]["__meta_score"] for i in rest if good[i]], [got[i]["__meta_score"] for i in rest if not good[i]]
    assert np.mean(meta[0]) > np.mean(meta[1])


def test_every_unlabelled_document_can_teach(spark):
    rows, truth = corpus(300)
    copies = [(1000 + 300 * k + i, t, *rest) for k in range(25) for i, t, *rest in rows]
    model = qc.train(frame(spark, rows + copies).repartition(5), spark.createDataFrame(truth, "doc_id long, quality int, toxic int"))
    assert model[5][0] > 5_000  # of 7,500 unlabelled rows
    one = qc.train(frame(spark, rows), spark.createDataFrame(truth, "doc_id long, quality int, toxic int"))
    assert one[5] == [0]  # nothing is unlabelled


def test_defined_cases(spark):
    docs = frame(spark, odd_docs()).withColumn("__n", F.lit(3))
    empty = spark.createDataFrame([], "doc_id long, quality int, toxic int")
    assert qc.train(docs, empty) is None
    out = qc.score(docs, None)
    assert out.columns[: len(docs.columns)] == docs.columns and out.where("__score = 0.5 and __kept").count() == docs.count()
    rows, truth = corpus(200)
    model = qc.train(frame(spark, rows), spark.createDataFrame([*truth, (None, 1, 0), (5, None, None)], "doc_id long, quality int, toxic int"))
    assert qc.score(docs, model).count() == docs.count()
    assert qc.score(docs.limit(0), model).count() == 0
