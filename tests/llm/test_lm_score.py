"""The two-model score against a plain dictionary version, and the exact sums of large counts."""

import math
from collections import Counter

import numpy as np
import pytest

from unicat.llm import lm_score

from .helpers import frame, odd_docs, prose


def brute(rows, target):
    words = {k: (t or "").encode().lower().split() for k, (_, t, *_) in enumerate(rows)}
    words = {k: [w for w in v] for k, v in words.items()}
    marked = [k for k, r in enumerate(rows) if r[0] is not None and r[0] in target]
    total = Counter(w for v in words.values() for w in v)
    vocab = {w for w, n in total.items() if n >= 2}
    seq = {k: ["<s>", *(w if w in vocab else "<unk>" for w in v)] for k, v in words.items()}
    raw = Counter(p for v in words.values() for p in zip(["<s>", *v], v))
    kept = {p for p, n in raw.items() if n >= 2}
    def model(keys):
        uni = Counter(w for k in keys for w in seq[k][1:])
        bi = Counter(p for k in keys for p in zip(seq[k], seq[k][1:]))
        return uni, bi, sum(uni.values())
    back, front = model(seq), model(marked) if marked else model(seq)
    size = len(vocab) + 1
    def loss(m, s):
        uni, bi, n = m
        return sum(math.log(uni[v] + 50 if v != "<s>" else 50) - math.log((bi[v, w] if (v, w) in kept else 0) + 50 * (uni[w] + 1) / (n + size)) for v, w in zip(s, s[1:]))
    out = []
    for k, r in enumerate(rows):
        n = len(seq[k]) - 1
        out.append((str(r[0]), n, *((round(x, 6) for x in (loss(front, seq[k]) / n, loss(back, seq[k]) / n)) if n else (None, None))))
    return sorted(out, key=str)


@pytest.mark.parametrize(("chunk", "bucket"), [(1_000_000, 1_500_000), (100, 20)])
@pytest.mark.parametrize("target", [{4, 7, 300, 303}, set()])
def test_scores_match_brute_force(spark, chunk, bucket, target):
    rows = [r for r in odd_docs() if r[0] != 7] + [(300 + i, prose(i, 150, 60), "en", "s", 0) for i in range(6)] + [(400 + i, prose(i, 150, 90), "en", "s", 0) for i in range(6)]
    ids = spark.createDataFrame([(i,) for i in target], "doc_id long")
    got = lm_score.score(frame(spark, rows).repartition(3), ids, chunk_tokens=chunk, bucket_tokens=bucket).collect()
    plain = sorted(((str(r.id), r.n_tokens, *(None if x is None else round(x, 6) for x in (r.target_loss, r.background_loss))) for r in got), key=str)
    for g, w in zip(plain, brute(rows, target), strict=True):
        assert g[:2] == w[:2] and (g[2] is None) == (w[2] is None)
        assert g[2] is None or (abs(g[2] - w[2]) < 1e-5 and abs(g[3] - w[3]) < 1e-5), (g, w)
    assert target or all(r.score in (None, 0) for r in got)


def test_target_like_documents_score_lower(spark):
    rows = [(i, prose(i, 200, 50), "en", "s", 0) for i in range(10)] + [(100 + i, prose(i, 200, 500).replace("w", "v"), "en", "s", 0) for i in range(10)]
    got = {r.id: r.score for r in lm_score.score(frame(spark, rows), spark.createDataFrame([(i,) for i in range(5)], "doc_id long")).collect()}
    assert max(v for k, v in got.items() if k < 100) < min(v for k, v in got.items() if k >= 100)


def test_empty(spark):
    assert lm_score.score(frame(spark, []), spark.createDataFrame([], "doc_id long")).count() == 0


def test_counts_are_exact_beyond_float32():
    big = (1 << 24) + 1
    keys = [np.array([3, 9], np.uint64), np.array([3], np.uint64), np.array([9, 1 << 63], np.uint64)]
    n, t = [np.array([big, 1]), np.array([2]), np.array([1, 1])], [np.array([1, 0]), np.array([big]), np.array([0, 1])]
    (got_n, got_t), stats = lm_score.add_up(keys, n, t, 2)
    assert [x.tolist() for x in got_n] == [[big + 2, 2], [big + 2], [2, 0]] and [x.tolist() for x in got_t] == [[big + 1, 0], [big + 1], [0, 0]]
    assert stats == [2, big + 5, big + 2, 1, 1]
    packer = lm_score.Packer()
    for a in ([], [0], [255, 256], [big, 1 << 40], [(1 << 64) - 1, 0]):
        assert packer.unpack(packer.pack(np.array(a, np.uint64))).tolist() == a
