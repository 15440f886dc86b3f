"""Brute-force versions of the operators that judge or group documents."""

import hashlib
import random
import re
import zlib
from collections import defaultdict

import pytest
from pyspark.sql import functions as F

from unicat.llm import decontam, jaccard_join, line_dedup, packing, quality_rules
from unicat.llm.components import components
from unicat.llm.queries import tokenizer_path

from .helpers import DOCS, frame, odd_docs, prose

BLANK = "[^ \t\n\x0b\x0c\r]+"


def lower(s):
    return re.sub("[A-Z]", lambda m: m[0].lower(), s)


def test_line_dedup_matches_brute_force(spark):
    rows = odd_docs()
    docs = frame(spark, rows).withColumn("__n", F.lit(1)).withColumn("pos", F.lit("x"))
    got = line_dedup.dedup_lines(docs).collect()
    holders = defaultdict(set)
    for i, t, *_ in rows:
        for x in (t or "").split("\n"):
            k = lower(x.strip(" \t\n\x0b\x0c\r"))
            if len(k) >= 40:
                holders[k].add(i)
    keep = {k: max(x for x in v if x is not None) for k, v in holders.items() if len(v - {None}) >= 5}
    want = sorted((str(i), "\n".join(x for x in (t or "").split("\n") if keep.get(lower(x.strip(" \t\n\x0b\x0c\r")), i) == i)) for i, t, *_ in rows)
    assert sorted((str(r.doc_id), r.text) for r in got) == want
    assert sum(r["__n_dropped"] for r in got) == 7
    assert line_dedup.dedup_lines(frame(spark, [])).count() == 0


def test_heavy_lines_take_the_broadcast_path(spark):
    text = "A header that every one of the documents repeats, over and over."
    docs = spark.range(3000).select(F.col("id").alias("doc_id"), F.concat(F.lit(text + "\n"), F.col("id").cast("string")).alias("text"))
    got = line_dedup.dedup_lines(docs)
    assert got.where("__n_dropped = 1").count() == 2999
    assert got.where("__n_dropped = 0").first().doc_id == 2999


def brute_components(rows):
    sets = {}
    for i, t, *_ in rows:
        w = re.findall(BLANK, lower(t or ""))
        sets.setdefault(i, set()).update({tuple(w[k : k + 5]) for k in range(len(w) - 4)} if len(w) >= 5 else {tuple(w)} if w else set())
    ids = [i for i in sets if i is not None]
    parent = {i: i for i in ids}

    def root(i):
        while parent[i] != i:
            i = parent[i]
        return i

    for x in ids:
        for y in ids:
            if x < y and sets[x] and sets[y] and 100 * len(sets[x] & sets[y]) >= 75 * len(sets[x] | sets[y]):
                a, b = sorted((root(x), root(y)))
                parent[b] = a
    return {i: (len(sets[i]), root(i)) for i in ids}


def near_copies(n=60, seed=3):
    r = random.Random(seed)
    base, rows = [prose(s, 120).split() for s in range(4)], []
    for i in range(n):
        w = list(base[i % 4])
        for _ in range(r.choice([0, 0, 1, 2, 3, 5, 9])):
            w[r.randrange(len(w))] = f"edit{r.randrange(10**6)}"
        rows.append((1000 + i, " ".join(w), "en", "s", 0))
    return rows


@pytest.mark.parametrize("rows", [odd_docs(), near_copies(), near_copies(90, 5)], ids=["odd", "near", "more"])
def test_jaccard_join_matches_brute_force(spark, rows):
    got = jaccard_join.link_components(frame(spark, rows).repartition(3)).collect()
    want = brute_components(rows)
    assert len(got) == len(rows)
    assert {r.id: (r.n_shingles, r.component_id) for r in got if r.id is not None} == want


def test_jaccard_join_of_nothing(spark):
    assert jaccard_join.link_components(frame(spark, [])).count() == 0
    got = jaccard_join.link_components(frame(spark, [(None, "a b c d e f", None, None, None), (None, None, None, None, None)])).collect()
    assert sorted((r.n_shingles, r.component_id) for r in got) == [(0, None), (2, None)]


def test_components_of_a_shuffled_chain(spark):
    ids = list(range(4000))
    random.Random(3).shuffle(ids)
    parts = ids[:3000], ids[3000:]
    edges = spark.createDataFrame([e for p in parts for e in zip(p, p[1:])], "a long, b long")  # noqa: B905
    got = {r.node: r.label for r in components(edges).collect()}
    assert got == {x: min(p) for p in parts for x in p}


def test_jaccard_join_of_a_long_chain(spark):
    words = prose(1, 4_000, 10**9).split()
    texts = [" ".join(words[12 * i : 12 * i + 150]) for i in range(300)]  # each links with its neighbours only
    ids = list(range(300))
    random.Random(4).shuffle(ids)
    got = jaccard_join.link_components(frame(spark, [(i, t, None, None, None) for i, t in zip(ids, texts, strict=True)]))
    assert {r.component_id for r in got.collect()} == {0}


@pytest.mark.parametrize("block_words", [500_000, 15])
def test_decontamination_matches_brute_force(spark, block_words):
    items = [(1, prose(1, 30)), (2, "Only, three words"), (3, None), (4, "?!"), (5, prose(1, 30)), (6, prose(6, 10))]
    docs = [(1, "x " + prose(1, 30)[4:].upper() + " y"), (2, "say only three words. only three"), (3, None), (4, ""), (5, prose(9, 50)), (None, prose(6, 10) * 2), (7, prose(6, 10) + " " + prose(6, 10))]
    item_df = spark.createDataFrame(items, "item_id long, text string")
    got = decontam.report(frame(spark, [(*d, None, None, None) for d in docs]), item_df, block_words=block_words).collect()
    pattern = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")
    want = []
    for i, t in docs:
        w, hit, found = pattern.findall(lower(t or "")), set(), set()
        for item, text in items:
            v = pattern.findall(lower(text or ""))
            k = min(10, len(v))
            wins = {tuple(v[j : j + k]) for j in range(len(v) - k + 1)} if v else set()
            for j in range(len(w) - k + 1):
                if k and tuple(w[j : j + k]) in wins:
                    hit.update(range(j, j + k))
                    found.add(str(item))
        want.append((str(i), len(w), len(hit), len(found), hashlib.sha256(",".join(sorted(found)).encode()).hexdigest(), bool(hit)))
    assert sorted((str(r.doc_id), *list(r)[1:]) for r in got) == sorted(want)
    kept = decontam.drop_contaminated(frame(spark, [(*d, None, None, None) for d in docs]), item_df)
    assert kept.columns == DOCS.names and sorted(str(r.doc_id) for r in kept.collect()) == sorted(x[0] for x in want if not x[-1])
    assert decontam.report(frame(spark, []), item_df).count() == 0
    assert decontam.report(frame(spark, odd_docs()), item_df.limit(0)).where("contaminated").count() == 0


def test_packing_round_trip(spark, sf):
    from tokenizers import Tokenizer

    one = Tokenizer.from_file(tokenizer_path())
    docs = frame(spark, odd_docs()).select("doc_id", "text").union(spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text").where("doc_id >= 100"))
    pieces = packing.pack(docs, tokenizer_path(), shard_tokens=20_000).toPandas()
    want = sorted(tuple(one.encode(t or "", add_special_tokens=False).ids) + (1,) for _, t in docs.collect())
    by_doc = defaultdict(list)
    for p in pieces.itertuples():
        assert zlib.crc32(b"".join(x.to_bytes(4, "little") for x in memoryview(p.ids).cast("H"))) == p.ids_crc32
        by_doc[p.id].append(p)
    got = []
    for own in by_doc.values():
        at = 0
        for p in sorted(own, key=lambda p: (p.doc_tokens, p.ids_crc32 if len(own) == 2 and own[0].start == own[1].start else 0, p.start)):
            if p.start == 0:
                got.append(())
                at = 0
            assert p.start == at
            at += p.length
            got[-1] += tuple(memoryview(p.ids).cast("H"))
    assert sorted(got) == want
    for _, seq in pieces.sort_values("offset").groupby("sequence_id"):
        assert seq.offset.tolist() == [0, *seq.length.cumsum().tolist()[:-1]]
        total = int(seq.length.sum())
        assert total == 2048 or (total < 2048 and total & (total - 1) == 0)
    assert packing.pack(frame(spark, []), tokenizer_path()).count() == 0


def test_packing_prefers_lexical_neighbours():
    import numpy as np

    r = np.random.default_rng(1)
    topics = [r.integers(100 * k, 100 * k + 90, (12, 500)).astype(np.uint16) for k in range(1, 4)]
    ids = [t[j] for j in range(12) for t in topics]
    df = np.bincount(np.concatenate([np.unique(x) for x in ids]), minlength=1 << 16)
    pieces = packing.pack_shard(ids, np.log1p((36 - df + 0.5) / (df + 0.5)), 500.0)
    together = defaultdict(set)
    for d, _, _, q, _ in pieces:
        together[q].add(d % 3)
    assert sum(len(v) for v in together.values()) <= len(together) + 4


def test_packing_uses_all_terms_and_all_neighbours():
    import numpy as np

    r = np.random.default_rng(2)
    # Short documents of two topics, in turn: over 64 of a topic fit into a window.
    ids = [(r.integers(0, 40, 14) + 1_000 * (1 + j % 2)).astype(np.uint16) for j in range(600)]
    pieces = packing.pack_shard(ids, np.ones(1 << 16), 14.0)
    mixed = defaultdict(set)
    for d, _, _, q, _ in pieces:
        mixed[q].add(d % 2)
    assert sum(len(v) > 1 for q, v in mixed.items() if q < 4) <= 1
    # The only neighbour shares none of the twelve heaviest terms of the seed.
    seed = np.concatenate([np.repeat(np.arange(100, 112), 50), np.arange(200, 230)]).astype(np.uint16)
    other = np.arange(5_000, 5_400).astype(np.uint16)
    near = np.concatenate([np.arange(200, 230), np.arange(6_000, 6_400)]).astype(np.uint16)
    order = dict.fromkeys(d for d, *_ in packing.pack_shard([seed, other, near], np.ones(1 << 16), 500.0))
    assert list(order) == [0, 2, 1]


def test_quality_counts_match_brute_force(spark):
    rows = odd_docs() + [(50, "a b c a b c x # * <b>\nrow\n\nrow\n \nrow ", "en", "s", 1), (51, "spam now " * 400, "en", "s", 1), (52, prose(5, 400), "en", "s", 1)]
    got = quality_rules.judge(frame(spark, rows).withColumn("n_words", F.lit("clash"))).collect()
    for r in got:
        text = r.text or ""
        w = re.findall(BLANK, text)
        spots = defaultdict(list)
        for k in range(len(w) - 2):
            spots[tuple(w[k : k + 3])].append(k)
        cover = {k + j for v in spots.values() if len(v) > 1 for k in v for j in range(3)}
        lines = [x for x in text.split("\n") if re.search(BLANK, x)]
        want = (len(w), sum(map(len, w)), len(re.findall(r"[#*$%&|<>]", text)), sum(x in lines[:k] for k, x in enumerate(lines)), len(cover))
        assert (r["__n_words"], r["__word_chars"], r["__n_symbols"], r["__n_dup_lines"], r["__n_repeat_words"]) == want
        assert r["__base_failed"] == (len(w) < 50 or 100 * len(cover) > 50 * len(w))
        assert not (r["__base_failed"] and r["__kept"])
    kept = {r.doc_id for r in got if r["__kept"]}
    assert 52 in kept and 51 not in kept and 4 in kept
    assert quality_rules.judge(frame(spark, [])).count() == 0


def test_bands_reject_noise_and_repetition():
    import os

    import zstandard

    compress, bands = zstandard.ZstdCompressor(level=3).compress, quality_rules.Bands()
    assert not quality_rules.in_bands(os.urandom(30_000), bands, compress)[0]
    assert not quality_rules.in_bands(b"abc " * 5000, bands, compress)[0]
    assert quality_rules.in_bands(prose(1, 3000).encode(), bands, compress)[0]
    half = prose(2, 3000).encode()
    assert not quality_rules.in_bands(half + b"buy it now! " * 4000, bands, compress)[0]


def test_every_chunk_counts_and_encoded_text_goes():
    import base64

    import zstandard

    compress, bands, r = zstandard.ZstdCompressor(level=3).compress, quality_rules.Bands(), random.Random(6)
    mime = base64.encodebytes(r.randbytes(60_000))
    tokens = " ".join("".join(r.choices("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789", k=8)) for _ in range(7_000)).encode()
    for junk in (mime, tokens):
        for size in (1_000, 3_000, 6_000, 13_000, 60_000):
            assert not quality_rules.in_bands(junk[:size], bands, compress)[0], size
    good = prose(3, 20_000).encode()
    for size in (1_000, 3_000, 4_097, 6_000, 13_000, 90_000):
        assert quality_rules.in_bands(good[:size], bands, compress)[0], size
    assert not quality_rules.in_bands(good[:24_576] + mime[:12_288], bands, compress)[0]  # a third is junk
    assert not quality_rules.in_bands(good[:4_096] + mime[:4_000], bands, compress)[0]  # all of it in the last chunk


def test_a_worker_remembers_a_bounded_number_of_chunks_and_forgets_them(spark):
    memo, free = packing.ChunkIds(tokenizer_path(), 50), packing.ChunkIds(tokenizer_path())
    for i in range(20):
        texts = [" ".join(f"word{chr(97 + k)}{chr(97 + i)}." for k in range(26)), prose(i, 12)]
        assert memo.encode(texts) == free.encode(texts)
        assert len(memo.known) + len(memo.older) <= 200 < 400_000
    packing.chunk_ids(tokenizer_path(), 50).encode(["some words"])
    packing.forget()
    assert packing.chunk_ids.cache_info().currsize == 0
    rows = [(i, prose(i, 40)) for i in range(30)]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    assert sorted(packing.pack(docs, tokenizer_path(), bound=20).collect()) == sorted(packing.pack(docs, tokenizer_path()).collect())


def test_words_are_learnt_without_the_marks_behind_them():
    import pyarrow as pa
    from tokenizers import Tokenizer

    one, memo = Tokenizer.from_file(tokenizer_path()), packing.ChunkIds(tokenizer_path())
    words = [f"word{chr(97 + k)}{end}" for k in range(26) for end in ("", ".", ",", ";!", "?")]
    assert [tuple(memoryview(x).cast("H")) for x in memo.encode(words)] == [tuple(one.encode(w, add_special_tokens=False).ids) for w in words]
    assert not [c for c in memo.known if c[:1].isalpha() and c[-1:] in b".,;!?"]
    texts = ["", " ", ".", "\u00a0a.\u0085b\x1fc\x0bd.", "It's. it.'s 'll. don't, x.'re", "a=\u0338. e\u0301. E\u0301; \u00c9t\u00c9! \u0130. \u1e9e: \ufb01. \u01c5, \u01c6",
             "<|endoftext|>. A.<|endoftext|>b <|EndOfText|>! <|x.", "a.b@c.d 1.2.3, x..y ...z a.\u2026 \u2026. \u00aa. \u00ba, \u00b5m.", "\U0001f600. \u4e2d\u6587. z\u0301.", "\u00f1and\u00fa: \u00dfa, \u00e6\u00f8; \u0142.", ".a", "a"]
    for step in (1, 5, len(texts)):
        for k in range(0, len(texts), step):
            ids, flat, place = memo.encode_array(pa.array(["skipped.", *texts[k : k + step]]).slice(1), [1])
            want = [(*one.encode(t, add_special_tokens=False).ids, 1) for t in texts[k : k + step]]
            assert [tuple(memoryview(x).cast("H")) for x in ids.to_pylist()] == want
            assert [tuple(flat[a:b].tolist()) for a, b in zip(place, place[1:], strict=False)] == want
