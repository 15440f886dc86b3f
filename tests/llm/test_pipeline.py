"""The pipeline against a chain of plain versions of its stages, on the smallest tables."""

import re
from collections import defaultdict

import zstandard

import corpus_pipeline
from unicat.llm import quality_rules
from unicat.llm.queries import tokenizer_path

from .test_documents import brute_components, lower


def plain(rows, items):
    compress = zstandard.ZstdCompressor(level=3).compress
    kept = []
    for i, t in rows:
        n, *_, repeat = quality_rules.base_counts(t)
        if n >= 50 and 100 * repeat <= 50 * n and quality_rules.in_bands(t.encode(), quality_rules.Bands(), compress)[0]:
            kept.append((i, t))
    key = lambda x: lower(x.strip(" \t\n\x0b\x0c\r"))
    holders = defaultdict(set)
    for i, t in kept:
        for x in t.split("\n"):
            if len(key(x)) >= 40:
                holders[key(x)].add(i)
    keeper = {k: max(v) for k, v in holders.items() if len(v) >= 5}
    kept = [(i, "\n".join(x for x in t.split("\n") if keeper.get(key(x), i) == i)) for i, t in kept]
    groups = brute_components(kept)
    kept = [(i, t) for i, t in kept if groups[i][1] == i]
    pattern = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")
    wins = defaultdict(set)
    for t in items:
        w = pattern.findall(lower(t or ""))
        k = min(10, len(w))
        wins[k].update(tuple(w[j : j + k]) for j in range(len(w) - k + 1) if k)
    clean = []
    for i, t in kept:
        w = pattern.findall(lower(t))
        if not any(tuple(w[j : j + k]) in own for k, own in wins.items() for j in range(len(w) - k + 1)):
            clean.append((i, t))
    return clean


def test_pipeline_matches_plain_stages(spark, sf):
    from tokenizers import Tokenizer

    docs = spark.read.parquet(f"{sf}/documents.parquet")
    items = [r.text for r in spark.read.parquet(f"{sf}/benchmark.parquet").collect()]
    want = plain([(r.doc_id, r.text) for r in docs.collect()], items)
    one = Tokenizer.from_file(tokenizer_path())
    got = corpus_pipeline.run(spark, sf).collect()
    spans = defaultdict(list)
    for r in got:
        spans[r.doc_id].append((r.start, r.length))
    assert len(want) > 50 and {i: sum(n for _, n in v) for i, v in spans.items()} == {i: len(one.encode(t, add_special_tokens=False).ids) + 1 for i, t in want}


def test_stages_keep_columns_and_survive_odd_tables(spark, sf):
    from .helpers import frame, odd_docs

    for rows in ([], odd_docs()):
        docs = frame(spark, rows)
        for name, stage in corpus_pipeline.STAGES[:-1]:
            assert stage(spark, docs, sf).columns == docs.columns, name
            assert stage(spark, docs, sf).count() <= docs.count()
        corpus_pipeline.into_sequences(spark, docs, sf).count()


def test_one_row_of_each_group_stays(spark):
    from unicat.llm import jaccard_join

    from .helpers import frame, odd_docs, prose

    a, b, c = prose(1, 80), prose(2, 80), prose(3, 80)
    texts = [(3, a), (3, a), (3, a), (None, a), (None, a), (8, a + " end"), (None, b), (None, b), (None, c), (9, c), (9, "one two"), (4, ""), (6, None), (None, " "), (None, " ")]
    got = jaccard_join.keep_one(frame(spark, [(i, t, f"l{k}", "s", k) for k, (i, t) in enumerate(texts)]))
    kept = got.collect()
    assert got.columns[0] == "doc_id" and all(r.lang == f"l{r.n_chars}" for r in kept)
    want = [(3, a), (None, b), (4, ""), (6, None), (None, " ")]
    nine = [(r.doc_id, r.text) for r in kept if r.doc_id == 9]
    assert nine in ([(9, c)], [(9, "one two")], [(9, c), (9, "one two")])
    assert sorted(map(str, ((r.doc_id, r.text) for r in kept if r.doc_id != 9))) == sorted(map(str, want))
    odd = [(r.doc_id, r.text) for r in jaccard_join.keep_one(frame(spark, odd_docs() * 3)).collect()]
    assert len(odd) == len(set(odd)) and [i for i, _ in odd].count(None) == 1
