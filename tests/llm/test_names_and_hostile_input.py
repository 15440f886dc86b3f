"""Columns of the caller that are named like the operators' own, and pages made to take long."""

import time

import pytest
from pyspark.sql import functions as F

from unicat.llm import decontam, html_extract, jaccard_join, line_dedup, pii, quality_classifier, quality_rules, url_filter

from .helpers import frame, odd_docs, prose

CLASHES = ("__lines", "__text_hash", "__n_lines", "__drops", "__row", "__host", "__key", "__spans", "__kept", "__ratio", "__id", "__of", "__clean", "__score", "__text", "rep", "token", "n", "id", "ids")


def clashing(df):
    return df.withColumns({c: F.lit(f"own {c}") for c in CLASHES})


def test_names_that_clash(spark):
    docs = clashing(frame(spark, odd_docs()))
    items = spark.createDataFrame([(1, prose(4, 80))], "item_id long, text string")
    pages = clashing(spark.createDataFrame([(1, "http://a.org/x", "<p>Some text, here.</p>"), (2, None, None)], "page_id long, url string, html string"))
    entries = url_filter.entry_table(spark.createDataFrame([("org/", "allow")], "entry string, verdict string"), spark.createDataFrame([("b.org/",)], "url string"))
    added = {
        "lines": (line_dedup.dedup_lines(docs), docs),
        "match": (decontam.match(docs, items), docs),
        "judge": (quality_rules.judge(docs), docs),
        "score": (quality_classifier.score(docs, None), docs),
        "url": (url_filter.judge(pages, entries), pages),
        "html": (html_extract.extract_text(pages, drop_html=False), pages),
    }
    for name, (out, df) in added.items():
        assert len(set(out.columns)) == len(out.columns) and out.count() == df.count(), name
        row = out.first()
        for c in CLASHES:
            assert f"own {c}" in (row[c], row[f"in{c}"] if f"in{c}" in out.columns else None), (name, c)
    for name, out in {"drop": quality_rules.drop_rejected(docs), "clean": decontam.drop_contaminated(docs, items), "one": jaccard_join.keep_one(docs), "sanitise": pii.sanitise(docs)}.items():
        assert out.columns == docs.columns, name
        assert out.where(F.col("__ratio") != "own __ratio").count() == 0 and out.count() > 0, name


def test_many_urls_without_a_hit_are_spread(spark):
    pages = spark.range(2_000).select(F.col("id").alias("page_id"), F.concat(F.lit("http://h"), "id", F.lit(".net/")).alias("url"))
    listed = spark.range(5_000).select(F.concat(F.lit("http://bad"), "id", F.lit(".net/")).alias("url"))
    entries = url_filter.entry_table(spark.createDataFrame([("h7.net/", "block")], "entry string, verdict string"), listed)
    got = url_filter.judge(pages.unionByName(listed.select(F.lit(-1).cast("long").alias("page_id"), "url")), entries)
    assert got.where("__verdict = 'block' and page_id >= 0").count() == 1 and got.where("__listed is not null and __verdict = 'block'").count() == 5_000 and got.count() == 7_000


N = 30_000
HOSTILE = {
    "open inline": "<b>" * N + "<p>x" * N,
    "open quotes": '<a "x ' * N,
    "open quotes, one end": '<a "x ' * N + ">",
    "stray ends": "<div>" * N + "</p>" * N,
    "lists": "<ul><li>" * N,
    "mixed quotes": "<a '>\"<b \">'" * N,
    "marked spans": "<span class=ad>" * N + "x",
    "comments": "<!--" * N,
}


@pytest.mark.parametrize("name", HOSTILE)
def test_time_is_linear_in_the_page(name):
    html_extract.fitted()
    began = time.time()
    html_extract.extract(HOSTILE[name])
    assert time.time() - began < 15


def test_long_and_unclosed_attributes():
    long = "<article><p title='" + "y" * 5_000 + " > z'>One.</p><p class=\"a b>Two, with an open quote.</p><p>Three.</p></article>"
    assert html_extract.extract(long).split("\n\n")[0] == "One." and html_extract.extract(long).endswith("Three.")
