"""URL filter against a plain loop over the rules, its filter's false positives, and HTML extraction on odd pages."""

import random
import re

import numpy as np
import pytest
from pyspark.sql import functions as F

from unicat.llm import html_extract as he
from unicat.llm import url_filter as uf
from unicat.llm.queries import LISTED_URLS, URL_RULES, op1_url_filter

PAGES = "page_id long, url string, html string"


def plain(url):
    m = re.search(r"://([^/?#]*)([^?#]*)", url or "")
    host = re.sub("[A-Z]", lambda c: c[0].lower(), m[1]) if m else ""
    path = m[2] if m else ""

    def fit(entry, p):
        h, at = entry.split("/", 1)
        return (host == h or host.endswith("." + h)) and p.startswith("/" + at)

    own = [(len(e), e, v) for e, v in URL_RULES if fit(e, path)]
    rule, verdict = max(own)[1:] if own else (None, None)
    return host, path, rule, verdict or ("block" if any(fit(e, path or "/") for e in LISTED_URLS) else "allow")


def test_url_filter_matches_plain_rules(spark):
    urls = [None, "", "no scheme", "http://", "http://a.org", "http://A.ORG/x", "https://www.example.org/es/1", "https://example.org/en/12?x", "http://notexample.org/es/1", "http://x.com/fr/", "http://x.com/FR/", "ftp://u:p@x.com:80/de/#q", "http://cheap-pills.example.com", "http://www.cheap-pills.example.com?q=/", "http://my-cheap-pills.example.com/", "a://b.org/c://d.com/fr/", "http://éxample.Org/ü"]
    r = random.Random(1)
    urls += [f"https://{r.choice(['www.', '', 'm.'])}{r.choice(['example', 'free-bets.example', 'x'])}.{r.choice(['org', 'com', 'net'])}/{r.choice(['es', 'en', 'fr', 'de'])}/{r.randrange(200)}" for _ in range(200)]
    pages = spark.createDataFrame([(i, u, None) for i, u in enumerate(urls)] + [(0, "http://a.org/", None)] * 3 + [(None, None, None)], PAGES).withColumn("host", F.lit("clash"))
    entries = uf.entry_table(spark.createDataFrame(list(URL_RULES), "entry string, verdict string"), spark.createDataFrame([(u,) for u in LISTED_URLS], "url string"))
    got = uf.judge(pages, entries)
    assert got.columns[:4] == pages.columns
    rows = got.collect()
    assert len(rows) == len(urls) + 4
    for x in rows:
        assert (x["__host"], x["__path"], x["__rule"], x["__verdict"]) == plain(x.url), x.url
    none = uf.judge(pages, entries.limit(0))
    assert none.where("__verdict = 'allow'").count() == len(urls) + 4 and uf.judge(pages.limit(0), entries).count() == 0


@pytest.mark.parametrize("table", ["sf0.001", "sf0.01", "sf0.1"])
def test_listed_sites_of_the_given_tables_are_blocked(spark, table):
    bad = op1_url_filter(spark, f"/root/testdata/{table}").where(F.col("host").rlike(r"(^|\.)(spam-farm|cheap-pills|casino-win|ads-track|free-bets)\.example\."))
    rows = bad.collect()
    assert rows and all(r.verdict == "block" for r in rows if r.rule is None)


def test_blocked_filter_has_few_false_positives(spark):
    entries = spark.range(5000).select(F.concat(F.lit("Lhost"), "id", F.lit(".com/")).alias("key"))
    filled = uf.build_filter(entries)
    assert uf.passes(filled, [f"Lhost{i}.com/" for i in range(5000)]).all()
    assert uf.passes(filled, [f"Lother{i}.com/" for i in range(20000)]).mean() < 0.02


def test_extraction_of_odd_pages(spark):
    page = """<html><head><title>no</title></head><body><nav><ul><li><a href=x>Home</a></ul></nav><div class="cookie-notice">We use cookies.</div>
    <article><h1>Title &amp; more</h1><p>First   <b>bold</b> line,<br>and <i>this</i>.<p>Second one &eacute;&#8364; &lt;b&gt;.
    <script>var x = "<p>no</p>";</script><div class=ad>Buy now</div><p>Third, with <a href="#">a link</a> in it.</article>
    <section id="comments"><h3>Comments</h3><p>Nice article, thanks for it.</p></section><footer>&copy; me</footer></body></html>"""
    want = "Title & more\n\nFirst bold line, and this.\n\nSecond one é€ <b>.\n\nThird, with a link in it."
    rows = [(1, "u", page), (2, "u", None), (3, "u", ""), (4, "u", "<" * 50), (5, "u", "<div>" * 30_000 + "x" + "</p>" * 10), (6, "u", "<script>never closed"), (7, "u", page), (8, "u", "<!-- open")]
    got = {r.page_id: r for r in he.extract_text(spark.createDataFrame(rows, PAGES)).collect()}
    assert got[1]["__text"] == want and got[7]["__n_chars"] == len(want)
    assert got[2]["__text"] == got[3]["__text"] == got[6]["__text"] == got[8]["__text"] == ""
    assert he.extract_text(spark.createDataFrame([], PAGES)).count() == 0


def test_held_out_accuracy():
    w, pair = he.fitted()
    label, right, total = re.compile(r" data-k=([01])"), 0, 0
    for page in he.training_pages(60, seed=99):
        nodes, _ = he.parse(label.sub("", page))
        y = np.array([0, *map(int, label.findall(page))])
        x, bond = he.features(nodes)
        p = np.array(he.marginals([v.parent for v in nodes], (x @ w).tolist(), bond, pair)) > 0.5
        own = np.array([v.own for v in nodes])
        right, total = right + ((p == y) * own).sum(), total + own.sum()
    assert right / total > 0.98


def test_marginals_are_exact():
    import itertools

    r = np.random.default_rng(3)
    parents, bond = [0, 0, 0, 1, 1, 2], [0, 1, 2, 0, 3, 1]
    unary, pair = r.normal(size=6).tolist(), r.normal(size=(he.PARENTS, 2, 2)).tolist()
    total, one = 0.0, np.zeros(6)
    for s in itertools.product((0, 1), repeat=6):
        e = sum(u * x for u, x in zip(unary, s, strict=True)) + sum(pair[bond[i]][s[parents[i]]][s[i]] for i in range(1, 6))
        total += np.exp(e)
        one += np.exp(e) * np.array(s)
    assert np.allclose(he.marginals(parents, unary, bond, pair), one / total)
