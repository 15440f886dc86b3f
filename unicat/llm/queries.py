"""The queries of the training-data operators, with production parameters, and the SQL that checks them."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import decontam, html_extract, jaccard_join, line_dedup, lm_score, packing, pii, quality_classifier, quality_rules, url_filter
from .common import read_table


#: The rules of op1, host and path in one.
URL_RULES = (("org/", "allow"), ("example.org/es/", "block"), ("example.org/en/1", "block"), ("com/fr/", "allow"), ("com/de/", "block"))
#: The listed canonical URLs of op1: sites that are blocked whole, under every top-level domain in use, unless a rule says otherwise.
LISTED_SITES = ("spam-farm.example", "cheap-pills.example", "casino-win.example", "ads-track.example", "free-bets.example")
LISTED_URLS = tuple(f"{site}.{top}/" for site in LISTED_SITES for top in ("com", "net", "org"))


def op1_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = read_table(spark, sf_dir, "pages").select("page_id", "url")
    entries = url_filter.entry_table(spark.createDataFrame(list(URL_RULES), "entry string, verdict string"), spark.createDataFrame([(u,) for u in LISTED_URLS], "url string"))
    return url_filter.judge(pages, entries).select("page_id", *[F.col(f"__{c}").alias(c) for c in ("host", "path", "rule", "verdict")])


OP1_SQL = f"""
WITH u AS (
  SELECT page_id, row_number() OVER () AS r,
    translate(regexp_extract(coalesce(url, ''), '://([^/?#]*)', 1), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host,
    regexp_extract(coalesce(url, ''), '://[^/?#]*([^?#]*)', 1) AS path FROM pages
), rules(entry, verdict) AS (VALUES {", ".join(f"('{e}', '{v}')" for e, v in URL_RULES)}),
listed(entry) AS (VALUES {", ".join(f"('{e}')" for e in LISTED_URLS)}),
split AS (SELECT entry, verdict, split_part(entry, '/', 1) AS h, substr(entry, strpos(entry, '/')) AS p FROM rules),
best AS (
  SELECT r, max_by(entry, length(entry)) AS rule, max_by(verdict, length(entry)) AS verdict FROM u JOIN split ON (host = h OR ends_with(host, '.' || h)) AND starts_with(path, p) GROUP BY r
), spam AS (SELECT DISTINCT r FROM u JOIN listed ON host = split_part(entry, '/', 1) OR ends_with(host, '.' || split_part(entry, '/', 1)))
SELECT page_id, host, path, rule, coalesce(verdict, CASE WHEN spam.r IS NULL THEN 'allow' ELSE 'block' END) AS verdict
FROM u LEFT JOIN best USING (r) LEFT JOIN spam USING (r)
"""


def tokenizer_path(name: str = "word_bpe_49k.json") -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def op2_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read_table(spark, sf_dir, "documents").select("doc_id", "text")
    return packing.pack(docs, tokenizer_path(), with_ids=False).withColumnRenamed("id", "doc_id")


def op3_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read_table(spark, sf_dir, "documents").select("doc_id", "text")
    return line_dedup.dedup_lines(docs).select("doc_id", F.col("__n_lines").alias("n_lines"), F.col("__n_dropped").alias("n_dropped"), F.sha2("text", 256).alias("kept_sha256"))


OP3_SQL = """
WITH lines AS (
  SELECT doc_id, unnest(string_split(coalesce(text, ''), chr(10))) AS line, unnest(range(len(string_split(coalesce(text, ''), chr(10))))) AS pos FROM documents
), keyed AS (
  SELECT doc_id, pos, line, translate(trim(line, ' ' || chr(9) || chr(10) || chr(11) || chr(12) || chr(13)), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS k FROM lines
), shared AS (
  SELECT k, max(doc_id) AS keeper FROM keyed WHERE length(k) >= 40 GROUP BY k HAVING count(DISTINCT doc_id) >= 5
), marked AS (
  SELECT doc_id, pos, line, s.k IS NOT NULL AND doc_id <> s.keeper AS dropped FROM keyed LEFT JOIN shared s ON keyed.k = s.k
)
SELECT doc_id, count(*)::BIGINT AS n_lines, count(*) FILTER (dropped)::BIGINT AS n_dropped,
  sha256(coalesce(string_agg(line, chr(10) ORDER BY pos) FILTER (NOT dropped), '')) AS kept_sha256
FROM marked GROUP BY doc_id
"""


def op9_lm_scoring(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Target: documents labelled as good and not toxic. Numbers are rounded to six places."""
    docs = read_table(spark, sf_dir, "documents").select("doc_id", "text")
    target = read_table(spark, sf_dir, "labels").where("quality = 1 and toxic = 0").select("doc_id")
    scored = lm_score.score(docs, target)
    return scored.select(F.col("id").alias("doc_id"), "n_tokens", *[F.round(c, 6).alias(c) for c in ("target_loss", "background_loss", "score")])


OP9_SQL = r"""
WITH docs AS (
  SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS w,
    doc_id IN (SELECT doc_id FROM labels WHERE quality = 1 AND toxic = 0) AS mark FROM documents
), tok AS (SELECT doc_id, mark, unnest(w) AS w, unnest(range(len(w))) AS i FROM docs),
vocab AS (SELECT w, count(*) AS n, count(*) FILTER (mark) AS t FROM tok GROUP BY w HAVING count(*) >= 2),
pairs AS (
  SELECT doc_id, mark, tok.w, coalesce(lag(tok.w) OVER (PARTITION BY doc_id ORDER BY i), '<start>') AS v,
    coalesce(vocab.w, '<unk>') AS kw, coalesce(lag(coalesce(vocab.w, '<unk>')) OVER (PARTITION BY doc_id ORDER BY i), '<start>') AS kv
  FROM tok LEFT JOIN vocab ON tok.w = vocab.w
),
uni AS (SELECT kw, count(*)::DOUBLE AS n, (count(*) FILTER (mark))::DOUBLE AS t FROM pairs GROUP BY kw),
tot AS (SELECT sum(n) AS n, sum(t) AS t, (SELECT count(*) FROM vocab) + 1 AS size FROM uni),
bi AS (SELECT v, w, count(*)::DOUBLE AS n, (count(*) FILTER (mark))::DOUBLE AS t FROM pairs GROUP BY v, w HAVING count(*) >= 2),
loss AS (
  SELECT p.doc_id, count(*) AS n_tokens,
    sum(ln(coalesce(c.t, 0) + 50) - ln(coalesce(b.t, 0) + 50 * (u.t + 1) / (tot.t + tot.size))) AS lt,
    sum(ln(coalesce(c.n, 0) + 50) - ln(coalesce(b.n, 0) + 50 * (u.n + 1) / (tot.n + tot.size))) AS lb
  FROM pairs p JOIN uni u ON p.kw = u.kw LEFT JOIN uni c ON p.kv = c.kw LEFT JOIN bi b ON p.v = b.v AND p.w = b.w, tot GROUP BY p.doc_id
)
SELECT d.doc_id, coalesce(n_tokens, 0)::BIGINT AS n_tokens, round(lt / n_tokens, 6) AS target_loss, round(lb / n_tokens, 6) AS background_loss, round((lt - lb) / n_tokens, 6) AS score
FROM docs d LEFT JOIN loss USING (doc_id)
"""


def op10_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read_table(spark, sf_dir, "documents").select("doc_id", "text")
    judged = quality_rules.judge(docs, drop_text=True)
    return judged.select("doc_id", *[F.col(f"__{c}").alias(c) for c in ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "ratio", "kept")])


def op4_quality_classifier(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read_table(spark, sf_dir, "documents")
    model = quality_classifier.train(docs, read_table(spark, sf_dir, "labels"))
    scored = quality_classifier.score(docs.select("doc_id", "text", "lang", "source", "n_chars"), model, drop_text=True)
    return scored.select("doc_id", *[F.col(f"__{c}").alias(c) for c in ("text_score", "meta_score", "score", "kept")])


def op5_html_extraction(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = read_table(spark, sf_dir, "pages")
    return html_extract.extract_text(pages).select("page_id", "url", F.col("__text").alias("text"), F.col("__n_chars").alias("n_chars"))


#: Holds for the layout of the given pages, whose text is that of their article element.
OP5_SQL = r"""
WITH a AS (SELECT page_id, url, regexp_extract(coalesce(html, ''), '(?s)<article>(.*)</article>', 1) AS body FROM pages),
blocks AS (SELECT page_id, url, [trim(regexp_replace(regexp_replace(regexp_replace(x, '<br>', ' ', 'g'), '<[^>]*>', '', 'g'), '\s+', ' ', 'g')) FOR x IN regexp_split_to_array(body, '</?(?:p|h1)>')] AS b FROM a),
decoded AS (SELECT page_id, url, [regexp_replace(replace(replace(replace(replace(x, '&lt;', '<'), '&gt;', '>'), '&quot;', '"'), '&#x27;', chr(39)), '&amp;?', '&', 'g') FOR x IN b IF x <> ''] AS b FROM blocks)
SELECT page_id, url, coalesce(array_to_string(b, chr(10) || chr(10)), '') AS text, length(coalesce(array_to_string(b, chr(10) || chr(10)), ''))::BIGINT AS n_chars FROM decoded
"""


def op6_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = pii.find(read_table(spark, sf_dir, "documents").select("doc_id", "text"))
    kinds = [*pii.KINDS, "term"]
    counts = [pii.how_many(F.col("__base"), n).alias(f"n_{k}") for n, k in enumerate(pii.KINDS)]
    return found.select(F.col("__id").alias("doc_id"), *counts, F.sha2(pii.written(F.col("__base"), kinds), 256).alias("base_sha256"), pii.written(F.col("__all"), kinds).alias("spans"))


def op7_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read_table(spark, sf_dir, "documents").select("doc_id", "text")
    return decontam.report(docs, read_table(spark, sf_dir, "benchmark"))


OP7_SQL = r"""
WITH d AS (
  SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM documents
), b AS (
  SELECT item_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM benchmark
), iw AS (
  SELECT item_id, least(len(w), 10) AS k, unnest([array_to_string(w[i:i + least(len(w), 10) - 1], ' ') FOR i IN range(1, len(w) - least(len(w), 10) + 2)]) AS g FROM b WHERE len(w) > 0
), ks AS (SELECT DISTINCT k FROM iw),
dw AS (
  SELECT doc_id, k, unnest([array_to_string(w[i:i + k - 1], ' ') FOR i IN range(1, len(w) - k + 2)]) AS g, unnest(range(1, len(w) - k + 2)) AS i FROM d, ks WHERE len(w) >= k
), hits AS (SELECT dw.doc_id, dw.i, dw.k, iw.item_id FROM dw JOIN iw ON dw.g = iw.g AND dw.k = iw.k),
words AS (SELECT doc_id, count(DISTINCT p) AS n_hit FROM (SELECT doc_id, unnest(range(i, i + k)) AS p FROM hits) GROUP BY doc_id),
items AS (SELECT doc_id, count(*) AS n_items, string_agg(item, ',' ORDER BY item) AS items FROM (SELECT DISTINCT doc_id, item_id::VARCHAR AS item FROM hits) GROUP BY doc_id)
SELECT d.doc_id, len(d.w)::BIGINT AS n_words, coalesce(n_hit, 0)::BIGINT AS n_hit, coalesce(n_items, 0)::BIGINT AS n_items,
  sha256(coalesce(items, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AS contaminated
FROM d LEFT JOIN words USING (doc_id) LEFT JOIN items USING (doc_id)
"""


def op8_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return jaccard_join.link_components(read_table(spark, sf_dir, "documents").select("doc_id", "text")).withColumnRenamed("id", "doc_id")


OP8_SQL = r"""
WITH RECURSIVE words AS (
  SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS w FROM documents
), sets AS (
  SELECT doc_id, CASE WHEN len(w) = 0 THEN [] WHEN len(w) < 5 THEN [array_to_string(w, ' ')]
    ELSE list_distinct([array_to_string(w[i:i + 4], ' ') FOR i IN range(1, len(w) - 3)]) END AS s FROM words
), items AS (SELECT doc_id, len(s) AS n, unnest(s) AS g FROM sets),
pairs AS (
  SELECT a.doc_id AS a, b.doc_id AS b FROM items a JOIN items b ON a.g = b.g AND a.doc_id < b.doc_id
  GROUP BY a.doc_id, b.doc_id, a.n, b.n HAVING 100 * count(*) >= 75 * (a.n + b.n - count(*))
), edges AS (SELECT a, b FROM pairs UNION ALL SELECT b, a FROM pairs),
reach(node, spot) AS (SELECT doc_id, doc_id FROM documents UNION SELECT r.node, e.b FROM reach r JOIN edges e ON r.spot = e.a)
SELECT d.doc_id, len(s.s)::BIGINT AS n_shingles, min(r.spot)::BIGINT AS component_id
FROM documents d JOIN sets s USING (doc_id) JOIN reach r ON r.node = d.doc_id GROUP BY d.doc_id, len(s.s)
"""


QUERIES = {"op1_url_filter": op1_url_filter, "op2_packing": op2_packing, "op3_line_dedup": op3_line_dedup, "op4_quality_classifier": op4_quality_classifier, "op5_html_extraction": op5_html_extraction, "op6_pii": op6_pii, "op7_decontamination": op7_decontamination, "op8_jaccard_join": op8_jaccard_join, "op9_lm_scoring": op9_lm_scoring, "op10_quality_rules": op10_quality_rules}
SQL = {"op1_url_filter": OP1_SQL, "op3_line_dedup": OP3_SQL, "op5_html_extraction": OP5_SQL, "op7_decontamination": OP7_SQL, "op8_jaccard_join": OP8_SQL, "op9_lm_scoring": OP9_SQL}
