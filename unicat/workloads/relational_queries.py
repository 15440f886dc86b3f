"""Relational, scalar and streaming-twin queries around the methods, on the star tables and the events."""

from __future__ import annotations

from pyspark.sql import functions as F
from pyspark.sql import Window

from ..plans import planner
from ..registry import query
from ..sources.tables import table


def t(spark, sf_dir, name):
    return table(spark, sf_dir, name)


@query("q01_filters", "SELECT l_orderkey, l_linenumber, CASE WHEN l_quantity >= 25 THEN 'big' ELSE 'small' END AS size FROM lineitem WHERE l_discount BETWEEN 0.02 AND 0.04 AND l_returnflag IN ('A', 'R') AND l_linestatus IS NOT DISTINCT FROM 'F'")
def q01(spark, sf_dir):
    x = t(spark, sf_dir, "lineitem").where(F.col("l_discount").between(0.02, 0.04) & F.col("l_returnflag").isin("A", "R") & F.col("l_linestatus").eqNullSafe("F"))
    return x.select("l_orderkey", "l_linenumber", F.when(F.col("l_quantity") >= 25, "big").otherwise("small").alias("size"))


for _how, _sql in (("inner", "JOIN"), ("left", "LEFT JOIN"), ("right", "RIGHT JOIN"), ("full", "FULL JOIN")):

    @query(f"q02_join_{_how}", f"SELECT c_mktsegment, o_orderstatus, count(*) AS n FROM (SELECT * FROM customer WHERE c_acctbal > 0) c {_sql} (SELECT * FROM orders WHERE o_totalprice > 1000) o ON c_custkey = o_custkey GROUP BY ALL")
    def q02(spark, sf_dir, how=_how):
        c, o = t(spark, sf_dir, "customer").where("c_acctbal > 0"), t(spark, sf_dir, "orders").where("o_totalprice > 1000")
        return c.join(o, c.c_custkey == o.o_custkey, how).groupBy("c_mktsegment", "o_orderstatus").agg(F.count(F.lit(1)).alias("n"))


for _how, _sql in (("left_semi", "IN"), ("left_anti", "NOT IN")):

    @query(f"q03_{_how}", f"SELECT doc_id, lang FROM documents WHERE doc_id {_sql} (SELECT doc_id FROM labels)")
    def q03(spark, sf_dir, how=_how):
        return t(spark, sf_dir, "documents").select("doc_id", "lang").join(t(spark, sf_dir, "labels").select("doc_id"), "doc_id", how)


for _hint in ("broadcast", "merge", "shuffle_hash"):

    @query(f"q04_hint_{_hint}", "SELECT o_orderpriority, round(sum(l_extendedprice), 2) AS total FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1")
    def q04(spark, sf_dir, hint=_hint):
        o = t(spark, sf_dir, "orders").select("o_orderkey", "o_orderpriority")
        # Beyond what a broadcast can hold, all rows are shuffled instead.
        o = o.hint("merge" if hint == "broadcast" and not planner.broadcasts(o) else hint)
        return t(spark, sf_dir, "lineitem").join(o, F.col("l_orderkey") == F.col("o_orderkey")).groupBy("o_orderpriority").agg(F.round(F.sum("l_extendedprice"), 2).alias("total"))


BANDS = ((0, 0.0, 1000.0), (1, 1000.0, 1300.0), (2, 1300.0, 1e9))


@query("q05_range_join", "SELECT band, count(*) AS n FROM part JOIN (VALUES (0, 0.0, 1000.0), (1, 1000.0, 1300.0), (2, 1300.0, 1e9)) b(band, lo, hi) ON p_retailprice >= lo AND p_retailprice < hi GROUP BY band")
def q05(spark, sf_dir):
    b = spark.createDataFrame(list(BANDS), "band int, lo double, hi double")
    return t(spark, sf_dir, "part").join(F.broadcast(b), (F.col("p_retailprice") >= F.col("lo")) & (F.col("p_retailprice") < F.col("hi"))).groupBy("band").agg(F.count(F.lit(1)).alias("n"))


@query("q06_asof_previous", "SELECT event_id, lag(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS previous, last_value(CASE WHEN event_type = 'purchase' THEN event_id END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS last_purchase FROM events")
def q06(spark, sf_dir):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    last = F.last(F.when(F.col("event_type") == "purchase", F.col("event_id")), ignorenulls=True).over(w.rowsBetween(Window.unboundedPreceding, -1))
    return t(spark, sf_dir, "events").select("event_id", F.lag("event_id").over(w).alias("previous"), last.alias("last_purchase"))


@query("q08_aggregates", "SELECT l_returnflag, l_linestatus, count(*) AS n, count(DISTINCT l_suppkey) AS suppliers, count(*) FILTER (l_quantity > 40) AS big, round(sum(l_extendedprice * (1 - l_discount)), 2) AS revenue FROM lineitem GROUP BY 1, 2")
def q08(spark, sf_dir):
    return t(spark, sf_dir, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(
        F.count(F.lit(1)).alias("n"), F.countDistinct("l_suppkey").alias("suppliers"), F.count(F.when(F.col("l_quantity") > 40, 1)).alias("big"), F.round(F.sum(F.col("l_extendedprice") * (1 - F.col("l_discount"))), 2).alias("revenue")
    )


@query("q09_rollup", "SELECT lang, source, count(*) AS n FROM documents GROUP BY ROLLUP (lang, source)")
def q09(spark, sf_dir):
    return t(spark, sf_dir, "documents").rollup("lang", "source").agg(F.count(F.lit(1)).alias("n"))


@query("q09_grouping_sets", "SELECT lang, source, count(*) AS n FROM documents GROUP BY GROUPING SETS ((lang), (source), ())")
def q09_sets(spark, sf_dir):
    return t(spark, sf_dir, "documents").groupingSets([["lang"], ["source"], []], "lang", "source").agg(F.count(F.lit(1)).alias("n"))


@query("q09_pivot", "SELECT source, count(*) FILTER (lang = 'de') AS de, count(*) FILTER (lang = 'en') AS en FROM documents GROUP BY source")
def q09_pivot(spark, sf_dir):
    return t(spark, sf_dir, "documents").groupBy("source").pivot("lang", ["de", "en"]).count().na.fill(0, ["de", "en"])


@query("q10_approximate", "SELECT event_type, true AS users_near, true AS hll_near, true AS median_near FROM events GROUP BY event_type")
def q10(spark, sf_dir):
    """Sketches against exact numbers: within five per cent, and a median of middle rank."""
    e = t(spark, sf_dir, "events")
    g = e.groupBy("event_type").agg(
        F.countDistinct("user_id").alias("users"), F.approx_count_distinct("user_id", 0.01).alias("approx"), F.hll_sketch_estimate(F.hll_sketch_agg("user_id", F.lit(14))).alias("hll"),
        F.percentile_approx("value", 0.5, 10_000).alias("m"), F.percentile("value", [0.45, 0.55]).alias("middle"),
    )
    near = lambda c: F.abs(F.col(c) / F.col("users") - 1) <= 0.05
    return g.select("event_type", near("approx").alias("users_near"), near("hll").alias("hll_near"), F.col("m").between(F.col("middle")[0], F.col("middle")[1]).alias("median_near"))


@query("q11_windows", "SELECT o_orderkey, rank() OVER w AS r, dense_rank() OVER w AS dr, ntile(4) OVER w AS q, round(sum(o_totalprice) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 2) AS run FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey)")
def q11(spark, sf_dir):
    w = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")
    return t(spark, sf_dir, "orders").select("o_orderkey", F.rank().over(w).alias("r"), F.dense_rank().over(w).alias("dr"), F.ntile(4).over(w).alias("q"), F.round(F.sum("o_totalprice").over(w.rowsBetween(-2, 0)), 2).alias("run"))


@query("q12_topk", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 20 OFFSET 5")
def q12(spark, sf_dir):
    return t(spark, sf_dir, "orders").orderBy(F.desc("o_totalprice"), "o_orderkey").select("o_orderkey", "o_totalprice").offset(5).limit(20)


@query("q12_topk_per_group", "SELECT o_custkey, o_orderkey FROM (SELECT *, row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS n FROM orders) WHERE n <= 2")
def q12_group(spark, sf_dir):
    w = Window.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey")
    return t(spark, sf_dir, "orders").withColumn("n", F.row_number().over(w)).where("n <= 2").select("o_custkey", "o_orderkey")


@query("q13_set_operations", "SELECT 'union' AS op, k FROM (SELECT o_custkey AS k FROM orders UNION SELECT c_custkey FROM customer) UNION ALL SELECT 'intersect', k FROM (SELECT o_custkey AS k FROM orders INTERSECT SELECT c_custkey FROM customer) UNION ALL SELECT 'except', k FROM (SELECT c_custkey AS k FROM customer EXCEPT SELECT o_custkey FROM orders)")
def q13(spark, sf_dir):
    o, c = t(spark, sf_dir, "orders").select(F.col("o_custkey").alias("k")), t(spark, sf_dir, "customer").select(F.col("c_custkey").alias("k"))
    return o.union(c).distinct().select(F.lit("union").alias("op"), "k").union(o.intersect(c).select(F.lit("intersect"), "k")).union(c.exceptAll(o.distinct()).select(F.lit("except"), "k"))


@query("q14_subqueries", "SELECT n_name, (SELECT count(*) FROM customer WHERE c_nationkey = n_nationkey) AS customers FROM nation WHERE EXISTS (SELECT 1 FROM supplier WHERE s_nationkey = n_nationkey)")
def q14(spark, sf_dir):
    for name in ("nation", "customer", "supplier"):
        t(spark, sf_dir, name).createOrReplaceTempView(f"unicat_{name}")
    return spark.sql("SELECT n_name, (SELECT count(*) FROM unicat_customer WHERE c_nationkey = n_nationkey) AS customers FROM unicat_nation WHERE EXISTS (SELECT 1 FROM unicat_supplier WHERE s_nationkey = n_nationkey)")


@query("q16_keyed_sample", "SELECT doc_id FROM documents WHERE ('0x' || substr(md5('42|' || doc_id), 1, 8))::BIGINT / 4294967296.0 < 0.25")
def q16(spark, sf_dir):
    from ..rng import u01

    return t(spark, sf_dir, "documents").where(u01(42, F.col("doc_id")) < 0.25).select("doc_id")


@query("f_string", "SELECT doc_id, upper(lang) AS up, substr(source, 1, 3) AS head, length(text) AS n, levenshtein(lang, source) AS lev FROM documents")
def f_string(spark, sf_dir):
    return t(spark, sf_dir, "documents").select("doc_id", F.upper("lang").alias("up"), F.substring("source", 1, 3).alias("head"), F.length("text").cast("long").alias("n"), F.levenshtein("lang", "source").cast("long").alias("lev"))


@query("f_date", "SELECT o_orderkey, year(o_orderdate)::INT AS y, month(o_orderdate)::INT AS m, date_trunc('month', o_orderdate)::DATE AS first_day FROM orders")
def f_date(spark, sf_dir):
    return t(spark, sf_dir, "orders").select("o_orderkey", F.year("o_orderdate").alias("y"), F.month("o_orderdate").alias("m"), F.date_trunc("month", F.col("o_orderdate").cast("timestamp")).cast("date").alias("first_day"))


@query("f_math", "SELECT l_orderkey, l_linenumber, round(exp(l_discount), 6) AS e, round(ln(1 + l_tax), 6) AS l, round(pow(l_quantity, 0.5), 6) AS p FROM lineitem")
def f_math(spark, sf_dir):
    return t(spark, sf_dir, "lineitem").select("l_orderkey", "l_linenumber", F.round(F.exp("l_discount"), 6).alias("e"), F.round(F.log1p("l_tax"), 6).alias("l"), F.round(F.pow("l_quantity", F.lit(0.5)), 6).alias("p"))


@query("f_array", "SELECT vec_id, round(list_sum([x::DOUBLE * x::DOUBLE FOR x IN embedding]), 5) AS norm, len([x FOR x IN embedding IF x > 0]) AS positive FROM embeddings")
def f_array(spark, sf_dir):
    e = F.col("embedding")
    return t(spark, sf_dir, "embeddings").select("vec_id", F.round(F.aggregate(e, F.lit(0.0), lambda a, x: a + x.cast("double") * x.cast("double")), 5).alias("norm"), F.size(F.filter(e, lambda x: x > 0)).cast("long").alias("positive"))


@query("f_json", "SELECT event_id, (props->>'$.k')::BIGINT AS k FROM events")
def f_json(spark, sf_dir):
    return t(spark, sf_dir, "events").select("event_id", F.get_json_object("props", "$.k").cast("long").alias("k"))


# Batch twins of the streams


@query("t2_tumbling", "SELECT time_bucket(INTERVAL 1 HOUR, ts) AS start, event_type, count(*) AS n, round(sum(value), 4) AS total FROM events GROUP BY ALL")
def t2_tumbling(spark, sf_dir):
    from ..streaming.streams import tumbling

    return tumbling(t(spark, sf_dir, "events"), None).select(F.col("start").cast("timestamp_ntz").alias("start"), "event_type", "n", "total")


@query("t2_session", "SELECT user_id, count(*) AS n FROM (SELECT user_id, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS s FROM (SELECT *, CASE WHEN lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) + INTERVAL 30 MINUTE > ts THEN 0 ELSE 1 END AS fresh FROM events)) GROUP BY user_id, s")
def t2_session(spark, sf_dir):
    from ..streaming.streams import sessions

    return sessions(t(spark, sf_dir, "events"), None).select("user_id", "n")


@query("t4_interval_join", "SELECT c.event_id AS click, p.event_id AS purchase FROM events c JOIN events p ON c.user_id = p.user_id AND c.event_type = 'click' AND p.event_type = 'purchase' AND p.ts >= c.ts AND p.ts <= c.ts + INTERVAL 1 HOUR")
def t4(spark, sf_dir):
    from ..streaming.streams import click_to_purchase

    return click_to_purchase(t(spark, sf_dir, "events"), None)
