"""Queries of sources, sinks, functions and streams, each with its DuckDB twin where SQL can say it."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..functions import columns as fc
from ..operators import graph, posterior
from ..operators import text_words as tw
from ..registry import query
from ..sources import io, rasters
from ..sources.tables import file_system, keep, new_path, table
from ..streaming import streams as st
from . import raster_queries as ra
from . import text_queries as q

SIDE = rasters.PLANTED_SIDE


# Sources and sinks


@query("s02_formats", "SELECT f AS fmt, lang, count(*) AS n, sum(doc_id)::BIGINT AS ids FROM documents, (VALUES ('csv'), ('json'), ('orc'), ('parquet'), ('text')) v(f) GROUP BY ALL")
def s02(spark, sf_dir):
    """Labels of documents written and read in each exchange format."""
    labels, out = table(spark, sf_dir, "documents").select("doc_id", "lang"), None
    for fmt in io.FORMATS:
        path = new_path(spark, f"labels-{fmt}")
        io.save_as(labels, path, fmt)
        r = io.load_as(spark, path, fmt, labels.schema).select(F.lit(fmt).alias("fmt"), "doc_id", "lang")
        out = r if out is None else out.unionByName(r)
    path = new_path(spark, "labels-text")
    io.save_lines(labels.select(F.concat_ws(",", F.col("doc_id").cast("string"), "lang").alias("line")), path, "line")
    lines = spark.read.text(path).select(F.split("value", ",").alias("p"))
    out = out.unionByName(lines.select(F.lit("text").alias("fmt"), F.col("p")[0].cast("long").alias("doc_id"), F.col("p")[1].alias("lang")))
    return out.groupBy("fmt", "lang").agg(F.count(F.lit(1)).alias("n"), F.sum("doc_id").alias("ids"))


@query("s03_partitioned_responses", q.TEXT + " SELECT wtype, count(*) AS n, round(sum(r), 4) AS total FROM resp WHERE wtype = 'T' GROUP BY wtype")
def s03(spark, sf_dir):
    path = new_path(spark, "responses-by-type")
    io.save_responses(q.responses(spark, sf_dir), path)
    return spark.read.parquet(path).where("wtype = 'T'").groupBy("wtype").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("r"), 4).alias("total"))


@query("s06_carrier_source", ra.P + " SELECT item_id, x, y, round(v, 6) AS v FROM planted")
def s06(spark, sf_dir):
    """The planted rasters of all embeddings, with the carriers of their labels read from the source."""
    spark.dataSource.register(io.CarrierRasters)
    e = table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("item_id"), "label", "embedding")
    labels = ",".join(str(r.label) for r in e.where("label IS NOT NULL").select("label").distinct().orderBy("label").collect())
    carriers = spark.read.format("unicat_carriers").option("only", labels).load().withColumnRenamed("v", "carrier")
    at = F.sequence(F.lit(0), F.lit(SIDE - 1))
    p = e.withColumn("y", F.explode(at)).withColumn("x", F.explode(at)).join(F.broadcast(carriers), ["label", "x", "y"], "left")
    noise = F.element_at("embedding", ((7 * F.col("x") + 13 * F.col("y") + 3 * F.col("x") * F.col("y")) % 64 + 1).cast("int")).cast("double")
    # Items without a label have the dark carrier everywhere.
    return p.select("item_id", "x", "y", F.round(F.coalesce("carrier", F.lit(78.0)) + rasters.SIGMA * 8 * noise, 6).alias("v"))


@query("s07_images", "SELECT image, 8 AS w, (n // 8)::INT AS h, total FROM (SELECT vec_id // 100 AS image, count(*) AS n, sum(least(255, greatest(0, round(128 + 320 * f::DOUBLE))))::BIGINT AS total FROM (SELECT vec_id, unnest(embedding) AS f FROM embeddings) GROUP BY 1)")
def s07(spark, sf_dir):
    """All embeddings as rasters, a hundred below each other in an image, written by the tasks as plain PGM files to the
    shared folder, read as files and decoded in batches."""
    path = new_path(spark, "images")
    e = table(spark, sf_dir, "embeddings").select(F.expr("vec_id div 100").alias("image"), "vec_id", F.transform("embedding", lambda f: F.least(F.lit(255), F.greatest(F.lit(0), F.round(128 + 320 * f.cast("double")))).cast("int").cast("string")).alias("px"))
    rows = e.groupBy("image").agg(F.array_sort(F.collect_list(F.struct("vec_id", "px"))).alias("r")).select("image", F.flatten(F.transform("r", lambda x: x["px"])).alias("px"))
    text = F.concat(F.lit("P2\n8 "), F.expr("size(px) div 8").cast("string"), F.lit("\n255\n"), F.array_join("px", "\n"))
    rows.where("size(px) > 0").select("image", text.alias("value")).write.partitionBy("image").text(path)
    images = io.read_images(spark, path)
    return images.select(F.regexp_extract("path", r"image=(-?\d+)/", 1).cast("long").alias("image"), "w", "h", F.aggregate("px", F.lit(0.0), lambda t, x: t + x).cast("long").alias("total"))


@query("s08_solution", q.MODELS + " SELECT l.cat, count(*) AS items, (SELECT count(*) FROM models m WHERE m.cat = l.cat)::BIGINT AS words FROM labels_now l GROUP BY l.cat")
def s08(spark, sf_dir):
    path = new_path(spark, "solution")
    io.save_solution(path, labels=q.languages(spark, sf_dir), models=q.models(spark, sf_dir))
    got = io.load_solution(spark, path)
    words = got["models"].groupBy("cat").agg(F.count(F.lit(1)).alias("words"))
    return got["labels"].groupBy("cat").agg(F.count(F.lit(1)).alias("items")).join(words, "cat")


# Functions


@query("u1_sym_kl", q.GRAPH + " SELECT s, t, round(j, 6) AS j FROM jp JOIN edges USING (s, t)")
def u1(spark, sf_dir):
    """The divergence of word maps as a column expression, on the pairs of the graph."""
    m = keep(q.responses(spark, sf_dir).groupBy("item_id").agg(F.map_from_entries(F.collect_list(F.struct("feat", "r"))).alias("m")), "word-maps")
    e = q.edges(spark, sf_dir).join(m.select(F.col("item_id").alias("s"), F.col("m").alias("a")), "s").join(m.select(F.col("item_id").alias("t"), F.col("m").alias("b")), "t")
    return e.select("s", "t", F.round(fc.sym_kl(F.col("a"), F.col("b"), q.DIMS), 6).alias("j"))


@query("u1_sql_functions", q.GRAPH + " SELECT s, t, round(least(0.999999999, exp(-0.2 * j)), 6) AS q FROM jp JOIN edges USING (s, t)")
def u1_sql(spark, sf_dir):
    fc.register_sql(spark)
    graph.pair_divergences(q.responses(spark, sf_dir), q.edges(spark, sf_dir).select("s", "t"), q.DIMS).createOrReplaceTempView("unicat_pairs")
    return spark.sql("SELECT s, t, round(unicat_edge(j, 0.2D), 6) AS q FROM unicat_pairs")


@query("u2_cs_codes_arrow", ra.CODE + " SELECT item_id, x, y, code::INT AS code FROM codes")
def u2(spark, sf_dir):
    """The codes of whole rasters in Arrow batches: equal to those of expressions."""
    c = ra.planted(spark, sf_dir).select("item_id", fc.cs_codes(SIDE)("px").alias("c"))
    return c.select("item_id", F.posexplode("c").alias("i", "code")).select("item_id", (F.col("i") % SIDE).alias("x"), F.floor(F.col("i") / SIDE).cast("int").alias("y"), "code")


@query("r05_cs_codes_circle")
def r05_circle(spark, sf_dir):
    """Codes with neighbours on the circle, by bilinear interpolation: how many of each."""
    c = ra.planted(spark, sf_dir).select(F.explode(fc.cs_codes(SIDE, interpolate=True)("px")).alias("code"))
    return c.groupBy("code").agg(F.count(F.lit(1)).alias("n"))


@query("u3_measures_udaf", q.GUESS_SQL + " SELECT round((SELECT sum(top)::DOUBLE / sum(n) FROM (SELECT max(n) AS top, sum(n) AS n FROM cont GROUP BY cat)), 6) AS purity, round((SELECT sum(n * ln(total / n)) / sum(n) FROM (SELECT n, (sum(n) OVER (PARTITION BY cat))::DOUBLE AS total FROM cont)), 6) AS cond_entropy")
def u3(spark, sf_dir):
    return q.rounded(q.guess(spark, sf_dir).agg(fc.purity("cat", "truth").alias("purity"), fc.cond_entropy("cat", "truth").alias("cond_entropy")), "purity", "cond_entropy")


@query("u4_patches_udtf", ra.P + ", o AS (SELECT i, j FROM range(7) a(i), range(7) b(j)) SELECT (j * 7 + i)::INT AS patch, count(*) AS n, round(sum(v), 3) AS total FROM planted JOIN o ON x >= 4 * i AND x < 4 * i + 8 AND y >= 4 * j AND y < 4 * j + 8 GROUP BY ALL")
def u4(spark, sf_dir):
    """Overlapping patches (a stride of half a patch) of all planted rasters by the table function."""
    fc.register_sql(spark)
    ra.planted(spark, sf_dir).createOrReplaceTempView("unicat_rasters")
    return spark.sql("SELECT p.patch, count(*) AS n, round(sum(p.v), 3) AS total FROM unicat_rasters, LATERAL unicat_patches(px, 32, 32, 8, 4) p GROUP BY p.patch")


# Streams, run over all that is there


def events(spark, sf_dir):
    """Events as a stream of files in an order by hash, so that many come late; event times as timestamps."""
    e = table(spark, sf_dir, "events").select("event_id", F.col("ts").cast("timestamp").alias("ts"), "user_id", "event_type", "value")
    return st.replay(e, 4, "event_id")


@query("t2_tumbling_stream", "SELECT time_bucket(INTERVAL 1 HOUR, ts) AS start, event_type, count(*) AS n, round(sum(value), 4) AS total FROM events GROUP BY ALL")
def t2_stream(spark, sf_dir):
    out = st.collected(st.tumbling(events(spark, sf_dir), None), "complete")
    return out.select(F.col("start").cast("timestamp_ntz").alias("start"), "event_type", "n", "total")


@query("t2_sliding", "SELECT start, event_type, count(*) AS n FROM (SELECT event_type, unnest([time_bucket(INTERVAL 15 MINUTE, ts) - INTERVAL 15 MINUTE * i FOR i IN range(4)]) AS start FROM events) GROUP BY ALL")
def t2_sliding(spark, sf_dir):
    return st.sliding(table(spark, sf_dir, "events"), None).select(F.col("start").cast("timestamp_ntz").alias("start"), "event_type", "n")


@query("t2_session_stream", "SELECT user_id, count(*) AS n FROM (SELECT user_id, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS s FROM (SELECT *, CASE WHEN lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) + INTERVAL 30 MINUTE > ts THEN 0 ELSE 1 END AS fresh FROM events)) GROUP BY user_id, s")
def t2_session_stream(spark, sf_dir):
    return st.collected(st.sessions(events(spark, sf_dir), None), "complete").select("user_id", "n")


@query("t4_interval_join_stream", "SELECT c.event_id AS click, p.event_id AS purchase FROM events c JOIN events p ON c.user_id = p.user_id AND c.event_type = 'click' AND p.event_type = 'purchase' AND p.ts >= c.ts AND p.ts <= c.ts + INTERVAL 1 HOUR")
def t4_stream(spark, sf_dir):
    """Both sides are one replay; the watermark is wider than the replay's disorder, so no pair is lost."""
    return st.collected(st.click_to_purchase(events(spark, sf_dir), "3650 days"), "append")


@query("t5_dedup", "SELECT count(DISTINCT md5(text)) AS n FROM documents WHERE text IS NOT NULL")
def t5(spark, sf_dir):
    """First arrivals of equal texts, as a stream in which every document has its place as time."""
    d = table(spark, sf_dir, "documents").where("text is not null").select(F.md5("text").alias("h"), F.timestamp_seconds("doc_id").alias("ts"))
    return st.collected(st.first_seen(st.replay(d, 4, "h"), "3650 days", "h"), "append").agg(F.count(F.lit(1)).alias("n"))


@query("t1_assign_batch", q.LL + " SELECT item_id, arg_max(cat, (round(ll, 6), -cat)) AS cat, round(max(ll), 6) AS ll FROM ll GROUP BY item_id")
def t1(spark, sf_dir):
    """Documents assigned to frozen category models, as the stream does for arrivals."""
    return st.assign(q.responses(spark, sf_dir), q.models(spark, sf_dir), q.items(spark, sf_dir))


@query("t1_assign_stream", q.LL + " SELECT item_id, arg_max(cat, (round(ll, 6), -cat)) AS cat, round(max(ll), 6) AS ll FROM ll GROUP BY item_id")
def t1_stream(spark, sf_dir):
    """The same for documents that arrive in files: words by the frozen dictionary, then the models, in each batch."""
    models, words = q.models(spark, sf_dir), tw.token_dictionary(q.items(spark, sf_dir))
    path = new_path(spark, "assigned")

    def batch(rows, _):
        resp = tw.text_responses(rows, dictionary=words)
        st.assign(resp, models, rows).write.mode("append").parquet(path)

    spark.createDataFrame([], "item_id long, cat long, ll double").write.parquet(path)
    st.run_once(st.replay(q.items(spark, sf_dir), 3, "item_id"), "append", batch)
    return spark.read.parquet(path)


@query("t3_running_stats", q.STATE + posterior.model_sql(q.N_SQL, q.TYPES) + " SELECT cat, feat::INT AS feat, count(*) AS n, round(sum(r), 6) AS total FROM resp JOIN labels_now USING (item_id) GROUP BY ALL")
def t3(spark, sf_dir):
    """Sufficient statistics of categories kept up by a stream of responses."""
    arriving = st.replay(q.responses(spark, sf_dir), 4, "item_id", each=2)
    return q.rounded(st.collected(st.running_stats(arriving, q.languages(spark, sf_dir)), "complete"), "total")


UNFIT = 20.0


@query("t6_unfit_pool", q.LL + f" SELECT item_id, round(max(ll), 6) AS ll FROM ll GROUP BY item_id HAVING round(max(ll), 6) < {UNFIT}")
def t6(spark, sf_dir):
    """Arrivals that no frozen category fits gather in a pool."""
    models, path = q.models(spark, sf_dir), new_path(spark, "pool")
    resp = q.responses(spark, sf_dir)

    def batch(rows, _):
        own = resp.join(F.broadcast(rows.select("item_id")), "item_id", "left_semi")
        st.unfit(st.assign(own, models, rows), UNFIT).select("item_id", "ll").write.mode("append").parquet(path)

    spark.createDataFrame([], "item_id long, ll double").write.parquet(path)
    st.run_once(st.replay(q.items(spark, sf_dir).select("item_id"), 3, "item_id"), "append", batch)
    return spark.read.parquet(path)


# The rest of the relational and scalar families


@query("q04_hint_nested_loop", "SELECT r_name, count(*) AS n FROM nation JOIN region ON n_regionkey <= r_regionkey GROUP BY 1")
def q04_nl(spark, sf_dir):
    r = table(spark, sf_dir, "region").hint("shuffle_replicate_nl")
    return table(spark, sf_dir, "nation").join(r, F.col("n_regionkey") <= F.col("r_regionkey")).groupBy("r_name").agg(F.count(F.lit(1)).alias("n"))


@query("q07_cross_join", "SELECT n_name, r_name FROM nation, region")
def q07(spark, sf_dir):
    """All pairs, for sides of a few rows by their nature."""
    return table(spark, sf_dir, "nation").select("n_name").crossJoin(F.broadcast(table(spark, sf_dir, "region").select("r_name")))


_G4 = "resp AS (SELECT c_nationkey::BIGINT AS item_id, (dense_rank() OVER (ORDER BY c_mktsegment) - 1)::INT AS feat, 2 / (1 + exp(-n / 20.0)) - 1 AS r FROM (SELECT c_nationkey, c_mktsegment, count(*) AS n FROM customer GROUP BY ALL))"


@query("g04_full_graph", f"WITH {_G4}, full_r AS (SELECT i.item_id, f.feat, coalesce(r, 0) + 0.01 AS r FROM (SELECT DISTINCT item_id FROM resp) i, range(5) f(feat) LEFT JOIN resp ON resp.item_id = i.item_id AND resp.feat = f.feat), p AS (SELECT item_id, feat, r / sum(r) OVER (PARTITION BY item_id) AS p FROM full_r) SELECT a.item_id AS s, b.item_id AS t, round(sum((a.p - b.p) * ln(a.p / b.p)), 6) AS j FROM p a JOIN p b ON a.feat = b.feat AND a.item_id < b.item_id GROUP BY ALL")
def g04(spark, sf_dir):
    """The full graph by the definition, on nations described by their customers' segments."""
    from pyspark.sql import Window

    from ..operators import graph

    n = table(spark, sf_dir, "customer").groupBy("c_nationkey", "c_mktsegment").agg(F.count(F.lit(1)).alias("n"))
    names = n.select("c_mktsegment").distinct().withColumn("feat", F.row_number().over(Window.orderBy("c_mktsegment")) - 1)
    resp = n.join(F.broadcast(names), "c_mktsegment").select(F.col("c_nationkey").cast("long").alias("item_id"), "feat", tw.saturate(F.col("n"), s=20.0).alias("r"))
    return q.rounded(graph.symmetric_kl_dense(resp, 5), "j")


@query("q09_unpivot", "SELECT source, lang, n FROM (SELECT source, count(*) FILTER (lang = 'de') AS de, count(*) FILTER (lang = 'en') AS en FROM documents GROUP BY source) UNPIVOT (n FOR lang IN (de, en))")
def q09_unpivot(spark, sf_dir):
    wide = table(spark, sf_dir, "documents").groupBy("source").pivot("lang", ["de", "en"]).count().na.fill(0, ["de", "en"])
    return wide.unpivot("source", ["de", "en"], "lang", "n")


@query("q14_lateral", "SELECT c_custkey, top FROM customer, LATERAL (SELECT max(o_totalprice) AS top FROM orders WHERE o_custkey = c_custkey) x")
def q14_lateral(spark, sf_dir):
    for name in ("orders", "customer"):
        table(spark, sf_dir, name).createOrReplaceTempView(f"unicat_{name}")
    return spark.sql("SELECT c_custkey, top FROM unicat_customer, LATERAL (SELECT max(o_totalprice) AS top FROM unicat_orders WHERE o_custkey = c_custkey)")


@query("q14_in", "SELECT o_orderkey FROM orders WHERE o_custkey IN (SELECT c_custkey FROM customer WHERE c_acctbal > 9000) AND o_totalprice > (SELECT avg(o_totalprice) FROM orders)")
def q14_in(spark, sf_dir):
    for name in ("orders", "customer"):
        table(spark, sf_dir, name).createOrReplaceTempView(f"unicat_{name}")
    return spark.sql("SELECT o_orderkey FROM unicat_orders WHERE o_custkey IN (SELECT c_custkey FROM unicat_customer WHERE c_acctbal > 9000) AND o_totalprice > (SELECT avg(o_totalprice) FROM unicat_orders)")


@query("q15_recursion", "WITH RECURSIVE r(root, node, depth) AS (SELECT n_nationkey, n_nationkey, 0 FROM nation UNION ALL SELECT r.root, n.n_nationkey, depth + 1 FROM r JOIN nation n ON n.n_nationkey = r.node + 5) SELECT root::BIGINT AS root, count(*) AS reached, max(depth)::BIGINT AS deepest FROM r GROUP BY root")
def q15(spark, sf_dir):
    """Reachability over links that only grow (each nation to the one five places on), by SQL recursion."""
    table(spark, sf_dir, "nation").createOrReplaceTempView("unicat_nation")
    return spark.sql("WITH RECURSIVE r(root, node, depth) AS (SELECT n_nationkey, n_nationkey, 0 FROM unicat_nation UNION ALL SELECT r.root, n.n_nationkey, depth + 1 FROM r JOIN unicat_nation n ON n.n_nationkey = r.node + 5) SELECT cast(root AS BIGINT) AS root, count(*) AS reached, cast(max(depth) AS BIGINT) AS deepest FROM r GROUP BY root")


@query("f_map", "SELECT doc_id, ((CASE WHEN a > 8 THEN a ELSE 0 END) + (CASE WHEN b > 8 THEN b ELSE 0 END))::BIGINT AS total, ((a > 8)::INT + (b > 8)::INT)::INT AS n FROM (SELECT doc_id, 2 * (length(text) + 1) AS a, 2 * (length(lang) + 2) AS b FROM documents WHERE text IS NOT NULL AND lang IS NOT NULL)")
def f_map(spark, sf_dir):
    d = table(spark, sf_dir, "documents").where("text is not null and lang is not null")
    a, b = F.create_map(F.lit("a"), F.length("text"), F.lit("b"), F.length("lang")), F.map_from_entries(F.array(F.struct(F.lit("a"), F.lit(1)), F.struct(F.lit("b"), F.lit(2))))
    m = F.map_filter(F.transform_values(F.map_zip_with(a, b, lambda _, x, y: x + y), lambda _, v: 2 * v), lambda _, v: v > 8)
    return d.select("doc_id", m.alias("m")).select("doc_id", F.aggregate(F.map_values("m"), F.lit(0).cast("long"), lambda t, x: t + x).alias("total"), F.size("m").alias("n"))


@query("f_json_struct", "SELECT event_id, (props->>'$.k')::INT AS k, '{\"k\":' || (props->>'$.k') || '}' AS again FROM events")
def f_json_struct(spark, sf_dir):
    e = table(spark, sf_dir, "events").select("event_id", F.from_json("props", "k int").alias("p"))
    return e.select("event_id", "p.k", F.to_json("p").alias("again"))


@query("f_hash", "SELECT doc_id, md5(source) AS m, sha256(source) AS s FROM documents")
def f_hash(spark, sf_dir):
    return table(spark, sf_dir, "documents").select("doc_id", F.md5("source").alias("m"), F.sha2("source", 256).alias("s"))
