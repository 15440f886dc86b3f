"""Streams of events and of arriving items. Every function takes a static or a streaming frame; watermark is an interval
or None for static input. Event times are cast to timestamps, as streams need them."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators import posterior
from ..sources.tables import new_path


def timed(events: DataFrame, watermark: str | None) -> DataFrame:
    e = events.withColumn("ts", F.col("ts").cast("timestamp"))
    return e.withWatermark("ts", watermark) if watermark else e


def tumbling(events: DataFrame, watermark: str | None, size: str = "1 hour") -> DataFrame:
    g = timed(events, watermark).groupBy(F.window("ts", size), "event_type").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("value"), 4).alias("total"))
    return g.select(F.col("window.start").alias("start"), "event_type", "n", "total")


def sliding(events: DataFrame, watermark: str | None, size: str = "1 hour", step: str = "15 minutes") -> DataFrame:
    g = timed(events, watermark).groupBy(F.window("ts", size, step), "event_type").agg(F.count(F.lit(1)).alias("n"))
    return g.select(F.col("window.start").alias("start"), "event_type", "n")


def sessions(events: DataFrame, watermark: str | None, gap: str = "30 minutes") -> DataFrame:
    return timed(events, watermark).groupBy(F.session_window("ts", gap), "user_id").agg(F.count(F.lit(1)).alias("n")).select("user_id", F.col("session_window.start").alias("start"), "n")


def click_to_purchase(events: DataFrame, watermark: str | None) -> DataFrame:
    e = timed(events, watermark)
    c = e.where("event_type = 'click'").select(F.col("event_id").alias("click"), F.col("user_id").alias("u"), F.col("ts").alias("clicked"))
    p = e.where("event_type = 'purchase'").select(F.col("event_id").alias("purchase"), "user_id", F.col("ts").alias("bought"))
    return c.join(p, F.expr("u = user_id AND bought >= clicked AND bought <= clicked + interval 1 hour")).select("click", "purchase")


def first_seen(items: DataFrame, watermark: str, key: str) -> DataFrame:
    return timed(items, watermark).dropDuplicatesWithinWatermark([key])


def assign(resp: DataFrame, models: DataFrame, items: DataFrame | None = None) -> DataFrame:
    """item_id, cat, ll: the category under whose frozen model each item is likeliest. The models are a few rows a category
    and are broadcast; nothing else is joined, so the plan is the same for arrivals in foreachBatch."""
    ll = posterior.item_loglik(resp, models, items)
    return ll.groupBy("item_id").agg(F.max_by("cat", F.struct(F.round("ll", 6), (-F.col("cat")).alias("minus"))).alias("cat"), F.round(F.max("ll"), 6).alias("ll"))


def running_stats(resp: DataFrame, labels: DataFrame) -> DataFrame:
    """cat, feat, n, total: sufficient statistics of categories, kept up as responses of labelled items arrive."""
    return resp.join(labels, "item_id").groupBy("cat", "feat").agg(F.count(F.lit(1)).alias("n"), F.sum("r").alias("total"))


def unfit(assigned: DataFrame, least: float) -> DataFrame:
    """The arrivals that no frozen category fits: their best log-likelihood is under a bound. They wait for the next run of a
    sampler, which starts from the frozen labels."""
    return assigned.where(F.col("ll") < least)


def run_once(stream: DataFrame, mode: str, sink) -> None:
    """Runs a stream over all that is there now; sink gets (rows, batch number) of each batch."""
    path = new_path(stream.sparkSession, "stream-state")
    q = stream.writeStream.outputMode(mode).option("checkpointLocation", path).foreachBatch(sink).trigger(availableNow=True).start()
    q.awaitTermination()


def collected(stream: DataFrame, mode: str) -> DataFrame:
    """What a stream over all that is there now has given: every row (append) or the last state (complete)."""
    path = new_path(stream.sparkSession, "stream-out")

    def sink(rows: DataFrame, _: int) -> None:
        rows.write.mode("append" if mode == "append" else "overwrite").parquet(path)

    stream.sparkSession.createDataFrame([], stream.schema).write.parquet(path)
    run_once(stream, mode, sink)
    return stream.sparkSession.read.schema(stream.schema).parquet(path)


def replay(df: DataFrame, files: int, key: str, each: int = 1) -> DataFrame:
    """A table as a stream of files, dealt by a hash of the key and read a few at a time, so that rows come late."""
    path = new_path(df.sparkSession, "replay")
    df.repartition(files, key).write.parquet(path)
    return df.sparkSession.readStream.schema(df.schema).option("maxFilesPerTrigger", each).parquet(path)
