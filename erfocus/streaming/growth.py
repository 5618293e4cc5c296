"""Canopies that grow with a stream of mentions."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from erfocus.functions.strings import normal, qgrams
from erfocus.operators.durable import cut, shared_path, sized
from erfocus.sources import fixtures
from erfocus.sources.io import read_mention_stream

WATERMARK = "1 day"


def watch(mentions: DataFrame, n: int = 5) -> DataFrame:
    """(query_id, mention): a small fixed watchlist of handles."""
    return mentions.where(F.col("mention") == F.concat(F.lit("user"), F.col("gold"))).select(F.col("gold").cast("long").alias("query_id"), "mention").distinct().orderBy("query_id").limit(n)


def matches(mentions: DataFrame, watchlist: DataFrame, min_shared: int = 6, q: int = 3) -> DataFrame:
    """(query_id, mention_id, ts): a stream-static join on q-grams of the watchlist; no state is kept."""
    # The watchlist lies written down: micro-batches would work it out anew.
    grams = watchlist.select("query_id", qgrams(F.col("mention"), q).alias("own")).select("query_id", "own", F.explode("own").alias("gram"))
    keyed = mentions.select("mention_id", "ts", normal(F.col("mention")).alias("string"))
    probe = keyed.select("mention_id", "ts", "string", F.explode(qgrams(F.col("string"), q)).alias("gram"))
    hits = probe.join(F.broadcast(grams) if mentions.isStreaming else sized(grams), "gram")
    # Of a pair's common grams only the first makes a row, so that pairs need no distinct.
    common = F.array_intersect(F.col("own"), qgrams(F.col("string"), q))
    return hits.where((F.size(common) >= F.least(F.lit(min_shared), F.size("own"))) & (F.col("gram") == F.get(common, F.lit(0)))).select("query_id", "mention_id", "ts")


def counts(mentions: DataFrame, watchlist: DataFrame) -> DataFrame:
    """(query_id, n_mentions)."""
    return matches(mentions, watchlist).groupBy("query_id").agg(F.count(F.lit(1)).alias("n_mentions"))


def windowed(mentions: DataFrame, watchlist: DataFrame, width: str = "7 days", late: str = WATERMARK) -> DataFrame:
    """(window, query_id, n_mentions) over event time: repeated mentions within the watermark count once, late ones not."""
    fresh = mentions.withWatermark("ts", late).dropDuplicatesWithinWatermark(["mention_id"])
    found = matches(fresh, watchlist)
    return found.groupBy(F.window("ts", width), "query_id").agg(F.count(F.lit(1)).alias("n_mentions"))


def sessions(mentions: DataFrame, gap: str = "6 hours", late: str = WATERMARK) -> DataFrame:
    """(session, doc_id, n): bursts of a document's mentions."""
    return mentions.withWatermark("ts", late).groupBy(F.session_window("ts", gap), "doc_id").agg(F.count(F.lit(1)).alias("n"))


def grow(stream: DataFrame, watchlist: DataFrame, table: str, checkpoint: str):
    """A query that appends each micro-batch's canopy rows to Parquet; a batch that is retried overwrites its own."""
    fixed = watchlist

    def append(batch: DataFrame, number: int) -> None:
        matches(batch, fixed).write.mode("overwrite").parquet(f"{table}/batch={number}")

    return stream.writeStream.foreachBatch(append).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def _events(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    """(the events table as a stream of mentions, the watchlist, written down)."""
    schema = spark.read.parquet(f"{sf_dir}/events.parquet").schema
    stream = fixtures.event_mentions(spark, sf_dir, read_mention_stream(spark, f"{sf_dir}/events.parquet*", schema))
    return stream, cut(watch(fixtures.event_mentions(spark, sf_dir)))


def replay(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(query_id, n_mentions) after the events table has passed through grow() as a stream."""
    stream, watchlist = _events(spark, sf_dir)
    table = shared_path(spark, "stream")
    grow(stream, watchlist, table, shared_path(spark, "stream-offsets")).awaitTermination()
    return spark.read.parquet(table).groupBy("query_id").agg(F.count(F.lit(1)).alias("n_mentions"))


def last_of_each(updates: DataFrame, spark: SparkSession, name: str, *keys: str) -> DataFrame:
    """A streaming aggregate's last state of each group, after all that is there has passed through it."""
    table = shared_path(spark, name)

    def keep(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{table}/batch={number}")

    updates.writeStream.outputMode("update").foreachBatch(keep).option("checkpointLocation", shared_path(spark, f"{name}-offsets")).trigger(availableNow=True).start().awaitTermination()
    rows = spark.read.parquet(table)
    values = [c for c in rows.columns if c not in (*keys, "batch")]
    return rows.groupBy(*keys).agg(*[F.max_by(c, "batch").alias(c) for c in values])


def replay_windows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(start, query_id, n_mentions): the week's canopy mentions, each mention once, of the events as a stream."""
    stream, watchlist = _events(spark, sf_dir)
    rows = windowed(stream, watchlist).select(F.date_format("window.start", "yyyy-MM-dd").alias("start"), "query_id", "n_mentions")
    return last_of_each(rows, spark, "windows", "start", "query_id")


def replay_sessions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(start, doc_id, n): users' bursts of events, of the events as a stream; only sessions that are over come out."""
    stream, _ = _events(spark, sf_dir)
    table = shared_path(spark, "sessions")
    rows = sessions(stream).select(F.date_format("session_window.start", "yyyy-MM-dd HH:mm:ss").alias("start"), "doc_id", "n")
    rows.writeStream.outputMode("append").format("parquet").option("path", table).option("checkpointLocation", shared_path(spark, "sessions-offsets")).trigger(availableNow=True).start().awaitTermination()
    return spark.read.parquet(table)
