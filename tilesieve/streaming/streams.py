"""Structured Streaming: ingest into a filter, probe a stream of texts, and the event operators.

The event operators take any DataFrame with ``event_id, ts, user_id, event_type, value``; on a stream
they keep state under a watermark, on a table they are the same plan without one.
"""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery

from tilesieve.functions.sizing import FilterSpec
from tilesieve.operators import bloom, chain


def open_dir(spark: SparkSession, path: str, schema: str, *, files_per_batch: int | None = None) -> DataFrame:
    """A file stream; ``path`` may be a glob."""
    reader = spark.readStream.schema(schema)
    return (reader.option("maxFilesPerTrigger", files_per_batch) if files_per_batch else reader).parquet(path)


BITMAPS = "bucket bigint, bitmap binary"


def ingest_stream(stream: DataFrame, spec: FilterSpec, path: str, checkpoint: str, *, text: str = "text", key: str = "doc_id") -> StreamingQuery:
    """Bits of every micro-batch, as ``path/batch=n``: only the buckets that batch n touched.

    A replayed batch writes the same bits again, and ORing bits twice changes nothing, so delivery at least once
    is enough.
    """

    def step(batch: DataFrame, number: int) -> None:
        bloom.corpus_filter(batch, text=text, key=key, spec=spec).table.write.mode("overwrite").parquet(f"{path}/batch={number}")

    return stream.writeStream.foreachBatch(step).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def ingested(spark: SparkSession, spec: FilterSpec, path: str) -> bloom.Filter:
    """The filter of all batches in the folder, whichever run wrote them: the OR of their bits."""
    folder = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    if not folder.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).exists(folder):
        return bloom.Filter(spec, spark.createDataFrame([], BITMAPS))
    parts = spark.read.schema(f"{BITMAPS}, batch int").parquet(path).drop("batch")
    return bloom.Filter(spec, parts.groupBy("bucket").agg(F.bitmap_or_agg("bitmap").alias("bitmap")))


def compact(spark: SparkSession, spec: FilterSpec, path: str, to: str) -> bloom.Filter:
    """All batches of ``path`` as the one batch of the folder ``to``, from which ingesting may go on."""
    ingested(spark, spec, path).table.write.parquet(f"{to}/batch=-1")
    return ingested(spark, spec, to)


def probe_stream(stream: DataFrame, filter_: bloom.Filter, out: str, checkpoint: str, *, key: str) -> StreamingQuery:
    """Longest chains of each text as it comes: a text is whole in its batch, so nothing is kept between batches."""

    def step(batch: DataFrame, number: int) -> None:
        texts = bloom.normalized(batch, filter_.spec, key=key)
        best = chain.longest_chain(chain.chain_hits(bloom.probe_texts(texts, filter_, key=key, hits_only=True), key=key), texts, key=key)
        best.write.mode("overwrite").parquet(f"{out}/batch={number}")

    return stream.writeStream.foreachBatch(step).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def _marked(events: DataFrame, late: str) -> DataFrame:
    rows = events.withColumn("ts", F.col("ts").cast("timestamp"))
    return rows.withWatermark("ts", late) if events.isStreaming else rows


def tumbling(events: DataFrame, *, width: str = "1 hour", late: str = "10 minutes") -> DataFrame:
    w = F.window("ts", width)
    return _marked(events, late).groupBy(w.alias("w"), "event_type").agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "event_type", "n")


def sliding(events: DataFrame, *, width: str = "2 hours", slide: str = "30 minutes", late: str = "10 minutes") -> DataFrame:
    w = F.window("ts", width, slide)
    return _marked(events, late).groupBy(w.alias("w")).agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "n")


def sessions(events: DataFrame, *, gap: str = "30 minutes", late: str = "10 minutes") -> DataFrame:
    w = F.session_window("ts", gap)
    return _marked(events, late).groupBy(w.alias("w"), "user_id").agg(F.count("*").alias("n")).select("user_id", F.col("w.start").alias("start"), F.col("w.end").alias("end"), "n")


def deduplicated(events: DataFrame, *, late: str = "10 minutes") -> DataFrame:
    """One row of each event id."""
    rows = _marked(events, late)
    return rows.dropDuplicatesWithinWatermark(["event_id"]) if events.isStreaming else rows.dropDuplicates(["event_id"])


def within(events: DataFrame, first: str = "view", then: str = "purchase", *, gap: str = "15 minutes", late: str = "10 minutes") -> DataFrame:
    """Pairs of one user's ``first`` and ``then`` events at most ``gap`` apart, on streams with state bounded by both watermarks."""
    a = _marked(events.where(F.col("event_type") == first), late).select(F.col("user_id").alias("u"), F.col("ts").alias("a_ts"), F.col("event_id").alias("first_id"))
    b = _marked(events.where(F.col("event_type") == then), late).select("user_id", F.col("ts").alias("b_ts"), F.col("event_id").alias("then_id"))
    return a.join(b, F.expr(f"u = user_id AND b_ts >= a_ts AND b_ts <= a_ts + INTERVAL {gap}")).select("user_id", "first_id", "then_id")


def latest_by_user(events: DataFrame) -> DataFrame:
    """(user_id, events, last_id): kept for each user across batches in arbitrary state."""

    def update(key: tuple, parts: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        n, last = state.get if state.exists else (0, -1)
        for p in parts:
            n, last = n + len(p), max(last, int(p["event_id"].max()))
        state.update((n, last))
        yield pd.DataFrame({"user_id": [key[0]], "events": [n], "last_id": [last]})

    return events.groupBy("user_id").applyInPandasWithState(update, "user_id bigint, events bigint, last_id bigint", "events bigint, last_id bigint", "update", "NoTimeout")
