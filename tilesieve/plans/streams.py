"""Streaming queries on the given tables. Event operators run over the table; tests run them as streams too."""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tilesieve.operators import bloom
from tilesieve.plans import oracle as o
from tilesieve.plans.membership import corpus
from tilesieve.sources.io import SCHEMAS, load_table, scratch_root
from tilesieve.streaming import streams

Query = Callable[[SparkSession, str], DataFrame]
REGISTRY: dict[str, tuple[Query, str | None]] = {}
EVENTS = "event_id bigint, ts timestamp_ntz, user_id bigint, event_type string, value double, props string"


def query(sql: str | None = None):
    def add(f: Query) -> Query:
        REGISTRY[f.__name__] = f, sql
        return f

    return add


def _folder(s: SparkSession) -> str:
    return f"{scratch_root(s)}/stream-{uuid.uuid4().hex}"


def _source(d: str, name: str) -> str:
    return f"{d}/{name[:-1]}[{name[-1]}].parquet"


def events(s: SparkSession, d: str) -> DataFrame:
    return load_table(s, d, "events")


@query(f"WITH {o.corpus()} SELECT p // 32768 AS bucket, count(*) AS set_bits, sum(p % 32768)::BIGINT AS place_sum FROM bits GROUP BY 1")
def stream_ingest(s, d):
    spec, path = corpus(s, d).spec, _folder(s)
    stream = streams.open_dir(s, _source(d, "documents"), SCHEMAS["documents"], files_per_batch=4)
    streams.ingest_stream(stream, spec, f"{path}/filter", f"{path}/checkpoint").awaitTermination()
    return bloom.filter_digest(streams.ingested(s, spec, f"{path}/filter"))


@query(f"WITH {o.corpus()}, {o.asked('benchmark', 'item_id')} SELECT item_id, max_tiles, lcs_chars FROM qbest")
def stream_probe(s, d):
    path = _folder(s)
    stream = streams.open_dir(s, _source(d, "benchmark"), SCHEMAS["benchmark"])
    streams.probe_stream(stream, corpus(s, d), f"{path}/out", f"{path}/checkpoint", key="item_id").awaitTermination()
    return s.read.schema("item_id bigint, max_tiles bigint, lcs_chars bigint, start bigint, batch int").parquet(f"{path}/out").select("item_id", "max_tiles", "lcs_chars")


@query("SELECT date_trunc('hour', ts) AS start, event_type, count(*) AS n FROM events GROUP BY 1, 2")
def stream_tumbling(s, d):
    return streams.tumbling(events(s, d)).withColumn("start", F.col("start").cast("timestamp_ntz"))


@query("SELECT b - INTERVAL (30 * k) MINUTE AS start, count(*) AS n FROM (SELECT time_bucket(INTERVAL 30 MINUTE, ts) AS b, k FROM events, range(4) r(k)) GROUP BY 1")
def stream_sliding(s, d):
    return streams.sliding(events(s, d)).withColumn("start", F.col("start").cast("timestamp_ntz"))


@query("SELECT user_id, min(ts) AS start, max(ts) + INTERVAL 30 MINUTE AS \"end\", count(*) AS n FROM (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS g FROM (SELECT *, CASE WHEN lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) > ts - INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS fresh FROM events)) GROUP BY user_id, g")
def stream_session(s, d):
    out = streams.sessions(events(s, d))
    return out.select("user_id", *[F.col(c).cast("timestamp_ntz").alias(c) for c in ("start", "end")], "n")


@query("SELECT event_id, user_id FROM events")
def stream_dedup(s, d):
    """Every event sent twice, kept once."""
    return streams.deduplicated(events(s, d).unionAll(events(s, d))).select("event_id", "user_id")


@query("SELECT a.user_id AS user_id, a.event_id AS first_id, b.event_id AS then_id FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 15 MINUTE WHERE a.event_type = 'view' AND b.event_type = 'purchase'")
def stream_interval_join(s, d):
    return streams.within(events(s, d))


@query("SELECT user_id, count(*) AS events, max(event_id) AS last_id FROM events GROUP BY user_id")
def stream_state(s, d):
    """State of each user over a stream of the table; the last update of each is the answer."""
    path, name = _folder(s), f"t{uuid.uuid4().hex}"
    stream = streams.open_dir(s, _source(d, "events"), EVENTS, files_per_batch=2).select("user_id", "event_id")
    out = streams.latest_by_user(stream)

    def keep(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/{name}/batch={number}")

    out.writeStream.outputMode("update").foreachBatch(keep).option("checkpointLocation", f"{path}/checkpoint").trigger(availableNow=True).start().awaitTermination()
    seen = s.read.schema("user_id bigint, events bigint, last_id bigint, batch int").parquet(f"{path}/{name}")
    return seen.groupBy("user_id").agg(F.max("events").alias("events"), F.max("last_id").alias("last_id"))


_LATE = "SELECT date_trunc('hour', ts) AS start, event_type, count(*) AS n FROM (SELECT *, event_id % 4 = 0 AS late, max(ts) FILTER (WHERE event_id % 4 >= 2) OVER () - INTERVAL 10 MINUTE AS first_mark, max(ts) OVER () - INTERVAL 10 MINUTE AS last_mark FROM events) WHERE (NOT late OR date_trunc('hour', ts) + INTERVAL 1 HOUR > first_mark) AND date_trunc('hour', ts) + INTERVAL 1 HOUR <= last_mark GROUP BY 1, 2"


@query(_LATE)
def stream_late(s, d):
    """A stream whose third file holds old times again: what lies behind the watermark of the batch before the last is
    dropped, and each hour is given out once, when the watermark has passed its end."""
    path = _folder(s)
    e = events(s, d).withColumn("part", F.when(F.col("event_id") % 4 == 0, 2).when(F.col("event_id") % 4 == 1, 1).otherwise(0))
    for part in (0, 1, 2):
        e.where(F.col("part") == part).drop("part").coalesce(1).write.parquet(f"{path}/in/{part}")
    stream = streams.open_dir(s, f"{path}/in/*", EVENTS, files_per_batch=1)
    keep = lambda b, n: b.write.mode("overwrite").parquet(f"{path}/out/batch={n}")
    streams.tumbling(stream).writeStream.outputMode("append").foreachBatch(keep).option("checkpointLocation", f"{path}/checkpoint").trigger(availableNow=True).start().awaitTermination()
    out = s.read.schema("start timestamp, event_type string, n bigint, batch int").parquet(f"{path}/out")
    return out.select(F.col("start").cast("timestamp_ntz").alias("start"), "event_type", "n")
