"""Continuous updates: streams of vectors become segments, profiles are kept per user, and drift asks for a rebuild."""

from __future__ import annotations

import json
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming.query import StreamingQuery
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..operators import graph as G
from ..operators import theory as T
from ..operators.codecs import ExactCodec
from ..sources import index_store as I


def windowed_counts(events: DataFrame, size: str = "1 day", slide: str | None = None, late: str = "1 hour") -> DataFrame:
    """(start, event_type, n) of a stream of events (ts, event_type); rows older than the watermark are left out."""
    w = F.window("ts", size, slide) if slide else F.window("ts", size)
    return events.withWatermark("ts", late).groupBy(w.alias("w"), "event_type").agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "event_type", "n")


def without_repeats(events: DataFrame, key: str = "event_id", late: str = "1 hour") -> DataFrame:
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark([key])


def click_to_purchase(events: DataFrame, within: str = "6 hours", late: str = "1 hour") -> DataFrame:
    """Stream-stream join: a purchase within the interval after a click of the same user."""
    e = events.withWatermark("ts", late)
    c = e.where("event_type = 'click'").select(F.col("user_id").alias("cu"), F.col("ts").alias("ct"))
    p = e.where("event_type = 'purchase'").select(F.col("user_id").alias("pu"), F.col("ts").alias("pt"))
    return c.join(p, F.expr(f"cu = pu AND pt > ct AND pt <= ct + INTERVAL {within}"))


def user_profiles(events: DataFrame, slots: int = 120, idle_days: int = 30, late: str = "1 hour") -> DataFrame:
    """(user_id, n, counts) of every user with new events in a batch: counts by type and hour, kept as state; users without events for idle_days
    of event time are dropped."""
    kind = F.pmod(F.crc32(F.col("event_type").cast("binary")), F.lit(slots // 24)).cast("int")
    rows = events.withWatermark("ts", late).select("user_id", "ts", (kind * 24 + F.hour("ts")).alias("slot"))

    def update(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        if state.hasTimedOut:
            state.remove()
            return
        n, counts = state.get if state.exists else (0, [0] * slots)
        counts, last = list(counts), 0
        for b in batches:
            n += len(b)
            last = max(last, int(b["ts"].max().timestamp() * 1000))
            for s, c in b["slot"].value_counts().items():
                counts[int(s)] += int(c)
        state.update((n, counts))
        state.setTimeoutTimestamp(max(last + idle_days * 86_400_000, state.getCurrentWatermarkMs() + 1))
        yield pd.DataFrame({"user_id": [key[0]], "n": [n], "counts": [counts]})

    return rows.groupBy("user_id").applyInPandasWithState(update, "user_id long, n long, counts array<long>", "n long, counts array<long>", "update", GroupStateTimeout.EventTimeTimeout)


class SegmentIngest:
    """Every micro-batch of (vec_id, vec) becomes a delta segment of an index folder. The manifest names the batches that are in; a batch that comes again after a
    failure is written over the same segment and listed once, so ingestion is idempotent."""

    def __init__(self, path: str, codec: ExactCodec, candidates: int = 64, degree: int = 16, first_segment: int = 0):
        self.path, self.codec, self.candidates, self.degree, self.first = path, codec, candidates, degree, first_segment

    def batches(self, spark) -> list[int]:
        try:
            return json.loads(I._get(spark, f"{self.path}/manifest"))["batches"]
        except Exception as e:  # no manifest yet
            if "PATH_NOT_FOUND" in str(e):
                return []
            raise

    def __call__(self, batch: DataFrame, batch_id: int) -> None:
        spark = batch.sparkSession
        done = self.batches(spark)
        if batch_id in done or batch.isEmpty():
            return
        segment = self.first + batch_id
        vectors = batch.select("vec_id", "vec").withColumn("segment", F.lit(segment))
        vectors.write.mode("overwrite").parquet(f"{self.path}/vectors/batch={batch_id}")
        kept = spark.read.parquet(f"{self.path}/vectors/batch={batch_id}")
        adjacency = G.build_graph(kept, self.codec, self.candidates, self.degree).withColumn("segment", F.lit(segment))
        I.write_segments(adjacency, self.path)
        I._put(spark, f"{self.path}/model", I.codec_to_json(self.codec))
        I._put(spark, f"{self.path}/manifest", {"segments": segment + 1, "degree": self.degree, "batches": [*done, batch_id]})

    def start(self, stream: DataFrame, checkpoint: str) -> StreamingQuery:
        return stream.writeStream.foreachBatch(self).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def needs_rebuild(fresh: DataFrame, codec: ExactCodec, reference: float, tolerance: float = 0.1, size: int = 500) -> bool:
    """Whether the share of comparisons that codes strictly keep on new vectors fell by more than the tolerance below the reference."""
    got = T.preserved_fraction(T.margins(T.sample_triples(fresh, size, 0), codec)).first()
    return (got["strict"] or 0.0) < reference - tolerance
