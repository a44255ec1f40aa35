"""Queries of the stream side: batch twins of windows, sessions, late rows and as-of joins."""

from __future__ import annotations

from pyspark.sql import functions as F
from pyspark.sql.window import Window as W

from ..queries import query, r6
from ..sources.tables import load


@query("SELECT time_bucket(INTERVAL 1 DAY, ts) AS start, event_type, count(*) AS n, round(sum(value), 4) + 0.0 AS total FROM events GROUP BY 1, 2")
def event_windows(spark, d):
    return load(spark, d, "events").groupBy(F.window("ts", "1 day").alias("w"), "event_type").agg(F.count("*").alias("n"), r6(F.sum("value"), 4).alias("total")).select(F.col("w.start").alias("start"), "event_type", "n", "total")


@query("SELECT start, count(*) AS n FROM (SELECT unnest([b, b - INTERVAL 6 HOUR, b - INTERVAL 12 HOUR, b - INTERVAL 18 HOUR]) AS start FROM (SELECT time_bucket(INTERVAL 6 HOUR, ts) AS b FROM events)) GROUP BY 1")
def event_sliding(spark, d):
    return load(spark, d, "events", "ts").groupBy(F.window("ts", "1 day", "6 hours").alias("w")).agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "n")


@query("WITH g AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS fresh FROM events), s AS (SELECT user_id, ts, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM g) SELECT user_id, min(ts) AS start, count(*) AS n FROM s GROUP BY user_id, k")
def event_sessions(spark, d):
    return load(spark, d, "events", "user_id", "ts").groupBy("user_id", F.session_window("ts", "30 minutes").alias("w")).agg(F.count("*").alias("n")).select("user_id", F.col("w.start").alias("start"), "n")


@query("WITH o AS (SELECT event_id, ts, max(ts) OVER (ORDER BY event_id * 7919 % 10007, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS seen, (event_id * 7919 % 10007) // 1000 AS file FROM events) SELECT file, count(*) AS n, count(*) FILTER (ts < seen - INTERVAL 1 HOUR) AS n_late FROM o GROUP BY file")
def late_rows(spark, d):
    """Rows older than the watermark of an hour when events arrive in a shuffled order. The running maximum is taken per file of the order, then carried over files."""
    place = F.col("event_id") * 7919 % 10007
    rows = load(spark, d, "events", "event_id", "ts").withColumns({"place": place, "file": F.floor(place / 1000)})
    inner = W.partitionBy("file").orderBy("place", "event_id").rowsBetween(W.unboundedPreceding, -1)
    tops = rows.groupBy("file").agg(F.max("ts").alias("top"))
    before = tops.alias("a").join(tops.alias("b"), F.col("b.file") < F.col("a.file"), "left").groupBy(F.col("a.file").alias("file")).agg(F.max("b.top").alias("carried"))  # a row for each file
    seen = F.greatest(F.max("ts").over(inner), F.col("carried"))
    late = F.col("ts") < F.col("seen") - F.expr("INTERVAL 1 HOUR")
    return rows.join(before, "file").withColumn("seen", seen).groupBy("file").agg(F.count("*").alias("n"), F.count(F.when(late, 1)).alias("n_late"))


@query("SELECT p.event_id, c.event_id AS last_click FROM (FROM events WHERE event_type = 'purchase') p ASOF LEFT JOIN (FROM events WHERE event_type = 'click') c ON p.user_id = c.user_id AND p.ts >= c.ts")
def asof_event(spark, d):
    """The last click of the user before each purchase: union, sort and carry forward."""
    rows = load(spark, d, "events", "event_id", "user_id", "ts", "event_type").where(F.col("event_type").isin("click", "purchase"))
    click = F.when(F.col("event_type") == "click", F.col("event_id"))
    w = W.partitionBy("user_id").orderBy("ts", F.col("event_type") == "purchase").rowsBetween(W.unboundedPreceding, 0)
    return rows.withColumn("last_click", F.last(click, ignorenulls=True).over(w)).where("event_type = 'purchase'").select("event_id", "last_click")


@query("SELECT count(*) AS n FROM events c JOIN events p ON c.user_id = p.user_id AND c.event_type = 'click' AND p.event_type = 'purchase' AND p.ts > c.ts AND p.ts <= c.ts + INTERVAL 6 HOUR")
def interval_join(spark, d):
    """Click and purchase of a user within six hours: an equi-join on user and bucket, then the exact bounds."""
    rows = load(spark, d, "events", "user_id", "ts", "event_type")
    bucket = F.floor(F.unix_timestamp("ts") / 21600)
    clicks = rows.where("event_type = 'click'").select("user_id", F.col("ts").alias("c"), F.explode(F.array(bucket, bucket + 1)).alias("b"))
    buys = rows.where("event_type = 'purchase'").select("user_id", F.col("ts").alias("p"), bucket.alias("b"))
    return clicks.join(buys, ["user_id", "b"]).where((F.col("p") > F.col("c")) & (F.col("p") <= F.col("c") + F.expr("INTERVAL 6 HOURS"))).agg(F.count("*").alias("n"))


@query("SELECT CAST(json_extract(props, '$.k') AS BIGINT) % 10 AS k, count(*) AS n FROM events GROUP BY 1")
def event_props(spark, d):
    return load(spark, d, "events", "props").groupBy((F.from_json("props", "k bigint")["k"] % 10).alias("k")).agg(F.count("*").alias("n"))


# -- the streams themselves, run over files until all are read


def _replay(spark, d, parts: int = 4):
    """events as a stream of files that are read one after another."""
    from ..sources.tables import shared_dir

    path = shared_dir(spark, "event-files")
    rows = load(spark, d, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    rows.repartitionByRange(parts, "event_id").write.parquet(path)
    return spark.readStream.schema(rows.schema).option("maxFilesPerTrigger", 1).parquet(path)


def _drain(stream, mode: str):
    from ..sources.tables import shared_dir

    spark = stream.sparkSession
    out = shared_dir(spark, "stream-out")
    if mode == "append":
        q = stream.writeStream.format("parquet").option("path", out).option("checkpointLocation", shared_dir(spark, "stream-state")).outputMode("append").trigger(availableNow=True).start()
    else:
        write = lambda batch, i: batch.write.mode("overwrite").parquet(f"{out}/batch={i:06d}")
        q = stream.writeStream.foreachBatch(write).option("checkpointLocation", shared_dir(spark, "stream-state")).outputMode(mode).trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.read.parquet(out)


@query()
def stream_windows(spark, d):
    """Daily counts with a watermark of an hour, appended as windows close."""
    from .ingest import windowed_counts

    return _drain(windowed_counts(_replay(spark, d)), "append")


@query("SELECT count(*) AS n FROM events")
def stream_dedup(spark, d):
    from .ingest import without_repeats

    twice = _replay(spark, d)
    return _drain(without_repeats(twice.unionByName(twice), late="60 days").select("event_id"), "append").agg(F.count_distinct("event_id").alias("n"))


@query("SELECT user_id, count(*) AS n FROM events GROUP BY user_id")
def stream_profiles(spark, d):
    """Per-user state over all batches; the largest count is the last."""
    from .ingest import user_profiles

    return _drain(user_profiles(_replay(spark, d), late="60 days"), "update").groupBy("user_id").agg(F.max("n").alias("n"))


@query("SELECT count(*) AS n FROM events c JOIN events p ON c.user_id = p.user_id AND c.event_type = 'click' AND p.event_type = 'purchase' AND p.ts > c.ts AND p.ts <= c.ts + INTERVAL 6 HOUR")
def stream_interval_join(spark, d):
    from .ingest import click_to_purchase

    return _drain(click_to_purchase(_replay(spark, d), late="60 days").select("cu", "ct", "pt"), "append").agg(F.count("*").alias("n"))


@query()
def stream_ingest(spark, d):
    """Vectors arrive in files; every micro-batch becomes a segment; the index is searched over all segments."""
    from ..operators import exact as E
    from ..operators import search as S
    from ..operators.codecs import AlignedCodec
    from ..sources.index_store import load_index
    from ..sources.tables import shared_dir
    from ..sources.vectors import embedding_vectors, split_queries
    from .ingest import SegmentIngest

    base, q = split_queries(embedding_vectors(spark, d).select("vec_id", "vec"))
    files, path = shared_dir(spark, "vector-files"), shared_dir(spark, "ingested")
    base.repartitionByRange(2, "vec_id").write.parquet(files)
    codec = AlignedCodec(16, iters=2, sample=0).fit(base)
    stream = spark.readStream.schema(base.schema).option("maxFilesPerTrigger", 1).parquet(files)
    SegmentIngest(path, codec).start(stream, shared_dir(spark, "ingest-state")).awaitTermination()
    index = load_index(spark, path)
    found = S.walk(index, q, 32)
    return E.rerank(E.top_k(found, 32), index.vectors, q, 10)
