"""Batch twins of the streaming windows, with SQL, and the streams themselves run over what is there."""

from __future__ import annotations

from pyspark.sql import functions as F

from codetrees.sources.tables import scratch
from codetrees.streaming import windows as w

Q: dict = {}
SQL: dict[str, str] = {}

MASK = "cast(CASE WHEN event_type = 'click' THEN 1 ELSE 0 END + CASE WHEN value > 100 THEN 2 ELSE 0 END AS bigint)"


def _events(spark, sf_dir):
    return spark.read.parquet(f"{sf_dir}/events.parquet")


def _text(df):
    return df.withColumn("start", F.date_format("start", "yyyy-MM-dd HH:mm:ss"))


Q["o55_tumbling"] = lambda s, d: _text(w.stream_compact(_events(s, d), "ts", MASK, "1 day"))
SQL["o55_tumbling"] = f"SELECT strftime(time_bucket(INTERVAL 1 DAY, ts), '%Y-%m-%d %H:%M:%S') AS start, {MASK} AS m, count(*) AS n FROM events GROUP BY 1, 2"
Q["o56_sliding"] = lambda s, d: _text(w.stream_compact(_events(s, d), "ts", MASK, "1 day", "6 hours"))
SQL["o56_sliding"] = f"SELECT strftime(time_bucket(INTERVAL 6 HOUR, ts) - k * INTERVAL 6 HOUR, '%Y-%m-%d %H:%M:%S') AS start, {MASK} AS m, count(*) AS n FROM events, (SELECT unnest(range(4)) AS k) GROUP BY 1, 2"
Q["o57_sessions"] = lambda s, d: _text(w.session_baskets(_events(s, d), "user_id", "ts", "event_type", "2 hours")).withColumn("items", F.concat_ws(",", "items"))
SQL["o57_sessions"] = (
    "WITH g AS (SELECT *, CASE WHEN ts < lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL 2 HOUR THEN 0 ELSE 1 END AS new FROM events), "
    "s AS (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS sid FROM g) "
    "SELECT user_id, strftime(min(ts), '%Y-%m-%d %H:%M:%S') AS start, array_to_string(list_sort(list_distinct(list(event_type))), ',') AS items, count(*) AS n FROM s GROUP BY user_id, sid"
)


def _stream(spark, sf_dir):
    df = _events(spark, sf_dir)
    path = scratch(spark, "events-in")
    df.repartition(2).write.parquet(path)
    return spark.readStream.schema(df.schema).option("maxFilesPerTrigger", 1).parquet(path)


def _stream_in_order(spark, sf_dir):
    """The events in two files, by halves of the range of event ids, the earlier one written first."""
    df = _events(spark, sf_dir)
    path = scratch(spark, "events-in")
    low, high = df.agg(F.min("event_id"), F.max("event_id")).first()
    late = F.col("event_id") > ((low or 0) + (high or 0)) // 2
    df.where(~late).coalesce(1).write.parquet(path)
    df.where(late).coalesce(1).write.mode("append").parquet(path)
    return spark.readStream.schema(df.schema).option("maxFilesPerTrigger", 1).parquet(path)


def _run(stream, mode: str):
    spark = stream.sparkSession
    out, at = scratch(spark, "events-out"), scratch(spark, "events-at")
    stream.writeStream.format("parquet").option("path", out).option("checkpointLocation", at).outputMode(mode).trigger(availableNow=True).start().awaitTermination()
    return spark.read.parquet(out)


Q["o58_stateful"] = lambda s, d: _run(w.previous_event(_stream_in_order(s, d).select("user_id", "event_id", "event_type"), "user_id", "event_type"), "append")
SQL["o58_stateful"] = "SELECT user_id, event_id, event_type, lag(event_type) OVER (PARTITION BY user_id ORDER BY event_id) AS prev FROM events"
Q["o59_stream_dedupe"] = lambda s, d: _run(w.without_repeats(_stream(s, d).withColumn("ts", F.col("ts").cast("timestamp")).select("event_id", "ts"), "ts", "event_id", "40 days"), "append").select("event_id")
SQL["o59_stream_dedupe"] = "SELECT DISTINCT event_id FROM events"


def o60_score_stream(spark, sf_dir):
    """Mean bits a row of each micro-batch under a model grown from the whole table."""
    from codetrees.plans.counts import counts_of
    from codetrees.plans.greedy import grow_model

    rows = lambda df: df.select(F.expr(MASK).alias("m"))
    ct = rows(_events(spark, sf_dir)).groupBy("m").agg(F.count("*").alias("n"))
    model = grow_model(counts_of(ct, 2), ["click", "large"])
    got: list = []
    w.score_stream(rows(_stream(spark, sf_dir)), model, lambda i, n, b: got.append((i, n, b))).awaitTermination()
    return spark.createDataFrame(got, "batch long, n_rows long, bits double")


Q["o60_score_stream"] = o60_score_stream
