"""Streaming queries: each runs to the end of its input and is read back as a table."""

from __future__ import annotations

from pyspark.sql import functions as F

from gapselect.queries.base import query
from gapselect.sources.tables import table
from gapselect.streaming import counts as st


def _stream(spark, sf, files: int = 3):
    events = table(spark, sf, "events")
    return st.stream_of(spark, st.split_by_time(events, files), events.schema)


def _shown(df):
    return df.withColumn("start", F.unix_timestamp("start"))


@query("SELECT CAST(floor(epoch(ts) / 3600) * 3600 AS BIGINT) AS start, event_type, count(*) AS n FROM events GROUP BY ALL")
def stream_tumbling(spark, sf):
    return _shown(st.run(st.tumbling(_stream(spark, sf)), "complete"))


@query("SELECT CAST(floor(epoch(ts) / 900) * 900 - 900 * k AS BIGINT) AS start, event_type, count(*) AS n FROM events, (SELECT unnest(range(4)) AS k) GROUP BY ALL")
def stream_sliding(spark, sf):
    return _shown(st.run(st.tumbling(_stream(spark, sf), "1 hour", "15 minutes"), "complete"))


@query("""WITH e AS (SELECT user_id, ts, CASE WHEN lag(ts) OVER w IS NULL OR ts >= lag(ts) OVER w + INTERVAL 30 MINUTE THEN 1 ELSE 0 END AS f FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)),
          s AS (SELECT user_id, ts, sum(f) OVER (PARTITION BY user_id ORDER BY ts, f DESC ROWS UNBOUNDED PRECEDING) AS k FROM e)
          SELECT user_id, CAST(floor(epoch(min(ts))) AS BIGINT) AS start, count(*) AS n FROM s GROUP BY user_id, k""")
def stream_session(spark, sf):
    return _shown(st.run(st.sessions(_stream(spark, sf)), "complete")).select("user_id", "start", "n")


@query("SELECT event_type, count(*) AS n FROM events GROUP BY event_type")
def stream_dedupe(spark, sf):
    """Every event arrives twice within the watermark and is counted once."""
    events = table(spark, sf, "events")
    folder = st.split_by_time(events, 3)
    twice = st.stream_of(spark, folder, events.schema).withColumn("again", F.explode(F.array(F.lit(0), F.lit(1)))).drop("again")
    return st.run(st.deduplicated(twice)).groupBy("event_type").agg(F.count(F.lit(1)).alias("n"))


@query("SELECT band, event_type, count(*) AS n FROM (SELECT event_type, CASE WHEN user_id % 3 = 0 THEN 'a' ELSE 'b' END AS band FROM events) GROUP BY ALL")
def stream_static_join(spark, sf):
    bands = table(spark, sf, "events").select("user_id").distinct().withColumn("band", F.when(F.col("user_id") % 3 == 0, "a").otherwise("b"))
    joined = _stream(spark, sf).join(bands, "user_id").groupBy("band", "event_type").agg(F.count(F.lit(1)).alias("n"))
    return st.run(joined, "complete")


@query("""WITH c AS (SELECT CAST(user_id % 4 AS INTEGER) AS sg, floor(hour(ts) / 6) AS h, least(3, floor(CAST(json_extract_string(props, '$.k') AS INTEGER) / 25)) AS k, event_type AS y, count(*) AS c FROM events GROUP BY ALL),
          o AS (SELECT *, sum(c) OVER (PARTITION BY sg, h, k) AS cf, sum(c) OVER (PARTITION BY sg, y) AS cy, sum(c) OVER (PARTITION BY sg) AS t FROM c)
          SELECT sg, round(sum(c / t * log2(c * t / (cf * cy))), 6) + 0.0 AS mi FROM o GROUP BY sg""")
def stream_mi_counts(spark, sf):
    return st.mi_counts(_stream(spark, sf)).select("sg", (F.round("mi", 6) + 0.0).alias("mi"))


@query()
def stream_late(spark, sf):
    """A last file repeats the earliest hours: its rows are beyond the watermark."""
    events = table(spark, sf, "events")
    folder = st.split_by_time(events, 3)
    first = events.agg(F.min("ts")).first()[0]
    late = events.filter(F.col("ts") < F.lit(first) + F.expr("INTERVAL 2 HOURS")).withColumn("event_id", -F.col("event_id") - 1)
    late.coalesce(1).write.mode("append").parquet(folder)
    out = st.run(st.tumbling(st.stream_of(spark, folder, events.schema)), "append")
    return out.agg(F.sum("n").alias("counted")).withColumn("sent", F.lit(events.count() + late.count()))


@query()
def stream_stateful(spark, sf):
    return st.run(st.running_totals(_stream(spark, sf)), "update").groupBy("sg").agg(F.max("n").alias("n"))
