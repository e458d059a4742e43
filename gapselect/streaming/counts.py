"""Streams of events: windows, state, and mutual information kept from additive counts.

Counts of (subgroup, cell, target) are additive, so MI after any batch equals MI of the
batch query over the same events. Late events beyond the watermark are dropped by windowed
queries; the count state has no watermark and takes every event once per id.
"""

from __future__ import annotations

import uuid

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from gapselect.sources.formats import scratch

WATERMARK = "1 hour"
#: State lies in files beside the tasks with a bounded cache, not in the heap: complete
#: results and keys within the watermark grow with the events.
_STATE = {
    "spark.sql.streaming.stateStore.providerClass": "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider",
    "spark.sql.streaming.stateStore.rocksdb.boundedMemoryUsage": "true",
    "spark.sql.streaming.stateStore.rocksdb.maxMemoryUsageMB": "256",
}


def split_by_time(events: DataFrame, files: int = 4) -> str:
    """The events as ordered files of one folder, which a stream then reads one by one."""
    from gapselect.operators.prep import ranked, tile

    folder = scratch(events.sparkSession, "events")
    out = ranked(events, [F.col("ts"), F.col("event_id")], "r", "t").withColumn("file", tile("r", "t", files)).drop("r", "t")
    for k in range(files):  # one write per file keeps their order of arrival
        out.filter(F.col("file") == k).drop("file").coalesce(1).write.mode("append").parquet(folder)
    return folder


def stream_of(spark: SparkSession, folder: str, schema) -> DataFrame:
    """One file per batch; event time as an instant, which watermarks need."""
    read = spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(folder)
    return read.withColumn("ts", F.col("ts").cast("timestamp"))


def run(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Everything available through the query, then its result as a table: the last
    batch's for ``complete``, else the rows of all batches. Each batch is written under its
    number, so a repeated one replaces its own rows, and none of them reach the driver."""
    spark = stream.sparkSession
    folder = scratch(spark, "result")
    last = []

    def keep(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{folder}/batch={number}")
        last[:] = [number]

    before = {k: spark.conf.get(k, None) for k in _STATE}
    for k, v in _STATE.items():
        spark.conf.set(k, v)
    try:
        q = stream.writeStream.outputMode(mode).foreachBatch(keep).option("checkpointLocation", scratch(spark, "stream")).trigger(availableNow=True).start()
    finally:  # the query has its own copy from its start on
        for k, v in before.items():
            spark.conf.unset(k) if v is None else spark.conf.set(k, v)
    q.awaitTermination()
    if not last:
        return spark.createDataFrame([], stream.schema)
    return spark.read.schema(stream.schema).parquet(f"{folder}/batch={last[0]}" if mode == "complete" else f"{folder}/batch=*")


def tumbling(stream: DataFrame, width: str = "1 hour", step: str | None = None) -> DataFrame:
    w = F.window("ts", width, step) if step else F.window("ts", width)
    counts = stream.withWatermark("ts", WATERMARK).groupBy(w.alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n"))
    return counts.select(F.col("w.start").alias("start"), "event_type", "n")


def sessions(stream: DataFrame, gap: str = "30 minutes") -> DataFrame:
    s = stream.withWatermark("ts", WATERMARK).groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count(F.lit(1)).alias("n"))
    return s.select("user_id", F.col("w.start").alias("start"), F.col("w.end").alias("end"), "n")


def deduplicated(stream: DataFrame) -> DataFrame:
    return stream.withWatermark("ts", WATERMARK).dropDuplicatesWithinWatermark(["event_id"])


def cell(df: DataFrame) -> DataFrame:
    """Subgroup, two coded features and the target of an event."""
    return df.select(
        (F.col("user_id") % 4).cast("int").alias("sg"), F.floor(F.hour("ts") / 6).cast("int").alias("hour_band"),
        F.least(F.floor(F.get_json_object("props", "$.k").cast("int") / 25), F.lit(3)).cast("int").alias("k_band"), "event_type",
    )


def mi_counts(stream: DataFrame, folder: str | None = None) -> DataFrame:
    """(sg, mi): MI of (hour_band, k_band) with the event type from counts merged batch by
    batch. Each batch writes its counts under its number, so a batch that runs again after
    a failure replaces its own file and is not counted twice."""
    spark = stream.sparkSession
    folder = folder or scratch(spark, "counts")
    keys = ["sg", "hour_band", "k_band", "event_type"]

    def merge(batch: DataFrame, number: int) -> None:
        batch.groupBy(*keys).agg(F.count(F.lit(1)).alias("n")).write.mode("overwrite").parquet(f"{folder}/batch={number}")

    q = cell(stream).writeStream.foreachBatch(merge).option("checkpointLocation", scratch(spark, "stream")).trigger(availableNow=True).start()
    q.awaitTermination()
    return mi_of_counts(spark.read.parquet(folder).groupBy(*keys).agg(F.sum("n").alias("c")))


def mi_of_counts(c: DataFrame) -> DataFrame:
    from pyspark.sql import Window

    over = c.withColumns({
        "cf": F.sum("c").over(Window.partitionBy("sg", "hour_band", "k_band")), "cy": F.sum("c").over(Window.partitionBy("sg", "event_type")), "t": F.sum("c").over(Window.partitionBy("sg")),
    })
    return over.groupBy("sg").agg(F.sum(F.col("c") / F.col("t") * F.log2(F.col("c") * F.col("t") / (F.col("cf") * F.col("cy")))).alias("mi"))


def running_totals(stream: DataFrame) -> DataFrame:
    """(sg, n) by an own state per subgroup, which a timeout would drop."""
    from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

    def add(key, frames, state: GroupState):
        n = sum(len(f) for f in frames) + (state.get[0] if state.exists else 0)
        state.update((n,))
        yield pd.DataFrame({"sg": [key[0]], "n": [n]})

    keyed = stream.select((F.col("user_id") % 4).cast("int").alias("sg"), "event_id")
    return keyed.groupBy("sg").applyInPandasWithState(add, "sg int, n long", "n long", "update", GroupStateTimeout.NoTimeout)
