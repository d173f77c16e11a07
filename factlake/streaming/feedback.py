"""Feedback and ingest as streams. Batch code is reused; event time is zoned and watermarked."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from factlake.sources import scratch

EVENTS = T.StructType([
    T.StructField("event_id", T.LongType()), T.StructField("ts", T.TimestampNTZType()), T.StructField("user_id", T.LongType()),
    T.StructField("event_type", T.StringType()), T.StructField("value", T.DoubleType()), T.StructField("props", T.StringType()),
])


def folder(spark: SparkSession) -> str:
    return scratch.folder(spark, "stream")


def events(spark: SparkSession, sf_dir: str, delay: str = "1 day") -> DataFrame:
    """The events table as a stream with a watermark."""
    s = spark.readStream.schema(EVENTS).option("pathGlobFilter", "events*").parquet(sf_dir)
    return s.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", delay)


def drained(df: DataFrame, mode: str = "append") -> DataFrame:
    """Runs a stream over all that there is and returns its rows, from a sink in the shared folder."""
    spark = df.sparkSession
    at = folder(spark)
    if mode == "append":
        df.writeStream.format("parquet").option("path", f"{at}/out").option("checkpointLocation", f"{at}/state").trigger(availableNow=True).start().awaitTermination()
        return spark.read.schema(df.schema).parquet(f"{at}/out")
    # complete results replace each other batch by batch
    df.writeStream.outputMode(mode).foreachBatch(lambda rows, n: rows.write.mode("overwrite").parquet(f"{at}/out")).option("checkpointLocation", f"{at}/state").trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(df.schema).parquet(f"{at}/out")


def action() -> Column:
    t = F.col("event_type")
    return F.when(t.isin("view", "click"), "access").when(t == "purchase", "accept").when(t == "error", "correct").otherwise("validate")


def counters(s: DataFrame) -> DataFrame:
    """Running counters of each user's actions: state is one row a key touched."""
    a = s.withColumn("action", action())
    n = lambda x: F.count_if(F.col("action") == x)
    return a.groupBy("user_id").agg(n("access").alias("access_n"), n("accept").alias("pos_n"), n("correct").alias("neg_n"))


def windowed(s: DataFrame, size: str, slide: str | None = None) -> DataFrame:
    w = F.window("ts", size, slide) if slide else F.window("ts", size)
    return s.groupBy(w.alias("w"), "event_type").agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "event_type", "n")


def sessions(s: DataFrame, gap: str = "30 minutes") -> DataFrame:
    return s.groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "user_id", "n")


def deduplicated(s: DataFrame) -> DataFrame:
    return s.dropDuplicatesWithinWatermark(["event_id"])


def attributed(s: DataFrame, hours: int = 1) -> DataFrame:
    """Purchases and errors within ``hours`` after the same user's view: an interval join of two streams."""
    shown = s.filter("event_type = 'view'").select(F.col("user_id").alias("viewer"), F.col("ts").alias("seen"), F.col("event_id").alias("view_id"))
    judged = s.filter("event_type IN ('purchase', 'error')").select("user_id", "ts", "event_id")
    return shown.join(judged, F.expr(f"user_id = viewer AND ts >= seen AND ts <= seen + INTERVAL {hours} HOURS")).select("view_id", "event_id")


def enriched(s: DataFrame, names: DataFrame) -> DataFrame:
    """Stream-static join with a small table."""
    return s.join(F.broadcast(names), "event_type", "left")


def ingest(spark: SparkSession, stream: DataFrame, encode, key: str = "doc_id") -> DataFrame:
    """Arrivals written batch by batch, then encoded as versions with the batch code; a batch that is run again replaces its own rows."""
    at = folder(spark)

    def land(rows: DataFrame, n: int) -> None:
        rows.write.mode("overwrite").parquet(f"{at}/landed/batch={n}")

    stream.writeStream.foreachBatch(land).option("checkpointLocation", f"{at}/state").trigger(availableNow=True).start().awaitTermination()
    return encode(spark.read.parquet(f"{at}/landed").drop("batch"))


def unit_counters(spark: SparkSession, stream: DataFrame) -> DataFrame:
    """access_n, pos_n and neg_n by unit from a stream of (unit_id, action): partial counts of each batch, merged when read.

    A batch writes its own partial counts and replaces them if it is run again, so nothing is counted twice.
    """
    at = folder(spark)
    n = lambda a: F.count_if(F.col("action") == a)

    def merge(rows: DataFrame, k: int) -> None:
        rows.groupBy("unit_id").agg(n("access").alias("access_n"), n("accept").alias("pos_n"), n("correct").alias("neg_n")).write.mode("overwrite").parquet(f"{at}/counts/batch={k}")

    stream.writeStream.foreachBatch(merge).option("checkpointLocation", f"{at}/state").trigger(availableNow=True).start().awaitTermination()
    return spark.read.parquet(f"{at}/counts").groupBy("unit_id").agg(*(F.sum(c).alias(c) for c in ("access_n", "pos_n", "neg_n")))


class Dormancy:
    """Keeps each user's last access and reports when the trust that it carries has decayed to the threshold.

    The age of crossing is closed-form, so no cold key is polled: an event-time timer is set for it and
    moved by every new access.
    """

    schema = "user_id long, last_seen timestamp, dormant_on timestamp"

    def __init__(self, base: float, threshold: float, half_life: float):
        from math import log2

        self.seconds = half_life * log2(base / threshold) * 86400

    def processor(self):
        from pyspark.sql.streaming import StatefulProcessor

        seconds = self.seconds

        class Watch(StatefulProcessor):
            def init(self, handle):
                self.handle = handle
                self.last = handle.getValueState("last", "ms long")

            def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timerValues):
                ms = max(pd.Timestamp(x.ts.max()).as_unit("ns").value // 1_000_000 for x in rows)
                if self.last.exists():
                    ms = max(ms, self.last.get()[0])
                for timer in list(self.handle.listTimers()):
                    self.handle.deleteTimer(timer)
                self.last.update((ms,))
                self.handle.registerTimer(ms + int(seconds * 1000))
                yield pd.DataFrame({"user_id": pd.Series([], dtype="int64"), "last_seen": pd.Series([], dtype="datetime64[us]"), "dormant_on": pd.Series([], dtype="datetime64[us]")})

            def handleExpiredTimer(self, key, timerValues, expiredTimerInfo):
                ms = self.last.get()[0]
                yield pd.DataFrame({"user_id": [key[0]], "last_seen": [pd.Timestamp(ms, unit="ms")], "dormant_on": [pd.Timestamp(expiredTimerInfo.getExpiryTimeInMs(), unit="ms")]})

            def close(self):
                pass

        return Watch()


def dormancy(s: DataFrame, base: float = 0.6, threshold: float = 0.15, half_life: float = 1.0) -> DataFrame:
    d = Dormancy(base, threshold, half_life)
    return s.select("user_id", "ts").groupBy("user_id").transformWithStateInPandas(d.processor(), Dormancy.schema, "Append", "eventtime")

