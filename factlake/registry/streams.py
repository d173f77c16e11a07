"""Streams over the events table, drained and compared with batch SQL."""

from __future__ import annotations

from pyspark.sql import functions as F

from factlake.operators import lifecycle as L
from factlake.registry.base import query
from factlake.sources import given as G
from factlake.streaming import feedback as X

CLOSED = "(SELECT max(ts) FROM events) - INTERVAL 1 DAY"


@query("stream_counters", "SELECT user_id, count(CASE WHEN event_type IN ('view', 'click') THEN 1 END) AS access_n, count(CASE WHEN event_type = 'purchase' THEN 1 END) AS pos_n, count(CASE WHEN event_type = 'error' THEN 1 END) AS neg_n FROM events GROUP BY user_id")
def stream_counters(spark, d):
    return X.drained(X.counters(X.events(spark, d)), "complete")


@query("stream_tumbling", f"SELECT date_trunc('day', ts) AS start, event_type, count(*) AS n FROM events GROUP BY 1, 2 HAVING date_trunc('day', any_value(ts)) + INTERVAL 1 DAY <= {CLOSED}")
def stream_tumbling(spark, d):
    return X.drained(X.windowed(X.events(spark, d), "1 day")).withColumn("start", F.col("start").cast("timestamp_ntz"))


@query("stream_sliding", f"SELECT start, event_type, count(*) AS n FROM (SELECT date_trunc('day', ts) - to_days(CAST(k AS INTEGER)) AS start, event_type FROM events, (SELECT unnest(range(7)) AS k)) GROUP BY 1, 2 HAVING start + INTERVAL 7 DAY <= {CLOSED}")
def stream_sliding(spark, d):
    return X.drained(X.windowed(X.events(spark, d), "7 days", "1 day")).withColumn("start", F.col("start").cast("timestamp_ntz"))


@query("stream_session", f"SELECT start, user_id, n FROM (SELECT user_id, s, min(ts) AS start, max(ts) AS last, count(*) AS n FROM (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS s FROM (SELECT *, CASE WHEN lag(ts) OVER w IS NULL OR ts - lag(ts) OVER w > INTERVAL 30 MINUTE THEN 1 ELSE 0 END AS new FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id))) GROUP BY user_id, s) WHERE last + INTERVAL 30 MINUTE <= {CLOSED}")
def stream_session(spark, d):
    return X.drained(X.sessions(X.events(spark, d))).withColumn("start", F.col("start").cast("timestamp_ntz"))


@query("stream_dedup", "SELECT count(*) AS n, count(DISTINCT event_id) AS ids FROM events")
def stream_dedup(spark, d):
    e = X.events(spark, d).withColumn("copy", F.explode(F.array(F.lit(1), F.lit(2))))
    return X.drained(X.deduplicated(e)).agg(F.count("*").alias("n"), F.countDistinct("event_id").alias("ids"))


@query("stream_late", "SELECT event_type, count(*) AS n FROM events WHERE ts >= TIMESTAMP '2024-01-10' GROUP BY event_type")
def stream_late(spark, d):
    """Two files in turn: the days from the tenth on, then the first day again; the second is past the watermark and dropped."""
    at = X.folder(spark)
    e = spark.read.schema(X.EVENTS).parquet(f"{d}/events.parquet")
    e.filter(F.col("ts") >= G.at("2024-01-10")).coalesce(1).write.parquet(f"{at}/in")
    s = spark.readStream.schema(X.EVENTS).option("maxFilesPerTrigger", 1).parquet(f"{at}/in").withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", "1 day")
    rows = s.dropDuplicatesWithinWatermark(["event_id"])

    def run():
        rows.writeStream.format("parquet").option("path", f"{at}/out").option("checkpointLocation", f"{at}/state").trigger(availableNow=True).start().awaitTermination()

    run()
    e.filter(F.col("ts") < G.at("2024-01-02")).coalesce(1).write.mode("append").parquet(f"{at}/in")
    run()
    return spark.read.schema(rows.schema).parquet(f"{at}/out").groupBy("event_type").agg(F.count("*").alias("n"))


@query("stream_attribution", "SELECT v.event_id AS view_id, j.event_id AS event_id FROM events v JOIN events j ON v.user_id = j.user_id AND v.event_type = 'view' AND j.event_type IN ('purchase', 'error') AND j.ts >= v.ts AND j.ts <= v.ts + INTERVAL 1 HOUR")
def stream_attribution(spark, d):
    return X.drained(X.attributed(X.events(spark, d)))


@query("stream_enriched", "SELECT CASE event_type WHEN 'view' THEN 'access' WHEN 'click' THEN 'access' ELSE 'other' END AS kind, count(*) AS n FROM events GROUP BY 1")
def stream_enriched(spark, d):
    names = spark.createDataFrame([("view", "access"), ("click", "access")], "event_type string, kind string")
    return X.drained(X.enriched(X.events(spark, d), names)).groupBy(F.coalesce("kind", F.lit("other")).alias("kind")).agg(F.count("*").alias("n"))


@query("stream_ingest", "SELECT CASE WHEN r = 1 THEN 'UNCONSOLIDATED' ELSE 'DEPRECATED' END AS status, count(*) AS n FROM (SELECT row_number() OVER (PARTITION BY user_id, event_type ORDER BY event_id DESC) AS r FROM events) GROUP BY 1")
def stream_ingest(spark, d):
    e = X.events(spark, d).select(F.col("user_id").alias("doc_id"), F.col("event_type").alias("chunk_no"), F.col("event_id").alias("version_no"), F.col("event_id").cast("string").alias("unit_id"))
    return X.ingest(spark, e, L.encode).groupBy("status").agg(F.count("*").alias("n"))


@query("stream_dormancy", f"SELECT user_id, last_seen FROM (SELECT user_id, make_timestamp((epoch_us(max(ts)) // 1000) * 1000) AS last_seen FROM events GROUP BY user_id) WHERE epoch_us(last_seen) // 1000 + CAST(floor(0.05 * log2(4.0) * 86400 * 1000) AS BIGINT) <= epoch_us({CLOSED}) // 1000")
def stream_dormancy(spark, d):
    spark.conf.set("spark.sql.streaming.stateStore.providerClass", "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    try:
        return X.drained(X.dormancy(X.events(spark, d), half_life=0.05)).select("user_id", F.col("last_seen").cast("timestamp_ntz").alias("last_seen"))
    finally:
        spark.conf.unset("spark.sql.streaming.stateStore.providerClass")
