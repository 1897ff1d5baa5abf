"""Streams of events: coding under a frozen model, windowed measures, sessions and deduplication.

Each query reads the table as a file stream, runs it to its end (availableNow) and returns what the sink holds.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from relcodec import archive as archives
from relcodec.plans.workloads import query
from relcodec.sources.tables import scratch, table


def events_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The events file as a stream (its folder holds other tables, so the file is matched by name)."""
    schema = table(spark, sf_dir, "events").schema
    return spark.readStream.schema(schema).option("pathGlobFilter", "events.parquet").parquet(sf_dir).withColumn("ts", F.col("ts").cast("timestamp"))


def finished(stream: DataFrame, spark: SparkSession, mode: str = "append") -> DataFrame:
    """The rows of a stream run to its end."""
    if mode == "append":
        out = scratch(spark)
        stream.writeStream.format("parquet").option("path", out).option("checkpointLocation", scratch(spark)).trigger(availableNow=True).start().awaitTermination()
        return spark.read.schema(stream.schema).parquet(out)
    # Whole results go to files, not to a sink in the driver's memory: a folder per batch, of which the last one holds.
    out, last = scratch(spark), []

    def keep(rows: DataFrame, batch: int) -> None:
        rows.write.mode("overwrite").parquet(f"{out}/{batch}")
        last[:] = [batch]

    stream.writeStream.foreachBatch(keep).outputMode(mode).option("checkpointLocation", scratch(spark)).trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(stream.schema).parquet(f"{out}/{last[0]}") if last else spark.createDataFrame([], stream.schema)


@query("stream_scan_events", "SELECT event_type, count(*)::BIGINT AS n FROM events GROUP BY 1")
def stream_scan_events(spark, sf_dir):
    return finished(events_stream(spark, sf_dir).select("event_id", "event_type"), spark).groupBy("event_type").agg(F.count(F.lit(1)).alias("n"))


@query("stream_tumbling_bits", "SELECT date_trunc('day', ts)::DATE AS day, count(*)::BIGINT AS n, sum(length(props))::BIGINT AS chars FROM events GROUP BY 1")
def stream_tumbling_bits(spark, sf_dir):
    s = events_stream(spark, sf_dir).withWatermark("ts", "1 hour").groupBy(F.window("ts", "1 day").alias("w")).agg(F.count(F.lit(1)).alias("n"), F.sum(F.length("props").cast("long")).alias("chars"))
    return finished(s, spark, "complete").select(F.to_date("w.start").alias("day"), "n", "chars")


@query("stream_sliding_counts", "SELECT epoch_us(s)::BIGINT AS start_us, count(*)::BIGINT AS n FROM (SELECT time_bucket(INTERVAL '6 hours', ts) - to_hours((6 * k)::INT) AS s FROM events, range(0, 4) AS t(k)) GROUP BY 1")
def stream_sliding_counts(spark, sf_dir):
    s = events_stream(spark, sf_dir).groupBy(F.window("ts", "1 day", "6 hours").alias("w")).agg(F.count(F.lit(1)).alias("n"))
    return finished(s, spark, "complete").select(F.unix_micros("w.start").alias("start_us"), "n")


@query("stream_sessions", "WITH g AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL '30 minutes' THEN 0 ELSE 1 END AS new FROM events), s AS (SELECT user_id, sum(new) OVER (PARTITION BY user_id ORDER BY ts) AS k FROM g) SELECT user_id, count(DISTINCT k)::BIGINT AS sessions FROM s GROUP BY 1")
def stream_sessions(spark, sf_dir):
    s = events_stream(spark, sf_dir).groupBy("user_id", F.session_window("ts", "30 minutes").alias("w")).agg(F.count(F.lit(1)).alias("n"))
    return finished(s, spark, "complete").groupBy("user_id").agg(F.count(F.lit(1)).alias("sessions"))


@query("stream_dedup", "SELECT count(DISTINCT event_id)::BIGINT AS n FROM events")
def stream_dedup(spark, sf_dir):
    s = events_stream(spark, sf_dir)
    s = s.unionByName(events_stream(spark, sf_dir)).withWatermark("ts", "1 hour").dropDuplicatesWithinWatermark(["event_id"]).select("event_id")
    return finished(s, spark).agg(F.count(F.lit(1)).alias("n"))


@query("stream_static_masses", "WITH c AS (SELECT event_type, count(*) AS n, sum(count(*)) OVER () AS t FROM events GROUP BY 1) SELECT event_id, round(-log2(n / t), 6) AS bits FROM events JOIN c USING (event_type)")
def stream_static_masses(spark, sf_dir):
    """Bits of each streamed row under a fixed model."""
    c = table(spark, sf_dir, "events").groupBy("event_type").agg(F.count(F.lit(1)).alias("n"))
    c = c.crossJoin(c.agg(F.sum("n").alias("t")))
    return finished(events_stream(spark, sf_dir).join(F.broadcast(c), "event_type").select("event_id", F.round(-F.log2(F.col("n") / F.col("t")), 6).alias("bits")), spark)


@query("stream_encode_roundtrip", "SELECT event_id, user_id, event_type, value FROM events")
def stream_encode_roundtrip(spark, sf_dir):
    """Micro-batches are coded under a frozen model; a batch writes its own folder, so a replay overwrites."""
    columns = ["event_id", "user_id", "event_type", "value"]
    images, network, _ = archives.fit(table(spark, sf_dir, "events").select(*columns), archives.Options(structure="empty"))
    out = scratch(spark)

    def append(batch: DataFrame, batch_id: int) -> None:
        archives.encode(network.spec.images(batch), network).write.mode("overwrite").parquet(f"{out}/batch={batch_id}")

    events_stream(spark, sf_dir).select(*columns).writeStream.foreachBatch(append).option("checkpointLocation", scratch(spark)).trigger(availableNow=True).start().awaitTermination()
    return network.spec.restored(archives.decode(spark.read.schema(archives.BLOCKS).parquet(f"{out}/batch=*"), network))


@query("stream_state_counts", "SELECT event_type, count(*)::BIGINT AS n FROM events GROUP BY 1")
def stream_state_counts(spark, sf_dir):
    """Counts per symbol kept in keyed state, for the next model."""
    import pandas as pd
    from pyspark.sql.streaming.state import GroupStateTimeout

    def update(key, frames, state):
        n = (state.get[0] if state.exists else 0) + sum(len(f) for f in frames)
        state.update((n,))
        yield pd.DataFrame({"event_type": [key[0]], "n": [n]})

    s = events_stream(spark, sf_dir).select("event_type", "event_id").groupBy("event_type").applyInPandasWithState(update, "event_type string, n long", "n long", "update", GroupStateTimeout.NoTimeout)
    return finished(s, spark, "update").groupBy("event_type").agg(F.max("n").alias("n"))


@query("stream_interval_join", """SELECT count(*)::BIGINT AS n FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL '10 minutes'""")
def stream_interval_join(spark, sf_dir):
    """Events of one user within ten minutes of each other: two streams joined on a time range."""
    one = events_stream(spark, sf_dir).select(F.col("user_id").alias("u"), F.col("ts").alias("t")).withWatermark("t", "1 hour")
    other = events_stream(spark, sf_dir).select("user_id", "ts").withWatermark("ts", "1 hour")
    joined = one.join(other, F.expr("u = user_id AND ts > t AND ts <= t + INTERVAL 10 MINUTES"))
    return finished(joined.select("u"), spark).agg(F.count(F.lit(1)).alias("n"))


@query("stream_drift_alarm", """WITH w AS (SELECT date_trunc('day', ts)::DATE AS day, avg(value) AS mean, count(*) AS n FROM events GROUP BY 1) SELECT day, round(mean, 6) AS mean, n::BIGINT AS n FROM w WHERE abs(mean - 50) > 2""")
def stream_drift_alarm(spark, sf_dir):
    """Days on which a number's mean is off the one that a model was fitted with."""
    s = events_stream(spark, sf_dir).groupBy(F.window("ts", "1 day").alias("w")).agg(F.avg("value").alias("mean"), F.count(F.lit(1)).alias("n"))
    return finished(s, spark, "complete").filter(F.abs(F.col("mean") - 50) > 2).select(F.to_date("w.start").alias("day"), F.round("mean", 6).alias("mean"), "n")


@query("stream_late_rows", "SELECT count(*)::BIGINT AS rows_kept FROM events")
def stream_late_rows(spark, sf_dir):
    """Every row in a side table as it came, whatever the watermark: late rows leave a state, not the raw archive."""
    out = scratch(spark)

    def keep(batch: DataFrame, batch_id: int) -> None:
        batch.write.mode("overwrite").parquet(f"{out}/batch={batch_id}")

    events_stream(spark, sf_dir).withWatermark("ts", "10 minutes").writeStream.foreachBatch(keep).option("checkpointLocation", scratch(spark)).trigger(availableNow=True).start().awaitTermination()
    return spark.read.parquet(out).agg(F.count(F.lit(1)).alias("rows_kept"))
