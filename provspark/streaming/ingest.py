"""Events as a stream of files: windows, duplicates and growing facts.  Each stream writes to a table that is read back."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..sources.tables import scratch_root


def events(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The events table replayed file by file; its times carry no zone and are read as UTC."""
    schema = spark.read.parquet(f"{sf_dir}/events.parquet").schema
    return spark.readStream.schema(schema).option("pathGlobFilter", "*.parquet").option("maxFilesPerTrigger", 1).parquet(f"{sf_dir}/events.parquet*").withColumn("ts", F.col("ts").cast("timestamp"))


def drained(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Run the stream to the end of its input and read what it wrote."""
    spark = stream.sparkSession
    at = f"{scratch_root(spark)}/stream-{uuid.uuid4().hex[:12]}"
    if mode == "append":
        run = stream.writeStream.format("parquet").option("path", f"{at}/out").option("checkpointLocation", f"{at}/state").outputMode("append").trigger(availableNow=True).start()
        run.awaitTermination()
        return spark.read.schema(stream.schema).parquet(f"{at}/out")

    def keep(batch: DataFrame, _: int) -> None:
        batch.write.mode("overwrite").parquet(f"{at}/out")

    run = stream.writeStream.foreachBatch(keep).option("checkpointLocation", f"{at}/state").outputMode(mode).trigger(availableNow=True).start()
    run.awaitTermination()
    return spark.read.schema(stream.schema).parquet(f"{at}/out")


def tumbling(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = events(spark, sf_dir).withWatermark("ts", "10 minutes").groupBy(F.window("ts", "1 hour").alias("w"), "event_type").agg(F.count("*").alias("n"))
    return drained(out, "complete").select(F.unix_timestamp("w.start").alias("start"), "event_type", "n")


def sliding(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = events(spark, sf_dir).withWatermark("ts", "10 minutes").groupBy(F.window("ts", "2 hours", "1 hour").alias("w")).agg(F.count("*").alias("n"))
    return drained(out, "complete").select(F.unix_timestamp("w.start").alias("start"), "n")


def session(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = events(spark, sf_dir).withWatermark("ts", "10 minutes").groupBy(F.session_window("ts", "30 minutes").alias("w"), "user_id").agg(F.count("*").alias("n"))
    return drained(out, "complete").groupBy("user_id").agg(F.count("*").alias("sessions"), F.sum("n").alias("n"))


def dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = events(spark, sf_dir).withWatermark("ts", "60 days").dropDuplicatesWithinWatermark(["user_id", "event_type"]).select("user_id", "event_type")
    return drained(out)


def stream_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Purchases within an hour after a view of the same user: two streams, joined by time."""
    of = lambda kind, at, name: events(spark, sf_dir).where(F.col("event_type") == kind).withWatermark("ts", "2 hours").select(F.col("user_id").alias(f"{name}_user"), F.col("ts").alias(at), F.col("event_id").alias(f"{name}_id"))
    views, bought = of("view", "seen", "view"), of("purchase", "paid", "purchase")
    near = F.expr("view_user = purchase_user AND paid >= seen AND paid <= seen + INTERVAL 1 HOUR")
    return drained(views.join(bought, near).select("view_id", "purchase_id"))


STREAMS = {
    "stream_join": (stream_join, "SELECT v.event_id AS view_id, p.event_id AS purchase_id FROM events v JOIN events p ON v.user_id = p.user_id AND v.event_type = 'view' AND p.event_type = 'purchase' AND p.ts >= v.ts AND p.ts <= v.ts + INTERVAL 1 HOUR"),
    "stream_tumbling": (tumbling, "SELECT CAST(epoch(date_trunc('hour', ts)) AS BIGINT) AS start, event_type, count(*) AS n FROM events GROUP BY 1, 2"),
    "stream_sliding": (sliding, "SELECT start, count(*) AS n FROM (SELECT CAST(epoch(date_trunc('hour', ts)) AS BIGINT) - 3600 * o AS start FROM events, (SELECT 0 AS o UNION ALL SELECT 1)) GROUP BY 1"),
    "stream_session": (session, "SELECT user_id, count(*) FILTER (gap) AS sessions, count(*) AS n FROM (SELECT user_id, coalesce(ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) > INTERVAL 30 MINUTE, true) AS gap FROM events) GROUP BY 1"),
    "stream_dedup": (dedup, "SELECT DISTINCT user_id, event_type FROM events"),
}


def grown_facts(stream: DataFrame, path: str, checkpoint: str, reason_over) -> list[int]:
    """Append each micro-batch of facts to a table at ``path`` and reason over all of it again; lineage only grows.

    ``reason_over(facts)`` returns a number, say of answers; the numbers are returned, batch by batch.
    """
    seen: list[int] = []

    def take(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/batch={number:06d}")
        seen.append(reason_over(batch.sparkSession.read.parquet(path).drop("batch")))

    run = stream.writeStream.foreachBatch(take).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    run.awaitTermination()
    return seen


def incremental(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Users with a purchase, from facts that arrive as a stream: the last of the growing answers."""
    from ..plans.baselines import set_fixpoint
    from ..rules import Program, rules

    at = f"{scratch_root(spark)}/grown-{uuid.uuid4().hex[:12]}"

    def answers(facts: DataFrame) -> int:
        return set_fixpoint(Program(rules("buyer(U) :- bought(U,E)."), {"bought": facts})).of("buyer").count()

    grown = grown_facts(facts_of_purchases(events(spark, sf_dir)), f"{at}/facts", f"{at}/state", answers)
    return spark.createDataFrame([(grown[-1],)], "buyers bigint")


def facts_of_purchases(df: DataFrame) -> DataFrame:
    bought = df.where("event_type = 'purchase'").select(F.col("user_id").alias("a0"), F.col("event_id").alias("a1"), F.lit(1.0).alias("pi"))
    return bought.withColumn("fid", F.xxhash64(F.lit("bought"), "a0", "a1"))


STREAMS["stream_incremental"] = (incremental, "SELECT count(DISTINCT user_id) AS buyers FROM events WHERE event_type = 'purchase'")
