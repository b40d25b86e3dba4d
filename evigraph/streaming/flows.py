"""Streaming forms. Each runs to the end of what is there (``availableNow``) into a table in the shared
folder, so a query can hand back a batch DataFrame."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from evigraph.plans.store import path_for

EVENTS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def events(spark: SparkSession, sf_dir: str, name: str = "events", files: int | None = None) -> DataFrame:
    """The events as a stream; ``files`` a micro-batch, all that are there by default."""
    reader = spark.readStream.schema(EVENTS).option("pathGlobFilter", "*.parquet")
    s = (reader.option("maxFilesPerTrigger", files) if files else reader).parquet(f"{sf_dir}/{name}*.parquet")
    return s.withColumn("at", F.col("ts").cast("timestamp"))


def drained(stream: DataFrame, mode: str = "append") -> DataFrame:
    spark = stream.sparkSession
    out, marks = path_for(spark, "stream"), path_for(spark, "marks")
    if mode == "append":
        stream.writeStream.format("parquet").option("path", out).option("checkpointLocation", marks).outputMode("append").trigger(availableNow=True).start().awaitTermination()
        return spark.read.schema(stream.schema).parquet(out)

    def land(batch: DataFrame, n: int) -> None:
        batch.write.mode("overwrite").parquet(out)

    stream.writeStream.foreachBatch(land).option("checkpointLocation", marks).outputMode(mode).trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(stream.schema).parquet(out)


def tumbling(spark: SparkSession, sf_dir: str, size: str = "1 day") -> DataFrame:
    w = events(spark, sf_dir).groupBy(F.window("at", size), "event_type").agg(F.count("*").alias("n"))
    return drained(w, "complete").select(F.unix_micros("window.start").alias("start_us"), "event_type", "n")


def sliding(spark: SparkSession, sf_dir: str, size: str = "2 days", step: str = "1 day") -> DataFrame:
    w = events(spark, sf_dir).groupBy(F.window("at", size, step)).agg(F.count("*").alias("n"))
    return drained(w, "complete").select(F.unix_micros("window.start").alias("start_us"), "n")


def session(spark: SparkSession, sf_dir: str, gap: str = "6 hours") -> DataFrame:
    w = events(spark, sf_dir).withWatermark("at", "1 day").groupBy(F.session_window("at", gap), "user_id").agg(F.count("*").alias("n"))
    return drained(w, "complete").select(F.unix_micros("session_window.start").alias("start_us"), "user_id", "n")


def dedupe(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A replayed stream: every event twice, each counted once."""
    e = events(spark, sf_dir)
    twice = e.withColumn("copy", F.explode(F.array(F.lit(1), F.lit(2)))).drop("copy")
    return drained(twice.withWatermark("at", "1 day").dropDuplicatesWithinWatermark(["event_id"]).select("event_id", "user_id", "event_type"))


def enriched(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Stream joined to the static subjects."""
    c = spark.read.parquet(f"{sf_dir}/customer.parquet").select(F.col("c_custkey").alias("user_id"), "c_mktsegment")
    return drained(events(spark, sf_dir).join(c, "user_id").groupBy("c_mktsegment").agg(F.count("*").alias("n")), "complete")


def late_audit(spark: SparkSession, sf_dir: str, cutoff_us: int) -> DataFrame:
    """Rows at or after the cut-off go on, older ones to an audit count."""
    e = events(spark, sf_dir).withColumn("late", F.unix_micros("at") < cutoff_us)
    return drained(e.groupBy("late").agg(F.count("*").alias("n")), "complete")


def interval_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Purchases with signups of the same user within the next day, stream to stream."""
    e = events(spark, sf_dir)
    a = e.filter("event_type = 'purchase'").select(F.col("user_id").alias("u"), F.col("event_id").alias("bought"), F.col("at").alias("t1")).withWatermark("t1", "1 day")
    b = e.filter("event_type = 'signup'").select("user_id", F.col("event_id").alias("signed"), F.col("at").alias("t2")).withWatermark("t2", "1 day")
    j = a.join(b, F.expr("u = user_id and t2 >= t1 and t2 <= t1 + interval 1 day"))
    return drained(j.select("bought", "signed"))


def scope_projection(spark: SparkSession, sf_dir: str, on_batch: Callable[[DataFrame], None]) -> None:
    """Each micro-batch names the scopes it touches; ``on_batch`` recomputes just those."""
    marks = path_for(spark, "marks")

    def run(batch: DataFrame, n: int) -> None:
        on_batch(batch.groupBy(F.col("user_id").alias("scope")).agg(F.max("event_id").alias("watermark")))

    events(spark, sf_dir).writeStream.foreachBatch(run).option("checkpointLocation", marks).trigger(availableNow=True).start().awaitTermination()


def landed(stream: DataFrame, on_batch: Callable[[DataFrame, int], None]) -> int:
    """Hand each micro-batch and its number to ``on_batch``, until all that is there has been handed on;
    returns how many there were."""
    seen: list[int] = []

    def run(batch: DataFrame, n: int) -> None:
        seen.append(n)
        on_batch(batch, n)

    stream.writeStream.foreachBatch(run).option("checkpointLocation", path_for(stream.sparkSession, "marks")).trigger(availableNow=True).start().awaitTermination()
    return len(set(seen))
