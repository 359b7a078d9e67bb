"""Streams of events: windows, pairs as positive edges, re-clustering of what changed."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from signedcluster.model import normalise
from signedcluster.operators import pivot
from signedcluster.operators.components import components
from signedcluster.shared import materialize, new_path


def event_stream(spark: SparkSession, folder: str, delay: str = "1 hour") -> DataFrame:
    """The events files as a stream, with a watermark; later rows are dropped by stateful operators."""
    path = f"{folder}/events.parquet"
    schema = spark.read.parquet(path).schema
    # As a pattern, so that one file and a folder of files are read alike.
    raw = spark.readStream.schema(schema).parquet(f"{folder}/events.parque[t]")
    return raw.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", delay)


def finished(stream: DataFrame, label: str, mode: str = "complete") -> DataFrame:
    """Run a stream over what is there and return the result as a table in the shared folder.

    Complete results replace the table at each batch; appended rows are written under their batch's number, so a
    repeated batch replaces itself.
    """
    spark = stream.sparkSession
    target = new_path(spark, label)

    def keep(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{target}/batch={0 if mode == 'complete' else number}")

    run = stream.writeStream.outputMode(mode).foreachBatch(keep).option("checkpointLocation", new_path(spark, f"{label}-state")).trigger(availableNow=True).start()
    run.awaitTermination()
    return spark.read.schema(stream.schema).parquet(f"{target}/batch=*")


def windows(stream: DataFrame, size: str = "6 hours", slide: str | None = None) -> DataFrame:
    """Counts and sums of each event type in tumbling (no slide) or sliding windows."""
    w = F.window("ts", size, slide) if slide else F.window("ts", size)
    return stream.groupBy(w.alias("w"), "event_type").agg(F.count("*").alias("events"), F.sum("value").alias("total")).select(F.unix_micros("w.start").alias("start_us"), "event_type", "events", "total")


def session_windows(stream: DataFrame, gap: str = "6 hours") -> DataFrame:
    return stream.groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("events")).select("user_id", F.unix_micros("w.start").alias("start_us"), F.unix_micros("w.end").alias("end_us"), "events")


def near_pairs(left: DataFrame, right: DataFrame, minutes: int = 60) -> DataFrame:
    """Stream-stream interval join: events of one user within ``minutes`` are a positive edge. Both sides' watermarks
    bound what the join has to remember."""
    a = left.select(F.col("event_id").alias("u"), F.col("user_id").alias("k"), F.col("ts").alias("tu"))
    b = right.select(F.col("event_id").alias("v"), F.col("user_id").alias("k2"), F.col("ts").alias("tv"))
    on = (F.col("k") == F.col("k2")) & (F.col("tv") >= F.col("tu")) & (F.col("tv") <= F.col("tu") + F.expr(f"INTERVAL {minutes} MINUTES")) & (F.col("u") != F.col("v"))
    return a.join(b, on).select(F.least("u", "v").alias("u"), F.greatest("u", "v").alias("v"))


def last_events(stream: DataFrame) -> DataFrame:
    """The latest event of each user, by an aggregate whose state is one row a user."""
    return stream.groupBy("user_id").agg(F.max(F.struct("ts", "event_id")).alias("last")).select("user_id", F.col("last.event_id").alias("event_id"))


def recluster(old_edges: DataFrame, old: DataFrame, new_edges: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(edges, clustering) after a batch: only components that a new edge touches are clustered again.

    The result equals clustering everything again, because a pivot cluster never leaves its component.
    """
    g = normalise(old_edges.unionByName(new_edges))
    edges = materialize(g.edges, "edges")
    comp = materialize(components(edges), "comp")
    touched = comp.join(new_edges.select(F.explode(F.array("u", "v")).alias("v")).distinct(), "v").select("comp").distinct()
    again = materialize(comp.join(touched, "comp", "left_semi").select("v"), "again")
    part = normalise(edges.join(again, "v", "left_semi"))
    new = pivot.cluster(part.stored("part"))
    kept = old.join(again, "v", "left_anti")
    return edges, kept.unionByName(new)
