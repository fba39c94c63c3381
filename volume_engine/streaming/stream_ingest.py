"""Streamed slices: sources, versions per micro-batch, and monitors run to the end of what is available."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .. import storage
from ..operators.pool import BrickPool
from ..sources.volumes import scan_events


def event_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The events table as a stream; ``at`` is its time as a timestamp (watermarks need one)."""
    schema = spark.read.parquet(f"{sf_dir}/events.parquet").schema
    rows = spark.readStream.schema(schema).option("pathGlobFilter", "events.parquet").parquet(sf_dir)
    return rows.withColumn("at", F.col("ts").cast("timestamp"))


def run_to_end(stream: DataFrame, mode: str, prepare=None) -> DataFrame:
    """Process all that is available into a memory table and return it as a batch."""
    name = f"m{uuid.uuid4().hex}"
    query = stream.writeStream.outputMode(mode).format("memory").queryName(name).trigger(availableNow=True).start()
    query.awaitTermination()
    return stream.sparkSession.table(name)


def tumbling_slices(spark, sf_dir) -> DataFrame:
    """Contributions and intensity per six-hour slice."""
    parts = scan_events(event_stream(spark, sf_dir).drop("at"))
    return run_to_end(parts.groupBy("z").agg(F.count("*").alias("n"), F.sum("v").alias("total")), "complete")


def sliding_slab(spark, sf_dir) -> DataFrame:
    """Maximum per channel over slabs of four slices, every two slices."""
    parts = scan_events(event_stream(spark, sf_dir).drop("at"))
    slabs = parts.withColumn("slab", F.explode(F.expr("sequence(greatest(0, (z - 2) div 2), z div 2)"))).filter("z >= 2 * slab and z < 2 * slab + 4")
    return run_to_end(slabs.groupBy("slab", "c").agg(F.max("v").alias("v")), "complete")


def slice_batches(spark: SparkSession, sf_dir: str, slices: int) -> str:
    """The scan's contributions as files of ``slices`` slices each, in time order, for a stream that takes one file a batch."""
    path = storage.new_path(spark, "slices")
    parts = scan_events(spark.read.parquet(f"{sf_dir}/events.parquet")).withColumn("batch", F.expr(f"z div {slices}"))
    parts.repartition("batch").sortWithinPartitions("batch", "event_id").write.partitionBy("batch").parquet(path)
    return path


def stream_build(pool: BrickPool, path: str, after=None, checkpoint: str | None = None, compact_every: int = 8) -> int:
    """Build a pool from streamed contributions (x, y, z, c, v): a version per micro-batch; return the number of versions.

    With the same ``checkpoint`` and ``pool.open_pool`` a new driver goes on where the last one stopped.

    A micro-batch adds to what its voxels held before, as a scanner that visits a place again does.
    A replayed batch overwrites the version of its number, and what it adds to is read from the versions
    before it, so a restart changes nothing.  ``after(version)`` is called when a version can be read.
    """
    spark = pool.spark
    versions: set[int] = set()
    cell = ["x", "y", "z", "c"]
    schema = spark.read.parquet(path).schema

    def batch(df: DataFrame, number: int) -> None:
        fresh = df.groupBy(*cell).agg(F.sum("v").alias("v"))
        earlier = [v for v in pool.commits if v < number]
        if earlier:
            old = pool.voxels(earlier[-1], 0).select(*cell, F.col("v").alias("was"))
            fresh = fresh.join(old, cell, "left").select(*cell, (F.col("v") + F.coalesce("was", F.lit(0))).alias("v"))
        pool.insert(fresh.withColumn("v", F.least("v", F.lit(pool.vm.hi))), number)
        versions.add(number)
        if len(pool.commits) > compact_every:
            pool.compact()
        if after is not None:
            after(number)

    stream = spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).option("latestFirst", "false").parquet(path)
    checkpoint = checkpoint or storage.new_path(spark, "stream-state")
    stream.writeStream.foreachBatch(batch).option("checkpointLocation", checkpoint).trigger(availableNow=True).start().awaitTermination()
    return len(versions)


def session_runs(spark, sf_dir, gap: str = "6 hours") -> DataFrame:
    """Scan runs: bursts of events of a user with no longer pause than ``gap``, as session windows."""
    rows = event_stream(spark, sf_dir).filter("event_type in ('view', 'click', 'purchase')").withWatermark("at", "30 days")
    runs = rows.groupBy(F.session_window("at", gap).alias("w"), "user_id").agg(F.count("*").alias("n"), F.sum(F.expr("cast(floor(value * 100) as bigint)")).alias("total"))
    return run_to_end(runs.select("user_id", F.unix_seconds("w.start").alias("begins"), "n", "total"), "complete")


def late_slices(spark, sf_dir, slice_no: int = 5) -> DataFrame:
    """Contributions per slice when one slice is delivered after all others: no watermark, so none is left out."""
    path = storage.new_path(spark, "late")
    parts = scan_events(spark.read.parquet(f"{sf_dir}/events.parquet")).withColumn("at", F.col("ts").cast("timestamp")).select("z", "v", "at")
    # file by file in name order: first all other slices, then the late one
    for k, rows in enumerate((parts.filter(F.col("z") != slice_no), parts.filter(F.col("z") == slice_no))):
        rows.coalesce(1).write.mode("append").parquet(f"{path}/turn={k}")
    stream = spark.readStream.schema("z int, v long, at timestamp, turn int").option("maxFilesPerTrigger", 1).parquet(path)
    return run_to_end(stream.groupBy("z").agg(F.count("*").alias("n"), F.sum("v").alias("total")), "complete")


def dedup(spark, sf_dir) -> DataFrame:
    """Distinct event ids of a stream that may deliver twice."""
    rows = event_stream(spark, sf_dir)
    twice = rows.select("event_id", "event_type").union(rows.select("event_id", "event_type"))
    return run_to_end(twice.dropDuplicates(["event_id"]).groupBy("event_type").agg(F.count("*").alias("n")), "complete")


def static_transfer(spark, sf_dir) -> DataFrame:
    """Stream joined with a static transfer table: contributions per colour class."""
    bands = F.broadcast(spark.createDataFrame([(0, 10000, "dark"), (10000, 30000, "mid"), (30000, 1 << 30, "bright")], "lo long, hi long, band string"))
    parts = scan_events(event_stream(spark, sf_dir).drop("at"))
    return run_to_end(parts.join(bands, F.expr("v >= lo and v < hi")).groupBy("band").agg(F.count("*").alias("n")), "complete")
