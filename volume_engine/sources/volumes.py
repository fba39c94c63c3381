"""Volumes derived from the given tables, as sparse voxels (x, y, z, c, v); an absent cell holds the background."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.grid import VolumeMeta

LEVEL_SLICE_HOURS = 6


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def voxels_of(df: DataFrame, **columns: str) -> DataFrame:
    return df.select(*(F.expr(e).cast("long" if k == "v" else "int").alias(k) for k, e in columns.items()))


def ribbon(spark, sf_dir) -> DataFrame:
    """Sparse, one channel: 512-character chunks of documents."""
    docs = table(spark, sf_dir, "documents").select("doc_id", "n_chars").filter("n_chars > 0")
    chunks = docs.withColumn("x", F.explode(F.expr("sequence(0, cast((n_chars - 1) div 512 as int))")))
    return voxels_of(chunks, x="x", y="doc_id % 64", z="doc_id div 64", c="0", v="least(512, n_chars - 512 * x)")


def scan_events(df: DataFrame) -> DataFrame:
    """Event rows (batch or stream) as single contributions of the scan volume, with their time."""
    kept = df.filter("event_type in ('view', 'click', 'purchase')")
    channel = "case event_type when 'view' then 0 when 'click' then 1 else 2 end"
    slice_no = f"date_diff(to_date(ts), date'2024-01-01') * {24 // LEVEL_SLICE_HOURS} + hour(ts) div {LEVEL_SLICE_HOURS}"
    return kept.select(F.expr("cast(user_id as int)").alias("x"), F.expr("cast(get_json_object(props, '$.k') as int)").alias("y"), F.expr(f"cast({slice_no} as int)").alias("z"), F.expr(channel).alias("c"), F.expr("cast(floor(value * 100) as bigint)").alias("v"), "ts", "event_id")


def scan(spark, sf_dir) -> DataFrame:
    """Three channels, streamed in time: user by key by six-hour slice."""
    parts = scan_events(table(spark, sf_dir, "events"))
    return parts.groupBy("x", "y", "z", "c").agg(F.least(F.sum("v"), F.lit(65535)).alias("v"))


def sales(spark, sf_dir) -> DataFrame:
    """Dense, three channels: part by supplier by ship time."""
    line = table(spark, sf_dir, "lineitem").select("l_partkey", "l_suppkey", "l_shipdate", "l_quantity", "l_extendedprice", "l_discount")
    parts, suppliers = (table(spark, sf_dir, t).agg(F.max(k).alias(k)).first()[0] + 1 for t, k in (("part", "p_partkey"), ("lineitem", "l_suppkey")))
    cells = line.select(F.expr(f"l_partkey * 64 div {parts}").alias("x"), F.expr(f"l_suppkey * 64 div {suppliers}").alias("y"), F.expr("date_diff(to_date(l_shipdate), date'1995-01-01') * 64 div 2520").alias("z"), "l_quantity", "l_extendedprice", "l_discount")
    sums = cells.groupBy("x", "y", "z").agg(F.expr("cast(max(l_quantity) * 1310 as bigint)").alias("c0"), F.expr("least(cast(floor(max(l_extendedprice)) as bigint), 65535)").alias("c1"), F.expr("least(sum(cast(round(l_discount * 100) as bigint)) * 1000, 65535)").alias("c2"))
    return voxels_of(sums.selectExpr("x", "y", "z", "stack(3, 0, c0, 1, c1, 2, c2) as (c, v)"), x="x", y="y", z="z", c="c", v="v")


def vec(spark, sf_dir) -> DataFrame:
    """One channel, one 8 x 8 slice per row: embeddings."""
    rows = table(spark, sf_dir, "embeddings").select(F.col("vec_id"), F.posexplode("embedding").alias("i", "e"))
    return voxels_of(rows, x="i % 8", y="i div 8", z="vec_id", c="0", v="floor((cast(e as double) + 1) * 1000)")


def conversations(spark, sf_dir) -> DataFrame:
    """Two dimensions, three channels: turns of conversations."""
    rows = table(spark, sf_dir, "conversations").select("conv_id", "turn", "role", F.length("text").alias("n"))
    return voxels_of(rows, x="conv_id", y="turn", z="0", c="case role when 'system' then 0 when 'user' then 1 else 2 end", v="n")


def labels(spark, sf_dir) -> DataFrame:
    """One dimension, partly covered: quality and toxicity labels shifted by one, so that 0 is the background."""
    rows = table(spark, sf_dir, "labels").selectExpr("doc_id", "stack(2, 0, quality, 1, toxic) as (c, n)")
    return voxels_of(rows, x="doc_id", y="0", z="0", c="c", v="n + 1")


def benchmark(spark, sf_dir) -> DataFrame:
    """One dimension: lengths of benchmark texts."""
    return voxels_of(table(spark, sf_dir, "benchmark").select("item_id", F.length("text").alias("n")), x="item_id", y="0", z="0", c="0", v="n")


#: voxeliser, brick, channels and declared range of each volume
VOLUMES = {
    "ribbon": (ribbon, (4, 4, 4), 1, 512),
    "scan": (scan, (8, 8, 8), 3, 65535),
    "sales": (sales, (8, 8, 8), 3, 65535),
    "vec": (vec, (4, 4, 16), 1, 2000),
    "conversations": (conversations, (32, 8, 2), 3, 2047),
    "labels": (labels, (16, 2, 2), 2, 2),
    "benchmark": (benchmark, (4, 2, 2), 1, 511),
}


#: Grids known up front rather than read off the data.
DECLARED = {"sales": (64, 64, 64)}


def extent(spark, sf_dir, name: str) -> DataFrame:
    """Grid of a volume as one row (dx, dy, dz), read off its table by the plan that uses it."""
    cells = scan_events(table(spark, sf_dir, "events")) if name == "scan" else VOLUMES[name][0](spark, sf_dir)
    return cells.agg(*(F.expr(f"coalesce(max({a}), 0) + 1L").alias(f"d{a}") for a in "xyz"))


def open_volume(spark, sf_dir, name: str) -> tuple[DataFrame, VolumeMeta]:
    """Voxels of a volume and its declaration; the grid is read off the data with one aggregate."""
    make, brick, channels, hi = VOLUMES[name]
    voxels = make(spark, sf_dir)
    dims = DECLARED.get(name) or tuple((f or 0) + 1 for f in voxels.agg(*(F.max(a) for a in "xyz")).first())
    return voxels, VolumeMeta(name, dims, brick, channels, 0, 0, hi)
