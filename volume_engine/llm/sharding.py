"""Minimax contiguous sharding: ordered atomic groups are cut so that the largest shard is as small as can be.

The smallest feasible capacity is found by a search over capacities in which every round tries
many of them at once; a capacity is feasible if greedy filling, group by group in order, needs no
more than the given number of shards.  A greedy step is one filtered maximum over the sorted group
ends in the shared folder, so the driver holds only a few numbers per capacity.  The cuts then lie
as near to equal shares as that capacity allows.

Defined results: a null text has no bytes (size 1) and belongs with the empty texts; equal texts
are one group and share a shard; rows that repeat in full stay rows of their own; an empty table
gives an empty result; extra columns are ignored by the query.  Texts are told apart by 64-bit
hash, so two texts that collide would merely be kept together.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import materialise
from .ordering import running_total


class GroupEnds:
    """Sorted end offsets of the groups, asked by ranges."""

    def __init__(self, ends: DataFrame, total: int, largest: int):
        self.ends, self.total, self.largest = ends, total, largest

    def last_upto(self, limits: list[int]) -> list[int]:
        """For each limit, the greatest group end (or 0) that does not exceed it."""
        near = self.ends.filter(F.col("end").between(min(limits) - self.largest, max(limits)))
        row = near.agg(*(F.max(F.when(F.col("end") <= x, F.col("end"))) for x in limits)).first()
        return [v or 0 for v in row]

    def first_from(self, limit: int) -> int:
        """The least group end that is not below ``limit`` (0 counts as an end)."""
        if limit <= 0:
            return 0
        return self.ends.filter(F.col("end").between(limit, limit + self.largest)).agg(F.min("end")).first()[0]

    def reach(self, capacities: list[int], shards: int) -> list[int]:
        at = [0] * len(capacities)
        for _ in range(shards):
            at = self.last_upto([x + c for x, c in zip(at, capacities, strict=True)])
        return at


def smallest_capacity(ends: GroupEnds, shards: int, tries: int = 48) -> int:
    low = max(-(-ends.total // shards), ends.largest)
    high = min(ends.total, -(-ends.total // shards) + ends.largest)  # greedy always fits into this
    while low < high:
        step = max(1, -(-(high - low) // (tries + 1)))
        capacities = list(range(low, high, step))
        reached = ends.reach(capacities, shards)
        fits = [c for c, x in zip(capacities, reached, strict=True) if x == ends.total]
        high = min([high, *fits])
        low = max([low, *(c + 1 for c in capacities if c < high)])
    return high


def balanced_cuts(ends: GroupEnds, shards: int, capacity: int) -> list[int]:
    """End offset of each shard but the last: nearest to equal shares among the cuts that keep ``capacity``."""
    least = [ends.total]
    for _ in range(shards - 1):
        least.append(ends.first_from(least[-1] - capacity))
    least.reverse()  # least[i]: where shard i must end at the earliest
    cuts, at = [], 0
    for i in range(shards - 1):
        share = (i + 1) * ends.total // shards
        at = ends.last_upto([min(at + capacity, max(least[i], share, at))])[0]
        cuts.append(at)
    return cuts


def minimax_shards(rows: DataFrame, order: list[str], size: str = "size", shards: int = 8) -> DataFrame:
    """``rows`` with ``shard`` and ``slot`` (row number in the shard).

    ``order[0]`` names the atomic groups and orders them; further columns order the rows of a
    group.  ``size`` is a positive long.  ``rows`` should be narrow: it is written twice.  Columns of
    ``rows`` called shard or slot are replaced.
    """
    spark = rows.sparkSession
    # the rows' own columns travel in a struct, so that none can clash with a helper
    kept = [c for c in rows.columns if c not in ("shard", "slot")]
    rows = rows.select(F.struct(*(F.col(f"`{c}`") for c in kept)).alias("_row"), F.col(size).alias("_size"), *(F.col(c).alias(f"_order{k}") for k, c in enumerate(order)))
    order, size = [f"_order{k}" for k in range(len(order))], "_size"
    placed = running_total(rows, order, order[0], size, "shard-rows")
    parts = placed.groupBy("pid").agg(F.count("*").alias("n"), F.max("upto").alias("bytes"), F.min(order[0]).alias("first"), F.max(order[0]).alias("last")).orderBy("pid").collect()  # a row per part
    offsets, at_row, at_byte = [], 0, 0
    for i, p in enumerate(parts):
        goes_on = i + 1 < len(parts) and parts[i + 1]["first"] == p["last"]
        offsets.append((p["pid"], at_row, at_byte, p["n"] - 1 if goes_on else -1))
        at_row, at_byte = at_row + p["n"], at_byte + p["bytes"]
    table = spark.createDataFrame(offsets, "pid int, row0 long, byte0 long, open_idx long")
    full = placed.join(F.broadcast(table), "pid").withColumns({"end": F.col("byte0") + F.col("upto"), "row": F.col("row0") + F.col("idx")})
    if at_row:
        largest = rows.groupBy(order[0]).agg(F.sum(size).alias("s")).agg(F.max("s")).first()[0]
        ends = GroupEnds(materialise(full.filter("ends and idx != open_idx").select("end"), "shard-ends"), at_byte, largest)
        cuts = balanced_cuts(ends, shards, smallest_capacity(ends, shards))
        starts = [0, *full.agg(*(F.count_if(F.col("end") <= c) for c in cuts)).first()]
    else:
        cuts, starts = [0] * (shards - 1), [0] * shards
    shard = sum((F.when(F.col("end") > c, 1).otherwise(0) for c in cuts), F.lit(0))
    out = full.withColumn("shard", shard.cast("int"))
    out = out.withColumn("slot", F.col("row") - F.element_at(F.array(*(F.lit(s).cast("long") for s in starts)), F.col("shard") + 1))
    return out.select(*(F.col(f"_row.`{c}`").alias(c) for c in kept), "shard", "slot")


def sized(docs: DataFrame, text: str = "text") -> list:
    """Columns ``size`` and ``text_crc32`` of a text."""
    raw = F.coalesce(F.col(text), F.lit("")).cast("binary")
    return [(F.octet_length(raw) + 1).cast("long").alias("size"), F.crc32(raw).alias("text_crc32")]


def op6_minimax_shards(spark, sf_dir) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    narrow = materialise(docs.select("doc_id", *sized(docs), F.xxhash64(F.coalesce("text", F.lit(""))).alias("same_text")), "shard-input")
    out = minimax_shards(narrow, ["same_text", "doc_id"])
    return out.select("doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"))
