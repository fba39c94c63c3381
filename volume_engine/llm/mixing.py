"""Mixing sources to target weights by proportionate-fair scheduling.

The rows of a source are cut into blocks.  Under weight w, block j of a source (from 1) may not
start before slot floor((j - 1) / w) and must be out by slot ceil(j / w); in every slot the
released block with the earliest deadline goes next.  Weights are exact fractions and the driver
works out the slots of all blocks, some at a time, so before any slot, each source that has not run
out has had its weighted share of slots to within less than one block, whatever the number of slots
and sources.  Where a source has run out its slots stay empty and the others close up.

Defined results: a null source is a source of its own; null and empty texts are rows like others;
rows that repeat keep their number; an empty table gives an empty result; all rows are kept; extra
columns pass through ``mix``, but for those with the names of the columns it adds, which are replaced.
"""

from __future__ import annotations

import heapq
import math
from collections.abc import Iterator, Mapping
from fractions import Fraction
from functools import reduce
from itertools import islice

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import materialise
from .ordering import place

NO_SOURCE = "\x00null"
ADDED = ("block", "release", "deadline", "slot", "position")
PLAN = {"_source": pa.string(), "block": pa.int64(), "release": pa.int64(), "deadline": pa.int64(), "slot": pa.int64(), "_start": pa.int64()}
#: Blocks of the schedule that the driver holds at once.
PLAN_BLOCKS = 1_000_000


def units(weights: Mapping[str, float], period: int) -> dict[str, int]:
    """Weights as whole units that sum to ``period``, at least one each (largest remainders)."""
    names = sorted(weights)
    total = sum(weights[s] for s in names)
    spare = period - len(names)
    if spare < 0:
        raise ValueError("more sources than slots in the period")
    exact = {s: spare * weights[s] / total for s in names}
    out = {s: 1 + int(exact[s]) for s in names}
    for s in sorted(names, key=lambda s: (int(exact[s]) - exact[s], s))[: period - sum(out.values())]:
        out[s] += 1
    return out


def blocks_in_order(weights: Mapping[str, float], blocks: Mapping[str, int]) -> Iterator[tuple[str, int, int, int, int]]:
    """(source, block from 0, release, deadline, slot) of all blocks, earliest deadline first; what is held is one block a source."""
    if any(not 0 < weights[s] < math.inf for s in blocks):
        raise ValueError("weights must be positive and finite")
    exact = {s: Fraction(weights[s]) for s in blocks}
    scale = math.lcm(*(w.denominator for w in exact.values()))
    units_of = {s: int(w * scale) for s, w in exact.items()}
    total = sum(units_of.values())
    coming = [(0, -units_of[s], s, 0) for s in blocks if blocks[s]]
    heapq.heapify(coming)
    ready: list[tuple[int, int, str, int, int]] = []
    slot = 0
    while coming or ready:
        if not ready:
            slot = max(slot, coming[0][0])
        while coming and coming[0][0] <= slot:
            release, k, s, j = heapq.heappop(coming)
            heapq.heappush(ready, (-((j + 1) * total // k), k, s, j, release))
        deadline, k, s, j, release = heapq.heappop(ready)
        if deadline <= slot:
            raise AssertionError("a block missed its deadline")
        yield s, j, release, deadline, slot
        if j + 1 < blocks[s]:
            heapq.heappush(coming, ((j + 1) * total // -k, k, s, j + 1))
        slot += 1


def schedule(shares: Mapping[str, int]) -> dict[str, list[tuple[int, int, int]]]:
    """(release, deadline, slot) of each source's blocks in one period, earliest deadline first."""
    out: dict[str, list[tuple[int, int, int]]] = {s: [] for s in shares}
    for s, _, *times in blocks_in_order(shares, shares):
        out[s].append(tuple(times))
    return out


def placed_blocks(spark, weights: Mapping[str, float], counts: Mapping[str, int], block_rows: int) -> DataFrame:
    """The schedule of all blocks with ``_start``, the position of a block's first row, written piece by piece."""
    order = blocks_in_order(weights, {s: -(-n // block_rows) for s, n in counts.items()})
    start, pieces = 0, []
    while not pieces or piece:
        piece = []
        for s, j, *times in islice(order, PLAN_BLOCKS):
            piece.append((s, j, *times, start))
            start += min(block_rows, counts[s] - j * block_rows)
        if piece or not pieces:
            columns = list(zip(*piece, strict=True)) or [()] * len(PLAN)
            plan = spark.createDataFrame(pa.table([pa.array(c, t) for c, t in zip(columns, PLAN.values(), strict=True)], names=list(PLAN)))
            pieces.append(materialise(plan, f"mix-plan-{len(pieces)}"))
    return reduce(DataFrame.unionByName, pieces)


def default_weights(counts: Mapping[str, int], temperature: float = 0.5) -> dict[str, float]:
    """Target weights that flatten the sources' sizes."""
    return {s: n**temperature for s, n in counts.items()}


def mix(docs: DataFrame, weights: Mapping[str, float] | None = None, source: str = "source", doc_id: str = "doc_id", block_rows: int = 64, period: int | None = None, seed: int = 0) -> DataFrame:
    """``docs`` with ``block``, ``release``, ``deadline``, ``slot`` and the gapless ``position`` of the mixed order.

    The rows of a source follow a seeded hash of ``doc_id``.  A caller who gives a ``period`` has the
    weights rounded to whole slots of it first.  The driver's time grows with the number of blocks;
    what it holds is bounded by the sources and a piece of the schedule.
    """
    spark = docs.sparkSession
    # the rows' own columns travel in a struct, so that none can clash with a helper
    kept = [c for c in docs.columns if c not in ADDED]
    packed = F.struct(*(F.col(f"`{c}`") for c in kept)).alias("_row")
    named = docs.select(F.coalesce(F.col(source), F.lit(NO_SOURCE)).alias("_source"), F.xxhash64(F.col(doc_id), F.lit(seed)).alias("_draw"), F.col(doc_id).alias("_id"), packed)
    placed = place(named, ["_source", "_draw", "_id"], "mix-rows")
    runs = placed.groupBy("_source", "pid").agg(F.count("*").alias("n"), F.min("idx").alias("idx0")).collect()  # parts + sources rows at most
    counts: dict[str, int] = {}
    table = []
    for r in sorted(runs, key=lambda r: (r["_source"], r["pid"])):
        table.append((r["_source"], r["pid"], counts.get(r["_source"], 0) - r["idx0"]))
        counts[r["_source"]] = counts.get(r["_source"], 0) + r["n"]
    offsets = spark.createDataFrame(table, "_source string, pid int, shift long")
    wanted = default_weights(counts) if weights is None else {s: weights[s] for s in counts}
    if period and counts:
        wanted = units(wanted, max(period, len(counts)))
    plan = placed_blocks(spark, wanted, counts, block_rows)
    ranked = placed.join(F.broadcast(offsets), ["_source", "pid"]).withColumn("_rank", F.col("idx") + F.col("shift"))
    found = ranked.withColumn("block", F.expr(f"_rank div {block_rows}")).join(plan, ["_source", "block"])
    return found.select(*(F.col(f"_row.`{c}`").alias(c) for c in kept), *ADDED[:-1], F.expr(f"_start + _rank % {block_rows}").alias("position"))


def op7_pfair_mix(spark, sf_dir) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    return mix(materialise(docs.select("doc_id", "source"), "mix-input"))
