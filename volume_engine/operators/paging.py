"""Demand paging and brick slots: uploads by policy and budget, LRU pages by stack distance or ordered fold, version deltas."""

from __future__ import annotations

from bisect import bisect_left
from collections import OrderedDict

import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def plan_uploads(candidates: DataFrame, slots: int, policy: str = "coarse_first") -> DataFrame:
    """The ``slots`` bricks that stay or come: ``candidates`` (level, key, used, resident, waiting, seq).

    ``coarse_first``: used or requested bricks by coarser level, residents before newcomers, then
    unused residents; ``fifo``: requests as they came; ``replace_all``: requests by waiting rays.
    """
    if policy == "coarse_first":
        order = [F.desc("used"), F.desc("level"), F.desc("resident"), F.col("key")]
    elif policy == "fifo":
        candidates, order = candidates.filter("resident = 0"), [F.col("seq"), F.desc("level"), F.col("key")]
    elif policy == "replace_all":
        candidates, order = candidates.filter("resident = 0"), [F.desc("waiting"), F.desc("level"), F.col("key")]
    else:
        raise ValueError(policy)
    # a limited sort runs as a top-k: only ``slots`` rows meet in one task
    return candidates.orderBy(*order).limit(slots)


def within_budget(planned: DataFrame, order: list, size: str, budget: int) -> DataFrame:
    """The leading uploads whose sizes add up to at most ``budget`` (``planned`` holds at most the number of slots)."""
    running = F.sum(size).over(Window.orderBy(*order).rowsBetween(Window.unboundedPreceding, 0))
    return planned.withColumn("running", running).filter(F.col("running") <= budget)


TRACE = ["cache", "seq", "page"]


def _in_order(trace: DataFrame, columns: list[str]) -> DataFrame:
    """Each cache in one partition, its accesses in order; a partition may hold many caches."""
    return trace.select(*columns).repartition("cache").sortWithinPartitions("cache", "seq")


def simulate_lru(trace: DataFrame, capacity: int) -> DataFrame:
    """LRU with pins and write-back per cache: ``trace`` (cache, seq, page, write, pin, unpin) to (cache, seq, page, hit, evicted, written, blocked).

    The fold is sequential per cache.  It runs over Arrow batches with the cache's state carried on, so a
    task holds a batch and ``capacity`` pages, however long a trace is.
    """

    def run(batches):
        cache, held, pinned = None, OrderedDict(), set()
        for batch in batches:
            cols = [batch[k].to_pylist() for k in ("cache", "page", "write", "pin", "unpin")]
            hits, evicted, written, blocked = [], [], [], []
            for of, page, write, pin, unpin in zip(*cols, strict=True):
                if of != cache:
                    cache, held, pinned = of, OrderedDict(), set()
                hit, victim, saved, stuck = page in held, -1, 0, 0
                if not hit and len(held) >= capacity:
                    found = next((p for p in held if p not in pinned), None)
                    if found is None:
                        stuck = 1
                    else:
                        victim, saved = found, int(held.pop(found))
                if not stuck:
                    held[page] = held.get(page, False) or bool(write)
                    held.move_to_end(page)
                    if pin:
                        pinned.add(page)
                if unpin:
                    pinned.discard(page)
                hits.append(int(hit)), evicted.append(victim), written.append(saved), blocked.append(stuck)
            out = {k: pa.array(v, t) for k, v, t in (("hit", hits, pa.int32()), ("evicted", evicted, pa.int64()), ("written", written, pa.int32()), ("blocked", blocked, pa.int32()))}
            yield pa.record_batch({k: batch[k] for k in TRACE} | out)

    ordered = _in_order(trace, [*TRACE, "write", "pin", "unpin"])
    return ordered.mapInArrow(run, "cache long, seq long, page long, hit int, evicted long, written int, blocked int")


def stack_distances(trace: DataFrame) -> DataFrame:
    """For each access of ``trace`` (cache, seq, page): distinct pages since the page's last access (null: first access).

    Without pins an access hits if and only if that number is below the capacity, whatever the capacity.
    The times of the pages' last accesses are kept in order, so an access costs a search among the
    distinct pages of its cache.
    """

    def run(batches):
        cache, last, times = None, {}, []
        for batch in batches:
            found = []
            for of, seq, page in zip(*(batch[k].to_pylist() for k in TRACE), strict=True):
                if of != cache:
                    cache, last, times = of, {}, []
                before = last.get(page)
                if before is None:
                    found.append(None)
                else:
                    at = bisect_left(times, before)
                    found.append(len(times) - at - 1)
                    del times[at]
                last[page] = seq
                times.append(seq)
            yield pa.record_batch({k: batch[k] for k in TRACE} | {"distance": pa.array(found, pa.int64())})

    return _in_order(trace, TRACE).mapInArrow(run, "cache long, seq long, page long, distance long")


def serve_requests(requests: DataFrame, resident: DataFrame, pages_in_ram: DataFrame, page_bits: int = 6) -> DataFrame:
    """Requests (level, key) with their page and the tier that answers: ``gpu``, ``ram`` or ``disk``."""
    rows = requests.select("level", "key").withColumn("page", F.shiftright("key", page_bits))
    rows = rows.join(resident.select("level", "key", F.lit(1).alias("g")), ["level", "key"], "left")
    rows = rows.join(pages_in_ram.select("level", "page", F.lit(1).alias("m")), ["level", "page"], "left")
    return rows.select("level", "key", "page", F.when(F.col("g") == 1, "gpu").when(F.col("m") == 1, "ram").otherwise("disk").alias("tier"))


def assign_pages(bricks: DataFrame, per_page: int, order: str = "morton") -> DataFrame:
    """Bricks (level, key) with the page they are stored in: neighbours by Morton prefix, or by order of insertion (seq).

    ``insertion`` numbers bricks level by level; a level's numbering runs in one task per level.
    """
    if order == "morton":
        bits = max(0, per_page.bit_length() - 1)
        return bricks.select("level", "key", F.shiftright("key", bits).alias("page"))
    if order == "insertion":
        number = F.row_number().over(Window.partitionBy("level").orderBy("seq", "key")) - 1
        return bricks.select("level", "key", F.floor(number / per_page).alias("page"))
    raise ValueError(order)


def page_trace(accesses: DataFrame, page_bits: int = 6) -> DataFrame:
    """The page accesses (cache, seq, page) of an ordered list of brick accesses (cache, seq, level, key)."""
    return accesses.select("cache", "seq", F.col("level").cast("long").bitwiseOR(F.shiftleft(F.shiftright("key", page_bits), 5)).alias("page"))


def diff_versions(old: DataFrame, new: DataFrame, key: list[str], value: str) -> DataFrame:
    """Create, update and delete events between two versions of a keyed relation."""
    joined = old.withColumnRenamed(value, "old").join(new.withColumnRenamed(value, "new"), key, "full")
    kind = F.when(F.col("old").isNull(), "create").when(F.col("new").isNull(), "delete").when(F.col("old") != F.col("new"), "update")
    return joined.withColumn("kind", kind).filter("kind is not null")


def apply_delta(buffer: DataFrame, delta: DataFrame, key: list[str], value: str) -> DataFrame:
    """The patched relation; untouched rows are not recomputed."""
    joined = buffer.join(delta.select(*key, "kind", "new"), key, "full")
    return joined.filter("kind is null or kind != 'delete'").select(*key, F.coalesce("new", value).alias(value))
