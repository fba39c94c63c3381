"""The packed node buffer: words in breadth-first order, patched by change events, by uploads and, as baseline, rebuilt.

A buffer is a relation (idx, word) without rows for nodes that do not exist; ``full`` writes those as 0.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import codec
from ..functions.grid import VolumeMeta, bfs_base


def node_words(kept: DataFrame, vm: VolumeMeta) -> DataFrame:
    """Words of collapsed nodes with nothing in the brick buffer: level, key, idx, word.

    A node's child-group pointer is its own number plus one; 0 says that it has no children.
    """
    payload = codec.pack_averages([F.col(f"avg{c}") for c in range(vm.channels)])
    group = F.when(F.col("leaf"), 0).otherwise(F.col("idx") + 1)
    return kept.select("level", "key", "idx", codec.encode_node(F.lit(False), F.col("has_brick"), group, payload).alias("word"))


def full(words: DataFrame, vm: VolumeMeta) -> DataFrame:
    """All words of the complete tree, 0 where there is no node: the baseline that a rebuild sends."""
    every = words.sparkSession.range(bfs_base(vm.top + 1)).select(F.col("id").alias("idx"))
    return every.join(words.select("idx", "word"), "idx", "left").select("idx", F.coalesce("word", F.lit(0).cast("long")).alias("word"))


def level_counts(words: DataFrame, vm: VolumeMeta) -> DataFrame:
    """Per level of the complete tree (level, words, nodes): its words, and those that belong to a node.

    The other words are 0 and are counted in closed form, as the complete tree grows eightfold with
    each level whatever the volume holds.
    """
    every = words.sparkSession.range(vm.top + 1).select(F.col("id").cast("int").alias("level"), F.expr(f"shiftleft(1L, cast(3 * ({vm.top} - id) as int))").alias("words"))
    held = words.groupBy("level").agg(F.count("*").alias("nodes"))
    return every.join(held, "level", "left").select("level", "words", F.coalesce("nodes", F.lit(0)).alias("nodes"))


def change_events(old: DataFrame, new: DataFrame) -> DataFrame:
    """Events (kind, idx, word) between two buffers; a changed flag, pointer or average is an update."""
    both = old.select("idx", F.col("word").alias("was")).join(new.select("idx", "word"), "idx", "full")
    kind = F.when(F.col("was").isNull(), "create").when(F.col("word").isNull(), "delete").when(F.col("was") != F.col("word"), "update")
    return both.select(kind.alias("kind"), "idx", F.coalesce("word", F.lit(0).cast("long")).alias("word")).filter("kind is not null")


def patch(buffer: DataFrame, events: DataFrame) -> DataFrame:
    """The buffer after some events; what they do not name stays as it is, loaded bricks included.

    A created or updated entry is written with nothing in the brick buffer, so its brick is loaded
    anew; parents whose children come or go are named by events of their own.
    """
    both = buffer.join(events.select("idx", "kind", F.col("word").alias("now")), "idx", "full")
    return both.filter("kind is null or kind != 'delete'").select("idx", F.coalesce("now", "word").alias("word"))


def load(buffer: DataFrame, slots: DataFrame, averages: DataFrame) -> DataFrame:
    """The buffer with the bricks of ``slots`` (idx, slot) in the brick buffer and all others out of it.

    Only entries whose residency changes get a new word: the slot's address with the flag set, or the
    packed averages (idx, payload) with the flag cleared.
    """
    rest = F.col("word").bitwiseAND(F.lit((1 << (2 + codec.POINTER_BITS)) - codec.IN_BUFFER - 1).cast("long"))
    was = F.col("word").bitwiseAND(F.lit(codec.IN_BUFFER).cast("long")) != 0
    rows = buffer.join(slots, "idx", "left").join(averages, "idx", "left")
    loaded = rest.bitwiseOR(F.lit(codec.IN_BUFFER).cast("long")).bitwiseOR(F.shiftleft(F.col("slot").cast("long"), 2 + codec.POINTER_BITS))
    emptied = rest.bitwiseOR(F.shiftleft(F.col("payload"), 2 + codec.POINTER_BITS))
    return rows.select("idx", F.when(F.col("slot").isNotNull(), loaded).when(was, emptied).otherwise(F.col("word")).alias("word"))
