"""Global order without a global sort task: range-placed rows with local positions, and offsets per part."""

from __future__ import annotations

import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import materialise


def place(df: DataFrame, order: list[str], label: str) -> DataFrame:
    """``df`` range-partitioned and sorted by ``order``, written once, with its part number ``pid`` and row number ``idx`` in it.

    Parts follow each other in the order.  Hot values of the first columns are split across parts
    as long as later order columns differ.
    """
    sized = df.repartitionByRange(*order).sortWithinPartitions(*order)
    placed = sized.withColumns({"pid": F.spark_partition_id(), "idx": F.monotonically_increasing_id().bitwiseAND((1 << 33) - 1)})
    return materialise(placed, label)


def running_total(df: DataFrame, order: list[str], key: str, size: str, label: str) -> DataFrame:
    """``place`` plus ``upto``, the sum of ``size`` in the part up to and with the row, and ``ends``, true on the last row of its key in the part."""
    ordered = df.repartitionByRange(*order).sortWithinPartitions(*order).withColumn("pid", F.spark_partition_id())
    schema = T.StructType([*ordered.schema.fields, *T._parse_datatype_string("idx long, upto long, ends boolean").fields])

    def close(batch: pa.Table, idx: int, total: int, following) -> tuple[pa.Table, int, int]:
        n = batch.num_rows
        upto = pc.add(pc.cumulative_sum(batch[size].combine_chunks()), total)
        keys = batch[key].combine_chunks()
        nxt = pa.concat_arrays([keys.slice(1), pa.array([following], keys.type)])
        ends = pc.fill_null(pc.not_equal(keys, nxt), True)
        ids = pa.array(range(idx, idx + n), pa.int64())
        table = batch.append_column("idx", ids).append_column("upto", upto).append_column("ends", ends)
        return table, idx + n, upto[-1].as_py()

    def run(batches):
        held, idx, total = None, 0, 0
        for batch in batches:
            if not batch.num_rows:
                continue
            if held is not None:
                out, idx, total = close(held, idx, total, batch[key][0].as_py())
                yield from out.to_batches()
            held = pa.Table.from_batches([batch])
        if held is not None:
            out, idx, total = close(held, idx, total, None)
            yield from out.to_batches()

    return materialise(ordered.mapInArrow(run, schema), label)
