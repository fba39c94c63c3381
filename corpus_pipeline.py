"""The corpus pipeline: quality rules, near-duplicate removal, decontamination, mixing and sharding.

Every stage takes (spark, docs, sf_dir) and works on all rows its predecessor kept; all but the
last return the columns of ``documents``.  The order that mixing decides is carried by the files a
stage is written to: their part numbers and row numbers give the sharding stage its order.  A stage
deletes the scratch tables of the stage before on the same tables, unless its own input still reads them.

Defined results: null and empty texts fall to the base rule of the quality stage; rows that repeat
are judged each, and those with the least doc_id of their group stay together; an empty table gives
an empty result at every stage; columns beyond those of ``documents`` are left out, whatever their names.
"""

from __future__ import annotations

import threading

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from volume_engine.llm.common import drop_scratch, materialise, reads_scratch, scratch_mark
from volume_engine.llm.decontamination import bounded, leaks
from volume_engine.llm.jaccard_join import link_components
from volume_engine.llm.mixing import mix
from volume_engine.llm.quality_rules import judge
from volume_engine.llm.sharding import minimax_shards, sized

COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]
_last: dict[tuple, list[tuple[int, int]]] = {}


def _fresh(docs: DataFrame, sf_dir) -> int:
    """Drop what stages before left behind and ``docs`` does not read; return where this stage's tables begin."""
    key = (threading.get_ident(), sf_dir)
    left = []
    for marks in _last.pop(key, []):
        if reads_scratch(docs, *marks):
            left.append(marks)
        else:
            drop_scratch(docs.sparkSession, *marks)
    _last[key] = left
    return scratch_mark()


def _done(begin: int, out: DataFrame, sf_dir) -> DataFrame:
    _last.setdefault((threading.get_ident(), sf_dir), []).append((begin, scratch_mark()))
    return out


def quality(spark, docs, sf_dir) -> DataFrame:
    """Documents whose posterior quality is good and that pass the base rule."""
    begin = _fresh(docs, sf_dir)
    return _done(begin, judge(docs.select(*COLUMNS)).filter("kept").select(*COLUMNS), sf_dir)


def near_duplicates(spark, docs, sf_dir) -> DataFrame:
    """One document, the one of least doc_id, of every group linked by shingle similarity."""
    begin = _fresh(docs, sf_dir)
    docs = docs.select(*COLUMNS)
    linked = materialise(link_components(docs).filter("doc_id != component_id").select("doc_id").distinct(), "dropped-copies")
    return _done(begin, docs.join(bounded(linked), "doc_id", "left_anti").select(*COLUMNS), sf_dir)


def decontaminate(spark, docs, sf_dir) -> DataFrame:
    """Documents without a window that matches a benchmark item."""
    begin = _fresh(docs, sf_dir)
    docs = docs.select(*COLUMNS)
    found = leaks(docs.select("doc_id", "text"), spark.read.parquet(f"{sf_dir}/benchmark.parquet"))
    found = materialise(found.select("doc_id").distinct(), "dropped-leaks")
    return _done(begin, docs.join(bounded(found), "doc_id", "left_anti").select(*COLUMNS), sf_dir)


def mixing(spark, docs, sf_dir) -> DataFrame:
    """All documents, written in the order of the mixed sources."""
    begin = _fresh(docs, sf_dir)
    mixed = mix(docs.select(*COLUMNS))
    return _done(begin, mixed.repartitionByRange("position").sortWithinPartitions("position").select(*COLUMNS), sf_dir)


def sharding(spark, docs, sf_dir) -> DataFrame:
    """doc_id, size, text_crc32, place (its number in file order), shard and slot of every document."""
    begin = _fresh(docs, sf_dir)
    if not docs.inputFiles():
        docs = materialise(docs.select(*COLUMNS), "shard-docs")
    part = F.coalesce(F.expr("try_cast(regexp_extract(_metadata.file_name, 'part-([0-9]+)', 1) as bigint)"), F.lit(0))
    rows = docs.select("doc_id", *sized(docs), (part * (1 << 40) + F.col("_metadata.row_index")).alias("place"))
    return _done(begin, minimax_shards(materialise(rows, "shard-input"), ["place", "doc_id"]), sf_dir)


STAGES = [
    ("quality rules", quality),
    ("near duplicates", near_duplicates),
    ("decontamination", decontaminate),
    ("mixing", mixing),
    ("sharding", sharding),
]
#: Expectation-maximisation and scheduling have no SQL form; the pipeline is tested against brute force.
ORACLE_SQL = None


def run(spark, sf_dir) -> DataFrame:
    """All stages over ``documents``, each written to the shared folder and read again."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES[:-1]:
        docs = materialise(stage(spark, docs, sf_dir), name.replace(" ", "-"))
    return STAGES[-1][1](spark, docs, sf_dir)
