"""Shared plumbing of the text operators: shared-folder tables, scan sizes and vectorised tokens."""

from __future__ import annotations

import gc
import uuid

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..storage import shared_dir

#: Java regular expression for the runs of white space between words (0x20 and 0x09-0x0D only).
SPACE_RUN = "[ \\t-\\r]+"
#: The characters of those runs, for trim.
SPACES = " \t\n\x0b\x0c\r"

_scratch: list[str] = []


def materialise(df: DataFrame, label: str) -> DataFrame:
    """Cut the lineage: write ``df`` as Parquet into the shared folder and read it back."""
    path = f"{shared_dir(df.sparkSession)}/{label}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    _scratch.append(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def reads_scratch(df: DataFrame, first: int, last: int) -> bool:
    """Whether ``df`` still reads tables written between two marks."""
    names = {path.rstrip("/").rsplit("/", 1)[-1] for path in _scratch[first:last] if path}
    return any(part in names for f in df.inputFiles() for part in f.split("/")[-2:])


def scratch_mark() -> int:
    """Number of tables written so far, for ``drop_scratch``."""
    return len(_scratch)


def drop_scratch(spark: SparkSession, first: int, last: int) -> None:
    """Delete the tables written between two marks, once nothing lazy reads them any more."""
    for path in _scratch[first:last]:
        if path:
            where = spark._jvm.org.apache.hadoop.fs.Path(path)
            where.getFileSystem(spark._jsc.hadoopConfiguration()).delete(where, True)
    _scratch[first:last] = [""] * (last - first)


def release(spark: SparkSession) -> None:
    """Let Spark delete the shuffle files of plans that are done: its cleaner acts on what the JVM has collected."""
    gc.collect()
    spark._jvm.System.gc()


def documents(spark: SparkSession, sf_dir: str, *columns: str) -> DataFrame:
    df = spark.read.parquet(f"{sf_dir}/documents.parquet")
    return df.select(*columns) if columns else df


def scan_bytes(df: DataFrame) -> int:
    """Catalyst's size estimate of ``df`` (file bytes for a scan); no job runs."""
    return int(str(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))


def crc_bucket(column: str, buckets: int):
    """crc32 of the column's text form modulo ``buckets``: the fold of a row."""
    return F.crc32(F.col(column).cast("string").cast("binary")) % buckets


def word_array(text):
    """Words of a text as a JVM array; null and blank texts give an empty array."""
    body = F.btrim(F.coalesce(text, F.lit("")), F.lit(SPACES))
    return F.when(body == "", F.array().cast("array<string>")).otherwise(F.split(body, SPACE_RUN))


# ---------------------------------------------------------------------------------------------
# numpy side: a batch of texts becomes one byte buffer, words become offsets and fingerprints.

_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32
_IS_SPACE = np.zeros(256, dtype=bool)
_IS_SPACE[[0x20, 9, 10, 11, 12, 13]] = True
_BYTE_CODE = np.random.RandomState(20240229).randint(1, 2**63 - 1, 256).astype(np.uint64) * np.uint64(2) + np.uint64(1)
_BASE = 0x9E3779B97F4A7C15 | 1
_BASE_INV = pow(_BASE, -1, 1 << 64)
_powers: dict[int, np.ndarray] = {}


def _power_table(base: int, n: int) -> np.ndarray:
    have = _powers.get(base)
    if have is None or len(have) < n:
        steps = np.full(max(n, 1 << 16), base, dtype=np.uint64)
        steps[0] = 1
        _powers[base] = have = np.cumprod(steps)
    return have


def mix64(x: np.ndarray) -> np.ndarray:
    """Finalising bit mixer for 64-bit fingerprints."""
    x = x.astype(np.uint64, copy=True)
    x ^= x >> np.uint64(30)
    x *= np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(27)
    x *= np.uint64(0x94D049BB133111EB)
    x ^= x >> np.uint64(31)
    return x


class TextBatch:
    """Texts of one slice of an Arrow column as one byte buffer.

    ``data`` holds the bytes with A-Z lowered, ``bounds`` the n + 1 document offsets;
    nulls count as empty texts.
    """

    def __init__(self, data: np.ndarray, bounds: np.ndarray):
        self.raw = data
        self.data = _LOWER[data]
        self.bounds = bounds
        self.n = len(bounds) - 1

    def words(self) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Start and end offset of each word, and the number of words of each document."""
        solid = ~_IS_SPACE[self.data]
        edge = np.empty(len(solid) + 1, dtype=bool)
        edge[0] = edge[-1] = True
        edge[1:-1] = solid[1:] != solid[:-1]
        edge[self.bounds] = True
        cuts = np.flatnonzero(edge)
        if not len(solid):
            return cuts[:0], cuts[:0], np.zeros(self.n, dtype=np.int64)
        starts, ends = cuts[:-1], cuts[1:]
        keep = solid[starts]
        starts, ends = starts[keep], ends[keep]
        counts = np.diff(np.searchsorted(starts, self.bounds))
        return starts, ends, counts

    def fingerprints(self, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
        """64-bit fingerprint of each byte range, from one running polynomial sum over the buffer."""
        if not len(starts):
            return np.zeros(0, dtype=np.uint64)
        sums = np.zeros(len(self.data) + 1, dtype=np.uint64)
        np.cumsum(_BYTE_CODE[self.data] * _power_table(_BASE, len(self.data))[: len(self.data)], out=sums[1:])
        return mix64((sums[ends] - sums[starts]) * _power_table(_BASE_INV, len(self.data) + 1)[starts])


def text_batches(column: pa.Array, limit: int = 4 << 20):
    """Cut an Arrow string column into (first row, TextBatch) slices of about ``limit`` bytes, without copying texts."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if len(column) == 0:
        return
    column = column.cast(pa.large_string()) if not pa.types.is_large_string(column.type) else column
    if column.null_count:
        column = column.fill_null("")
    offsets = np.frombuffer(column.buffers()[1], dtype=np.int64)[column.offset : column.offset + len(column) + 1]
    body = column.buffers()[2]
    data = np.frombuffer(body, dtype=np.uint8) if body is not None and body.size else np.zeros(0, np.uint8)
    first = 0
    while first < len(column):
        last = int(np.searchsorted(offsets, offsets[first] + limit, side="right")) - 1
        last = min(max(last, first + 1), len(column))
        yield first, TextBatch(data[offsets[first] : offsets[last]], offsets[first : last + 1] - offsets[first])
        first = last


def shingle_hashes(words: np.ndarray, counts: np.ndarray, width: int = 5) -> tuple[np.ndarray, np.ndarray]:
    """Fingerprints of every run of ``width`` words and the runs of each document.

    A document with fewer words gives its whole sequence as one shingle; one without words none.
    """
    ends = np.cumsum(counts)
    begins = ends - counts
    n = len(words)
    if not n:
        return np.zeros(0, np.uint64), np.zeros(len(counts), np.int64)
    rolled = np.zeros(n, dtype=np.uint64)
    span = np.minimum(counts, width)
    word_span = np.repeat(span, counts)
    word_end = np.repeat(ends, counts)
    at = np.arange(n)
    for k in range(width):
        take = at[(word_span > k) & (at + k < word_end)]
        rolled[take] = (rolled[take] ^ words[take + k]) * np.uint64(0xD6E8FEB86659FD93) + np.uint64(k + 1)
    keep = at + word_span <= word_end
    return mix64(rolled[keep]), np.where(counts > 0, counts - span + 1, 0)
