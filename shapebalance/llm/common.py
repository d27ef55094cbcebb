"""Shared plumbing of the corpus operators: work tables, code shipping, Arrow batches in slices."""

from __future__ import annotations

import contextlib
import ctypes
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..ship import ship
from ..sources.work import shared_root

#: Bytes of text that a Python worker holds in its arrays at once (one document may be longer).
SLICE_BYTES = 500_000
#: Rows of an id list that may be broadcast; beyond it the join shuffles both sides.
BROADCAST_IDS = 500_000
#: A key with over one in HOT_KEYS of all rows is joined by broadcast; there are fewer than HOT_KEYS of these.
HOT_KEYS = 1000


class Work:
    """Work tables of one operator call: Parquet in the shared folder, so that a lost executor costs no recomputation."""

    def __init__(self, spark: SparkSession):
        ship(spark)
        self.spark, self.root, self.n = spark, shared_root(spark), 0

    def table(self, df: DataFrame, name: str) -> DataFrame:
        """Writes df and returns a DataFrame that reads it back."""
        self.n += 1
        path = f"{self.root}/{self.n:03d}-{name}"
        df.write.parquet(path)
        return self.spark.read.schema(df.schema).parquet(path)

    def drop(self, *frames: DataFrame) -> None:
        """Deletes work tables that nothing reads any more."""
        sc = self.spark.sparkContext
        for df in frames:
            for f in {x.rpartition("/")[0] for x in df.inputFiles()}:
                p = sc._jvm.org.apache.hadoop.fs.Path(f)
                p.getFileSystem(sc._jsc.hadoopConfiguration()).delete(p, True)


def parts(spark: SparkSession) -> int:
    return max(1, int(spark.conf.get("spark.sql.shuffle.partitions", "200")))


def semi_join(df: DataFrame, ids: DataFrame, key: str, anti: bool = False) -> DataFrame:
    """Rows of df whose key is in ids (one column of that name, distinct), or is not: ids are broadcast if counted small, else both sides are shuffled."""
    if ids.count() <= BROADCAST_IDS:
        ids = F.broadcast(ids)
    return df.join(ids, key, "left_anti" if anti else "left_semi")


def spread_join(rows: DataFrame, values: DataFrame, keys: list[str], total: int | None = None, how: str = "inner") -> DataFrame:
    """rows with the columns of values, a written table of one row per key whose n bounds the rows of that key.

    Keys with over a HOT_KEYS-th of all rows (`total`, by default the sum of n) are fewer than HOT_KEYS and meet their
    rows by broadcast; the others are shuffled, and none of them fills a task. n stays. how: inner or left.
    """
    if total is None:
        total = values.agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0]
    hot = F.col("n") * HOT_KEYS > total
    few = values.where(hot)
    rest = rows.join(F.broadcast(few.select(*keys)), keys, "left_anti").join(values.where(~hot), keys, how)
    return rows.join(F.broadcast(few), keys).unionByName(rest)


def text_slices(batches: Iterator[pa.RecordBatch], column: str = "text", limit: int = SLICE_BYTES) -> Iterator[pa.RecordBatch]:
    """Cuts record batches into runs of rows with at most `limit` bytes of text, or one longer row."""
    for batch in batches:
        if not batch.num_rows:
            continue
        size = pc.fill_null(pc.binary_length(batch.column(column)), 0).to_numpy(zero_copy_only=False)
        run = np.cumsum(size, dtype=np.int64)
        at = 0
        while at < len(size):
            base = run[at - 1] if at else 0
            to = max(at + 1, int(np.searchsorted(run, base + limit, side="right")))
            yield batch.slice(at, to - at)
            at = to
    release()


def release() -> None:
    """Gives freed memory back to the system, as workers live on between stages."""
    pa.default_memory_pool().release_unused()
    with contextlib.suppress(OSError, AttributeError):
        ctypes.CDLL(None).malloc_trim(0)


def as_strings(column: pa.Array) -> pa.Array:
    """The column as large_string from offset 0 and without nulls: a null text counts as empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    s = pc.fill_null(column.cast(pa.large_string()), "")
    if not len(s):
        return s
    # some string kernels go wrong on slices, so the slice gets buffers of its own
    offsets = np.frombuffer(s.buffers()[1], np.int64)[s.offset : s.offset + len(s) + 1]
    data = s.buffers()[2] or pa.py_buffer(b"")
    return pa.LargeStringArray.from_buffers(len(s), pa.py_buffer(offsets - offsets[0]), data.slice(int(offsets[0]), int(offsets[-1] - offsets[0])))


def text_bytes(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """UTF-8 bytes of all texts in a row, and the n + 1 offsets of the texts in them."""
    s = as_strings(column)
    if not len(s):
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    return np.frombuffer(s.buffers()[2], np.uint8), np.frombuffer(s.buffers()[1], np.int64)
