"""Token ids in flat binary files that are mapped into memory.

A shard is two files: `<name>.bin`, unsigned little-endian ids one after another, and `<name>.idx`, little-endian
64-bit numbers: a mark, bytes per id, the number n of documents, n + 1 offsets (in ids), n doc_ids. Shards follow one
another in ascending doc_id order; the id count before a shard, its base, is the prefix sum over the shards before it.
"""

from __future__ import annotations

import uuid
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyarrow import fs
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import shared_root, ship, text_slices
from .ragged import GATHER_BYTES
from .wordtok import word_tokenizer

MARK = 0x544F4B4944583031
END = 2
#: Stands for a null doc_id in an index.
NO_ID = -(1 << 63)
#: Ids of one document that are read into memory at a time.
READ = 1 << 20


def _open(uri: str) -> tuple[fs.FileSystem, str]:
    return fs.FileSystem.from_uri(uri if "://" in uri else uri.replace("file:", "file://", 1) if uri.startswith("file:") else f"file://{uri}")


def _write(path: str, folder: str, end: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tokenizer = word_tokenizer(path)
        size = 2 if tokenizer.tokenizer.get_vocab_size() <= 1 << 16 else 4
        # each attempt of a task writes files of its own; the manifest names those of the attempt that succeeded
        name, out, at, offsets, docs, tie = uuid.uuid4().hex, None, 0, [np.zeros(1, np.int64)], [], 0
        system, where = _open(folder)
        for b in text_slices(batches, limit=GATHER_BYTES):
            if out is None:
                out, tie = system.open_output_stream(f"{where}/{name}.bin"), b.column("tie")[0].as_py()
            ids, bounds = tokenizer(b.column("text"))
            n = b.num_rows
            rows = np.empty(len(ids) + n, f"<u{size}")
            ends = bounds[1:] + np.arange(n)
            mask = np.ones(len(rows), bool)
            mask[ends] = False
            rows[mask], rows[ends] = ids, end
            out.write(rows.tobytes())
            offsets.append(at + ends + 1)
            at += len(rows)
            docs.append(b.column("doc_id").fill_null(NO_ID).to_numpy(zero_copy_only=False))
        if out is None:
            return
        out.close()
        docs = np.concatenate(docs)
        with system.open_output_stream(f"{where}/{name}.idx") as index:
            index.write(np.concatenate([np.array([MARK, size, len(docs)], "<i8"), *offsets, docs]).astype("<i8").tobytes())
        yield pa.RecordBatch.from_pylist([{"name": name, "first": int(docs[0]), "tie": tie, "n_docs": len(docs), "n_ids": at}])

    return run


def write_shards(docs: DataFrame, path: str, folder: str | None = None, end: int = END) -> tuple[str, list[dict]]:
    """Writes every row of docs (doc_id, text) in ascending doc_id order; returns the folder and the shards with their bases.

    Rows are range-partitioned by doc_id; only doc_ids are sampled for that. The driver gets one row per shard.
    """
    spark = docs.sparkSession
    ship(spark)
    folder = folder or f"{shared_root(spark)}"
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text", F.xxhash64("text").alias("tie"))
    ordered = rows.repartitionByRange("doc_id", "tie").sortWithinPartitions("doc_id", "tie")
    made = ordered.mapInArrow(_write(path, folder, end), "name string, first long, tie long, n_docs long, n_ids long").collect()
    shards, base = [], 0
    for r in sorted((r.asDict() for r in made), key=lambda r: (r["first"], r["tie"])):
        shards.append(r | {"base": base})
        base += r["n_ids"]
    return folder, shards


class Shard:
    """A shard's arrays: mapped where the folder is local, read in ranges elsewhere."""

    def __init__(self, folder: str, name: str):
        system, where = _open(folder)
        path = f"{where}/{name}"
        if isinstance(system, fs.LocalFileSystem):
            index = np.memmap(f"{path}.idx", "<i8", "r")
        else:
            with system.open_input_file(f"{path}.idx") as f:
                index = np.frombuffer(f.read(), "<i8")
        if index[0] != MARK:
            raise ValueError(f"{path}.idx is no index")
        size, n = int(index[1]), int(index[2])
        self.offsets, self.docs = index[3 : 4 + n], index[4 + n : 4 + 2 * n]
        self.dtype, self.file = np.dtype(f"<u{size}"), None
        if isinstance(system, fs.LocalFileSystem):
            self.map = np.memmap(f"{path}.bin", self.dtype, "r")
        else:
            self.map, self.file = None, system.open_input_file(f"{path}.bin")

    def __enter__(self) -> Shard:
        return self

    def __exit__(self, *_) -> None:
        if self.file:
            self.file.close()

    def ids(self, start: int, end: int) -> np.ndarray:
        if self.map is not None:
            return self.map[start:end]
        self.file.seek(start * self.dtype.itemsize)
        return np.frombuffer(self.file.read((end - start) * self.dtype.itemsize), self.dtype)


def _read(folder: str):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for row in b.to_pylist():
                with Shard(folder, row["name"]) as s:
                    crc = np.zeros(len(s.docs), np.int64)
                    for i, (start, end) in enumerate(zip(s.offsets[:-1].tolist(), s.offsets[1:].tolist(), strict=True)):
                        c = 0
                        for at in range(start, end, READ):
                            c = zlib.crc32(s.ids(at, min(end, at + READ)).astype("<u4").tobytes(), c)
                        crc[i] = c
                    docs = np.array(s.docs)
                    yield pa.record_batch([pa.array(docs, mask=docs == NO_ID), pa.array(row["base"] + s.offsets[:-1]), pa.array(np.diff(s.offsets)), pa.array(crc)], ["doc_id", "start", "n_tokens", "ids_crc32"])

    return run


def read_shards(spark, folder: str, shards: list[dict]) -> DataFrame:
    """doc_id, start (ids of all documents before), n_tokens, ids_crc32 of each document, from the files; a task per shard."""
    ship(spark)
    rows = spark.createDataFrame([(s["name"], s["base"]) for s in shards], "name string, base long").repartition(max(1, len(shards)))
    return rows.mapInArrow(_read(folder), "doc_id long, start long, n_tokens long, ids_crc32 long")


def round_trip(docs: DataFrame, path: str, end: int = END) -> DataFrame:
    """write_shards() and read_shards() of every row of docs.

    Null text counts as empty, so its document is the end id alone; a null doc_id sorts first and comes back null;
    rows that repeat a doc_id are ordered by their text's hash; an empty table gives an empty one.
    """
    folder, shards = write_shards(docs, path, end=end)
    return read_shards(docs.sparkSession, folder, shards)
