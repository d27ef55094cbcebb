"""Packing into sequences by minimum bin slack.

A document's ids are cut into windows of the capacity; what remains is packed with other remainders. For one sequence
at a time, the longest remainder opens it, and a bitset of reachable sums over the multiset of the remaining lengths
shows how close the rest can be filled; walking the bitsets back gives how many remainders of each length to take.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Work, text_slices
from .wordtok import word_tokenizer

#: Remainders that one task packs together.
GROUP = 16_384
#: Bytes of text that a task encodes at once, and memo entries of its tokenizer's younger half: workers of earlier stages
#: keep their memory, so the pipeline's last stage takes little of its own.
ENCODE_BYTES, MEMO = 1_000_000, 50_000
#: The id that ends each document.
END = 1


def fill(counts: dict[int, int], capacity: int) -> dict[int, int]:
    """How many items of each length to take so that their sum comes closest to the capacity from below.

    The bitset's bit t says that t is a reachable sum. Lengths enter from the longest on, each in portions of 1, 2, 4 ...
    items, until the capacity is reached; the bitset before each portion is kept for the way back.
    """
    limit = (1 << capacity + 1) - 1
    reach, steps = 1, []
    for length in sorted(counts, reverse=True):
        left, portion = min(counts[length], capacity // length), 1
        while left and not reach >> capacity & 1:
            take = min(portion, left)
            steps.append((reach, length, take))
            reach |= reach << length * take & limit
            left -= take
            portion *= 2
        if reach >> capacity & 1:
            break
    at, taken = reach.bit_length() - 1, {}
    for before, length, take in reversed(steps):
        if not before >> at & 1:
            taken[length] = taken.get(length, 0) + take
            at -= length * take
    return taken


def pack_lengths(lengths: np.ndarray, capacity: int) -> tuple[np.ndarray, np.ndarray]:
    """Sequence number and offset of each item (1 <= length <= capacity). Deterministic; items of one length go in order."""
    sequence, offset = np.empty(len(lengths), np.int64), np.empty(len(lengths), np.int64)
    order = np.argsort(-lengths, kind="stable")
    sorted_lengths = lengths[order]
    values, first, counts = np.unique(-sorted_lengths, return_index=True, return_counts=True)
    queue = {int(-v): iter(order[f : f + c]) for v, f, c in zip(values, first, counts, strict=True)}
    left = {int(-v): int(c) for v, c in zip(values, counts, strict=True)}
    number = 0
    while left:
        longest = max(left)
        taken = {longest: 1}
        left[longest] -= 1
        for length, n in fill({k: n for k, n in left.items() if n and k <= capacity - longest}, capacity - longest).items():
            taken[length] = taken.get(length, 0) + n
            left[length] -= n
        at = 0
        for length, n in taken.items():
            for _ in range(n):
                i = next(queue[length])
                sequence[i], offset[i] = number, at
                at += length
            if not left[length]:
                del left[length]
        number += 1
    return sequence, offset


def _pieces(path: str, capacity: int, end: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tokenizer = word_tokenizer(path, MEMO)
        for b in text_slices(batches, limit=ENCODE_BYTES):
            ids, at = tokenizer(b.column("text"))
            out: list[tuple] = []
            for row, doc in enumerate(b.column("doc_id").to_pylist()):
                own = np.append(ids[at[row] : at[row + 1]], end).astype("<u4")
                for start in range(0, len(own), capacity):
                    part = own[start : start + capacity]
                    out.append((doc, start, len(part), zlib.crc32(part.tobytes()), len(own)))
            yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in zip(*out, strict=True)], ["doc_id", "start", "length", "ids_crc32", "doc_tokens"])

    return run


SCHEMA = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long"


def pack_documents(docs: DataFrame, path: str, capacity: int = 2048, end: int = END, group: int = GROUP) -> DataFrame:
    """One row per piece: doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset.

    Every row of docs (doc_id, text; other columns are ignored) counts as a document of its own; null text counts as
    empty and has the end id alone. Null doc_ids pass through; an empty table gives an empty one. Texts stay where they
    are read; only pieces (a few numbers) are written to the work folder and dealt out by hash
    in groups of about `group` remainders, each packed in one task. Sequence ids are unique, not dense.
    """
    work = Work(docs.sparkSession)
    pieces = work.table(docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(_pieces(path, capacity, end), SCHEMA), "pieces")
    groups = max(1, -(-pieces.where(F.col("length") < capacity).count() // group))
    full = pieces.where(F.col("length") == capacity).withColumn("n", F.monotonically_increasing_id())
    full = full.select("doc_id", "start", "length", "ids_crc32", "doc_tokens", (F.lit(-1) - F.col("n")).alias("sequence_id"), F.lit(0).cast("long").alias("offset"))

    def pack(rows: pd.DataFrame) -> pd.DataFrame:
        rows = rows.sort_values(["doc_id", "start", "ids_crc32", "length"], ignore_index=True)
        number, offset = pack_lengths(rows["length"].to_numpy(), capacity)
        return rows.drop(columns="g").assign(sequence_id=number + (rows["g"].to_numpy(np.int64) << 32), offset=offset)

    # rows that repeat one document must not meet in one group, so the row's number takes part in the hash
    g = F.pmod(F.xxhash64("doc_id", "start", F.monotonically_increasing_id()), F.lit(groups)).alias("g")
    rest = pieces.where(F.col("length") < capacity).select("*", g).groupBy("g").applyInPandas(pack, SCHEMA + ", sequence_id long, offset long")
    return full.unionByName(rest)
