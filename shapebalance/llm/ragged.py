"""Encodes batches of texts chunk by chunk: each distinct chunk of a batch once, the rest by array gathers.

A splitter says where a tokenizer never merges across, so encoding chunks one by one gives the ids of the whole text.
Chunks met before come from a memo of two generations, which bounds its size and forgets what is rare.
"""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

#: Bytes of text in one gather.
GATHER_BYTES = 4_000_000


class Memo:
    """At most 2 * limit entries; the older half goes when the younger half is full. Long keys are never kept."""

    def __init__(self, limit: int = 200_000, longest: int = 64):
        self.limit, self.longest, self.young, self.old = limit, longest, {}, {}

    def many(self, keys: list[str], make: Callable[[list[str]], list[bytes]]) -> list[bytes]:
        young, old = self.young, self.old
        found = [young.get(k) for k in keys]
        missing = []
        for i, v in enumerate(found):
            if v is None:
                if (v := old.get(keys[i])) is None:
                    missing.append(i)
                else:
                    found[i] = young[keys[i]] = v
        if missing:
            for i, v in zip(missing, make([keys[i] for i in missing]), strict=True):
                found[i] = v
                if len(keys[i]) <= self.longest:
                    young[keys[i]] = v
        if len(young) > self.limit:
            self.young, self.old = {}, young
        return found


def gather(chunks: pa.ListArray, memo: Memo, make: Callable[[list[str]], list[bytes]], lead: str = "", dtype=np.uint16) -> tuple[np.ndarray, np.ndarray]:
    """Ids of all texts in a row, and n + 1 offsets of the texts in them.

    chunks: one list of chunks for each text. make: ids (bytes of dtype) of chunks. lead: what stood before every
    chunk but a text's first, where the splitter took it away.
    """
    at = np.asarray(chunks.offsets, dtype=np.int64)
    at = at - at[0]
    flat = chunks.flatten()
    if isinstance(flat, pa.ChunkedArray):
        flat = flat.combine_chunks()
    if not len(flat):
        return np.zeros(0, dtype), np.zeros(len(at), np.int64)
    coded = flat.dictionary_encode()
    index = coded.indices.to_numpy(zero_copy_only=False).astype(np.int64)
    names = coded.dictionary.to_pylist()
    if lead:
        first = np.zeros(len(index), np.int64)
        first[at[:-1][at[:-1] < at[1:]]] = 1
        index = index * 2 + first
        used = np.flatnonzero(np.bincount(index, minlength=2 * len(names)))
        place = np.zeros(2 * len(names), np.int64)
        place[used] = np.arange(len(used))
        index = place[index]
        names = [names[k >> 1] if k & 1 else lead + names[k >> 1] for k in used.tolist()]
    ids = memo.many(names, make)
    width = np.dtype(dtype).itemsize
    sizes = np.fromiter(map(len, ids), np.int64, len(ids)) // width
    table = np.frombuffer(b"".join(ids), dtype)
    begin = np.cumsum(sizes) - sizes
    each = sizes[index]
    ends = np.cumsum(each)
    total = int(ends[-1])
    pick = np.arange(total, dtype=np.int64) + np.repeat(begin[index] - (ends - each), each)
    bounds = np.concatenate(([0], ends))[at]
    return table[pick], bounds


def woven(parts: tuple[np.ndarray, np.ndarray], rows: np.ndarray, own: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    """gather()'s result for all texts but those in `rows`, with theirs put in at their places."""
    ids, at = parts
    n = len(at) - 1 + len(rows)
    rest = iter(zip(at[:-1], at[1:], strict=True))
    extra = dict(zip(rows.tolist(), own, strict=True))
    out = [extra[i] if i in extra else ids[slice(*next(rest))] for i in range(n)]
    return np.concatenate([ids[:0], *out]), np.concatenate(([0], np.cumsum([len(p) for p in out]))).astype(np.int64)
