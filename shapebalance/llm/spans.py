"""What the scanners for personal data and for secrets share: spans, their output columns and digests."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import SLICE_BYTES, ship, text_slices

#: start and end in code points (end exclusive), kind, score from 0 to 1.
Span = tuple[int, int, str, float]
SPANS = "array<struct<kind:string,start:int,`end`:int,score:double>>"
_TYPE = pa.list_(pa.struct([("kind", pa.string()), ("start", pa.int32()), ("end", pa.int32()), ("score", pa.float64())]))


def in_order(spans: list[Span], kinds: tuple[str, ...]) -> list[Span]:
    return sorted(spans, key=lambda s: (s[0], kinds.index(s[2]), s[1]))


def scan(docs: DataFrame, find: Callable[[str], list[Span]]) -> DataFrame:
    """doc_id and spans of every row's whole text; null text counts as empty. One narrow pass, a row at a time in memory."""
    ship(docs.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in text_slices(batches, limit=4 * SLICE_BYTES):
            found = [[{"kind": k, "start": s, "end": e, "score": x} for s, e, k, x in find(t.as_py())] if t.is_valid else [] for t in b.column("text")]
            yield pa.record_batch([b.column("doc_id"), pa.array(found, _TYPE)], ["doc_id", "spans"])

    return docs.select("doc_id", "text").mapInArrow(run, f"doc_id long, spans {SPANS}")


def written(spans: Column) -> Column:
    """kind:start:end of each span, comma-joined."""
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["start"], s["end"])), ",")


def _count(kind: str) -> Column:
    return F.size(F.filter("spans", lambda s: s["kind"] == kind)).cast("long")


def digests(scanned: DataFrame, base: tuple[str, ...]) -> DataFrame:
    """Counts of each base kind, the hash of the base spans, and all spans written out."""
    own = F.filter("spans", lambda s: s["kind"].isin(*base))
    return scanned.select(
        "doc_id",
        *[_count(k).alias(f"n_{k}") for k in base],
        F.sha2(written(own).cast("binary"), 256).alias("base_sha256"),
        written(F.col("spans")).alias("spans"),
    )
