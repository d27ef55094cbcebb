"""Quality by a factorisation machine over hashed words, structure statistics and the text's length.

Every pair of features interacts through the product of two short vectors. The sum over all pairs is half the square
of the summed vectors less the summed squares, so a text is scored in time linear in its features.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import release, ship, text_bytes, text_slices
from .hashing import span_hashes, word_spans
from .toxicity import BREAKS, held_out, labelled_texts


@dataclass(frozen=True)
class QualityConfig:
    #: Labelled rows to learn from at most, taken by a hash of doc_id.
    sample: int = 8_000
    buckets: int = 1 << 15
    rank: int = 8
    epochs: int = 14
    batch: int = 128
    rate: float = 0.1
    l2: float = 1e-5
    seed: int = 7
    threshold: float = 0.3
    held_out: int = 5


_STEPS = np.array([0, 0.002, 0.005, 0.01, 0.02, 0.04, 0.07, 0.1, 0.15, 0.2, 0.3, 0.4, 0.5, 0.6, 0.7, 0.8, 0.9, 1.0])
_BINS = 24


def _is(chars: str) -> np.ndarray:
    out = np.zeros(256, bool)
    out[list(chars.encode())] = True
    return out


_UPPER, _LETTER = _is("ABCDEFGHIJKLMNOPQRSTUVWXYZ"), _is("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz") | (np.arange(256) >= 128)
_COUNTED = (_UPPER, _is("|"), _is("!"), _is("#$%&*@^~=_+<>/\\{}[]"), _is("0123456789"), _is(".,;:?"), _is("\n"))


def features(column: pa.Array, c: QualityConfig) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Offsets of the rows, feature numbers and values: hashed words (their values' squares sum to 1), then bins of statistics (1 each)."""
    values, offsets = text_bytes(column)
    n = len(offsets) - 1

    def per_row(flags: np.ndarray, at: np.ndarray) -> np.ndarray:
        run = np.concatenate(([0], np.cumsum(flags)))
        return (run[at[1:]] - run[at[:-1]]).astype(float)

    starts, ends, at = word_spans(values, offsets, BREAKS)
    hashes = span_hashes(values, starts, ends)
    rows = np.repeat(np.arange(n), np.diff(at))
    words = np.maximum(np.diff(at), 1).astype(float)
    size = np.maximum(np.diff(offsets), 1).astype(float)
    again = np.zeros(len(hashes), bool)
    if len(hashes):
        again[1:] = (hashes[1:] == hashes[:-1]) & (rows[1:] == rows[:-1])
    pairs = np.unique(rows.astype(np.int64) * c.buckets + (hashes % np.uint64(c.buckets)).astype(np.int64))
    owner, bucket = pairs // c.buckets, pairs % c.buckets
    distinct = np.bincount(owner, minlength=n)
    letters = np.maximum(per_row(_LETTER[values], offsets), 1)
    counted = [per_row(k[values], offsets) for k in _COUNTED]
    shares = [counted[0] / letters, *[x / words for x in counted[1:]], per_row(again, at) / words, distinct / words, letters / size]
    stats = [np.searchsorted(_STEPS, x, side="right") for x in shares]
    stats += [np.minimum(np.log2(words).astype(int), _BINS - 1), np.minimum(np.log2(size).astype(int), _BINS - 1), np.minimum((letters / words).astype(int), _BINS - 1)]
    index = c.buckets + np.arange(len(stats)) * _BINS + np.column_stack(stats)
    k = len(stats)
    bounds = np.concatenate(([0], np.cumsum(distinct + k)))
    ids, x = np.empty(bounds[-1], np.int64), np.ones(bounds[-1], np.float32)
    tail = np.zeros(len(ids), bool)
    tail[(bounds[1:, None] - k + np.arange(k)).ravel()] = True
    ids[tail], ids[~tail] = index.ravel(), bucket
    x[~tail] = np.repeat(1 / np.sqrt(np.maximum(distinct, 1)), distinct)
    return bounds, ids, x


class FactorisationMachine:
    def __init__(self, config: QualityConfig):
        self.c = config
        size = config.buckets + 16 * _BINS
        self.w0, self.w = 0.0, np.zeros(size, np.float32)
        self.v = np.random.default_rng(config.seed).normal(0, 0.05, (size, config.rank)).astype(np.float32)

    def _sums(self, bounds, ids, x):
        vx = self.v[ids] * x[:, None]
        s = np.add.reduceat(vx, bounds[:-1], axis=0)
        pair = 0.5 * ((s * s).sum(axis=1) - np.add.reduceat((vx * vx).sum(axis=1), bounds[:-1]))
        return s, self.w0 + np.add.reduceat(self.w[ids] * x, bounds[:-1]) + pair

    def score(self, bounds: np.ndarray, ids: np.ndarray, x: np.ndarray) -> np.ndarray:
        """The probability of label 1. Every row has its statistics, so no row is without features."""
        if len(bounds) < 2:
            return np.zeros(0)
        return 1 / (1 + np.exp(-np.clip(self._sums(bounds, ids, x)[1].astype(np.float64), -30, 30)))

    def fit(self, rows: list[tuple[np.ndarray, np.ndarray]], y: np.ndarray) -> FactorisationMachine:
        """Adaptive gradient steps over rows of (feature numbers, values), in an order drawn by the seed."""
        c, size = self.c, len(self.w)
        if not len(rows):
            return self
        rng = np.random.default_rng(c.seed)
        gw, gv, g0 = np.full(size, 1e-6), np.full((size, c.rank), 1e-6), 1e-6
        for _ in range(c.epochs):
            order = rng.permutation(len(rows))
            for i in range(0, len(order), c.batch):
                own = [rows[k] for k in order[i : i + c.batch]]
                bounds = np.concatenate(([0], np.cumsum([len(a) for a, _ in own])))
                ids, x = np.concatenate([a for a, _ in own]), np.concatenate([b for _, b in own])
                s, z = self._sums(bounds, ids, x)
                d = (1 / (1 + np.exp(-np.clip(z.astype(np.float64), -30, 30))) - y[order[i : i + c.batch]]) / len(own)
                owner = np.repeat(np.arange(len(own)), np.diff(bounds))
                used, place = np.unique(ids, return_inverse=True)
                dx = d[owner] * x
                grad = np.bincount(place, dx, len(used)) + c.l2 * self.w[used]
                gw[used] += grad * grad
                self.w[used] -= c.rate * grad / np.sqrt(gw[used])
                inner = dx[:, None] * (s[owner] - self.v[ids] * x[:, None])
                grad = np.column_stack([np.bincount(place, inner[:, f], len(used)) for f in range(c.rank)]) + c.l2 * self.v[used]
                gv[used] += grad * grad
                self.v[used] -= c.rate / 2 * grad / np.sqrt(gv[used])
                g0 += d.sum() ** 2
                self.w0 -= c.rate * d.sum() / np.sqrt(g0)
        return self


def train_quality(docs: DataFrame, labels: DataFrame, config: QualityConfig = QualityConfig()) -> FactorisationMachine:
    """Fits the machine on the driver from the features of a bounded sample of labelled documents that are not held out.

    Null texts are left out; without labels the machine is its random start.
    """
    c = config
    ship(docs.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in text_slices(batches):
            bounds, ids, x = features(b.column("text"), c)
            yield pa.record_batch([b.column("doc_id"), b.column("y"), pa.array([ids[i:j].astype("<i4").tobytes() for i, j in zip(bounds[:-1], bounds[1:], strict=True)]), pa.array([x[i:j].tobytes() for i, j in zip(bounds[:-1], bounds[1:], strict=True)])], ["doc_id", "y", "ids", "x"])

    sample = labelled_texts(docs, labels.select("doc_id", F.col("quality").cast("int").alias("quality")), "quality", c.sample, c.held_out)
    table = sample.mapInArrow(run, "doc_id long, y int, ids binary, x binary").toArrow().sort_by("doc_id")
    rows = [(np.frombuffer(a, "<i4").astype(np.int64), np.frombuffer(b, np.float32)) for a, b in zip(table["ids"].to_pylist(), table["x"].to_pylist(), strict=True)]
    machine = FactorisationMachine(c).fit(rows, table["y"].to_numpy().astype(float))
    del table, rows
    release()
    return machine


def _scores(machine: FactorisationMachine, column: pa.Array) -> np.ndarray:
    return machine.score(*features(column, machine.c))


def score_quality(docs: DataFrame, machine: FactorisationMachine) -> DataFrame:
    """doc_id, held_out, score, predicted of every row of docs (doc_id, text; other columns are ignored).

    A null doc_id is not held out; null text counts as empty; empty texts have a score. Repeated rows pass through; an
    empty table gives an empty one. Narrow; the model is about a megabyte.
    """
    spark = docs.sparkSession
    ship(spark)
    model = spark.sparkContext.broadcast(machine)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in text_slices(batches):
            yield pa.record_batch([b.column("doc_id"), pa.array(_scores(model.value, b.column("text")))], ["doc_id", "score"])

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(run, "doc_id long, score double")
    return rows.select("doc_id", F.coalesce(held_out(machine.c.held_out), F.lit(False)).alias("held_out"), "score", (F.col("score") >= machine.c.threshold).cast("int").alias("predicted"))


def keep_good(docs: DataFrame, machine: FactorisationMachine) -> DataFrame:
    """The rows of docs predicted 1, all columns kept, in one narrow pass.

    Null text counts as empty, and empty texts go by their score. Repeated rows and null doc_ids pass like others; an
    empty table gives an empty one.
    """
    spark = docs.sparkSession
    ship(spark)
    model = spark.sparkContext.broadcast(machine)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in text_slices(batches):
            yield b.filter(pa.array(_scores(model.value, b.column("text")) >= model.value.c.threshold))

    return docs.mapInArrow(run, docs.schema)
