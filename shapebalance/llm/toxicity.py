"""Toxicity by a classifier chain over hashed words and word beginnings.

Labels know one thing, whether a document is toxic. The chain's categories come from it and the training texts: marks
are features that toxic texts have almost alone; `severe` are toxic texts whose share of marks reaches the median of
toxic texts, `mild` the other toxic ones, and `toxic` is the label. Each is a logistic model on the same features and
on the probabilities of the categories before it. In training those come from models of the other folds, whose
features, marks and categories are chosen from these folds alone. Scores come from text alone.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Work, release, ship, text_bytes, text_slices
from .hashing import span_hashes, word_spans

CATEGORIES = ("severe", "mild", "toxic")


@dataclass(frozen=True)
class ToxicityConfig:
    #: Labelled rows to learn from at most, taken by a hash of doc_id.
    sample: int = 20_000
    #: Features kept at most, documents that a feature must be in, and its least z-score between the classes.
    features: int = 4096
    least: int = 4
    z: float = 4.0
    #: Bytes of the word beginnings that are features beside whole words.
    heads: tuple[int, ...] = (4, 5, 6)
    folds: int = 4
    l2: float = 1e-3
    threshold: float = 0.5
    #: A labelled row is held out when crc32(doc_id as text) mod this is 0.
    held_out: int = 5


#: Everything in ASCII but letters, digits ends a word.
BREAKS = np.array([i < 128 and not chr(i).isalnum() for i in range(256)])


def token_hashes(column: pa.Array, heads: tuple[int, ...]) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of all words and word beginnings, and the row of each."""
    values, offsets = text_bytes(column)
    starts, ends, at = word_spans(values, offsets, BREAKS)
    rows = np.repeat(np.arange(len(offsets) - 1), np.diff(at))
    hashes, owners = [span_hashes(values, starts, ends)], [rows]
    for n in heads:
        long = np.flatnonzero(ends - starts > n)
        # the salt keeps the beginning of a longer word apart from the word that it spells
        hashes.append(span_hashes(values, starts[long], starts[long] + n) ^ np.uint64(n))
        owners.append(rows[long])
    return np.concatenate(hashes), np.concatenate(owners)


class Lookup:
    """Places of hashes in a sorted list; most misses are told by a table of bits."""

    def __init__(self, hashes: np.ndarray):
        self.hashes = np.sort(hashes)
        self.bits = np.zeros(1 << 20, bool)
        self.bits[self.hashes & np.uint64((1 << 20) - 1)] = True

    def __call__(self, hashes: np.ndarray, owners: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Rows and features of all hits, repeats included, by row."""
        near = np.flatnonzero(self.bits[hashes & np.uint64((1 << 20) - 1)])
        h = hashes[near]
        place = np.searchsorted(self.hashes, h)
        place[place == len(self.hashes)] = 0
        hit = self.hashes[place] == h if len(self.hashes) else np.zeros(len(h), bool)
        rows, places = owners[near][hit], place[hit]
        order = np.argsort(rows, kind="stable")
        return rows[order], places[order]


def _sigmoid(z: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(z, -30, 30)))


class Linear:
    """Logistic regression on sparse presence features and a few dense ones, by full gradients with momentum."""

    def __init__(self, n: int, dense: int, l2: float, steps: int = 150):
        self.n, self.dense, self.l2, self.steps = n, dense, l2, steps
        self.w, self.b = np.zeros(n + dense), 0.0

    def margin(self, rows: np.ndarray, cols: np.ndarray, dense: np.ndarray) -> np.ndarray:
        return np.bincount(rows, self.w[cols], len(dense)) + dense @ self.w[self.n :] + self.b

    def fit(self, rows: np.ndarray, cols: np.ndarray, dense: np.ndarray, y: np.ndarray) -> Linear:
        m = len(y)
        if not m:  # nothing is known, so nothing has the category
            self.b = -30.0
            return self
        square, speed, square_b, speed_b = np.zeros_like(self.w), np.zeros_like(self.w), 0.0, 0.0
        for k in range(1, self.steps + 1):
            d = (_sigmoid(self.margin(rows, cols, dense)) - y) / m
            g = np.concatenate([np.bincount(cols, d[rows], self.n), dense.T @ d]) + self.l2 * self.w / 100
            gb = d.sum()
            speed, square = 0.9 * speed + 0.1 * g, 0.99 * square + 0.01 * g * g
            speed_b, square_b = 0.9 * speed_b + 0.1 * gb, 0.99 * square_b + 0.01 * gb * gb
            scale = 0.3 / (1 - 0.9**k)
            self.w -= scale * speed / (np.sqrt(square / (1 - 0.99**k)) + 1e-9)
            self.b -= scale * speed_b / (np.sqrt(square_b / (1 - 0.99**k)) + 1e-9)
        return self


class ToxicityChain:
    """The chain over features 0 .. n-1; hits are (row, feature) pairs with repeats."""

    def __init__(self, config: ToxicityConfig):
        self.c, self.hashes, self.models = config, np.zeros(0, np.uint64), []

    @staticmethod
    def _presence(rows: np.ndarray, cols: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray]:
        pairs = np.unique(rows.astype(np.int64) * max(n, 1) + cols)
        return pairs // max(n, 1), pairs % max(n, 1)

    def _choose(self, n: np.ndarray, k: np.ndarray, total: float, positive: float) -> tuple[np.ndarray, np.ndarray]:
        """Features that tell toxic texts from others, by the texts (of `total`) and toxic texts (of `positive`) that have each; and the marks."""
        p = positive / total if total else 0.0
        if not 0 < p < 1:
            return np.zeros(0, np.int64), np.zeros(len(n), bool)
        z = (k - n * p) / np.sqrt(np.maximum(n, 1) * p * (1 - p))
        good = np.flatnonzero((n >= self.c.least) & (np.abs(z) >= self.c.z))
        good = np.sort(good[np.argsort(-np.abs(z[good]), kind="stable")][: self.c.features])
        marks = np.zeros(len(n), bool)
        marks[good] = (z[good] > 0) & (k[good] >= 0.8 * n[good])
        return good, marks

    def fit(self, hashes: np.ndarray, n: np.ndarray, k: np.ndarray, rows: np.ndarray, cols: np.ndarray, size: np.ndarray, toxic: np.ndarray, fold: np.ndarray, times: np.ndarray | None = None) -> ToxicityChain:
        """hashes: candidate features, sorted. n, k: documents and toxic documents of each fold (row) that have each feature
        (column). rows, cols: hits of the documents; times: how often each occurs, where rows and cols are distinct and in
        order, else None. size, toxic, fold of each document. One fold's hits are laid out at a time."""
        m, folds = len(toxic), range(self.c.folds)
        if times is None:
            pairs, times = np.unique(rows.astype(np.int64) * max(len(hashes), 1) + cols, return_counts=True)
            rows, cols = pairs // max(len(hashes), 1), pairs % max(len(hashes), 1)
        share = lambda marks: np.bincount(rows, marks[cols] * times, m) / np.maximum(size, 1) if len(rows) else np.zeros(m)
        held = [(fold != f) for f in folds] + [np.ones(m, bool)]
        views = []
        for f, own in enumerate(held):
            kept = [g for g in folds if g != f]
            good, marks = self._choose(n[kept].sum(axis=0), k[kept].sum(axis=0), own.sum(), toxic[own].sum())
            rate = share(marks)
            middle = np.median(rate[own & toxic]) if (own & toxic).any() else 0.0
            severe = toxic & (rate >= max(middle, 1e-12))
            views.append((good, {"severe": severe, "mild": toxic & ~severe, "toxic": toxic}))

        def laid_out(good: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
            place = np.full(len(hashes), -1)
            place[good] = np.arange(len(good))
            pick = place[cols] >= 0
            return rows[pick].astype(np.int64), place[cols[pick]]

        self.hashes, dense = hashes[views[-1][0]], np.zeros((m, 0))
        for name in CATEGORIES:
            good, labels = views[-1]
            self.models.append(Linear(len(good), dense.shape[1], self.c.l2).fit(*laid_out(good), dense, labels[name].astype(float)))
            out = np.zeros(m)
            for f in folds:
                good, labels = views[f]
                r, c = laid_out(good)
                own = held[f]
                place, pick = np.cumsum(own) - 1, own[r]
                model = Linear(len(good), dense.shape[1], self.c.l2).fit(place[r[pick]], c[pick], dense[own], labels[name][own].astype(float))
                out[~own] = _sigmoid(model.margin(r, c, dense))[~own]
            dense = np.column_stack([dense, out])
        return self

    def predict(self, rows: np.ndarray, cols: np.ndarray, m: int) -> np.ndarray:
        """Probabilities of the categories in order, one row per document."""
        rows, cols = self._presence(rows, cols, len(self.hashes))
        dense = np.zeros((m, 0))
        for model in self.models:
            dense = np.column_stack([dense, _sigmoid(model.margin(rows, cols, dense))])
        return dense


def held_out(n: int):
    return F.crc32(F.col("doc_id").cast("string").cast("binary")) % n == 0


def labelled_texts(docs: DataFrame, labels: DataFrame, label: str, n: int, fold: int) -> DataFrame:
    """doc_id, text, y of at most n labelled documents that are not held out, by a hash of doc_id. Conflicting labels: the smallest; of texts that share an id the least."""
    own = labels.where(F.col(label).isNotNull() & F.col("doc_id").isNotNull() & ~held_out(fold)).groupBy("doc_id").agg(F.min(label).alias("y"))
    own = own.orderBy(F.xxhash64("doc_id"), "doc_id").limit(n)  # at most n rows, so it may be broadcast
    found = docs.select("doc_id", "text").join(F.broadcast(own), "doc_id").where("text IS NOT NULL")
    ids = docs.select("doc_id").join(F.broadcast(own.select("doc_id")), "doc_id")
    if not ids.groupBy("doc_id").count().where("count > 1").isEmpty():  # an id counts once, so that n rows at most reach the driver
        found = found.groupBy("doc_id").agg(F.min("text").alias("text"), F.first("y").alias("y"))
    return found


def train_toxicity(docs: DataFrame, labels: DataFrame, config: ToxicityConfig = ToxicityConfig()) -> ToxicityChain:
    """Fits the chain on a bounded sample of labelled documents.

    The first pass counts, on the executors, in how many toxic and other documents of each fold each feature is; the
    features that tell them apart in all folds or in all but one come to the driver, and with them the sample's hits.
    Null texts are left out. Labels of one class alone, or none, give a chain that says what it has seen of them.
    """
    c, work = config, Work(docs.sparkSession)

    def features(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in text_slices(batches):
            hashes, owners = token_hashes(b.column("text"), c.heads)
            order = np.argsort(owners, kind="stable")
            at = np.searchsorted(owners[order], np.arange(b.num_rows + 1)).astype(np.int32)
            yield pa.record_batch([b.column("doc_id"), b.column("y"), pa.ListArray.from_arrays(pa.array(at), pa.array(hashes[order].view(np.int64)))], ["doc_id", "y", "features"])

    sample = labelled_texts(docs, labels.select("doc_id", F.col("toxic").cast("int").alias("toxic")), "toxic", c.sample, c.held_out)
    rows = work.table(sample.mapInArrow(features, "doc_id long, y int, features array<long>").withColumn("fold", F.pmod(F.xxhash64("doc_id"), F.lit(c.folds)).cast("int")), "sample")
    seen = {r["fold"]: (r["n"], r["k"]) for r in rows.groupBy("fold").agg(F.count("*").alias("n"), F.sum("y").alias("k")).collect()}
    cells = [(F.sum((F.col("fold") == f).cast("long")).alias(f"n{f}"), F.sum(F.when(F.col("fold") == f, F.col("y")).otherwise(0)).alias(f"k{f}")) for f in range(c.folds)]
    counts = rows.select("fold", "y", F.explode(F.array_distinct("features")).alias("h")).groupBy("h").agg(*[x for cell in cells for x in cell])
    scores = []
    for left_out in (None, *range(c.folds)):
        kept = [f for f in range(c.folds) if f != left_out]
        total, positive = (sum(seen.get(f, (0, 0))[i] for f in kept) for i in (0, 1))
        if 0 < positive < total:
            p, n, k = positive / total, sum(F.col(f"n{f}") for f in kept), sum(F.col(f"k{f}") for f in kept)
            scores.append(F.when(n >= c.least, F.abs(k - n * p) / F.sqrt(n * (p * (1 - p)))))
    if scores:
        best = F.array_max(F.array(*scores))
        chosen = counts.withColumn("best", best).where(F.col("best") >= c.z).orderBy(F.desc("best"), "h").limit(2 * c.features).collect()
    else:
        chosen = []
    hashes = np.array([r["h"] for r in chosen], np.int64).view(np.uint64)
    order = np.argsort(hashes)
    per_fold = lambda x: np.array([[r[f"{x}{f}"] for r in chosen] for f in range(c.folds)], float).reshape(c.folds, -1)[:, order]
    wanted = hashes[order]

    def found(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            size = pc.list_value_length(b.column("features")).to_numpy(zero_copy_only=False)
            values = b.column("features").flatten().to_numpy(zero_copy_only=False).view(np.uint64)
            hit = np.flatnonzero(np.isin(values, wanted))
            owners = np.repeat(np.arange(b.num_rows), size)[hit]
            pairs, times = np.unique(owners * max(len(wanted), 1) + np.searchsorted(wanted, values[hit]), return_counts=True)
            at = pa.array(np.searchsorted(pairs, np.arange(b.num_rows + 1) * max(len(wanted), 1)).astype(np.int32))
            hits = [pa.ListArray.from_arrays(at, pa.array(x.astype(np.int32))) for x in (pairs % max(len(wanted), 1), times)]
            yield pa.record_batch([b.column("doc_id"), b.column("y"), b.column("fold"), pa.array(size, pa.int32()), *hits], ["doc_id", "y", "fold", "size", "hits", "times"])

    # by Arrow, as numbers of features: as rows the hits would be Python numbers, whose memory the driver keeps
    local = rows.mapInArrow(found, "doc_id long, y int, fold int, size int, hits array<int>, times array<int>").toArrow().sort_by("doc_id")
    column = lambda x: local[x].to_numpy().astype(int)
    rows_at = np.repeat(np.arange(local.num_rows, dtype=np.int32), pc.list_value_length(local["hits"]).to_numpy())
    cols, times = (pc.list_flatten(local[x]).to_numpy().astype(np.int32) for x in ("hits", "times"))
    size, toxic, fold = column("size"), column("y") == 1, column("fold")
    del local
    chain = ToxicityChain(c).fit(wanted, per_fold("n"), per_fold("k"), rows_at, cols, size, toxic, fold, times)
    del rows_at, cols, times
    release()
    return chain


def score_toxicity(docs: DataFrame, chain: ToxicityChain) -> DataFrame:
    """doc_id, p_severe, p_mild, p_toxic, rejected of every row of docs (doc_id, text; other columns are ignored).

    Null and empty texts have the probabilities of no features. Repeated rows and null doc_ids pass through; an empty
    table gives an empty one. Narrow; the model is a few hundred kilobytes.
    """
    spark = docs.sparkSession
    ship(spark)
    model = spark.sparkContext.broadcast(chain)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        chain = model.value
        lookup = Lookup(chain.hashes)
        for b in text_slices(batches):
            p = chain.predict(*lookup(*token_hashes(b.column("text"), chain.c.heads)), b.num_rows)
            yield pa.record_batch([b.column("doc_id"), *[pa.array(x) for x in p.T], pa.array(p[:, -1] >= chain.c.threshold)], ["doc_id", *[f"p_{x}" for x in CATEGORIES], "rejected"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(run, "doc_id long, " + ", ".join(f"p_{x} double" for x in CATEGORIES) + ", rejected boolean")


def keep_clean(docs: DataFrame, chain: ToxicityChain) -> DataFrame:
    """The rows of docs that the chain does not reject, all columns kept, in one narrow pass.

    Null and empty texts have no features and stay, unless most of the labels were toxic. Repeated rows and null doc_ids
    pass like others; an empty table gives an empty one.
    """
    spark = docs.sparkSession
    ship(spark)
    model = spark.sparkContext.broadcast(chain)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        chain = model.value
        lookup = Lookup(chain.hashes)
        for b in text_slices(batches):
            p = chain.predict(*lookup(*token_hashes(b.column("text"), chain.c.heads)), b.num_rows)[:, -1]
            yield b.filter(pa.array(p < chain.c.threshold))

    return docs.mapInArrow(run, docs.schema)
