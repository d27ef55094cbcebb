"""Exact top-k inner products: a ball tree per shard, searched by branch and bound.

Vectors are dealt into shards of bounded size, each packed into one row and sent once; queries into blocks of bounded
size, which visit the shard's tree one after another. A query opens nodes in the order of their upper bounds,
q.c + |q| r for a ball of centre c and radius r, and stops at the first bound below its kth score so far. Shards go in
rounds, each several times as many as all before; after each, a query's best k so far are merged, and their kth score
is where the next round's searches start, so that later shards are mostly cut at the root.
"""

from __future__ import annotations

import heapq
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import Work

#: Vectors in a shard, queries in a block, vectors in a leaf; shards up to the end of a round by those up to its start.
SHARD, BLOCK, LEAF, GROWTH = 8192, 512, 64, 4
#: Whole numbers below this are exact in doubles.
EXACT = float(1 << 53)
_LARGEST = (1 << 63) - 1


class BallTree:
    """Nodes in arrays: centre, radius, rows [start, end) of the reordered vectors, children (-1: leaf)."""

    def __init__(self, ids: np.ndarray, vectors: np.ndarray, leaf: int = LEAF):
        order = np.argsort(ids, kind="stable")
        self.ids, self.vectors = ids[order], vectors[order].astype(np.float64)
        centres, radii, spans, children = [], [], [], []
        todo = [(0, len(ids), -1, 0)] if len(ids) else []
        place = np.arange(len(ids))
        while todo:
            start, end, parent, side = todo.pop()
            x = self.vectors[place[start:end]]
            centre = x.mean(axis=0)
            apart = np.sqrt(((x - centre) ** 2).sum(axis=1))
            node = len(centres)
            centres.append(centre)
            radii.append(float(apart.max()))
            spans.append((start, end))
            children.append([-1, -1])
            if parent >= 0:
                children[parent][side] = node
            if end - start > leaf and radii[-1] > 0:
                # split at the median along the line between two far points
                a = x[apart.argmax()]
                b = x[((x - a) ** 2).sum(axis=1).argmax()]
                along = x @ (b - a)
                half = (end - start) // 2
                place[start:end] = place[start:end][np.argsort(along, kind="stable")]
                todo += [(start + half, end, node, 1), (start, start + half, node, 0)]
        self.ids, self.vectors = self.ids[place], self.vectors[place]
        self.top = float(np.abs(self.vectors).max()) if self.vectors.size else 0.0
        self.centres, self.radii = np.array(centres).reshape(len(centres), -1), np.array(radii)
        self.spans, self.children = spans, children

    def search(self, query: np.ndarray, own: int, k: int, floor: float = -np.inf) -> list[tuple[int, int]]:
        """The k best (score, id) of rows with another id than `own` and a score of at least `floor`, ties to smaller ids."""
        if not len(self.radii):
            return []
        q = query.astype(np.float64)
        size = np.sqrt(q @ q)
        bounds = self.centres @ q + size * self.radii
        # a margin for rounding, by the size of what is added up
        bounds += 1e-6 + 1e-9 * size * (np.sqrt((self.centres * self.centres).sum(axis=1)) + self.radii)
        small = len(q) * self.top * float(np.abs(q).max(initial=0.0)) < EXACT
        whole = None if small else [int(x) for x in q]
        best: list[tuple[float, int]] = []  # a heap whose first is the worst: (score, -id)
        heap = [(-bounds[0], 0)]
        while heap:
            bound, node = heapq.heappop(heap)
            kth = max(floor, best[0][0]) if len(best) == k else floor
            if -bound < kth:
                break
            left, right = self.children[node]
            if left >= 0:
                for child in (left, right):
                    if bounds[child] >= kth:
                        heapq.heappush(heap, (-bounds[child], child))
                continue
            start, end = self.spans[node]
            if small:  # sums of products are exact in doubles
                scores = self.vectors[start:end] @ q
            else:
                sums = (sum(int(x) * y for x, y in zip(row, whole, strict=True)) for row in self.vectors[start:end].tolist())
                scores = np.array([max(-_LARGEST, min(_LARGEST, s)) for s in sums], object)
            for i in np.flatnonzero((scores >= kth).astype(bool)).tolist():
                item = (scores[i], -int(self.ids[start + i]))
                if -item[1] == own:
                    continue
                if len(best) < k:
                    heapq.heappush(best, item)
                elif item > best[0]:
                    heapq.heapreplace(best, item)
        return [(int(s), -i) for s, i in sorted(best, reverse=True)]


def whole_numbers(vectors: DataFrame, factor: int = 256) -> DataFrame:
    """vec_id, n (length), v array<double>: the whole numbers floor(factor * x). Rows with null ids or vectors, or with null or non-finite components, go."""
    ok = F.col("vec_id").isNotNull() & F.col("embedding").isNotNull() & ~F.exists("embedding", lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf")))
    rows = vectors.select("vec_id", "embedding").where(ok)
    scaled = F.transform("embedding", lambda x: x.cast("double") * factor)
    # floor() gives a 64-bit number, which large components exceed; they are whole numbers anyway
    floors = F.transform(scaled, lambda x: F.when(F.abs(x) < EXACT, F.floor(x).cast("double")).otherwise(x))
    return rows.select(F.col("vec_id").cast("long").alias("vec_id"), F.size("embedding").alias("n"), floors.alias("v"))


def _packed(rows: pd.DataFrame) -> tuple[bytes, bytes]:
    return rows["vec_id"].to_numpy(np.int64).tobytes(), np.stack(rows["v"].to_list()).astype("<f8").tobytes()


def _unpack(ids: bytes, data: bytes) -> tuple[np.ndarray, np.ndarray]:
    i = np.frombuffer(ids, np.int64)
    return i, np.frombuffer(data, "<f8").reshape(len(i), -1)


_STREAM = "n int, shard long, block long, ids binary, data binary, floors binary"

def _shard(g: pd.DataFrame) -> pd.DataFrame:
    ids, data = _packed(g.sort_values("vec_id", kind="stable"))
    return pd.DataFrame({"n": [int(g["n"].iloc[0])], "shard": [int(g["shard"].iloc[0])], "block": [-1], "ids": [ids], "data": [data], "floors": [None]})


def _block(g: pd.DataFrame) -> pd.DataFrame:
    g = g.sort_values("vec_id", kind="stable")
    ids, data = _packed(g)
    return pd.DataFrame({"n": [int(g["n"].iloc[0])], "block": [int(g["block"].iloc[0])], "ids": [ids], "data": [data], "floors": [g["floor"].astype(float).fillna(-np.inf).to_numpy().tobytes()]})


def _search(k: int):
    """Of a stream of shards, each followed by its blocks of queries: the best k of each query in the shard."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tree = None
        for b in batches:
            for i in range(b.num_rows):
                row = {x: b.column(x)[i].as_py() for x in ("block", "ids", "data", "floors")}
                ids, v = _unpack(row["ids"], row["data"])
                if row["block"] < 0:
                    tree = BallTree(ids, v)
                    continue
                out = []
                for own, query, floor in zip(ids.tolist(), v, np.frombuffer(row["floors"]).tolist(), strict=True):
                    out += [(own, x, s) for s, x in tree.search(query, own, k, floor)]
                if out:
                    yield pa.RecordBatch.from_arrays([pa.array(x, pa.int64()) for x in zip(*out, strict=True)], ["query_id", "vec_id", "score"])

    return run


def top_k(vectors: DataFrame, k: int = 5, every: int = 50) -> DataFrame:
    """query_id, rank (from 1), vec_id, score: the k highest inner products of each query over all rows but those with its own id.

    Queries are the rows of vectors (vec_id, embedding; other columns are ignored) whose id is divisible by `every`; a
    query is compared with the vectors of its own length. Scores are exact whole numbers; those beyond 64 bits
    count as the largest or least that fits. Ties go to smaller ids; fewer than k others give fewer rows; rows that
    cannot take part (null or non-finite) are left out; rows that repeat an id are candidates each, and the least of them
    by length and numbers is the query. An empty table gives an empty one. Shards and blocks are of bounded size; a shard
    is sent once, a block once for each shard; a round leaves at most k rows per query and shard, merged by a window.
    """
    spark = vectors.sparkSession
    work = Work(spark)
    rows = work.table(whole_numbers(vectors), "vectors")
    queries = work.table(rows.where(F.col("vec_id") % every == 0).groupBy("vec_id").agg(F.min(F.struct("n", "v")).alias("q")).select("vec_id", "q.n", "q.v"), "queries")
    shards, blocks = max(1, -(-rows.count() // SHARD)), max(1, -(-queries.count() // BLOCK))
    # rows with one id meet in one shard; ids are dealt evenly
    dealt = rows.withColumn("shard", F.pmod(F.xxhash64("vec_id"), F.lit(shards))).groupBy("n", "shard").applyInPandas(_shard, _STREAM)
    dealt = work.table(dealt, "shards")
    best, low = None, 0
    while low < shards:
        high = min(shards, max(1, low * GROWTH))
        asked = queries.withColumn("block", F.pmod(F.xxhash64("vec_id"), F.lit(blocks)))
        if best is None:
            asked = asked.withColumn("floor", F.lit(None).cast("double"))
        else:
            kth = best.where(F.col("rank") == k).select(F.col("query_id").alias("vec_id"), F.col("score").cast("double").alias("floor"))
            asked = asked.join(kth, "vec_id", "left")
            # a score that a double rounds up must not shut out its equals
            asked = asked.withColumn("floor", F.when(F.abs("floor") < EXACT, F.col("floor")))
        packed = asked.groupBy("n", "block").applyInPandas(_block, "n int, block long, ids binary, data binary, floors binary")
        own = dealt.where((F.col("shard") >= low) & (F.col("shard") < high))
        visits = work.table(packed, "blocks").withColumn("shard", F.explode(F.sequence(F.lit(low).cast("long"), F.lit(high - 1).cast("long"))))
        visits = visits.join(own.select("n", "shard"), ["n", "shard"], "left_semi").select(*own.columns)
        stream = own.unionByName(visits).repartition("n", "shard").sortWithinPartitions("n", "shard", "block")
        found = stream.mapInArrow(_search(k), "query_id long, vec_id long, score long")
        if best is not None:
            found = found.unionByName(best.drop("rank"))
        order = Window.partitionBy("query_id").orderBy(F.col("score").desc(), "vec_id")
        best = work.table(found.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k), "best")
        low = high
    return best.select("query_id", F.col("rank").cast("int").alias("rank"), "vec_id", "score")
