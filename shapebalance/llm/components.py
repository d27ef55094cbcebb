"""Connected components of a table of links, by alternating large-star and small-star steps on DataFrames."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Work, spread_join


def _state(edges: DataFrame) -> tuple:
    row = edges.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
    return tuple(row)


def _to_least(work: Work, rows: DataFrame, near: DataFrame, total: int) -> DataFrame:
    """rows (u, v) with m, the least neighbour of u in `near` (u, v); hot ends meet theirs by broadcast."""
    least = work.table(near.groupBy("u").agg(F.min("v").alias("m"), F.count("*").alias("n")), "least")
    return spread_join(rows, least, ["u"], total).drop("n")


def components(work: Work, links: DataFrame) -> DataFrame:
    """node, component (smallest node reachable) of every node in links (u, v long; either order, repeats allowed).

    Each step joins links with their ends' smallest neighbours and is written to the work folder; the number of steps
    grows with the logarithm of the longest path. Minima are pre-aggregated, and a node with over a thousandth of the
    links meets its minimum by broadcast, so no task gets all links of one node. No row for nodes without links; an
    empty table gives an empty one.
    """
    edges = work.table(links.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).where("u != v").distinct(), "links")
    state = _state(edges)
    while state[0]:
        # large star: a node's larger neighbours move to the smallest node around it
        both = edges.unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
        large = _to_least(work, both.where("v > u"), both, 2 * state[0]).select(F.col("v").alias("u"), F.least("m", "u").alias("v"))
        large = work.table(large.where("u != v").distinct(), "large")
        # small star: a node and its smaller neighbours move to the smallest of these
        small = _to_least(work, large, large, 2 * state[0]).select(F.explode(F.array("u", "v")).alias("u"), F.col("m").alias("v"))
        new = work.table(small.where("u != v").distinct(), "small")
        now = _state(new)
        work.drop(edges, large)
        edges, done = new, now == state
        state = now
        if done:
            break
    return edges.select(F.col("u").alias("node"), F.col("v").alias("component")).unionByName(edges.select(F.col("v").alias("node"), F.col("v").alias("component")).distinct())
