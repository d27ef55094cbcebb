"""Batches on ranks and synchronous steps (M9-M12), and the dual bound on Spark's own tasks."""

from __future__ import annotations

import heapq

import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..plans.model import SEED, Bounds, CostModel
from ..ship import ship
from ..sources.work import written
from .batching import assign_buckets, bucket_stats, form_batches, plan_buckets
from .ranks import key, ranked

POLICIES = ("random", "round_robin", "bucket_hash", "load_sorted", "lpt")


def assign_steps(batches: DataFrame, n_ranks: int, policy: str = "random", seed: int = SEED, p: float = 2.0, window: int = 8) -> DataFrame:
    """M9: adds step, rank and full (whether the step has a batch for each rank).

    random: a keyed permutation, dealt out in turn; round_robin: in order of bucket and batch; bucket_hash: each bucket
    on one rank; load_sorted: batches of neighbouring load B * S^p share a step; lpt: inside windows of window * n_ranks
    random batches, the heaviest go first, each to the least loaded rank that has a step left.
    """
    rows = batches.withColumn("k", key(seed, "batch_id"))
    if policy == "random":
        placed = ranked(rows, "g", "k")
    elif policy == "round_robin":
        placed = ranked(rows.withColumn("o", F.lpad(F.hex("batch_no"), 12, "0")), "g", "o", order=(("bucket_id", True),), digits=9).drop("o")
    elif policy == "load_sorted":
        placed = ranked(rows.withColumn("load", F.col("b") * F.pow(F.col("s").cast("double"), F.lit(p))), "g", "k", order=(("load", False),)).drop("load")
    elif policy == "bucket_hash":
        rank = (F.conv(F.substring(key(seed, "bucket_id"), 1, 8), 16, 10).cast("long") % n_ranks).cast("int")
        placed = ranked(rows.withColumn("rank", rank), "step", "k", within=("rank",))
    elif policy == "lpt":
        placed = _lpt(ranked(rows, "g", "k"), n_ranks, p, window)
    else:
        raise ValueError(f"unknown policy {policy!r}")
    if policy not in ("bucket_hash", "lpt"):
        placed = placed.withColumns({"step": F.floor(F.col("g") / n_ranks).cast("long"), "rank": (F.col("g") % n_ranks).cast("int")})
    sizes = placed.groupBy("step").agg((F.count("*") == n_ranks).alias("full"))
    return placed.join(sizes, "step").select(*batches.columns, "step", "rank", "full")


def _lpt(rows: DataFrame, n_ranks: int, p: float, window: int) -> DataFrame:
    """Longest processing time first inside windows of bounded size."""
    size = window * n_ranks

    ship(rows.sparkSession)

    def spread(g: pd.DataFrame) -> pd.DataFrame:
        g = g.assign(load=g["b"] * g["s"].astype(float) ** p).sort_values(["load", "k"], ascending=[False, True])
        ranks = [(0.0, r, 0) for r in range(n_ranks)]
        heapq.heapify(ranks)
        step, rank = [], []
        for load in g["load"]:
            total, r, used = heapq.heappop(ranks)
            step.append(int(g["win"].iloc[0]) * window + used)
            rank.append(r)
            if used + 1 < window:
                heapq.heappush(ranks, (total + load, r, used + 1))
        return g.assign(step=step, rank=rank).drop(columns=["load", "win"])

    kept = [f for f in rows.schema.fields]
    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in kept) + ", step long, rank int"
    return rows.withColumn("win", F.floor(F.col("g") / size).cast("long")).groupBy("win").applyInPandas(spread, schema)


def with_times(steps: DataFrame, model: CostModel = CostModel(), noise: float = 0.0, seed: int = SEED) -> DataFrame:
    """Adds load B * S^p and the model's time t, times 1 + noise * u with u in [-1, 1) from a keyed hash."""
    s = F.col("s").cast("double") / model.s_ref
    load = F.col("b") * (s * s if model.p == 2 else F.pow(s, F.lit(model.p)))
    t = model.a + model.b * load
    if noise:
        t = t * (1 + noise * (F.conv(F.substring(key(seed + 1, "batch_id"), 1, 8), 16, 10).cast("double") / 2**31 - 1))
    return steps.withColumns({"load": load, "t": t})


def simulate(steps: DataFrame, model: CostModel = CostModel(), noise: float = 0.0, seed: int = SEED) -> DataFrame:
    """Adds load, t, t_sync (the slowest rank of the step) and wait = t_sync - t. One shuffle by step."""
    timed = with_times(steps, model, noise, seed).withColumn("t_sync", F.max("t").over(Window.partitionBy("step")))
    return timed.withColumn("wait", F.col("t_sync") - F.col("t"))


def step_time(steps: DataFrame) -> DataFrame:
    """Per step the slowest rank's time, batches and tokens; partial maxima before the shuffle."""
    return steps.groupBy("step").agg(F.max("t").alias("t_sync"), F.count("*").alias("ranks"), F.sum("tokens").alias("tokens"))


def schedule(samples: DataFrame, policy: str = "dual", n_ranks: int = 16, bounds: Bounds = Bounds(), steps: str = "random", kind: str = "shape", seed: int = SEED, tail: str = "keep", **plan) -> DataFrame:
    """Samples to batches on ranks: buckets, statistics, sizes, batches, steps.

    The batches, a few numbers each, are written to a work folder when this is called, which runs their jobs: numbering and
    closing steps reads them several times.
    """
    placed = assign_buckets(samples, kind)
    sizes = plan_buckets(bucket_stats(placed), bounds, policy, **plan)
    return assign_steps(written(form_batches(placed, sizes, seed, tail)), n_ranks, steps, seed, bounds.p)


def run(samples: DataFrame, policy: str = "dual", n_ranks: int = 16, bounds: Bounds = Bounds(), model: CostModel = CostModel(), noise: float = 0.0, **how) -> DataFrame:
    """schedule() and simulate(). Like schedule() it runs jobs when called: batches are written before steps are numbered."""
    return simulate(schedule(samples, policy, n_ranks, bounds, **how), model, noise)


def balance_tasks(groups: DataFrame, bounds: Bounds, split: bool = True) -> DataFrame:
    """Groups (group_id, rows) to task slots, none of which exceeds a bound; adds part, parts, size, load, slot.

    A group over half a bound is cut in `parts` parts of nearly equal size when the operator on it can be split. Parts
    line up by size, the largest first; a slot is what starts within one half of m_mem in the running sum of sizes and
    within one half of m_comp in that of loads, so its sums stay under both bounds. (A group that cannot be split and is
    over half a bound may exceed it, alone with what starts after it.) The number of slots follows from the data. Parts
    of one size are numbered without a global sort; windows see a row for each distinct size and for each slot.
    """
    n = F.col("rows").cast("double")
    half_m, half_c = bounds.m_mem / 2, bounds.m_comp / 2
    need = F.greatest(F.lit(1), F.ceil(n / half_m), F.ceil(F.pow(F.pow(n, F.lit(bounds.p)) / half_c, F.lit(1 / bounds.p)))).cast("long") if split else F.lit(1).cast("long")
    parts = groups.withColumn("parts", need).withColumn("part", F.explode(F.sequence(F.lit(0).cast("long"), F.col("parts") - 1)))
    parts = parts.withColumn("size", F.expr("(rows + parts - 1 - part) DIV parts")).withColumn("k", key(SEED, "group_id", "part"))
    load = F.pow(F.col("size").cast("double"), F.lit(bounds.p))
    before = Window.partitionBy(F.lit(0)).orderBy(F.desc("size")).rowsBetween(Window.unboundedPreceding, -1)
    sizes = parts.groupBy("size").agg(F.count("*").alias("_n"))
    sizes = sizes.select("size", F.coalesce(F.sum(F.col("_n") * F.col("size")).over(before), F.lit(0)).alias("_rows"), F.coalesce(F.sum(F.col("_n") * load).over(before), F.lit(0.0)).alias("_load"))
    placed = ranked(parts, "_at", "k", within=("size",)).join(sizes, "size").withColumn("load", load)
    cell = {"_cm": F.floor((F.col("_rows") + F.col("_at") * F.col("size")) / half_m), "_cc": F.floor((F.col("_load") + F.col("_at") * F.col("load")) / half_c)}
    placed = placed.withColumns(cell)
    slots = placed.select("_cm", "_cc").distinct().withColumn("slot", (F.row_number().over(Window.partitionBy(F.lit(0)).orderBy("_cm", "_cc")) - 1).cast("long"))
    return placed.join(slots, ["_cm", "_cc"]).drop("k", "_at", "_rows", "_load", "_cm", "_cc")


def to_slots(df: DataFrame, slot: str, n_slots: int) -> DataFrame:
    """Puts rows in the partition that their slot names; adaptive execution leaves the count alone."""
    return df.repartitionById(n_slots, F.col(slot))
