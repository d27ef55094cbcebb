"""Waits at the barrier, what causes them, and recalibration in batch."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..plans.model import Bounds, CostModel
from .costmodel import S_REF, compute_bound, fit_grid, sync_matrix, to_model


def waits(times: DataFrame, by: str = "step") -> DataFrame:
    """Adds t_sync, the slowest time of the step, and wait = t_sync - t. One shuffle by step."""
    out = times.withColumn("t_sync", F.max("t").over(Window.partitionBy(by)))
    return out.withColumn("wait", F.col("t_sync") - F.col("t"))


def bottlenecks(steps: DataFrame, top: int | None = None) -> DataFrame:
    """Per bucket of the slowest batch of a step: steps it held up, and the waiting it caused; `top` keeps the worst."""
    ids = F.struct("t", "batch_id", "bucket_id")
    per = steps.groupBy("step").agg(F.max(ids).alias("slow"), (F.count("*") * F.max("t") - F.sum("t")).alias("caused"))
    out = per.groupBy(F.col("slow.bucket_id").alias("bucket_id")).agg(F.count("*").alias("steps"), F.sum("caused").alias("caused"))
    return out.orderBy(F.desc("caused"), "bucket_id").limit(top) if top else out


def recalibrate(bounds: Bounds, telemetry: DataFrame, target: float, damping: float = 1.0, least_r2: float = 0.0, lo: float = 1.6, hi: float = 2.4) -> tuple[Bounds, CostModel]:
    """New bounds from telemetry (rep, b, s, t): matrix, fit, bound for the target; damping in (0, 1] moves part of the way.

    Only the 81 fit rows meet the driver, and of them the best one. A fit under least_r2 leaves the bounds alone.
    """
    model = to_model(fit_grid(sync_matrix(telemetry), lo, hi, s_ref=S_REF))
    if model.r2 < least_r2:
        return bounds, model
    new = compute_bound(model, target)
    # the exponent may change, so loads are compared at the crossover of the old bounds
    s = (bounds.m_comp / bounds.m_mem) ** (1 / max(bounds.p - 1, 1e-9)) if bounds.p > 1 else S_REF
    old = bounds.m_comp / s**bounds.p * s**model.p
    return Bounds(bounds.m_mem, old + damping * (new - old), model.p), model


def closed_loop(samples: DataFrame, truth: CostModel, start: Bounds, target: float, rounds: int = 4, n_ranks: int = 16, damping: float = 1.0, least_move: float = 1e-3, noise: float = 0.0) -> list[dict]:
    """Schedule, observe, recalibrate, until the bound moves by less than `least_move`; one record per round.

    Each round plans anew from the samples, so its lineage holds no round before it and needs no checkpoint.
    """
    from . import metrics, schedule

    out, bounds = [], start
    for k in range(rounds):
        steps = schedule.run(samples, "dual", n_ranks, bounds, truth, noise)
        cv = metrics.compute_cv(steps, truth.p).agg(F.avg("cv")).first()[0]
        speed = metrics.throughput(steps).first()["tokens_per_s"]
        out.append({"round": k, "m_comp": bounds.m_comp, "p": bounds.p, "cv": cv, "tokens_per_s": speed})
        # the benchmark sees what the schedule has run, each cell once per step
        seen = steps.select(F.lit(0).alias("rep"), "b", "s", "t").distinct()
        new, _ = recalibrate(bounds, seen, target, damping)
        moved = abs(new.m_comp / bounds.m_comp - 1) + abs(new.p - bounds.p)
        bounds = new
        if moved < least_move:
            break
    return out


def waits_in_windows(events: DataFrame, width: str = "6 hours") -> DataFrame:
    """D9 in batch: per window the slowest rank's summed value, ranks seen, and the waiting of the others. events: ts, rank, value."""
    per = events.groupBy(F.window("ts", width).alias("w"), "rank").agg(F.sum("value").alias("t"))
    out = per.groupBy("w").agg(F.max("t").alias("t_sync"), F.count("*").alias("ranks_seen"), (F.count("*") * F.max("t") - F.sum("t")).alias("wait"))
    return out.select(F.col("w.start").alias("window_start"), F.col("w.end").alias("window_end"), "t_sync", "ranks_seen", "wait")
