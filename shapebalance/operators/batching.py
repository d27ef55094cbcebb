"""Buckets and batch sizes (M4-M8, M41) with the baselines they are compared with (Bl1-Bl3)."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.shapes import visual_len
from ..plans.model import SEED, Bounds
from .ranks import key, ranked

LADDER = (256, 640, 1600, 4680, 12_000, 24_000, 36_000, 52_800)


def assign_buckets(df: DataFrame, kind: str = "shape", width: int = 4096, ladder: tuple[int, ...] = LADDER) -> DataFrame:
    """M4: adds bucket_id and s_pad, the length that its samples are padded to. Narrow.

    shape: one bucket per (f, h, w), and per 64 text tokens where s_text is there; linear: lengths in bins of `width`;
    geometric: powers of two; ladder: the shortest allowed length that holds the sample, beyond the last one its multiples.
    """
    s = F.col("s")
    if kind == "shape":
        parts = [F.col(c).cast("string") for c in ("f", "h", "w")]
        if "s_text" in df.columns:
            parts.append(F.when(F.col("s_text") > 0, F.ceil(F.col("s_text") / 64).cast("string")))
        return df.withColumn("bucket_id", F.concat_ws("x", *parts)).withColumn("s_pad", s)
    if kind == "linear":
        top = F.ceil(s / width).cast("long") * width
    elif kind == "geometric":
        top = F.expr("CASE WHEN s <= 1 THEN 1L ELSE shiftleft(1L, length(bin(s - 1))) END")
    elif kind == "ladder":
        steps = F.array(*[F.lit(x).cast("long") for x in ladder])
        top = F.coalesce(F.array_min(F.filter(steps, lambda x: x >= s)), F.ceil(s / max(ladder)).cast("long") * max(ladder))
    else:
        raise ValueError(f"unknown kind {kind!r}")
    return df.withColumn("s_pad", top).withColumn("bucket_id", F.concat(F.lit(kind[0]), top.cast("string")))


def bucket_stats(df: DataFrame) -> DataFrame:
    """M5: n, sum_s, min_s, max_s and s (the padded length) per bucket; partial sums leave K rows per partition to shuffle."""
    return df.groupBy("bucket_id").agg(F.count("*").alias("n"), F.sum("s").alias("sum_s"), F.min("s").alias("min_s"), F.max("s").alias("max_s"), F.max("s_pad").alias("s"))


def _power(s: Column, p: float) -> Column:
    return s.cast("double") * s.cast("double") if p == 2 else F.pow(s.cast("double"), F.lit(float(p)))


def batch_size(s: Column, bounds: Bounds, policy: str = "dual", fixed: int = 4) -> Column:
    """M6, M6c, M6d, Bl1, Bl2: samples of length s in a batch, at least 1."""
    memory, compute = F.floor(F.lit(bounds.m_mem) / s).cast("long"), F.floor(F.lit(bounds.m_comp) / _power(s, bounds.p)).cast("long")
    sizes = {"dual": F.least(memory, compute), "memory": memory, "equal_token": memory, "compute": compute, "fixed": F.lit(fixed).cast("long")}
    if policy not in sizes:
        raise ValueError(f"unknown policy {policy!r}")
    return F.greatest(F.lit(1).cast("long"), sizes[policy])


def binding_constraint(s: Column, bounds: Bounds) -> Column:
    """What sets the dual batch size: memory, compute, tie (both floors agree), or unit (a floor is 0, so a bound is exceeded at one sample)."""
    memory, compute = F.floor(F.lit(bounds.m_mem) / s), F.floor(F.lit(bounds.m_comp) / _power(s, bounds.p))
    return F.when((memory < 1) | (compute < 1), "unit").when(memory < compute, "memory").when(compute < memory, "compute").otherwise("tie")


def plan_buckets(stats: DataFrame, bounds: Bounds = Bounds(), policy: str = "dual", fixed: int = 4, table: DataFrame | None = None) -> DataFrame:
    """M6: the statistics with b, bound and over_memory, over_compute (one sample alone exceeds a bound).

    policy manual takes b from `table` (bucket_id, b), a small table that Spark broadcasts after its size check, and the
    fixed size where a bucket is missing.
    """
    s = F.col("s")
    if policy == "manual":
        plan = stats.join(table.select("bucket_id", F.col("b").cast("long").alias("b")), "bucket_id", "left").withColumn("b", F.greatest(F.lit(1), F.coalesce("b", F.lit(fixed).cast("long"))))
    else:
        plan = stats.withColumn("b", batch_size(s, bounds, policy, fixed))
    return plan.withColumns({"bound": binding_constraint(s, bounds), "over_memory": s > bounds.m_mem, "over_compute": _power(s, bounds.p) > bounds.m_comp})


def crossover_len(bounds: Bounds) -> float:
    """The length at which both bounds allow the same batch (p > 1)."""
    if bounds.p <= 1:
        raise ValueError("the bounds cross for p > 1 only")
    return (bounds.m_comp / bounds.m_mem) ** (1 / (bounds.p - 1))


def memory_bound(capacity: float, static: float, bytes_per_token: float) -> float:
    """M7: tokens that fit beside the static part."""
    if bytes_per_token <= 0 or capacity <= static:
        raise ValueError("nothing fits")
    return (capacity - static) / bytes_per_token


def max_frames(m_mem: float, b: int, h: int, w: int, lam: int = 8, eta: int = 16, gamma: int = 16) -> int:
    """Most frames (of the form 1 + lam * k) with b samples within m_mem tokens; 0 if none."""
    latent = math.floor(m_mem / (b * (h // eta) * (w // gamma)))
    return 0 if latent < 1 else 1 + lam * (latent - 1)


def most_frames(m_mem: Column, b: Column, h: Column, w: Column, lam: int = 8) -> Column:
    """M41 over columns; null where a frame has no latent pixel."""
    latent = F.floor(m_mem / F.nullif(b * visual_len(F.lit(1), h, w, lam), F.lit(0)))
    return F.when(latent < 1, F.lit(0)).otherwise(1 + lam * (latent - 1)).cast("long")


def form_batches(df: DataFrame, plan: DataFrame, seed: int = SEED, tail: str = "keep", members: bool = False) -> DataFrame:
    """M8: samples (sample_id, bucket_id, s) in batches: batch_id, bucket_id, batch_no, s (padded), b, tokens, plan_b[, members].

    Inside a bucket samples follow a keyed hash and are cut by the plan's b. tail: keep the short last batch, drop it,
    or pad (it counts as b). One shuffle of ids by (bucket, hash digits) and one of batches; the plan has K rows.
    """
    rows = df.select("sample_id", "bucket_id", F.col("s").alias("own_s")).withColumn("k", key(seed, "sample_id"))
    placed = ranked(rows, "r", "k", within=("bucket_id",)).join(plan.select("bucket_id", F.col("s"), F.col("b").alias("plan_b")), "bucket_id")
    placed = placed.withColumn("batch_no", F.floor(F.col("r") / F.col("plan_b")).cast("long"))
    more = [F.sort_array(F.collect_list("sample_id")).alias("members")] if members else []
    out = placed.groupBy("bucket_id", "batch_no", "s", "plan_b").agg(F.count("*").alias("b"), F.sum("own_s").alias("real_tokens"), *more)
    if tail == "drop":
        out = out.where("b = plan_b")
    elif tail == "pad":
        out = out.withColumn("b", F.col("plan_b"))
    out = out.withColumn("batch_id", F.concat_ws("#", "bucket_id", F.col("batch_no").cast("string"))).withColumn("tokens", F.col("b") * F.col("s"))
    return out.select("batch_id", "bucket_id", "batch_no", "s", "b", "plan_b", "tokens", "real_tokens", *(["members"] if members else []))


def sorted_padded_batches(df: DataFrame, m_mem: float = 144_000.0, block: int = 1024) -> DataFrame:
    """Bl3: samples sorted by length, descending, cut where the padded tokens of a batch would exceed m_mem.

    The order is cut in runs of `block` equal-or-shorter samples, inside which the padded length is the run's longest, so
    runs are packed apart from each other: batch number = position in run // (m_mem // longest).
    """
    rows = df.select("sample_id", "s").withColumn("k", key(SEED, "sample_id"))
    placed = ranked(rows, "r", "k", order=(("s", False),)).withColumn("run", F.floor(F.col("r") / block).cast("long"))
    top = placed.groupBy("run").agg(F.max("s").alias("top"))
    size = F.greatest(F.lit(1), F.floor(F.lit(m_mem) / F.col("top"))).cast("long")
    placed = placed.join(top, "run").withColumn("no", F.floor((F.col("r") % block) / size).cast("long"))
    return placed.groupBy("run", "no").agg(F.max("s").alias("s"), F.count("*").alias("b"), F.sum("s").alias("real_tokens"))


def running_lengths(df: DataFrame) -> DataFrame:
    """Share of samples and of tokens up to each distinct length (a table of distinct lengths, not of samples)."""
    by = df.groupBy("s").agg(F.count("*").alias("n")).withColumn("tokens", F.col("n") * F.col("s"))
    w = Window.orderBy("s")
    return by.select("s", "n", F.sum("n").over(w).alias("n_to"), F.sum("tokens").over(w).alias("tokens_to"))
