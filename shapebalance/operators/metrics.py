"""Measures of runs (C1-C19): per step they need one shuffle by step; totals are partial sums."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

QUANTITIES = ("s", "tokens", "load", "t")


def theta(f, h, w, b, t, lam: int = 8, eta: int = 16, gamma: int = 16) -> Column:
    """Latent units of a batch per second."""
    from ..functions.shapes import visual_len

    return visual_len(f, h, w, lam, eta, gamma) * b / t


def pressure(b: str = "b", s: str = "s") -> Column:
    """B * S^2."""
    return F.col(b) * F.col(s).cast("double") * F.col(s).cast("double")


def throughput(steps: DataFrame) -> DataFrame:
    """Tokens over synchronous time, of the run and as the mean of its steps."""
    per = steps.groupBy("step").agg(F.sum("tokens").alias("tokens"), F.max("t").alias("t_sync"))
    return per.agg(F.count("*").alias("steps"), F.sum("tokens").alias("tokens"), F.sum("t_sync").alias("seconds"), (F.sum("tokens") / F.sum("t_sync")).alias("tokens_per_s"), F.avg(F.col("tokens") / F.col("t_sync")).alias("mean_step_tokens_per_s"))


def series(steps: DataFrame) -> DataFrame:
    """step, tokens_per_s of each step."""
    return steps.groupBy("step").agg((F.sum("tokens") / F.max("t")).alias("tokens_per_s"))


def smooth(values: DataFrame, w: int = 20, value: str = "tokens_per_s", block: int = 10_000) -> DataFrame:
    """Trailing mean over w steps, in blocks of steps that carry the w - 1 rows before them, so no task sorts the whole series."""
    block = max(block, w)
    own = F.floor(F.col("step") / block).cast("long")
    # a row also serves the next block when fewer than w steps lie between
    blocks = F.when(F.col("step") % block > block - w, F.array(own, own + 1)).otherwise(F.array(own))
    rows = values.withColumn("_block", F.explode(blocks)).withColumn("_guest", F.col("_block") != own)
    frame = Window.partitionBy("_block").orderBy("step").rangeBetween(-w + 1, 0)
    return rows.withColumn("smoothed", F.avg(value).over(frame)).where("NOT _guest").drop("_block", "_guest")


def changes(values: DataFrame, value: str, block: int = 10_000) -> DataFrame:
    """step and the change of a value since the step before, null at the first; steps count from 0 without gaps, as schedules number them.

    In blocks of steps that carry the one row before them, so no task sorts the whole series.
    """
    own = F.floor(F.col("step") / block).cast("long")
    blocks = F.when(F.col("step") % block == block - 1, F.array(own, own + 1)).otherwise(F.array(own))
    rows = values.withColumn("_block", F.explode(blocks)).withColumn("_guest", F.col("_block") != own)
    change = F.col(value) - F.lag(value).over(Window.partitionBy("_block").orderBy("step"))
    return rows.withColumn("change", change).where("NOT _guest").select("step", "change")


def dips(values: DataFrame, k: float = 2.0, value: str = "tokens_per_s") -> DataFrame:
    """Steps whose value is under mean - k * standard deviation."""
    stats = values.agg(F.avg(value).alias("mean"), F.stddev_pop(value).alias("sd"))
    return values.crossJoin(F.broadcast(stats)).where(F.col(value) < F.col("mean") - k * F.col("sd")).select("step", value)


def range_ratio(steps: DataFrame, quantities: tuple[str, ...] = QUANTITIES, full: bool = True) -> DataFrame:
    """C4: step and (max - min) / max over its ranks of each quantity."""
    rows = steps.where("full") if full else steps
    return rows.groupBy("step").agg(*[((F.max(q) - F.min(q)) / F.max(q)).alias(f"range_{q}") for q in quantities])


def compute_cv(steps: DataFrame, p: float = 2.0, ddof: int = 0, full: bool = True) -> DataFrame:
    """Step and standard deviation over mean of B * S^p over its ranks."""
    rows = (steps.where("full") if full else steps).withColumn("_o", pressure() if p == 2 else F.col("b") * F.pow(F.col("s").cast("double"), F.lit(p)))
    sd = F.stddev_samp("_o") if ddof else F.stddev_pop("_o")
    return rows.groupBy("step").agg((sd / F.avg("_o")).alias("cv"))


def summary(values: DataFrame, columns: list[str], high: float = 0.55) -> DataFrame:
    """Mean of each column over steps and the share of steps over `high`."""
    return values.agg(F.count("*").alias("steps"), *[F.avg(c).alias(f"mean_{c}") for c in columns], *[F.avg((F.col(c) > high).cast("double")).alias(f"high_{c}") for c in columns])


def relative_drop(base: Column, method: Column) -> Column:
    """C7."""
    return (base - method) / base


def load_correlations(steps: DataFrame, p: float = 2.0) -> DataFrame:
    """Correlation of time with tokens, S^2, B * S^2 and B * S^p, in one pass."""
    s = F.col("s").cast("double")
    x = {"r_tokens": F.col("b") * s, "r_s2": s * s, "r_bs2": F.col("b") * s * s, "r_bsp": F.col("b") * F.pow(s, F.lit(p))}
    return steps.agg(F.count("*").alias("n"), *[F.corr("t", v).alias(k) for k, v in x.items()])


def idle_share(steps: DataFrame, n_ranks: int) -> DataFrame:
    """Waiting time over ranks times synchronous time, of full steps."""
    per = steps.where("full").groupBy("step").agg(F.sum("wait").alias("wait"), F.max("t_sync").alias("t"))
    return per.agg(F.sum("wait").alias("wait"), (F.sum("wait") / (n_ranks * F.sum("t"))).alias("idle_share"))


def memory_utilisation(steps: DataFrame, m_mem: float) -> DataFrame:
    """C11: step, highest and mean tokens over m_mem, and the spread across ranks. Tokens are added as whole numbers, so the mean does not depend on their order."""
    u = F.col("tokens") / m_mem
    return steps.groupBy("step").agg(F.max(u).alias("peak"), (F.sum("tokens") / (F.count("*") * F.lit(m_mem))).alias("mean"), (F.max(u) - F.min(u)).alias("spread"))


def spread(values: DataFrame, column: str, high: float | None = None) -> DataFrame:
    """Of a measure over steps: steps, mean, least, percentiles 5, 50, 95, greatest, and the share over `high`.

    Exact percentiles keep one count for each distinct value; steps are few beside samples.
    """
    q = F.percentile(column, F.array(F.lit(0.05), F.lit(0.5), F.lit(0.95)))
    more = [F.avg((F.col(column) > high).cast("double")).alias("share_high")] if high is not None else []
    out = values.agg(F.count(column).alias("steps"), F.avg(column).alias("mean"), F.min(column).alias("least"), q.alias("_q"), F.max(column).alias("greatest"), *more)
    return out.withColumns({f"p{n}": F.col("_q")[i] for i, n in enumerate((5, 50, 95))}).drop("_q")


def padding_waste(batches: DataFrame) -> DataFrame:
    """Share of padded tokens that are padding."""
    return batches.agg(F.sum("real_tokens").alias("real_tokens"), F.sum(F.col("b") * F.col("s")).alias("padded_tokens"), (1 - F.sum("real_tokens") / F.sum(F.col("b") * F.col("s"))).alias("waste"))


def max_diff(a: DataFrame, b: DataFrame, keys: list[str], value: str) -> DataFrame:
    """Rows matched, and the largest absolute and relative difference of a value."""
    both = a.select(*keys, F.col(value).alias("_a")).join(b.select(*keys, F.col(value).alias("_b")), keys)
    d = F.abs(F.col("_a") - F.col("_b"))
    return both.agg(F.count("*").alias("n"), F.max(d).alias("max_abs"), F.max(d / F.greatest(F.abs("_a"), F.abs("_b"), F.lit(1e-12))).alias("max_rel"))


def loss_gap(base: DataFrame, method: DataFrame, w: int = 10) -> DataFrame:
    """Largest and mean relative gap of two smoothed loss curves (step, loss)."""
    a, b = (smooth(x, w, "loss").select("step", F.col("smoothed").alias(n)) for x, n in ((base, "_a"), (method, "_b")))
    gap = F.abs(F.col("_a") - F.col("_b")) / F.greatest(F.abs("_a"), F.lit(1e-12))
    return a.join(b, "step").agg(F.max(gap).alias("max_gap"), F.avg(gap).alias("mean_gap"))


def spikes(curve: DataFrame, low: int, high: int, w: int = 10, k: float = 3.0) -> DataFrame:
    """Steps in [low, high) whose loss exceeds the trailing mean by k standard deviations of the rest."""
    rest = smooth(curve, w, "loss").where((F.col("step") >= low) & (F.col("step") < high)).withColumn("rest", F.col("loss") - F.col("smoothed"))
    sd = rest.agg(F.stddev_pop("rest").alias("sd"))
    return rest.crossJoin(F.broadcast(sd)).where("rest > 0").where(F.col("rest") > k * F.col("sd")).select("step", "loss")


def distribution_gap(samples: DataFrame, batches: DataFrame) -> DataFrame:
    """C17: per bucket, samples before and in batches, and the shares' difference; chi-square sums over buckets at the caller."""
    before = samples.groupBy("bucket_id").agg(F.count("*").alias("before"))
    after = batches.groupBy("bucket_id").agg(F.sum("b").cast("long").alias("after"))
    both = before.join(after, "bucket_id", "full_outer").fillna(0, ["before", "after"])
    return both.withColumn("gap", F.col("after") - F.col("before"))


def chi_square(batches: DataFrame) -> DataFrame:
    """C17: chi-square of the buckets' sample counts (bucket_id, step, b) in the first against the second half of a run's steps, and its degrees of freedom."""
    top = batches.agg((F.max("step") / 2).alias("mid"))
    half = lambda late: F.sum(F.when((F.col("step") >= F.col("mid")) if late else (F.col("step") < F.col("mid")), F.col("b")).otherwise(0))
    cells = batches.crossJoin(F.broadcast(top)).groupBy("bucket_id").agg(half(False).alias("x"), half(True).alias("y"))
    sums = cells.agg(F.sum("x").alias("sx"), F.sum("y").alias("sy"))
    share = F.col("sx") / (F.col("sx") + F.col("sy"))
    want = (F.col("x") + F.col("y")) * share
    apart = (F.col("x") - want) * (F.col("x") - want)
    term = apart / want + apart / ((F.col("x") + F.col("y")) * (1 - share))
    return cells.crossJoin(F.broadcast(sums)).agg(F.sum(term).alias("chi_square"), (F.count("*") - 1).alias("freedom"))


def ks_by_half(steps: DataFrame) -> DataFrame:
    """C17: largest distance of the length distributions of a run's first and second half, over distinct lengths."""
    top = steps.agg((F.max("step") / 2).alias("mid"))
    n = steps.crossJoin(F.broadcast(top)).groupBy("s").agg(F.sum(F.when(F.col("step") < F.col("mid"), F.col("b")).otherwise(0)).alias("x"), F.sum(F.when(F.col("step") >= F.col("mid"), F.col("b")).otherwise(0)).alias("y"))
    w, all_rows = Window.orderBy("s"), Window.partitionBy()
    gap = F.abs(F.sum("x").over(w) / F.sum("x").over(all_rows) - F.sum("y").over(w) / F.sum("y").over(all_rows))
    return n.select(gap.alias("gap")).agg(F.max("gap").alias("ks"))


def scaling(small: Column, large: Column, factor: float = 2.0) -> Column:
    """Throughput of `factor` times the ranks over `factor` times the throughput."""
    return large / (factor * small)


def speedup(native: Column, fused: Column) -> Column:
    """C13."""
    return native / fused


def plan_cost(df: DataFrame) -> dict[str, int]:
    """Exchanges, joins, generated rows' operators and Python nodes of a physical plan."""
    text = df._jdf.queryExecution().executedPlan().toString()
    count = lambda *names: sum(text.count(n) for n in names)
    return {"exchanges": count("Exchange hashpartitioning", "Exchange rangepartitioning", "Exchange SinglePartition"), "joins": count("SortMergeJoin", "BroadcastHashJoin", "ShuffledHashJoin"), "generates": count("Generate "), "python": count("MapInArrow", "MapInPandas", "FlatMapGroups")}
