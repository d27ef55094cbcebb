"""The experiments on the given tables (W1-W13), composed of the operators."""

from __future__ import annotations

import time
from itertools import groupby

import numpy as np
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.sql import register
from ..operators import adaln, batching, costmodel, graphmem, metrics, schedule, telemetry
from ..operators.ranks import key
from ..sources import tables
from ..sources.work import shared_root, written
from ..streaming import loop
from .model import ARMS, SEED, Bounds, CostModel

#: Step-time factor of the fused kernel at equal load, from the published system table (62 s to 56 s).
FUSED_FACTOR = 56 / 62


def _union(frames: list[DataFrame]) -> DataFrame:
    out = frames[0]
    for f in frames[1:]:
        out = out.unionByName(f)
    return out


def flagship(spark: SparkSession, sf_dir: str, n_ranks: int = 16) -> DataFrame:
    """One row per arm: compute variation, range ratios, idle share and throughput under one cost model."""
    rows = tables.clips(spark, sf_dir)
    out = []
    for arm in ARMS:
        steps = schedule.run(rows, arm, n_ranks)
        per = steps.groupBy("step").agg(
            F.first("full").alias("full"), F.sum("tokens").alias("tokens"), F.max("t").alias("t_sync"), F.sum("wait").alias("wait"), (F.stddev_pop("load") / F.avg("load")).alias("cv"),
            *[((F.max(q) - F.min(q)) / F.max(q)).alias(f"range_{q}") for q in metrics.QUANTITIES],
        )
        full = lambda c: F.avg(F.when(F.col("full"), F.col(c)))
        out.append(per.agg(F.lit(arm).alias("arm"), F.count("*").alias("steps"), full("cv").alias("compute_cv"), *[full(f"range_{q}").alias(f"range_{q}") for q in metrics.QUANTITIES], (F.sum(F.when(F.col("full"), F.col("wait"))) / (n_ranks * F.sum(F.when(F.col("full"), F.col("t_sync"))))).alias("idle_share"), (F.sum("tokens") / F.sum("t_sync")).alias("tokens_per_s")))
    return _union(out)


def imbalance_drop(spark: SparkSession, sf_dir: str, n_ranks: int = 16) -> DataFrame:
    """Mean compute variation of both arms and its relative drop."""
    rows = tables.clips(spark, sf_dir)
    base, method = (metrics.compute_cv(schedule.run(rows, arm, n_ranks)).agg(F.avg("cv").alias(n)) for arm, n in zip(ARMS, ("base", "method"), strict=True))
    both = base.crossJoin(method)  # one row each
    return both.select(F.round("base", 6).alias("base"), F.round("method", 6).alias("method"), F.round(metrics.relative_drop(F.col("base"), F.col("method")), 6).alias("relative_drop"))


def ablation(spark: SparkSession, sf_dir: str, n_ranks: int = 16) -> DataFrame:
    """W10, Bl8: throughput of base, fused only, dual only and both; fusing scales times by the published factor."""
    rows = tables.clips(spark, sf_dir)
    out = []
    for arm in ARMS:
        speed = metrics.throughput(schedule.run(rows, arm, n_ranks)).select("tokens_per_s")
        for name, factor in (("unfused", 1.0), ("fused", FUSED_FACTOR)):
            out.append(speed.select(F.lit(f"{arm}_{name}").alias("arm"), F.round(F.col("tokens_per_s") / factor, 4).alias("tokens_per_s")))
    return _union(out)


def scaling(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Per arm, throughput of 16 ranks over twice that of 8."""
    rows, out = tables.clips(spark, sf_dir), []
    for arm in ARMS:
        small, large = (metrics.throughput(schedule.run(rows, arm, n)).select(F.col("tokens_per_s").alias(f"v{n}")) for n in (8, 16))
        out.append(small.crossJoin(large).select(F.lit(arm).alias("arm"), F.round(metrics.scaling(F.col("v8"), F.col("v16")), 6).alias("efficiency")))  # one row each
    return _union(out)


def memory_arms(spark: SparkSession, sf_dir: str, n_ranks: int = 16) -> DataFrame:
    """C11: per arm, greatest and mean tokens of a batch over the memory bound, and the mean's gain over equal-token batching."""
    rows, out = tables.clips(spark, sf_dir), []
    m = Bounds().m_mem
    use = [schedule.schedule(rows, arm, n_ranks).agg((F.max("tokens") / m).alias("peak"), (F.sum("tokens") / (F.count("*") * F.lit(m))).alias("mean")) for arm in ARMS]
    for arm, one in zip(ARMS, use, strict=True):
        both = one.crossJoin(use[0].select(F.col("mean").alias("base")))  # one row each
        out.append(both.select(F.lit(arm).alias("arm"), F.round("peak", 6).alias("peak"), F.round("mean", 6).alias("mean"), F.round(F.col("mean") / F.col("base") - 1, 6).alias("mean_gain")))
    return _union(out)


def swept_lengths(spark: SparkSession, sf_dir: str, step: int = 4000) -> DataFrame:
    """The clips' lengths, rounded up to multiples of `step`: what a sweep has to cover. At most as many rows as there are steps in the longest."""
    return tables.clips(spark, sf_dir).select((F.ceil(F.col("s") / step) * step).cast("long").alias("s")).distinct()


def fit_measured(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Times measured here over the full sweep of the clips' lengths, fitted, and the bound for twice the median time. Differs from run to run."""
    plan = written(costmodel.sweep_plan(spark, swept_lengths(spark, sf_dir), [1, 2, 4, 8]))
    matrix = written(costmodel.sync_matrix(costmodel.run_benchmark(plan, executor="arrow"), "median"))
    top = costmodel.best(costmodel.fit_grid(matrix))
    half = matrix.agg((2 * F.median("t")).alias("target"))
    return top.crossJoin(half).select("n", "p", "a", "slope", "r2", "target", ((F.col("target") - F.col("a")) / F.col("slope")).alias("m_comp"))  # one row each


def loss_agreement(spark: SparkSession, sf_dir: str, w: int = 10) -> DataFrame:
    """Greatest and mean relative gap of the arms' smoothed losses over common steps, and each arm's spikes in the second half of its steps."""
    curves = written(loss_curves(spark, sf_dir))
    base, dual = (curves.where(F.col("arm") == arm).select("step", "loss") for arm in ARMS)
    gap = metrics.loss_gap(base, dual, w)
    for arm, curve in zip(ARMS, (base, dual), strict=True):
        end = (curve.agg(F.max("step")).first()[0] or 0) + 1
        gap = gap.crossJoin(metrics.spikes(curve, end // 2, end, w).agg(F.count("*").alias(f"spikes_{arm}")))  # one row each
    return gap


def gradient_precision(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Greatest differences of parameter gradients accumulated in float32, in order, from those in float64."""
    x = tables.activations(spark, sf_dir)
    full, half = adaln.grad_params(x, "strided"), adaln.grad_params(x, "tiled", acc="float32", ordered=True)
    out = [metrics.max_diff(full, half, ["label", "d"], g).select(F.lit(g).alias("gradient"), "n", "max_abs", "max_rel") for g in ("grad_shift", "grad_scale")]
    return _union(out)


def bounds_sweep(spark: SparkSession, sf_dir: str, n_ranks: int = 16, bounds: tuple[float, ...] = (6e8, 1.2e9, 2.4e9, 4.8e9, 9.6e9)) -> DataFrame:
    """Compute variation and throughput over the compute bound: neither moves in one direction only."""
    rows = tables.clips(spark, sf_dir)
    out = []
    for m in bounds:
        steps = schedule.run(rows, "dual", n_ranks, Bounds(144_000.0, m + 1.5, 2.0))
        per = steps.groupBy("step").agg(F.first("full").alias("full"), (F.stddev_pop("load") / F.avg("load")).alias("cv"), F.sum("tokens").alias("k"), F.max("t").alias("t"))
        out.append(per.agg(F.lit(m).alias("m_comp"), F.avg(F.when(F.col("full"), F.col("cv"))).alias("cv"), (F.sum("k") / F.sum("t")).alias("tokens_per_s")))
    return _union(out)


#: Bounds and step times on the scale of text lengths.
TEXT_BOUNDS, TEXT_MODEL = Bounds(8192.0, 4_194_304.5, 2.0), CostModel(0.01, 2e-7, 2.0)


def text_corpora(spark: SparkSession, sf_dir: str, n_ranks: int = 8) -> DataFrame:
    """The arms on text lengths, in length bins; memory and compute bounds scaled to these lengths, cost without a large constant."""
    bounds, model = TEXT_BOUNDS, TEXT_MODEL
    out = []
    for corpus in ("documents", "conversations", "pages", "benchmark"):
        rows = tables.text_samples(spark, sf_dir, corpus)
        for arm in ARMS:
            steps = schedule.run(rows, arm, n_ranks, bounds, model, kind="geometric")
            per = steps.groupBy("step").agg((F.stddev_pop("load") / F.avg("load")).alias("cv"), ((F.max("t") - F.min("t")) / F.max("t")).alias("rr"), F.sum("tokens").alias("k"), F.max("t").alias("t"))
            out.append(per.agg(F.lit(corpus).alias("corpus"), F.lit(arm).alias("arm"), F.count("*").alias("steps"), F.avg("cv").alias("cv"), F.avg("rr").alias("range_t"), (F.sum("k") / F.sum("t")).alias("tokens_per_s")))
    return _union(out)


def closed_loop(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Recalibration from a bound eight times too high; the truth has exponent 2.1 and a tenth of noise, so bounds move for several rounds."""
    truth = CostModel(2.0, 1.2, 2.1, 1e4)
    start = Bounds(144_000.0, 8 * costmodel.compute_bound(truth, 20.0), 2.1)
    rounds = telemetry.closed_loop(tables.clips(spark, sf_dir), truth, start, 20.0, rounds=4, damping=0.7, noise=0.1)
    return spark.createDataFrame([(r["round"], float(r["m_comp"]), float(r["p"]), float(r["cv"]), float(r["tokens_per_s"])) for r in rounds], "round int, m_comp double, p double, cv double, tokens_per_s double")


def _closed(spark: SparkSession, sf_dir: str, late: str) -> DataFrame:
    return tables.table(spark, sf_dir, "events").agg(F.expr(f"max(CAST(ts AS TIMESTAMP)) - INTERVAL {late}").alias("closed"))


def stream_waits(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The replayed events' windows that the watermark has closed, written by the stream and read back."""
    folder = shared_root(spark, "stream")
    stream = loop.event_stream(spark, f"{sf_dir}/events.parquet")
    query = loop.stream_waits(stream).writeStream.format("parquet").option("path", f"{folder}/out").option("checkpointLocation", f"{folder}/checkpoint").outputMode("append").trigger(availableNow=True).start()
    query.awaitTermination()
    schema = "window_start timestamp, window_end timestamp, t_sync double, ranks_seen long, wait double"
    done = spark.read.schema(schema).parquet(f"{folder}/out").crossJoin(_closed(spark, sf_dir, "1 DAY")).where("window_end <= closed")
    return done.select(F.unix_seconds("window_start").alias("window_start"), F.round("t_sync", 4).alias("t_sync"), "ranks_seen", F.round("wait", 4).alias("wait"))


def stream_sessions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sessions of each user; the streaming form differs by its watermark alone."""
    rows = tables.table(spark, sf_dir, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    out = loop.sessions(rows)
    return out.select("user_id", F.unix_micros("started").alias("started"), F.unix_micros("ended").alias("ended"), "n", F.round("busy", 4).alias("busy"))


def stream_loop(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Bounds refitted by the stream; the last version."""
    folder = shared_root(spark, "stream")
    loop.start_loop(loop.event_stream(spark, f"{sf_dir}/events.parquet"), folder, 20.0).awaitTermination()
    return loop.latest_bounds(spark, folder).select("version", "m_comp", "p", "a", "b", "r2")


def kernel_sweep(spark: SparkSession, sf_dir: str, tokens: tuple[int, ...] = tuple(range(8000, 64_001, 8000))) -> DataFrame:
    """For 8,000 to 64,000 tokens (copies of embeddings): seconds of fused and discrete forward and of tiled and strided
    gradients, their speedups, and bytes of saved activations by the model. Measured here, the better of two runs."""
    out, params = [], tables.modulation(spark, sf_dir).persist()
    n = tables.activations(spark, sf_dir).count()
    for size in tokens:
        x = tables.activations(spark, sf_dir, max(1, -(-size // max(n, 1)))).where(F.col("vec_id") < size).persist()
        seconds = []
        for df in (adaln.forward(x, params, "arrow"), adaln.forward(x, params, "discrete"), adaln.grad_params(x, "tiled"), adaln.grad_params(x, "strided")):
            runs = []
            for _ in range(2):
                start = time.perf_counter()
                df.write.format("noop").mode("overwrite").save()
                runs.append(time.perf_counter() - start)
            seconds.append(min(runs))
        out.append((x.count(), *seconds, seconds[1] / seconds[0], seconds[3] / seconds[2]))
        x.unpersist()
    params.unpersist()
    table = spark.createDataFrame(out, "n long, forward_fused double, forward_discrete double, gradient_tiled double, gradient_strided double, forward_speedup double, gradient_speedup double")
    return table.withColumns({"bytes_fused": graphmem.activation_bytes(F.col("n"), 64, 1, 8), "bytes_discrete": graphmem.activation_bytes(F.col("n"), 64, 5, 8)})


def loss_curves(spark: SparkSession, sf_dir: str, rate: float = 0.5) -> DataFrame:
    """Softmax regression from vectors to labels, mini-batches in both schedulers' order; raw losses by arm and step.

    Lengths come from documents of the same id. Both arms train on every step of their schedule. Vectors pass through the
    driver once an arm, as a training loop would read them: it holds one partition of the ordered rows and one step; of
    past steps it keeps the loss.
    """
    lengths = tables.text_samples(spark, sf_dir, "documents")
    vectors = tables.table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("sample_id"), "embedding", "label")
    rows = lengths.join(vectors.select("sample_id"), "sample_id")
    top = vectors.join(lengths.select("sample_id"), "sample_id").agg(F.max("label")).first()[0]
    bounds, out = Bounds(8192.0, 4_194_304.5, 2.0), []
    for arm in ARMS:
        placed = batching.assign_buckets(rows, "geometric")
        batches = batching.form_batches(placed, batching.plan_buckets(batching.bucket_stats(placed), bounds, arm), members=True)
        order = schedule.assign_steps(batches, 8).select("step", F.explode("members").alias("sample_id"))
        data = order.join(vectors, "sample_id").orderBy("step", "sample_id").select("step", "embedding", "label")
        w = np.zeros((64, int(top or 0) + 1))
        for k, g in groupby(data.toLocalIterator(), key=lambda row: row[0]):
            _, x, y = zip(*g, strict=True)
            x, y = np.array(x, dtype=float), np.array(y)
            z = x @ w
            p = np.exp(z - z.max(axis=1, keepdims=True))
            p /= p.sum(axis=1, keepdims=True)
            out.append((arm, int(k), float(-np.log(np.maximum(p[np.arange(len(y)), y], 1e-12)).mean())))
            p[np.arange(len(y)), y] -= 1
            w -= rate * x.T @ p / len(y)
    return spark.createDataFrame(out, "arm string, step long, loss double")


def _groups(spark: SparkSession, sf_dir: str) -> DataFrame:
    return tables.table(spark, sf_dir, "lineitem").groupBy(F.col("l_partkey").alias("group_id")).agg(F.count("*").alias("rows"))


#: Rows and squared rows that a task may get in the packing workloads.
TASK = Bounds(2000.0, 20_000.0, 2.0)


def pack_tasks(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Parts, rows and load per slot of groups packed under both bounds."""
    slots = schedule.balance_tasks(_groups(spark, sf_dir), TASK)
    return slots.groupBy("slot").agg(F.count("*").alias("parts"), F.sum("size").alias("rows"), F.sum("load").alias("load"))


def barrier_tasks(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Heaviest slot over the mean when groups go by hash to as many slots as the dual bound makes, and by the dual bound; work is quadratic in a group (modelled)."""
    groups, packed = _groups(spark, sf_dir), written(pack_tasks(spark, sf_dir))
    n = packed.agg(F.greatest(F.count("*"), F.lit(1)).alias("n"))
    at = F.conv(F.substring(key(SEED, "group_id"), 1, 8), 16, 10).cast("long") % F.col("n")
    by_hash = groups.crossJoin(F.broadcast(n)).groupBy(at.alias("slot")).agg(F.sum(F.col("rows") * F.col("rows")).cast("double").alias("load"), F.first("n").alias("n"))
    return _union([by_hash.agg(F.lit("hash").alias("how"), (F.max("load") * F.first("n") / F.sum("load")).alias("max_over_mean")), packed.agg(F.lit("dual").alias("how"), (F.max("load") / F.avg("load")).alias("max_over_mean"))])


def asof_bounds(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Telemetry joined to the bounds valid at its time: union, then the last version before each event, per day and carried over days."""
    rows = [(d, f"2024-01-{1 + d:02d} 00:00:00", 1e9 * (1 + d)) for d in range(0, 30, 5)]
    versions = spark.createDataFrame(rows, "version int, since string, m_comp double").select("version", F.to_timestamp_ntz("since").alias("since"), "m_comp")
    # versions are few: each carries its end, and the join is a range join against a broadcast of them
    spans = versions.withColumn("until", F.lead("since").over(Window.orderBy("since")))
    ev = tables.table(spark, sf_dir, "events").select("event_id", "ts")
    return ev.join(F.broadcast(spans), (F.col("ts") >= F.col("since")) & (F.col("until").isNull() | (F.col("ts") < F.col("until")))).select("event_id", "version", "m_comp")


def range_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Clips in named length bands: a range join against a literal table."""
    bands = spark.createDataFrame([("short", 0, 2000), ("middle", 2000, 20_000), ("long", 20_000, 1_000_000)], "band string, lo long, hi long")
    rows = tables.clips(spark, sf_dir).select("s")
    return rows.join(F.broadcast(bands), (F.col("s") >= F.col("lo")) & (F.col("s") < F.col("hi"))).groupBy("band").agg(F.count("*").alias("n"), F.sum("s").alias("tokens"))


def sql_functions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The dual batch size by the registered SQL functions."""
    register(spark)
    batching.bucket_stats(batching.assign_buckets(tables.clips(spark, sf_dir))).createOrReplaceTempView("shape_stats")
    b = Bounds()
    return spark.sql(f"SELECT bucket_id, s, dual_batch(s, {b.m_mem}D, {b.m_comp}D, {b.p}D) AS b FROM shape_stats")
