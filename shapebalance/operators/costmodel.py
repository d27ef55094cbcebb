"""The shape benchmark, the fit of the step-time model and the compute bound (M13-M22, M28, M29, Bl6)."""

from __future__ import annotations

import time
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..plans.model import CostModel
from ..ship import ship

S_REF = 1e4


def sweep_plan(spark: SparkSession, s_values: list[int] | DataFrame, b_levels: list[int], reps: int = 3, mode: str = "grid", s_long: int = 20_000, cap: float = 144_000.0) -> DataFrame:
    """Cells (b, s, rep, priority) with b * s within the cap, for lengths given or read from a table's column s.

    grid: all pairs. throughput: all levels for s >= s_long, only the first and the last that fits for shorter ones;
    long cells come first by priority. A few thousand rows whatever the corpus.
    """
    s = s_values.select(F.col("s").cast("long").alias("s")).distinct() if isinstance(s_values, DataFrame) else spark.createDataFrame([(int(x),) for x in s_values], "s long")
    b = F.array(*[F.lit(int(x)).cast("long") for x in sorted(b_levels)])
    fits = F.filter(b, lambda x: x * F.col("s") <= cap)
    if mode == "throughput":
        fits = F.when(F.col("s") >= s_long, fits).otherwise(F.array_distinct(F.filter(F.array(F.element_at(fits, 1), F.element_at(fits, -1)), lambda x: x.isNotNull())))
    cells = s.where(F.size(F.filter(b, lambda x: x * F.col("s") <= cap)) > 0).select("s", F.explode(fits).alias("b"))
    cells = cells.withColumn("rep", F.explode(F.sequence(F.lit(0), F.lit(reps - 1))))
    return cells.withColumn("priority", F.when(F.col("s") >= s_long, F.col("b") * F.col("s")).otherwise(0)).select("b", "s", "rep", "priority")


def run_benchmark(plan: DataFrame, model: CostModel = CostModel(2.0, 1.2, 2.1, S_REF), ranks: int = 8, executor: str = "model", scale: int = 16, block: int = 512) -> DataFrame:
    """A trace (rep, rank, b, s, t) of the planned cells.

    model: the declared generator, ranks differing by a hundredth each. arrow: each cell in a task of its own multiplies
    b times all pairs of s / scale synthetic rows, `block` rows against all at a time, and takes the time of that alone:
    work b * (s / scale)^2 in memory for block * s / scale numbers. Making the rows, and one untimed product, come first.
    """
    if executor == "model":
        rows = plan.withColumn("rank", F.explode(F.sequence(F.lit(0), F.lit(ranks - 1))))
        t = model.a + model.b * F.col("b") * F.pow(F.col("s") / model.s_ref, F.lit(model.p))
        return rows.select("rep", "rank", "b", "s", (t * (1 - 0.01 * F.col("rank"))).alias("t"))

    ship(plan.sparkSession)

    def measure(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in batch.to_pylist():
                x = np.random.default_rng(row["rep"]).random((max(1, row["s"] // scale), 64), np.float32)
                (x[:block] @ x.T).sum()
                start = time.perf_counter()
                for _ in range(row["b"]):
                    for i in range(0, len(x), block):
                        (x[i : i + block] @ x.T).sum()
                yield pa.RecordBatch.from_pylist([{"rep": row["rep"], "rank": row["rep"] % ranks, "b": row["b"], "s": row["s"], "t": time.perf_counter() - start}], pa.schema([("rep", pa.int32()), ("rank", pa.int32()), ("b", pa.int64()), ("s", pa.int64()), ("t", pa.float64())]))

    n = plan.count()
    slots = plan.orderBy(F.desc("priority")).withColumn("_slot", F.pmod(F.hash("b", "s", "rep"), F.lit(max(1, n))))
    return slots.repartitionById(max(1, n), F.col("_slot")).drop("_slot", "priority").mapInArrow(measure, "rep int, rank int, b long, s long, t double")


def sync_matrix(trace: DataFrame, stat: str = "mean", warmup: int = 0) -> DataFrame:
    """Per (b, s): repetitions n, and mean or median over them of the slowest rank's time. Repetitions under `warmup` are left out."""
    slow = trace.where(F.col("rep") >= warmup).groupBy("rep", "b", "s").agg(F.max("t").alias("t"))
    return slow.groupBy("b", "s").agg(F.count("*").alias("n"), (F.avg("t") if stat == "mean" else F.median("t")).alias("t"))


def cells(trace: DataFrame) -> DataFrame:
    """Sufficient statistics (n, sum_t, sum_t2) per (b, s), so that a fit over any number of rows costs cells times grid."""
    return trace.groupBy("b", "s").agg(F.count("*").alias("n"), F.sum("t").alias("sum_t"), F.sum(F.col("t") * F.col("t")).alias("sum_t2"))


def as_matrix(matrix: DataFrame, levels: list[int]) -> DataFrame:
    """One row per s, one column b_<level> per batch size."""
    return matrix.groupBy("s").pivot("b", levels).agg(F.first("t")).select("s", *[F.col(str(x)).alias(f"b_{x}") for x in levels])


def _load(p, s_ref: float):
    return F.col("b") * F.pow(F.col("s") / s_ref, p)


def fit_grid(matrix: DataFrame, lo: float = 1.6, hi: float = 2.4, step: float = 0.01, s_ref: float = S_REF) -> DataFrame:
    """For each p of the grid, a, b and r2 of t on b * (s / s_ref)^p over a sync matrix."""
    n = round((hi - lo) / step)
    grid = F.explode(F.sequence(F.lit(0), F.lit(n))).alias("i")
    rows = matrix.select("b", "s", "t", grid).withColumn("p", F.round(lo + F.col("i") * step, 6)).withColumn("x", _load(F.col("p"), s_ref))
    return rows.groupBy("p").agg(F.count("*").alias("n"), F.regr_intercept("t", "x").alias("a"), F.regr_slope("t", "x").alias("slope"), F.regr_r2("t", "x").alias("r2"))


def fit_weighted(cell_rows: DataFrame, lo: float = 1.6, hi: float = 2.4, step: float = 0.01, s_ref: float = S_REF) -> DataFrame:
    """The same over all rows behind the cells, exactly, from their sums."""
    n = round((hi - lo) / step)
    rows = cell_rows.select("b", "s", "n", "sum_t", "sum_t2", F.explode(F.sequence(F.lit(0), F.lit(n))).alias("i")).withColumn("p", F.round(lo + F.col("i") * step, 6)).withColumn("x", _load(F.col("p"), s_ref))
    sums = rows.groupBy("p").agg(F.sum("n").alias("n"), F.sum(F.col("n") * F.col("x")).alias("sx"), F.sum("sum_t").alias("sy"), F.sum(F.col("n") * F.col("x") * F.col("x")).alias("sxx"), F.sum(F.col("x") * F.col("sum_t")).alias("sxy"), F.sum("sum_t2").alias("syy"))
    xx, xy, yy = (F.expr(e) for e in ("sxx - sx * sx / n", "sxy - sx * sy / n", "syy - sy * sy / n"))
    return sums.select("p", "n", ((F.col("sy") - xy / xx * F.col("sx")) / F.col("n")).alias("a"), (xy / xx).alias("slope"), (xy * xy / (xx * yy)).alias("r2"))


def best(fits: DataFrame, digits: int = 9) -> DataFrame:
    """The row of largest r2 (rounded to `digits`), the smallest p of equals."""
    return fits.orderBy(F.round("r2", digits).desc(), "p").limit(1)


def refine(matrix: DataFrame, lo: float = 1.6, hi: float = 2.4, s_ref: float = S_REF) -> DataFrame:
    """Steps of a tenth over the interval, then of a hundredth around the best."""
    top = best(fit_grid(matrix, lo, hi, 0.1, s_ref)).first()
    if top is None:
        return fit_grid(matrix, lo, hi, 0.1, s_ref)
    return best(fit_grid(matrix, max(lo, top["p"] - 0.1), min(hi, top["p"] + 0.1), 0.01, s_ref))


def fit_at(matrix: DataFrame, p: float, s_ref: float = S_REF) -> DataFrame:
    """M18, Bl6: the fit at one exponent; p = 1 is the linear baseline."""
    return fit_grid(matrix, p, p, 1.0, s_ref)


def to_model(fits: DataFrame, s_ref: float = S_REF) -> CostModel:
    """The best fit as a record: one row reaches the driver. Errors without two distinct loads or with a slope that is not positive."""
    row = best(fits).first()
    if row is None or row["slope"] is None or row["r2"] is None:
        raise ValueError("a fit needs at least two distinct loads")
    if row["slope"] <= 0:
        raise ValueError("time does not grow with load")
    return CostModel(row["a"], row["slope"], row["p"], s_ref, row["r2"], row["n"])


def compute_bound(model: CostModel, target: float) -> float:
    """The load at which the model reaches the target time, in units of s_ref = 1."""
    if model.b <= 0 or target <= model.a:
        raise ValueError("the target must exceed the constant part, and the slope be positive")
    return (target - model.a) / model.b * model.s_ref**model.p


def residuals(matrix: DataFrame, model: CostModel, band: int = 10_000) -> DataFrame:
    """Per band of s and in total (band null): cells, mean residual, mean absolute relative error, correlation r of time and fit within."""
    fit = model.a + model.b * _load(F.lit(model.p), model.s_ref)
    rows = matrix.withColumn("fit", fit).withColumn("band", F.floor(F.col("s") / band).cast("long"))
    return rows.rollup("band").agg(F.count("*").alias("n"), F.avg(F.col("t") - F.col("fit")).alias("mean_residual"), F.avg(F.abs(F.col("t") - F.col("fit")) / F.col("t")).alias("mape"), F.corr("t", "fit").alias("r"))


def fit_two_term(matrix: DataFrame, s_ref: float = S_REF) -> DataFrame:
    """t = a + b1 * B * S + b2 * B * S^2 by the normal equations over centred sums."""
    x, z = F.col("b") * F.col("s") / s_ref, F.col("b") * F.pow(F.col("s") / s_ref, F.lit(2.0))
    m = matrix.select("t", x.alias("x"), z.alias("z")).agg(F.count("*").alias("n"), F.avg("x").alias("mx"), F.avg("z").alias("mz"), F.avg("t").alias("mt"), F.covar_pop("x", "z").alias("xz"), F.var_pop("x").alias("xx"), F.var_pop("z").alias("zz"), F.covar_pop("x", "t").alias("xt"), F.covar_pop("z", "t").alias("zt"), F.var_pop("t").alias("tt"))
    det = "(xx * zz - xz * xz)"
    b1, b2 = f"((xt * zz - zt * xz) / {det})", f"((zt * xx - xt * xz) / {det})"
    return m.select("n", F.expr(f"mt - {b1} * mx - {b2} * mz").alias("a"), F.expr(b1).alias("b1"), F.expr(b2).alias("b2"), F.expr(f"({b1} * xt + {b2} * zt) / tt").alias("r2"))


def sweep_targets(stats: DataFrame, model: CostModel, targets: list[float], m_mem: float = 144_000.0) -> DataFrame:
    """Per target time: the bound it gives, tokens and model seconds of one pass over all buckets, tokens per second and the share of samples bound by compute."""
    bounds = stats.sparkSession.createDataFrame([(float(t), compute_bound(model, t)) for t in targets], "target double, m_comp double")
    s = F.col("s").cast("double")
    rows = stats.crossJoin(F.broadcast(bounds)).withColumn("mem", F.floor(m_mem / s)).withColumn("comp", F.floor(F.col("m_comp") / F.pow(s, F.lit(model.p))))
    rows = rows.withColumn("b", F.greatest(F.lit(1.0), F.least("mem", "comp"))).withColumn("batches", F.ceil(F.col("n") / F.col("b")))
    t = model.a + model.b * F.col("b") * F.pow(s / model.s_ref, F.lit(model.p))
    return rows.groupBy("target", "m_comp").agg(F.sum(F.col("n") * F.col("s")).alias("tokens"), F.sum(F.col("batches") * t).alias("seconds"), F.max(t).alias("slowest"), (F.sum(F.when(F.col("comp") < F.col("mem"), F.col("n")).otherwise(0)) / F.sum("n")).alias("compute_share")).withColumn("tokens_per_s", F.col("tokens") / F.col("seconds"))
