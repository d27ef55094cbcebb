"""All queries of the engine over the given tables, each with its SQL where SQL can express it."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.shapes import token_len, visual_len
from ..operators import adaln, batching, costmodel, graphmem, metrics, schedule, telemetry
from ..sources import tables
from . import oracles as O
from . import workloads
from .model import ARMS, Bounds, CostModel

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}
B, MODEL = Bounds(), CostModel()


def add(name: str, query: Query, sql: str | None = None) -> None:
    QUERIES[name] = query
    if sql is not None:
        ORACLES[name] = sql


def r(c: Column | str, digits: int = 6) -> Column:
    return F.round(F.col(c) if isinstance(c, str) else c, digits)


def rounded(df: DataFrame, *columns: str, digits: int = 6) -> DataFrame:
    return df.withColumns({c: F.round(c, digits) for c in columns})


def clips(spark, d) -> DataFrame:
    return batching.assign_buckets(tables.clips(spark, d))


def stats(spark, d) -> DataFrame:
    return batching.bucket_stats(clips(spark, d))


def steps_of(spark, d, policy="dual", n=16, how="random") -> DataFrame:
    return schedule.run(tables.clips(spark, d), policy, n, steps=how)


# ---- lengths ---------------------------------------------------------------------------------------------------------
add("seq_len_clips", lambda s, d: tables.clips(s, d), O.with_(O.CLIPS, select="SELECT sample_id, modality, CAST(f AS INTEGER) AS f, h, w, s_text, s_visual, s FROM clips"))
add("seq_len_documents", lambda s, d: tables.text_samples(s, d, "documents"), f"SELECT doc_id AS sample_id, 'documents' AS corpus, CAST({O.words('text')} AS BIGINT) AS s FROM documents")
add("seq_len_conversations", lambda s, d: tables.text_samples(s, d, "conversations"), f"SELECT conv_id AS sample_id, 'conversations' AS corpus, CAST(sum({O.words('text')}) AS BIGINT) AS s FROM conversations GROUP BY conv_id")
add("seq_len_pages", lambda s, d: tables.text_samples(s, d, "pages"), f"SELECT page_id AS sample_id, 'pages' AS corpus, CAST({O.words(O.STRIPPED)} AS BIGINT) AS s FROM pages")
add("seq_len_caption", lambda s, d: tables.clips(s, d, "caption").select("sample_id", "s_text", "s"), O.with_(O.CLIPS, f"caps AS (SELECT doc_id, CAST({O.words('text')} AS BIGINT) AS n FROM documents)", select="SELECT sample_id, coalesce(n, 0) AS s_text, s_visual + coalesce(n, 0) AS s FROM clips LEFT JOIN caps ON doc_id = sample_id % (SELECT count(*) FROM documents)"))
add("token_len_chars", lambda s, d: tables.table(s, d, "documents").select("doc_id", token_len("text", "chars").alias("s")), "SELECT doc_id, CAST(greatest(1, (length(coalesce(text, '')) + 3) // 4) AS BIGINT) AS s FROM documents")
add("visual_len_rounding", lambda s, d: tables.clips(s, d).select("sample_id", visual_len(rounding="ceil").alias("up"), visual_len().alias("down")), O.with_(O.CLIPS, select="SELECT sample_id, CAST(((f - 1 + 7) // 8 + 1) * ((h + 15) // 16) * ((w + 15) // 16) AS BIGINT) AS up, s_visual AS down FROM clips"))

# ---- buckets and sizes -----------------------------------------------------------------------------------------------
add("bucket_stats", stats, O.with_(O.CLIPS, O.stats(), select="SELECT * FROM stats"))
add("bucket_linear", lambda s, d: batching.bucket_stats(batching.assign_buckets(tables.text_samples(s, d, "documents"), "linear", 256)), O.with_(f"docs AS (SELECT CAST({O.words('text')} AS BIGINT) AS s FROM documents)", "b AS (SELECT s, CAST(ceil(s / 256.0) AS BIGINT) * 256 AS top, concat('l', CAST(ceil(s / 256.0) AS BIGINT) * 256) AS bucket_id FROM docs)", O.stats("b", "max(top)"), select="SELECT * FROM stats"))
add("bucket_geometric", lambda s, d: batching.bucket_stats(batching.assign_buckets(tables.text_samples(s, d, "documents"), "geometric")), O.with_(f"docs AS (SELECT CAST({O.words('text')} AS BIGINT) AS s FROM documents)", "t AS (SELECT s, CASE WHEN s <= 1 THEN 1 ELSE 1 << length(bin(s - 1)) END AS top FROM docs)", "b AS (SELECT s, CAST(top AS BIGINT) AS top, concat('g', top) AS bucket_id FROM t)", O.stats("b", "max(top)"), select="SELECT * FROM stats"))
add("bucket_ladder", lambda s, d: batching.bucket_stats(batching.assign_buckets(tables.clips(s, d), "ladder")), O.with_(O.CLIPS, f"steps AS (SELECT CAST(unnest([{O.LADDER_SQL}]) AS BIGINT) AS step)", "near AS (SELECT sample_id, s, min(step) AS top FROM clips, steps WHERE step >= s GROUP BY sample_id, s)", "b AS (SELECT s, top, concat('l', top) AS bucket_id FROM near)", O.stats("b", "max(top)"), select="SELECT * FROM stats"))
for policy, name in (("dual", "batch_dual"), ("equal_token", "batch_equal_token"), ("memory", "batch_memory_only"), ("compute", "batch_compute_only"), ("fixed", "batch_fixed")):
    add(name, lambda s, d, p=policy: batching.plan_buckets(stats(s, d), B, p).select("bucket_id", "n", "s", "b"), O.with_(O.CLIPS, O.stats(), select=f"SELECT bucket_id, n, s, CAST({O.size(policy)} AS BIGINT) AS b FROM stats"))
add("batch_manual", lambda s, d: batching.plan_buckets(stats(s, d), B, "manual", table=s.createDataFrame([("1x640x640", 64), ("233x640x640", 1)], "bucket_id string, b int")).select("bucket_id", "b"), O.with_(O.CLIPS, O.stats(), select="SELECT bucket_id, CAST(CASE bucket_id WHEN '1x640x640' THEN 64 WHEN '233x640x640' THEN 1 ELSE 4 END AS BIGINT) AS b FROM stats"))
add("batch_sorted_padded", lambda s, d: batching.sorted_padded_batches(tables.clips(s, d)).select("run", "no", "s", "b", "real_tokens"), O.with_(O.CLIPS, f"o AS (SELECT s, row_number() OVER (ORDER BY s DESC, md5(concat('{O.SEED}:', sample_id))) - 1 AS r FROM clips)", "t AS (SELECT *, r // 1024 AS run, max(s) OVER (PARTITION BY r // 1024) AS top FROM o)", select="SELECT run, CAST((r % 1024) // greatest(1, CAST(floor(144000.0 / top) AS BIGINT)) AS BIGINT) AS no, max(s) AS s, count(*) AS b, CAST(sum(s) AS BIGINT) AS real_tokens FROM t GROUP BY 1, 2"))
add("binding_constraint", lambda s, d: batching.plan_buckets(stats(s, d)).groupBy("bound").agg(F.count("*").alias("buckets"), F.sum("n").alias("samples"), F.sum(F.col("over_compute").cast("long")).alias("over_compute")), O.with_(O.CLIPS, O.stats(), select=f"SELECT {O.BOUND} AS bound, count(*) AS buckets, CAST(sum(n) AS BIGINT) AS samples, CAST(sum(CASE WHEN CAST(s AS DOUBLE) * s > {B.m_comp} THEN 1 ELSE 0 END) AS BIGINT) AS over_compute FROM stats GROUP BY 1"))


def _max_frames(spark, d):
    bounds = spark.createDataFrame([(m, b) for m in (144_000, 158_400) for b in (1, 3)], "m_mem long, b int")
    shapes = tables.clips(spark, d).groupBy("h", "w", "f").agg(F.count("*").alias("n")).crossJoin(F.broadcast(bounds))
    rows = shapes.withColumn("frames", batching.most_frames(F.col("m_mem"), F.col("b"), F.col("h"), F.col("w")))
    return rows.groupBy("m_mem", "b", "h", "w", "frames").agg(F.sum("n").alias("clips"), F.sum(F.when(F.col("f") > F.col("frames"), F.col("n")).otherwise(0)).alias("longer"))


add("max_frames", _max_frames, O.with_(O.CLIPS, "r AS (SELECT CAST(m_mem AS BIGINT) AS m_mem, b, h, w, f, CAST(CASE WHEN floor(m_mem / (b * (h // 16) * (w // 16))) < 1 THEN 0 ELSE 1 + 8 * (floor(m_mem / (b * (h // 16) * (w // 16))) - 1) END AS BIGINT) AS frames FROM clips, (SELECT unnest([144000, 158400]) AS m_mem), (SELECT unnest([1, 3]) AS b))", select="SELECT m_mem, b, h, w, frames, count(*) AS clips, count(*) FILTER (f > frames) AS longer FROM r GROUP BY m_mem, b, h, w, frames"))

# ---- batches and steps -----------------------------------------------------------------------------------------------
for policy, name in (("equal_token", "equal"), ("dual", "dual")):
    add(f"form_batches_{name}", lambda s, d, p=policy: batching.form_batches(clips(s, d), batching.plan_buckets(stats(s, d), B, p)), O.with_(O.CLIPS, O.stats(), O.batches(policy), select="SELECT * FROM batches"))
for how in ("random", "round_robin", "load_sorted", "bucket_hash"):
    add(f"steps_{how}", lambda s, d, h=how: steps_of(s, d, how=h).select("batch_id", "step", "rank", "full"), O.with_(O.CLIPS, O.stats(), O.run("dual", 16, how), select='SELECT batch_id, step, rank, "full" FROM steps'))
add("steps_lpt", lambda s, d: rounded(metrics.compute_cv(steps_of(s, d, how="lpt")), "cv"))
add("step_time", lambda s, d: rounded(schedule.step_time(steps_of(s, d)), "t_sync"), O.with_(O.CLIPS, O.stats(), O.run("dual", 16), select="SELECT step, round(max(t), 6) AS t_sync, count(*) AS ranks, CAST(sum(tokens) AS BIGINT) AS tokens FROM steps GROUP BY step"))
add("theta", lambda s, d: steps_of(s, d).select("batch_id", r(metrics.theta(*[F.element_at(F.split("bucket_id", "x"), i).cast("int") for i in (1, 2, 3)], F.col("b"), F.col("t")), 4).alias("theta")), O.with_(O.CLIPS, O.stats(), O.run("dual", 16), select="SELECT batch_id, round(s * b / t, 4) AS theta FROM steps"))


def thr_sql(policy, n):
    return O.with_(O.CLIPS, O.stats(), O.run(policy, n), "per AS (SELECT step, sum(tokens) AS k, max(t) AS t FROM steps GROUP BY step)", select="SELECT count(*) AS steps, CAST(sum(k) AS BIGINT) AS tokens, round(sum(t), 4) AS seconds, round(sum(k) / sum(t), 4) AS tokens_per_s, round(avg(k / t), 4) AS mean_step_tokens_per_s FROM per")


for n in (8, 16):
    for policy, name in (("equal_token", "equal"), ("dual", "dual")):
        add(f"throughput_{n}_{name}", lambda s, d, n=n, p=policy: rounded(metrics.throughput(steps_of(s, d, p, n)), "seconds", "tokens_per_s", "mean_step_tokens_per_s", digits=4), thr_sql(policy, n))
    both = lambda q: ", ".join(f"round((max({x}) - min({x})) / max({x}), 6) AS range_{x}" for x in q)
    add(f"range_ratio_{n}", lambda s, d, n=n: rounded(metrics.range_ratio(steps_of(s, d, n=n)), *[f"range_{q}" for q in metrics.QUANTITIES]), O.with_(O.CLIPS, O.stats(), O.run("dual", n), select=f'SELECT step, {both(metrics.QUANTITIES)} FROM steps WHERE "full" GROUP BY step'))
    add(f"compute_cv_{n}", lambda s, d, n=n: rounded(metrics.compute_cv(steps_of(s, d, n=n)), "cv"), O.with_(O.CLIPS, O.stats(), O.run("dual", n), select='SELECT step, round(stddev_pop(load) / avg(load), 6) AS cv FROM steps WHERE "full" GROUP BY step'))
add("throughput_smooth", lambda s, d: rounded(metrics.smooth(metrics.series(steps_of(s, d)), 20), "tokens_per_s", "smoothed", digits=4), O.with_(O.CLIPS, O.stats(), O.run("dual", 16), "per AS (SELECT step, sum(tokens) / max(t) AS v FROM steps GROUP BY step)", select="SELECT step, round(v, 4) AS tokens_per_s, round(avg(v) OVER (ORDER BY step RANGE BETWEEN 19 PRECEDING AND CURRENT ROW), 4) AS smoothed FROM per"))
add("throughput_dips", lambda s, d: rounded(metrics.dips(metrics.series(steps_of(s, d, "equal_token")), 1.5), "tokens_per_s", digits=4), O.with_(O.CLIPS, O.stats(), O.run("equal_token", 16), "per AS (SELECT step, sum(tokens) / max(t) AS v FROM steps GROUP BY step)", select="SELECT step, round(v, 4) AS tokens_per_s FROM per WHERE v < (SELECT avg(v) - 1.5 * stddev_pop(v) FROM per)"))


def _arms_cv(n):
    per = lambda x: f"{x}_cv AS (SELECT avg(cv) AS cv FROM (SELECT stddev_pop(load) / avg(load) AS cv FROM {x} WHERE \"full\" GROUP BY step))"
    return O.with_(O.CLIPS, O.stats(), O.run("equal_token", n, name="e"), O.run("dual", n, name="u"), per("e"), per("u"), select="SELECT round(e_cv.cv, 6) AS base, round(u_cv.cv, 6) AS method, round((e_cv.cv - u_cv.cv) / e_cv.cv, 6) AS relative_drop FROM e_cv, u_cv")


add("imbalance_drop", lambda s, d: workloads.imbalance_drop(s, d, 16), _arms_cv(16))
add("idle_share", lambda s, d: rounded(metrics.idle_share(steps_of(s, d), 16), "wait", "idle_share"), O.with_(O.CLIPS, O.stats(), O.run("dual", 16), 'per AS (SELECT sum(t_sync - t) AS w, max(t_sync) AS t FROM steps WHERE "full" GROUP BY step)', select="SELECT round(sum(w), 6) AS wait, round(sum(w) / (16 * sum(t)), 6) AS idle_share FROM per"))
add("memory_utilisation", lambda s, d: rounded(metrics.memory_utilisation(steps_of(s, d), B.m_mem), "peak", "mean", "spread"), O.with_(O.CLIPS, O.stats(), O.run("dual", 16), select="SELECT step, round(max(tokens / 144000.0), 6) AS peak, round(sum(tokens) / (count(*) * 144000.0), 6) AS mean, round(max(tokens / 144000.0) - min(tokens / 144000.0), 6) AS spread FROM steps GROUP BY step"))


# ---- both arms side by side ------------------------------------------------------------------------------------------
ARM_STEPS = [O.CLIPS, O.stats()]
_spread = lambda v, digits, high="": f"count({v}) AS steps, round(avg({v}), {digits}) AS mean, round(min({v}), {digits}) AS least, round(max({v}), {digits}) AS greatest, " + ", ".join(f"round(quantile_cont({v}, {q}), {digits}) AS p{n}" for q, n in ((0.05, 5), (0.5, 50), (0.95, 95))) + high


def both_arms(spark, d, measure, n: int, column: str, digits: int = 6, high: float | None = None) -> DataFrame:
    """A measure's distribution over the steps of both arms."""
    out = None
    for arm in ARMS:
        one = metrics.spread(measure(steps_of(spark, d, arm, n)), column, high)
        one = rounded(one, *[c for c in one.columns if c != "steps"], digits=digits).withColumn("arm", F.lit(arm))
        out = one if out is None else out.unionByName(one)
    return out


def both_sql(n: int, per: str, value: str, digits: int = 6, high: str = "") -> str:
    runs = [O.run(arm, n, name=arm) for arm in ARMS]
    parts = [f"SELECT '{arm}' AS arm, {_spread(value, digits, high)} FROM ({per.format(steps=arm)})" for arm in ARMS]
    return O.with_(*ARM_STEPS, *runs, select=" UNION ALL ".join(parts))


for n in (8, 16):
    for q in metrics.QUANTITIES:
        add(f"range_ratio_{n}_arms_{q}", lambda s, d, n=n, q=q: both_arms(s, d, metrics.range_ratio, n, f"range_{q}"), both_sql(n, f'SELECT (max({q}) - min({q})) / max({q}) AS v FROM {{steps}} WHERE "full" GROUP BY step', "v"))
    add(f"compute_cv_{n}_arms", lambda s, d, n=n: both_arms(s, d, metrics.compute_cv, n, "cv", high=0.55), both_sql(n, 'SELECT stddev_pop(load) / avg(load) AS v FROM {steps} WHERE "full" GROUP BY step', "v", high=", round(avg(CASE WHEN v > 0.55 THEN 1.0 ELSE 0.0 END), 6) AS share_high"))
    add(f"throughput_floor_{n}", lambda s, d, n=n: both_arms(s, d, metrics.series, n, "tokens_per_s", 4), both_sql(n, "SELECT sum(tokens) / max(t) AS v FROM {steps} GROUP BY step", "v", 4))
add("scaling", workloads.scaling, O.with_(*ARM_STEPS, *[O.run(arm, n, name=f"{arm}_{n}") for arm in ARMS for n in (8, 16)], *[f"v_{arm}_{n} AS (SELECT sum(k) / sum(t) AS v FROM (SELECT sum(tokens) AS k, max(t) AS t FROM {arm}_{n} GROUP BY step))" for arm in ARMS for n in (8, 16)], select=" UNION ALL ".join(f"SELECT '{arm}' AS arm, round(v_{arm}_16.v / (2 * v_{arm}_8.v), 6) AS efficiency FROM v_{arm}_8, v_{arm}_16" for arm in ARMS)))
_use = lambda arm: f"u_{arm} AS (SELECT max(tokens) / 144000.0 AS peak, sum(tokens) / (count(*) * 144000.0) AS mean FROM {arm})"
add("memory_utilisation_arms", workloads.memory_arms, O.with_(*ARM_STEPS, *[O.run(arm, 16, name=arm) for arm in ARMS], *[_use(arm) for arm in ARMS], select=" UNION ALL ".join(f"SELECT '{arm}' AS arm, round(u_{arm}.peak, 6) AS peak, round(u_{arm}.mean, 6) AS mean, round(u_{arm}.mean / u_equal_token.mean - 1, 6) AS mean_gain FROM u_equal_token" + ("" if arm == "equal_token" else f", u_{arm}") for arm in ARMS)))
_halves = "h AS (SELECT max(step) / 2 AS mid FROM steps)"
add("length_shift", lambda s, d: rounded(metrics.ks_by_half(steps_of(s, d)), "ks"), O.with_(*ARM_STEPS, O.run("dual", 16), _halves, "n AS (SELECT s, sum(CASE WHEN step < mid THEN b ELSE 0 END) AS x, sum(CASE WHEN step >= mid THEN b ELSE 0 END) AS y FROM steps, h GROUP BY s)", select="SELECT round(max(gap), 6) AS ks FROM (SELECT abs(sum(x) OVER (ORDER BY s) / (SELECT sum(x) FROM n) - sum(y) OVER (ORDER BY s) / (SELECT sum(y) FROM n)) AS gap FROM n)"))
add("bucket_chi_square", lambda s, d: rounded(metrics.chi_square(steps_of(s, d)), "chi_square", digits=4), O.with_(*ARM_STEPS, O.run("dual", 16), _halves, "n AS (SELECT bucket_id, CAST(sum(CASE WHEN step < mid THEN b ELSE 0 END) AS DOUBLE) AS x, CAST(sum(CASE WHEN step >= mid THEN b ELSE 0 END) AS DOUBLE) AS y FROM steps, h GROUP BY bucket_id)", "p AS (SELECT sum(x) / (sum(x) + sum(y)) AS share FROM n)", select="SELECT round(sum(pow(x - (x + y) * share, 2) / ((x + y) * share) + pow(y - (x + y) * (1 - share), 2) / ((x + y) * (1 - share))), 4) AS chi_square, count(*) - 1 AS freedom FROM n, p"))


def _crossover(spark, d):
    at = spark.createDataFrame([(p, batching.crossover_len(Bounds(144_000.0, m, p))) for p, m in ((2.0, B.m_comp), (2.1, 5e9))], "p double, at double")
    rows = tables.clips(spark, d).groupBy("s").agg(F.count("*").alias("n")).crossJoin(F.broadcast(at))
    side = lambda c: F.sum(F.when(c, F.col("n")).otherwise(0))
    return rows.groupBy("p", "at").agg(side(F.col("s") <= F.col("at")).alias("memory"), side(F.col("s") > F.col("at")).alias("compute")).select("p", r("at", 4).alias("s"), "memory", "compute")


add("crossover", _crossover, O.with_(O.CLIPS, f"a AS (SELECT p, pow(m / 144000.0, 1 / (p - 1)) AS top FROM (VALUES (2.0::DOUBLE, {B.m_comp}::DOUBLE), (2.1::DOUBLE, 5e9::DOUBLE)) AS v(p, m))", select="SELECT p, round(top, 4) AS s, count(*) FILTER (clips.s <= top) AS memory, count(*) FILTER (clips.s > top) AS compute FROM clips, a GROUP BY p, top"))


def _memory_bound(spark, d):
    bounds = spark.createDataFrame([(c, batching.memory_bound(c, 40e9, 5e5)) for c in (80e9, 139e9)], "capacity double, tokens double")
    return stats(spark, d).select("bucket_id", "n", "s").crossJoin(F.broadcast(bounds)).select("capacity", "tokens", "bucket_id", "n", "s", F.floor(F.col("tokens") / F.col("s")).cast("long").alias("fit"))


add("memory_bound", _memory_bound, O.with_(O.CLIPS, O.stats(), select="SELECT capacity, (capacity - 40e9) / 5e5 AS tokens, bucket_id, n, s, CAST(floor((capacity - 40e9) / 5e5 / s) AS BIGINT) AS fit FROM stats, (VALUES (80e9::DOUBLE), (139e9::DOUBLE)) AS v(capacity)"))
add("padding_waste", lambda s, d: rounded(metrics.padding_waste(batching.sorted_padded_batches(tables.clips(s, d))), "waste"), O.with_(ORACLES["batch_sorted_padded"].removeprefix("WITH ").rpartition(" SELECT run, CAST(")[0], "p AS (SELECT max(s) AS s, count(*) AS b, sum(s) AS k FROM t GROUP BY run, (r % 1024) // greatest(1, CAST(floor(144000.0 / top) AS BIGINT)))", select="SELECT CAST(sum(k) AS BIGINT) AS real_tokens, CAST(sum(b * s) AS BIGINT) AS padded_tokens, round(1 - sum(k) / sum(b * s), 6) AS waste FROM p"))
add("load_correlations", lambda s, d: rounded(metrics.load_correlations(steps_of(s, d, "equal_token"), 2.1), "r_tokens", "r_s2", "r_bs2", "r_bsp"), O.with_(O.CLIPS, O.stats(), O.run("equal_token", 16), select="SELECT count(*) AS n, round(corr(t, CAST(tokens AS DOUBLE)), 6) AS r_tokens, round(corr(t, CAST(s AS DOUBLE) * s), 6) AS r_s2, round(corr(t, b * CAST(s AS DOUBLE) * s), 6) AS r_bs2, round(corr(t, b * pow(CAST(s AS DOUBLE), 2.1)), 6) AS r_bsp FROM steps"))

# ---- benchmark, fit, bounds ------------------------------------------------------------------------------------------
S_VALUES, B_LEVELS = list(range(4000, 52_001, 4000)), [1, 2, 4, 8]
_swept = ("c AS (SELECT s, CAST(b AS BIGINT) AS b FROM (SELECT DISTINCT CAST(ceil(s / 4000.0) AS BIGINT) * 4000 AS s FROM clips), (SELECT unnest([1, 2, 4, 8]) AS b) WHERE b * s <= 144000)", "e AS (SELECT s, min(b) AS lo, max(b) AS hi FROM c GROUP BY s)")
_plan = "SELECT c.b, c.s, rep, CASE WHEN c.s >= 20000 THEN c.b * c.s ELSE 0 END AS priority FROM c JOIN e ON e.s = c.s, (SELECT CAST(unnest([0, 1, 2]) AS INTEGER) AS rep)"
add("sweep_plan_grid", lambda s, d: costmodel.sweep_plan(s, workloads.swept_lengths(s, d), B_LEVELS), O.with_(O.CLIPS, *_swept, select=_plan))
add("sweep_plan_throughput", lambda s, d: costmodel.sweep_plan(s, workloads.swept_lengths(s, d), B_LEVELS, mode="throughput"), O.with_(O.CLIPS, *_swept, select=f"{_plan} WHERE c.s >= 20000 OR c.b = lo OR c.b = hi"))
add("benchmark_model", lambda s, d: rounded(costmodel.sync_matrix(costmodel.run_benchmark(costmodel.sweep_plan(s, workloads.swept_lengths(s, d), B_LEVELS))), "t"), O.with_(O.CLIPS, *_swept, select="SELECT b, s, CAST(3 AS BIGINT) AS n, round(2.0 + 1.2 * b * pow(s / 10000.0, 2.1), 6) AS t FROM c"))
add("benchmark_measured", lambda s, d: costmodel.run_benchmark(costmodel.sweep_plan(s, S_VALUES, B_LEVELS), executor="arrow"))
add("fit_measured", workloads.fit_measured)
matrix = lambda s, d: costmodel.sync_matrix(tables.trace(s, d))
add("sync_matrix", lambda s, d: rounded(matrix(s, d), "t"), O.with_(O.TRACE, select="SELECT b, s, n, round(t, 6) AS t FROM matrix"))
add("sync_matrix_median", lambda s, d: rounded(costmodel.sync_matrix(tables.trace(s, d), "median", 1), "t"), O.with_(O.TRACE, select="SELECT b, s, count(*) AS n, round(median(t), 6) AS t FROM (SELECT rep, b, s, max(t) AS t FROM trace WHERE rep >= 1 GROUP BY rep, b, s) GROUP BY b, s"))
add("matrix_pivot", lambda s, d: rounded(costmodel.as_matrix(matrix(s, d), [1, 2, 3, 4]), "b_1", "b_2", "b_3", "b_4"), O.with_(O.TRACE, select="SELECT s, " + ", ".join(f"round(max(CASE WHEN b = {k} THEN t END), 6) AS b_{k}" for k in (1, 2, 3, 4)) + " FROM matrix GROUP BY s"))
add("fit_grid", lambda s, d: rounded(costmodel.fit_grid(matrix(s, d)), "a", "slope", "r2"), O.with_(O.TRACE, O.FITS, select="SELECT p, n, round(a, 6) AS a, round(slope, 6) AS slope, round(r2, 6) AS r2 FROM fits"))
add("fit_best", lambda s, d: rounded(costmodel.best(costmodel.fit_grid(matrix(s, d))), "a", "slope", "r2"), O.with_(O.TRACE, O.FITS, select="SELECT p, n, round(a, 6) AS a, round(slope, 6) AS slope, round(r2, 6) AS r2 FROM best"))
add("fit_refined", lambda s, d: costmodel.refine(matrix(s, d)).select("p", r("r2").alias("r2")), O.with_(O.TRACE, O.FITS, select="SELECT p, round(r2, 6) AS r2 FROM best"))
for p, name in ((1, "fit_linear_p1"), (2, "fit_fixed_p2")):
    add(name, lambda s, d, p=p: rounded(costmodel.fit_at(matrix(s, d), p).drop("p"), "a", "slope", "r2"), O.with_(O.TRACE, select=f"SELECT count(*) AS n, round(regr_intercept(t, b * pow(s / 10000.0, {p})), 6) AS a, round(regr_slope(t, b * pow(s / 10000.0, {p})), 6) AS slope, round(regr_r2(t, b * pow(s / 10000.0, {p})), 6) AS r2 FROM matrix"))
add("fit_weighted", lambda s, d: rounded(costmodel.fit_weighted(costmodel.cells(tables.trace(s, d))), "a", "slope", "r2"), O.with_(O.TRACE, "f AS (SELECT round(1.6 + i * 0.01, 6) AS p, t, b * pow(s / 10000.0, round(1.6 + i * 0.01, 6)) AS x FROM trace, (SELECT unnest(range(0, 81)) AS i))", select="SELECT p, count(*) AS n, round(regr_intercept(t, x), 6) AS a, round(regr_slope(t, x), 6) AS slope, round(regr_r2(t, x), 6) AS r2 FROM f GROUP BY p"))
_b1, _b2 = "((xt * zz - zt * xz) / (xx * zz - xz * xz))", "((zt * xx - xt * xz) / (xx * zz - xz * xz))"
_two = "k AS (SELECT t, CAST(b AS DOUBLE) * s / 10000.0 AS x, b * pow(s / 10000.0, 2.0) AS z FROM matrix), m AS (SELECT count(*) AS n, avg(x) AS mx, avg(z) AS mz, avg(t) AS mt, covar_pop(x, z) AS xz, var_pop(x) AS xx, var_pop(z) AS zz, covar_pop(x, t) AS xt, covar_pop(z, t) AS zt, var_pop(t) AS tt FROM k)"
add("fit_two_term", lambda s, d: rounded(costmodel.fit_two_term(matrix(s, d)), "a", "b1", "b2", "r2"), O.with_(O.TRACE, _two, select=f"SELECT n, round(mt - {_b1} * mx - {_b2} * mz, 6) AS a, round({_b1}, 6) AS b1, round({_b2}, 6) AS b2, round(({_b1} * xt + {_b2} * zt) / tt, 6) AS r2 FROM m"))
add("compute_bound", lambda s, d: costmodel.best(costmodel.fit_grid(matrix(s, d))).select("p", r((20.0 - F.col("a")) / F.col("slope")).alias("m_comp")), O.with_(O.TRACE, O.FITS, select="SELECT p, round((20.0 - a) / slope, 6) AS m_comp FROM best"))
add("residuals", lambda s, d: rounded(costmodel.residuals(matrix(s, d), CostModel(2.0, 1.2, 2.1, 1e4)), "mean_residual", "mape", "r"), O.with_(O.TRACE, "f AS (SELECT s // 10000 AS band, t, 2.0 + 1.2 * (b * pow(s / 10000.0, 2.1)) AS fit FROM matrix)", select="SELECT band, count(*) AS n, round(avg(t - fit), 6) AS mean_residual, round(avg(abs(t - fit) / t), 6) AS mape, round(corr(t, fit), 6) AS r FROM f GROUP BY ROLLUP (band)"))
TARGETS = [2.0, 4.0, 5.8, 8.0, 12.0]
add("sweep_targets", lambda s, d: costmodel.sweep_targets(stats(s, d), MODEL, TARGETS).select("target", "tokens", r("seconds", 4).alias("seconds"), r("slowest").alias("slowest"), r("compute_share").alias("compute_share")), O.with_(O.CLIPS, O.stats(), f"g AS (SELECT unnest({TARGETS}) AS target)", "x AS (SELECT target, n, s, floor(144000.0 / s) AS mem, floor((target - 1.0) / 2e-9 / pow(CAST(s AS DOUBLE), 2.0)) AS comp FROM stats, g)", "y AS (SELECT *, greatest(1.0, least(mem, comp)) AS b FROM x)", select="SELECT CAST(target AS DOUBLE) AS target, CAST(sum(n * s) AS BIGINT) AS tokens, round(sum(ceil(n / b) * (1.0 + 2e-9 * b * pow(CAST(s AS DOUBLE), 2.0))), 4) AS seconds, round(max(1.0 + 2e-9 * b * pow(CAST(s AS DOUBLE), 2.0)), 6) AS slowest, round(sum(CASE WHEN comp < mem THEN n ELSE 0 END) / sum(n), 6) AS compute_share FROM y GROUP BY target"))

# ---- telemetry -------------------------------------------------------------------------------------------------------
add("waits", lambda s, d: steps_of(s, d).select("batch_id", "step", "rank", r("wait").alias("wait")), O.with_(O.CLIPS, O.stats(), O.run("dual", 16), select="SELECT batch_id, step, rank, round(t_sync - t, 6) AS wait FROM steps"))
add("bottlenecks", lambda s, d: telemetry.bottlenecks(steps_of(s, d, "equal_token")).select("bucket_id", "steps", r("caused", 4).alias("caused")), O.with_(O.CLIPS, O.stats(), O.run("equal_token", 16), "w AS (SELECT step, arg_max(bucket_id, row(t, batch_id)) AS bucket_id, count(*) * max(t) - sum(t) AS caused FROM steps GROUP BY step)", select="SELECT bucket_id, count(*) AS steps, round(sum(caused), 4) AS caused FROM w GROUP BY bucket_id"))


def _recalibrated(spark, d):
    bounds, _ = telemetry.recalibrate(B, tables.trace(spark, d), 20.0)
    return batching.plan_buckets(stats(spark, d), bounds).select("bucket_id", "s", "b")


add("recalibrated_plan", _recalibrated, O.with_(O.CLIPS, O.stats(), O.TRACE, O.FITS, select="SELECT bucket_id, s, CAST(greatest(1, least(floor(144000.0 / s), floor((20.0 - a) / slope * pow(10000.0, p) / pow(CAST(s AS DOUBLE), p)))) AS BIGINT) AS b FROM stats, best"))
add("closed_loop", workloads.closed_loop)
ev = lambda s, d: tables.table(s, d, "events").select("event_id", F.col("ts").cast("timestamp").alias("ts"), "user_id", (F.col("user_id") % 8).alias("rank"), "value")
_win = "per AS (SELECT time_bucket(INTERVAL '6 hours', ts) AS w, user_id % 8 AS rank, sum(value) AS t FROM events GROUP BY 1, 2)"
add("window_waits", lambda s, d: telemetry.waits_in_windows(ev(s, d)).select(F.unix_seconds("window_start").alias("window_start"), r("t_sync", 4).alias("t_sync"), "ranks_seen", r("wait", 4).alias("wait")), O.with_(_win, select="SELECT CAST(epoch(w) AS BIGINT) AS window_start, round(max(t), 4) AS t_sync, count(*) AS ranks_seen, round(count(*) * max(t) - sum(t), 4) AS wait FROM per GROUP BY w"))
add("stream_waits", workloads.stream_waits, O.with_(_win, "top AS (SELECT max(ts) - INTERVAL '1 day' AS m FROM events)", select="SELECT CAST(epoch(w) AS BIGINT) AS window_start, round(max(t), 4) AS t_sync, count(*) AS ranks_seen, round(count(*) * max(t) - sum(t), 4) AS wait FROM per, top WHERE w + INTERVAL '6 hours' <= m GROUP BY w"))
add("stream_session", workloads.stream_sessions, "WITH g AS (SELECT user_id, ts, value, CASE WHEN ts < lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL '2 hours' THEN 0 ELSE 1 END AS new FROM events), k AS (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS no FROM g) SELECT user_id, epoch_us(min(ts)) AS started, epoch_us(max(ts) + INTERVAL '2 hours') AS ended, count(*) AS n, round(sum(value), 4) AS busy FROM k GROUP BY user_id, no")
_sums = "f AS (SELECT round(1.6 + i * 0.01, 6) AS p, t, b * pow(s / 10000.0, round(1.6 + i * 0.01, 6)) AS x FROM trace, (SELECT unnest(range(0, 81)) AS i)), g AS (SELECT p, regr_intercept(t, x) AS a, regr_slope(t, x) AS b, regr_r2(t, x) AS r2 FROM f GROUP BY p)"
add("stream_loop", lambda s, d: workloads.stream_loop(s, d).select("version", "p", r("a", 4).alias("a"), r("b", 4).alias("b"), r("r2", 4).alias("r2")), O.with_(O.TRACE, _sums, select="SELECT CAST(0 AS INTEGER) AS version, p, round(a, 4) AS a, round(b, 4) AS b, round(r2, 4) AS r2 FROM g ORDER BY round(g.r2, 9) DESC, p LIMIT 1"))

# ---- fused modulation ------------------------------------------------------------------------------------------------
act, mod = tables.activations, tables.modulation
_long = lambda df, name, keys=("vec_id",): df.select(*keys, F.posexplode(name).alias("d", "v")).select(*keys, "d", r("v").alias("v"))
_forward = O.with_(O.LONG, select="SELECT vec_id, CAST(n.d AS INTEGER) AS d, round(xhat * (1 + scale) + shift, 6) AS v FROM norm n JOIN params p ON p.label = n.label AND p.d = n.d")
for impl, name in (("sql", "fused_sql"), ("arrow", "fused_arrow"), ("discrete", "discrete")):
    add(f"adaln_forward_{name}", lambda s, d, i=impl: _long(adaln.forward(act(s, d), mod(s, d), i), "y"), _forward)
for algo in ("two_pass", "one_pass", "welford"):
    add(f"adaln_stats_{algo}", lambda s, d, a=algo: adaln.row_stats(act(s, d), stats_algo=a).select("vec_id", r("mu").alias("mu"), r("rstd").alias("rstd")), O.with_(O.LONG, select="SELECT vec_id, round(mu, 6) AS mu, round(rstd, 6) AS rstd FROM stat"))
add("adaln_stats", lambda s, d: adaln.row_stats(act(s, d), tile=32).select("vec_id", r("mu").alias("mu"), r("rstd").alias("rstd")), ORACLES["adaln_stats_two_pass"])
_grads = O.with_(O.LONG, select="SELECT label, CAST(d AS INTEGER) AS d, round(sum(dy), 6) AS grad_shift, round(sum(dy * xhat), 6) AS grad_scale FROM norm GROUP BY label, d")
for impl in ("tiled", "wide", "strided"):
    add(f"grad_params_{impl}", lambda s, d, i=impl: rounded(adaln.grad_params(act(s, d), i), "grad_shift", "grad_scale"), _grads)
add("grad_params_cached", lambda s, d: rounded(adaln.grad_params(adaln.row_stats(act(s, d)), "tiled", "cached", d_tile=48), "grad_shift", "grad_scale"), _grads)
add("grad_input", lambda s, d: _long(adaln.grad_input(act(s, d), mod(s, d)), "dx"), O.with_(O.LONG, "g AS (SELECT n.*, dy * (1 + scale) AS g FROM norm n JOIN params p ON p.label = n.label AND p.d = n.d)", "m AS (SELECT vec_id, avg(g) AS mg, avg(g * xhat) AS mx FROM g GROUP BY vec_id)", select="SELECT g.vec_id, CAST(d AS INTEGER) AS d, round(rstd * (g - mg - xhat * mx), 6) AS v FROM g JOIN m ON m.vec_id = g.vec_id"))
_qk = O.with_(O.LONG, "h AS (SELECT vec_id, d, x, sqrt(avg(x * x) OVER (PARTITION BY vec_id, d // 16) + 1e-6) AS qn, dy, sqrt(avg(dy * dy) OVER (PARTITION BY vec_id, d // 16) + 1e-6) AS kn FROM tok)", select="SELECT vec_id, CAST(d AS INTEGER) AS d, round(x / qn, 6) AS q, round(dy / kn, 6) AS k FROM h")
for impl in ("arrow", "discrete"):
    add(f"qk_norm_{impl}", lambda s, d, i=impl: adaln.qk_norm(act(s, d), "x", "dy", impl=i).select("vec_id", F.posexplode(F.arrays_zip("q", "k")).alias("d", "z")).select("vec_id", "d", r("z.q").alias("q"), r("z.k").alias("k")), _qk)
    add(f"gate_norm_{impl}", lambda s, d, i=impl: _long(adaln.gate_norm(act(s, d), "dy", mod(s, d), impl=i), "y"), O.with_(O.LONG, "b AS (SELECT vec_id, label, d, x, (dy - avg(dy) OVER (PARTITION BY vec_id)) / sqrt(var_pop(dy) OVER (PARTITION BY vec_id) + 1e-6) AS z FROM tok)", select="SELECT vec_id, CAST(b.d AS INTEGER) AS d, round(x + gate * z, 6) AS v FROM b JOIN params p ON p.label = b.label AND p.d = b.d"))
_batches = lambda s, d: batching.plan_buckets(stats(s, d)).select("bucket_id", (F.col("b") * F.col("s")).alias("tokens"))
_batch_sql = (O.CLIPS, O.stats(), f"batch AS (SELECT bucket_id, CAST({O.size('dual')} * s AS BIGINT) AS tokens FROM stats)")
add("activation_bytes", lambda s, d: _batches(s, d).select("bucket_id", "tokens", graphmem.activation_bytes(F.col("tokens"), 5120, 5).cast("long").alias("discrete"), graphmem.activation_bytes(F.col("tokens"), 5120, 1).cast("long").alias("fused")), O.with_(*_batch_sql, select="SELECT bucket_id, tokens, tokens * 5120 * 10 AS discrete, tokens * 5120 * 2 AS fused FROM batch"))


def _traffic(spark, d):
    g, batches = graphmem.nodes(spark), _batches(spark, d)
    chain = [x[0] for x in graphmem.CHAIN]
    both = [graphmem.traffic_bytes(x, batches, 5120).withColumn("arm", F.lit(n)) for n, x in (("discrete", g), ("fused", graphmem.collapse(g, chain)))]
    return both[0].unionByName(both[1]).select("arm", "bucket_id", "tokens", "bytes")


add("traffic_bytes", _traffic, O.with_(*_batch_sql, select="SELECT arm, bucket_id, tokens, CAST(vectors AS BIGINT) * tokens * 5120 * 40 * 2 * 2 AS bytes FROM batch, (VALUES ('discrete', 8), ('fused', 2)) AS v(arm, vectors)"))
add("transactions", lambda s, d: s.createDataFrame([(x,) for x in (1, 64, 5120)], "d long").select("d", graphmem.transactions(F.col("d")).alias("coalesced"), graphmem.transactions(F.col("d"), layout="strided").alias("strided")), "SELECT CAST(d AS BIGINT) AS d, CAST(4 AS BIGINT) AS coalesced, CAST(CASE WHEN d = 1 THEN 4 ELSE 32 END AS BIGINT) AS strided FROM (SELECT unnest([1, 64, 5120]) AS d)")


def _graph_collapse(spark, d):
    """The graph of each bucket's batch; moved: token vectors that a node reads and writes."""
    graphs = graphmem.nodes(spark).crossJoin(_batches(spark, d))  # five nodes a bucket
    out = graphmem.collapse(graphs, ["standardize", "mul", "add"], by=("bucket_id", "tokens"))
    return out.select("bucket_id", "op", F.array_join("inputs", ",").alias("inputs"), "saved", "reads", "writes", ((F.col("reads") + F.col("writes")) * F.col("tokens")).alias("moved"))


add("graph_collapse", _graph_collapse, O.with_(*_batch_sql, select="SELECT bucket_id, op, inputs, true AS saved, CAST(1 AS INTEGER) AS reads, CAST(w AS INTEGER) AS writes, CAST((1 + w) * tokens AS BIGINT) AS moved FROM batch, (VALUES ('mean', 'x', 0), ('var', 'x,mean', 0), ('fused', 'mean,scale,shift,var,x', 1)) AS v(op, inputs, w)"))


def _kernel_check(spark, d):
    """Speedups and saved share recomputed from each published row, and its times over the clips that it is the shortest row to hold."""
    k = graphmem.kernel_table(spark)
    n_k = F.greatest(F.lit(8), F.ceil(F.col("s") / 8000) * 8).cast("int")
    clips_of = tables.clips(spark, d).groupBy(n_k.alias("n_k")).agg(F.count("*").alias("n"))  # a row for each 8,000 tokens of the longest
    rows = k.join(clips_of, "n_k", "left").withColumn("clips", F.coalesce("n", F.lit(0)).cast("long"))
    gain = lambda x: r(F.col("clips") * (F.col(f"{x}_native") - F.col(x)), 3).alias(f"{x}_gain")
    return rows.select("n_k", r("fwd_speedup", 2).alias("fwd"), r("bwd_speedup", 2).alias("bwd"), r("saved_share", 3).alias("saved"), "clips", gain("fwd"), gain("bwd"))


add("published_tables_check", _kernel_check, O.with_(O.CLIPS, "k AS (SELECT CAST(greatest(8, ceil(s / 8000.0) * 8) AS INTEGER) AS n_k, count(*) AS n FROM clips GROUP BY 1)", select="SELECT v.n_k, round(fn / f, 2) AS fwd, round(bn / b, 2) AS bwd, round(1 - m / mn, 3) AS saved, coalesce(n, 0) AS clips, round(coalesce(n, 0) * (fn - f), 3) AS fwd_gain, round(coalesce(n, 0) * (bn - b), 3) AS bwd_gain FROM (VALUES " + ", ".join(f"({a}, {b}::DOUBLE, {c}::DOUBLE, {e}::DOUBLE, {f}::DOUBLE, {g}::DOUBLE, {h}::DOUBLE)" for a, b, c, e, f, g, h in graphmem.KERNEL) + ") AS v(n_k, f, fn, b, bn, m, mn) LEFT JOIN k ON k.n_k = v.n_k"))


def _system_check(spark, d):
    """Throughput recomputed from each published row, and what it means for the clips that are no longer than its samples."""
    arms = graphmem.system_table(spark).select("arm", F.col("s").alias("top"), "tokens_per_s")
    rows = tables.clips(spark, d).groupBy("s").agg(F.count("*").alias("n")).crossJoin(F.broadcast(arms))
    held = F.col("s") <= F.col("top")
    sums = rows.groupBy("arm", "tokens_per_s").agg(F.sum(F.when(held, F.col("n")).otherwise(0)).alias("clips"), F.sum(F.when(held, F.col("n") * F.col("s")).otherwise(0)).alias("tokens"))
    return sums.select("arm", r("tokens_per_s", 1).alias("tokens_per_s"), "clips", "tokens", r(F.col("tokens") / F.col("tokens_per_s")).alias("seconds"))


add("published_system_check", _system_check, O.with_(O.CLIPS, "v AS (SELECT arm, top, top * b / t AS rate FROM (VALUES ('unfused', 48000, 3, 62.0::DOUBLE), ('fused_same', 48000, 3, 56.0::DOUBLE), ('fused_max', 52800, 3, 68.0::DOUBLE)) AS x(arm, top, b, t))", select="SELECT arm, round(rate, 1) AS tokens_per_s, count(*) FILTER (s <= top) AS clips, CAST(sum(CASE WHEN s <= top THEN s ELSE 0 END) AS BIGINT) AS tokens, round(sum(CASE WHEN s <= top THEN s ELSE 0 END) / rate, 6) AS seconds FROM clips, v GROUP BY arm, rate"))

# ---- workloads and surface -------------------------------------------------------------------------------------------
add("loss_curves", workloads.loss_curves)
add("kernel_sweep", workloads.kernel_sweep)
_text = lambda c, arm: O.text_run(c, arm, 8, workloads.TEXT_BOUNDS, workloads.TEXT_MODEL, f"SELECT '{c}' AS corpus, '{arm}' AS arm, count(*) AS steps, round(avg(cv), 5) AS cv, round(avg(rr), 5) AS range_t, round(sum(k) / sum(t), 3) AS tokens_per_s FROM (SELECT step, stddev_pop(load) / avg(load) AS cv, (max(t) - min(t)) / max(t) AS rr, sum(tokens) AS k, max(t) AS t FROM steps GROUP BY step)")
add("text_corpora", lambda s, d: rounded(rounded(workloads.text_corpora(s, d), "cv", "range_t", digits=5), "tokens_per_s", digits=3), " UNION ALL ".join(_text(c, arm) for c in ("documents", "conversations", "pages", "benchmark") for arm in ARMS))
add("load_correlations_text", lambda s, d: rounded(metrics.load_correlations(schedule.run(tables.text_samples(s, d, "documents"), "equal_token", 8, workloads.TEXT_BOUNDS, workloads.TEXT_MODEL, kind="geometric"), 2.1), "r_tokens", "r_s2", "r_bs2", "r_bsp", digits=5), O.text_run("documents", "equal_token", 8, workloads.TEXT_BOUNDS, workloads.TEXT_MODEL, "SELECT count(*) AS n, round(corr(t, CAST(tokens AS DOUBLE)), 5) AS r_tokens, round(corr(t, CAST(s AS DOUBLE) * s), 5) AS r_s2, round(corr(t, b * CAST(s AS DOUBLE) * s), 5) AS r_bs2, round(corr(t, b * pow(CAST(s AS DOUBLE), 2.1)), 5) AS r_bsp FROM steps"))
_flag = lambda arm: f"""SELECT '{arm}' AS arm, count(*) AS steps, avg(CASE WHEN "full" THEN cv END) AS compute_cv, {', '.join(f'avg(CASE WHEN "full" THEN range_{q} END) AS range_{q}' for q in metrics.QUANTITIES)}, sum(CASE WHEN "full" THEN w END) / (16 * sum(CASE WHEN "full" THEN ts END)) AS idle_share, sum(k) / sum(ts) AS tokens_per_s FROM (SELECT step, bool_and("full") AS "full", sum(tokens) AS k, max(t) AS ts, sum(t_sync - t) AS w, stddev_pop(load) / avg(load) AS cv, {', '.join(f'(max({q}) - min({q})) / max({q}) AS range_{q}' for q in metrics.QUANTITIES)} FROM {arm} GROUP BY step)"""
_five = ["compute_cv", *[f"range_{q}" for q in metrics.QUANTITIES], "idle_share", "tokens_per_s"]
_short = lambda sql: f"SELECT arm, steps, {', '.join(f'round({c}, 5) AS {c}' for c in _five)} FROM ({sql})"
add("flagship", lambda s, d: rounded(workloads.flagship(s, d), *_five, digits=5), O.with_(*ARM_STEPS, *[O.run(arm, 16, name=arm) for arm in ARMS], select=" UNION ALL ".join(_short(_flag(arm)) for arm in ARMS)))
_sweep = (6e8, 1.2e9, 2.4e9, 4.8e9, 9.6e9)
_one = lambda k, m: f"SELECT {m}::DOUBLE AS m_comp, round(avg(CASE WHEN f THEN cv END), 5) AS cv, round(sum(k) / sum(t), 4) AS tokens_per_s FROM (SELECT step, bool_and(\"full\") AS f, stddev_pop(load) / avg(load) AS cv, sum(tokens) AS k, max(t) AS t FROM w{k} GROUP BY step)"
add("bounds_sweep", lambda s, d: workloads.bounds_sweep(s, d, bounds=_sweep).select("m_comp", r("cv", 5).alias("cv"), r("tokens_per_s", 4).alias("tokens_per_s")), O.with_(*ARM_STEPS, *[f"{O.batches('dual', Bounds(144_000.0, m + 1.5, 2.0), f'w{k}_b')}, {O.steps(16, 'random', f'w{k}_b', f'w{k}')}" for k, m in enumerate(_sweep)], select=" UNION ALL ".join(_one(k, m) for k, m in enumerate(_sweep))))
add("loss_agreement", workloads.loss_agreement)
add("gradient_precision", workloads.gradient_precision)
add("distribution_gap", lambda s, d: metrics.distribution_gap(clips(s, d), batching.form_batches(clips(s, d), batching.plan_buckets(stats(s, d)))), O.with_(O.CLIPS, select="SELECT bucket_id, count(*) AS before, count(*) AS after, CAST(0 AS BIGINT) AS gap FROM clips GROUP BY bucket_id"))
_abl = lambda x, f: f"SELECT '{x}_{'fused' if f else 'unfused'}' AS arm, round(sum(k) / sum(t) * {62 / 56 if f else 1.0}, 4) AS tokens_per_s FROM (SELECT step, sum(tokens) AS k, max(t) AS t FROM {x} GROUP BY step)"
add("ablation", workloads.ablation, O.with_(O.CLIPS, O.stats(), O.run("equal_token", 16, name="equal_token"), O.run("dual", 16, name="dual"), select=" UNION ALL ".join(_abl(x, f) for x in ARMS for f in (False, True))))
_T = workloads.TASK
_pack = f"""
g AS (SELECT l_partkey AS group_id, count(*) AS rows FROM lineitem GROUP BY 1),
n AS (SELECT *, CAST(greatest(1, ceil(rows / {_T.m_mem / 2}), ceil(sqrt(CAST(rows AS DOUBLE) * rows / {_T.m_comp / 2}))) AS BIGINT) AS parts FROM g),
p AS (SELECT group_id, part, (rows + parts - 1 - part) // parts AS size FROM (SELECT *, unnest(range(parts)) AS part FROM n)),
o AS (SELECT *, sum(size) OVER w - size AS r, sum(size * size) OVER w - size * size AS c FROM p WINDOW w AS (ORDER BY size DESC, md5(concat('{O.SEED}:', group_id, ':', part)) ROWS UNBOUNDED PRECEDING)),
s AS (SELECT size, dense_rank() OVER (ORDER BY floor(r / {_T.m_mem / 2}), floor(c / {_T.m_comp / 2})) - 1 AS slot FROM o),
packed AS (SELECT slot, count(*) AS parts, CAST(sum(size) AS BIGINT) AS rows, CAST(sum(size * size) AS DOUBLE) AS load FROM s GROUP BY slot)"""
add("pack_tasks", workloads.pack_tasks, O.with_(_pack, select="SELECT slot, parts, rows, load FROM packed"))
add("barrier_tasks", lambda s, d: rounded(workloads.barrier_tasks(s, d), "max_over_mean"), O.with_(_pack, f"h AS (SELECT sum(rows * rows) AS load FROM g GROUP BY CAST(concat('0x', substr(md5(concat('{O.SEED}:', group_id)), 1, 8)) AS BIGINT) % (SELECT count(*) FROM packed))", select="SELECT 'hash' AS how, round(max(load) * (SELECT count(*) FROM packed) / sum(load), 6) AS max_over_mean FROM h UNION ALL SELECT 'dual', round(max(load) / avg(load), 6) FROM packed"))
add("cube_loads", lambda s, d: tables.clips(s, d).join(tables.table(s, d, "orders").select(F.col("o_orderkey").alias("sample_id"), "o_orderpriority"), "sample_id").cube("modality", "o_orderpriority").agg(F.count("*").alias("n"), F.sum("s").alias("tokens")), O.with_(O.CLIPS, select="SELECT modality, o_orderpriority, count(*) AS n, CAST(sum(s) AS BIGINT) AS tokens FROM clips JOIN orders ON o_orderkey = sample_id GROUP BY CUBE (modality, o_orderpriority)"))
add("asof_bounds", workloads.asof_bounds, "WITH v AS (SELECT CAST(day AS INTEGER) AS version, TIMESTAMP '2024-01-01' + day * INTERVAL '1 day' AS since, 1e9 * (1 + day) AS m_comp FROM (SELECT unnest(range(0, 30, 5)) AS day)) SELECT event_id, version, m_comp FROM events ASOF JOIN v ON ts >= since")
add("anti_unlabelled", lambda s, d: tables.text_samples(s, d, "documents").join(tables.table(s, d, "labels").select(F.col("doc_id").alias("sample_id")), "sample_id", "left_anti").agg(F.count("*").alias("n"), F.sum("s").alias("tokens")), f"SELECT count(*) AS n, CAST(sum({O.words('text')}) AS BIGINT) AS tokens FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM labels)")
add("semi_quality", lambda s, d: tables.text_samples(s, d, "documents").join(tables.table(s, d, "labels").where("quality = 1 AND toxic = 0").select(F.col("doc_id").alias("sample_id")), "sample_id", "left_semi").agg(F.count("*").alias("n"), F.sum("s").alias("tokens")), f"SELECT count(*) AS n, CAST(sum({O.words('text')}) AS BIGINT) AS tokens FROM documents WHERE doc_id IN (SELECT doc_id FROM labels WHERE quality = 1 AND toxic = 0)")


def _conserved(spark, d):
    rows = clips(spark, d)
    inside = batching.form_batches(rows, batching.plan_buckets(batching.bucket_stats(rows)), members=True).select(F.explode("members").alias("sample_id"))
    ids = rows.select("sample_id")
    return ids.exceptAll(inside).agg(F.count("*").alias("lost")).crossJoin(inside.exceptAll(ids).agg(F.count("*").alias("doubled")))


add("sample_conservation", _conserved, "SELECT CAST(0 AS BIGINT) AS lost, CAST(0 AS BIGINT) AS doubled")
add("topk_stragglers", lambda s, d: steps_of(s, d).withColumn("k", F.row_number().over(Window.partitionBy("rank").orderBy(F.desc("load"), "batch_id"))).where("k <= 3").select("rank", "k", "batch_id", r("load", 0).alias("load")), O.with_(O.CLIPS, O.stats(), O.run("dual", 16), select="SELECT rank, CAST(k AS INTEGER) AS k, batch_id, round(load, 0) AS load FROM (SELECT *, row_number() OVER (PARTITION BY rank ORDER BY load DESC, batch_id) AS k FROM steps) WHERE k <= 3"))
add("approx_shapes", lambda s, d: clips(s, d).groupBy("modality").agg(F.approx_count_distinct("bucket_id").alias("shapes"), F.percentile_approx("s", 0.5).alias("median_s")))
add("exact_percentiles", lambda s, d: tables.clips(s, d).groupBy("modality").agg(r(F.percentile("s", 0.5)).alias("p50"), r(F.percentile("s", 0.9)).alias("p90")), O.with_(O.CLIPS, select="SELECT modality, round(quantile_cont(s, 0.5), 6) AS p50, round(quantile_cont(s, 0.9), 6) AS p90 FROM clips GROUP BY modality"))
add("arms_full_outer", lambda s, d: (lambda e, u: e.join(u, "step", "full_outer"))(*[steps_of(s, d, p).groupBy("step").agg(r(F.max("t")).alias(f"t_{p}")) for p in ARMS]), O.with_(O.CLIPS, O.stats(), O.run("equal_token", 16, name="e"), O.run("dual", 16, name="u"), select="SELECT coalesce(a.step, b.step) AS step, a.t AS t_equal_token, b.t AS t_dual FROM (SELECT step, round(max(t), 6) AS t FROM e GROUP BY step) a FULL JOIN (SELECT step, round(max(t), 6) AS t FROM u GROUP BY step) b ON a.step = b.step"))
add("range_join_bands", workloads.range_join, O.with_(O.CLIPS, "bands AS (SELECT * FROM (VALUES ('short', 0, 2000), ('middle', 2000, 20000), ('long', 20000, 1000000)) AS v(band, lo, hi))", select="SELECT band, count(*) AS n, CAST(sum(s) AS BIGINT) AS tokens FROM clips JOIN bands ON s >= lo AND s < hi GROUP BY band"))
add("lag_loads", lambda s, d: rounded(metrics.changes(schedule.step_time(steps_of(s, d)), "t_sync"), "change"), O.with_(O.CLIPS, O.stats(), O.run("dual", 16), "p AS (SELECT step, max(t) AS t FROM steps GROUP BY step)", select="SELECT step, round(t - lag(t) OVER (ORDER BY step), 6) AS change FROM p"))
add("sql_functions", workloads.sql_functions, O.with_(O.CLIPS, O.stats(), select=f"SELECT bucket_id, s, CAST({O.size('dual')} AS BIGINT) AS b FROM stats"))
