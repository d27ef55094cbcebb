"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; one JSON line with seconds per query and what is compared with the published numbers."""

from __future__ import annotations

import json
import os
import sys
import time
from pathlib import Path

sys.path.insert(0, str(Path(__file__).resolve().parent))

from pyspark.sql import SparkSession  # noqa: E402

from shapebalance.operators import adaln, metrics, schedule  # noqa: E402
from shapebalance.plans import registry, workloads  # noqa: E402
from shapebalance.plans.model import ARMS  # noqa: E402
from shapebalance.sources import tables  # noqa: E402

SF_DIR, CPUS = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1"), os.environ.get("BENCH_CPUS", "4")
QUERIES = (
    "seq_len_clips", "bucket_stats", "batch_dual", "form_batches_dual", "steps_random", "steps_lpt", "throughput_16_equal", "throughput_16_dual", "range_ratio_16", "compute_cv_16", "imbalance_drop", "load_correlations",
    "sync_matrix", "fit_best", "fit_weighted", "recalibrated_plan", "adaln_forward_fused_sql", "adaln_forward_fused_arrow", "adaln_forward_discrete", "grad_params_tiled", "grad_params_wide", "grad_params_strided", "stream_waits",
)


def timed(run) -> float:
    start = time.perf_counter()
    run().write.format("noop").mode("overwrite").save()
    return round(time.perf_counter() - start, 3)


def shape(spark: SparkSession) -> dict:
    """The measures that the paper reports, on these tables: ratios, not seconds."""
    rows = tables.clips(spark, SF_DIR)
    out = {}
    for n in (8, 16):
        arms = {}
        for arm in ARMS:
            steps = schedule.run(rows, arm, n).persist()
            speed = metrics.throughput(steps).first()["tokens_per_s"]
            cv = metrics.compute_cv(steps).agg({"cv": "avg"}).first()[0]
            rr = metrics.range_ratio(steps).agg(*[registry.F.avg(f"range_{q}").alias(q) for q in metrics.QUANTITIES]).first().asDict()
            r = metrics.load_correlations(steps).first().asDict()
            arms[arm] = {"tokens_per_s": speed, "cv": cv, **{f"range_{k}": v for k, v in rr.items()}, "r_tokens": r["r_tokens"], "r_s2": r["r_s2"]}
            steps.unpersist()
        base, dual = (arms[a] for a in ARMS)
        out[f"n{n}"] = {
            "throughput_gain": round(dual["tokens_per_s"] / base["tokens_per_s"] - 1, 4), "cv_base": round(base["cv"], 4), "cv_dual": round(dual["cv"], 4), "cv_drop": round(1 - dual["cv"] / base["cv"], 4),
            "range_t_drop": round(1 - dual["range_t"] / base["range_t"], 4), "r_tokens": round(base["r_tokens"], 4), "r_s2": round(base["r_s2"], 4),
        }
    return out


def kernels(spark: SparkSession) -> dict:
    """Fused against discrete over 8,000 to 32,000 tokens: seconds here, ratios beside the paper's."""
    params, out = tables.modulation(spark, SF_DIR).persist(), {}
    for copies in (4, 16):
        x = tables.activations(spark, SF_DIR, copies).persist()
        n = x.count()
        t = {i: min(timed(lambda i=i: adaln.forward(x, params, i)) for _ in range(2)) for i in ("arrow", "discrete")}
        g = {i: min(timed(lambda i=i: adaln.grad_params(x, i)) for _ in range(2)) for i in ("tiled", "strided")}
        out[str(n)] = {"forward_speedup": round(t["discrete"] / t["arrow"], 2), "gradient_speedup": round(g["strided"] / g["tiled"], 2)}
        x.unpersist()
    return out


def main() -> None:
    spark = SparkSession.builder.master(f"local[{CPUS}]").config("spark.sql.shuffle.partitions", CPUS).config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.driver.memory", "4g").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    workloads.flagship(spark, SF_DIR).collect()  # warm-up
    seconds = {q: timed(lambda q=q: registry.QUERIES[q](spark, SF_DIR)) for q in QUERIES}
    print(json.dumps({"metric": "headline queries", "value": round(sum(seconds.values()), 3), "unit": "sec", "queries": seconds, "sf": SF_DIR.rstrip("/").rpartition("sf")[2], "balance_modelled": shape(spark), "kernels_measured": kernels(spark)}))


if __name__ == "__main__":
    main()
