"""Queries over runs that are longer than the small tables give: every step counts."""

import numpy as np
import pandas as pd
from pyspark.sql import functions as F

from shapebalance.operators import batching, metrics, schedule
from shapebalance.plans import registry, workloads
from shapebalance.plans.model import Bounds
from shapebalance.sources import tables


def test_loss_curves_train_on_every_step(spark, tmp_path):
    n, ids = 520, np.arange(520)  # texts so long that a batch is one sample: 65 steps of 8 ranks
    pd.DataFrame({"doc_id": ids, "text": "a " * 9000}).to_parquet(tmp_path / "documents.parquet")
    vectors = np.random.default_rng(1).normal(size=(n, 64)).astype(np.float32)
    pd.DataFrame({"vec_id": ids, "embedding": list(vectors), "label": (ids % 3).astype(np.int32)}).to_parquet(tmp_path / "embeddings.parquet")
    got = workloads.loss_curves(spark, str(tmp_path)).toPandas()
    placed = batching.assign_buckets(tables.text_samples(spark, str(tmp_path), "documents"), "geometric")
    for arm, curve in got.groupby("arm"):
        plan = batching.plan_buckets(batching.bucket_stats(placed), Bounds(8192.0, 4_194_304.5, 2.0), arm)
        steps = schedule.assign_steps(batching.form_batches(placed, plan, members=True), 8).select("step", F.explode("members").alias("id")).toPandas()
        assert sorted(steps["id"]) == list(ids)
        w, want = np.zeros((64, 3)), []
        for _, g in steps.groupby("step"):  # by sample, from the definition
            grad, loss = np.zeros_like(w), 0.0
            for i in g["id"]:
                e = np.exp(vectors[i].astype(float) @ w)
                p = e / e.sum()
                loss -= np.log(p[i % 3]) / len(g)
                grad += np.outer(vectors[i].astype(float), p - np.eye(3)[i % 3]) / len(g)
            w -= 0.5 * grad
            want.append(loss)
        curve = curve.sort_values("step")
        assert list(curve["step"]) == list(range(65))
        assert np.allclose(curve["loss"], want)


def test_changes_cross_blocks(spark):
    values = spark.createDataFrame([(k, float(k * k)) for k in range(10)], "step long, t double")
    got = {r["step"]: r["change"] for r in metrics.changes(values, "t", block=4).collect()}
    assert got == {0: None} | {k: 2.0 * k - 1 for k in range(1, 10)}


def test_lag_loads_of_a_run_of_over_64_steps(spark):
    d = "/root/testdata/sf0.01"
    got = registry.QUERIES["lag_loads"](spark, d).toPandas().sort_values("step")
    t = schedule.step_time(registry.steps_of(spark, d)).toPandas().sort_values("step")
    assert len(got) == len(t) > 64
    assert list(got["step"]) == list(t["step"])
    assert got["change"].isna().sum() == 1
    assert np.allclose(got["change"], t["t_sync"].diff(), atol=1e-5, equal_nan=True)


def test_kernel_sweep_has_its_sizes(spark):
    rows = workloads.kernel_sweep(spark, "/root/testdata/sf0.001", (300, 1100)).collect()
    assert [r["n"] for r in rows] == [300, 1100] and all(r["forward_fused"] > 0 and r["bytes_discrete"] == 5 * r["bytes_fused"] == 5 * 8 * 64 * r["n"] for r in rows)
