"""Hand cases and properties of the methods."""

import hashlib
import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from shapebalance.functions.shapes import token_len, visual_len
from shapebalance.operators import adaln, batching, costmodel, graphmem, metrics, schedule, telemetry
from shapebalance.plans import workloads
from shapebalance.plans.model import ARMS, Bounds, CostModel
from shapebalance.sources import tables

from .conftest import SF


@pytest.mark.parametrize("shape, s", [((1, 256, 256), 256), ((1, 640, 640), 1600), ((233, 640, 640), 48_000), ((257, 640, 640), 52_800), ((9, 480, 832), 3120)])
def test_visual_len(spark, shape, s):
    assert spark.createDataFrame([shape], "f int, h int, w int").select(visual_len()).first()[0] == s


def test_token_len_of_nothing(spark):
    df = spark.createDataFrame([(None,), ("",), (" \n ",), ("a b\tc",)], "text string")
    assert [r[0] for r in df.select(token_len("text")).collect()] == [1, 1, 1, 3]


CASES = [(256, 562, 562, "memory"), (640, 225, 225, "memory"), (1600, 90, 90, "memory"), (4680, 30, 30, "memory"), (16_640, 8, 8, "tie"), (24_000, 4, 6, "compute"), (43_200, 1, 3, "compute"), (48_000, 1, 3, "compute"), (52_800, 1, 2, "unit"), (150_000, 1, 1, "unit")]


@pytest.mark.parametrize("s, dual, equal, bound", CASES)
def test_batch_sizes(spark, s, dual, equal, bound):
    df = spark.createDataFrame([(s,)], "s long")
    b = Bounds()
    row = df.select(batching.batch_size(F.col("s"), b), batching.batch_size(F.col("s"), b, "equal_token"), batching.binding_constraint(F.col("s"), b)).first()
    assert tuple(row) == (dual, equal, bound)


def test_dual_batches_are_maximal(spark):
    df = spark.range(1, 60_000, 37).select(F.col("id").alias("s"))
    for b in (Bounds(), Bounds(100_000.0, 3e9, 2.1)):
        rows = df.select("s", batching.batch_size(F.col("s"), b).alias("b"), batching.batch_size(F.col("s"), b, "equal_token").alias("e")).toPandas()
        s, n = rows["s"].to_numpy(float), rows["b"].to_numpy(float)
        many = n > 1
        assert (n >= 1).all() and (n <= rows["e"]).all()
        assert (n * s <= b.m_mem + 1e-6)[many].all() and (n * s**b.p <= b.m_comp * (1 + 1e-12))[many].all()
        assert (((n + 1) * s > b.m_mem) | ((n + 1) * s**b.p > b.m_comp * (1 - 1e-12))).all()
        assert (np.diff(n) <= 0).all()
    assert abs(batching.crossover_len(Bounds()) - 16_666.67) < 0.1


def test_bounds_and_frames():
    assert (batching.max_frames(144_000, 3, 640, 640), batching.max_frames(158_400, 3, 640, 640)) == (233, 257)
    assert batching.memory_bound(100.0, 20.0, 0.5) == 160
    for bad in (lambda: batching.memory_bound(1, 2, 1), lambda: batching.crossover_len(Bounds(p=1.0)), lambda: Bounds(m_mem=0)):
        with pytest.raises(ValueError):
            bad()


def test_barrier_by_hand(spark):
    df = spark.createDataFrame([(0, f"b{i}", t, 1, 1, 1) for i, t in enumerate((4.0, 7.0, 5.0, 7.0))], "step int, batch_id string, t double, s long, b long, tokens long")
    out = telemetry.waits(df).withColumn("full", F.lit(True))
    assert sorted(r["wait"] for r in out.collect()) == [0, 0, 2, 3]
    assert math.isclose(metrics.idle_share(out, 4).first()["idle_share"], 5 / 28)
    assert math.isclose(metrics.range_ratio(out, ("t",)).first()["range_t"], 3 / 7)
    assert metrics.compute_cv(out).first()["cv"] == 0
    two = spark.createDataFrame([(0, 1, 1, True), (0, 3, 1, True)], "step int, b long, s long, full boolean")
    assert metrics.compute_cv(two).first()["cv"] == 0.5


def test_fit_by_hand(spark):
    m = spark.createDataFrame([(1, s, 1.0 + 2.0 * s * s) for s in (1, 2, 3, 4)], "b long, s long, t double")
    model = costmodel.to_model(costmodel.fit_grid(m, s_ref=1.0), 1.0)
    assert model.p == 2.0 and math.isclose(model.a, 1, abs_tol=1e-9) and math.isclose(model.b, 2) and math.isclose(model.r2, 1)
    assert math.isclose(costmodel.compute_bound(model, 19.0), 9)
    for bad in (lambda: costmodel.compute_bound(model, 1.0), lambda: costmodel.to_model(costmodel.fit_grid(m.where("s = 1")))):
        with pytest.raises(ValueError):
            bad()


def test_trace_gives_its_exponent(spark):
    assert abs(costmodel.best(costmodel.fit_grid(costmodel.sync_matrix(tables.trace(spark, SF)))).first()["p"] - 2.1) <= 0.02


def test_batches_hold_every_sample_once_for_any_partitioning(spark):
    rows = batching.assign_buckets(tables.clips(spark, SF))
    plan = batching.plan_buckets(batching.bucket_stats(rows))
    seen = []
    for n in (1, 7):
        out = batching.form_batches(rows.repartition(n), plan, members=True).toPandas()
        members = [i for m in out["members"] for i in m]
        assert len(members) == len(set(members)) == rows.count() and (out["b"] <= out["plan_b"]).all()
        seen.append({r.batch_id: tuple(r.members) for r in out.itertuples()})
    assert seen[0] == seen[1]


@pytest.mark.parametrize("how", schedule.POLICIES)
def test_steps_place_each_batch_once(spark, how):
    steps = schedule.schedule(tables.clips(spark, SF), n_ranks=8, steps=how).toPandas()
    assert steps["batch_id"].is_unique and not steps.duplicated(["step", "rank"]).any() and steps["rank"].between(0, 7).all()


def test_dual_balances_and_is_faster(spark):
    rows = {r["arm"]: r for r in workloads.flagship(spark, "/root/testdata/sf0.01").collect()}
    base, dual = (rows[a] for a in ARMS)
    assert dual["compute_cv"] < base["compute_cv"] and dual["range_t"] < base["range_t"] and dual["range_load"] < base["range_load"]
    assert dual["tokens_per_s"] > base["tokens_per_s"] and dual["idle_share"] < base["idle_share"]
    assert dual["range_tokens"] > base["range_tokens"]  # equal-token batches balance tokens by design


def test_tail_rules(spark):
    rows = batching.assign_buckets(tables.clips(spark, SF))
    plan = batching.plan_buckets(batching.bucket_stats(rows))
    full = batching.form_batches(rows, plan, tail="drop").toPandas()
    padded = batching.form_batches(rows, plan, tail="pad").toPandas()
    assert (full["b"] == full["plan_b"]).all() and (padded["b"] == padded["plan_b"]).all() and len(padded) >= len(full)


def test_empty_input(spark):
    none = tables.clips(spark, SF).where("false")
    assert schedule.run(none).count() == 0 and metrics.throughput(schedule.run(none)).first()["steps"] == 0


def test_modulation_by_hand(spark):
    x = spark.createDataFrame([(0, 0, [1.0, 3.0]), (1, 0, [5.0, 5.0])], "vec_id long, label int, x array<double>")
    p = spark.createDataFrame([(0, [0.0, 1.0], [1.0, 0.0], [0.0, 0.0])], "label int, shift array<double>, scale array<double>, gate array<double>")
    for impl in ("sql", "arrow", "discrete"):
        out = {r["vec_id"]: r["y"] for r in adaln.forward(x, p, impl, eps=1e-12).collect()}
        assert np.allclose(out[0], [-2, 2], atol=1e-5) and np.allclose(out[1], [0, 1], atol=1e-5)
    g = spark.createDataFrame([(0, 0, [-1.0, 1.0], [1.0, 2.0]), (1, 0, [1.0, -1.0], [3.0, 4.0])], "vec_id long, label int, x array<double>, dy array<double>")
    for impl in ("tiled", "wide", "strided"):
        rows = {r["d"]: (r["grad_shift"], r["grad_scale"]) for r in adaln.grad_params(g, impl, eps=1e-12).collect()}
        assert np.allclose([rows[0], rows[1]], [(4, 2), (6, -2)], atol=1e-5)


def test_gradients_against_differences(spark):
    x, p = tables.activations(spark, SF).where("vec_id < 3"), tables.modulation(spark, SF)
    got = {r["vec_id"]: np.array(r["dx"]) for r in adaln.grad_input(x, p).collect()}
    params = {r["label"]: r for r in p.collect()}
    for r in x.collect():
        scale, shift, dy, v = (np.array(a) for a in (params[r["label"]]["scale"], params[r["label"]]["shift"], r["dy"], r["x"]))
        loss = lambda v: (dy * ((v - v.mean()) / np.sqrt(v.var() + adaln.EPS) * (1 + scale) + shift)).sum()
        for d in (0, 31, 63):
            e = np.zeros(len(v))
            e[d] = 1e-5
            assert abs((loss(v + e) - loss(v - e)) / 2e-5 - got[r["vec_id"]][d]) < 1e-4


def test_tiles_and_partitions_do_not_matter(spark):
    x = tables.activations(spark, SF)
    base = adaln.grad_params(x, "strided").toPandas().sort_values(["label", "d"])
    for n, d, t in ((1, 64, 256), (5, 48, 100), (3, 7, 33)):
        got = adaln.grad_params(x.repartition(n), "tiled", d_tile=d, n_tile=t).toPandas().sort_values(["label", "d"])
        assert np.allclose(got[["grad_shift", "grad_scale"]], base[["grad_shift", "grad_scale"]], atol=1e-9)


def test_ordered_merge_gives_the_same_bits(spark):
    """float32 sums, in the tiles' order: equal for any partitioning and Arrow batch size, and near those in float64."""
    x = tables.activations(spark, SF)
    seen = []
    for n, size in ((1, 10_000), (5, 37), (3, 256)):
        spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", size)
        try:
            got = adaln.grad_params(x.repartition(n, F.rand(n)), "tiled", n_tile=100, acc="float32", ordered=True).toPandas().sort_values(["label", "d"], ignore_index=True)
        finally:
            spark.conf.unset("spark.sql.execution.arrow.maxRecordsPerBatch")
        seen.append(got)
    assert seen[0].equals(seen[1]) and seen[0].equals(seen[2])
    full = adaln.grad_params(x, "strided").toPandas().sort_values(["label", "d"], ignore_index=True)
    gap = np.abs(full[["grad_shift", "grad_scale"]].to_numpy() - seen[0][["grad_shift", "grad_scale"]].to_numpy()).max()
    assert 0 < gap < 1e-4
    assert adaln.grad_params(x.where("false"), "tiled", ordered=True).count() == 0


def test_missing_vectors_and_parameters_give_nulls(spark):
    schema = "vec_id long, label int, x array<double>, dy array<double>"
    v = [1.0, 3.0, 2.0, 0.0]
    x = spark.createDataFrame([(0, 0, v, v), (1, 7, v, v), (2, None, v, v), (3, 0, None, v), (4, 0, v, None)], schema).coalesce(1)
    p = spark.createDataFrame([(0, [0.0] * 4, [1.0] * 4, [1.0] * 4)], "label int, shift array<double>, scale array<double>, gate array<double>")
    for impl in ("sql", "arrow", "discrete"):
        out = {r["vec_id"]: r["y"] for r in adaln.forward(x, p, impl).collect()}
        assert len(out) == 5 and {i for i, y in out.items() if y is None} == {1, 2, 3}, impl
    lost = x.where("vec_id = 1")
    assert [r["y"] for r in adaln.forward(lost, p, "arrow").collect()] == [None]
    sums = []
    for impl in ("tiled", "wide", "strided"):
        sums.append(sorted((str(r["label"]), r["d"], round(r["grad_shift"], 9), round(r["grad_scale"], 9)) for r in adaln.grad_params(x, impl).collect()))
    sums.append(sorted((str(r["label"]), r["d"], round(r["grad_shift"], 9), round(r["grad_scale"], 9)) for r in adaln.grad_params(x, "tiled", ordered=True).collect()))
    assert sums[0] == sums[1] == sums[2] == sums[3] and {r[0] for r in sums[0]} == {"0", "7", "None"}
    assert {r["vec_id"] for r in adaln.grad_input(x, p).collect() if r["dx"] is None} == {1, 2, 3, 4}
    assert {r["vec_id"] for r in adaln.gate_norm(x, "dy", p).collect() if r["y"] is None} == {1, 2, 3, 4}
    assert {r["vec_id"] for r in adaln.qk_norm(x, "x", "dy", heads=2).collect() if r["q"] is None or r["k"] is None} == {3, 4}


@pytest.mark.parametrize("kind", ["rms", "layer"])
def test_head_norms_with_weights(spark, kind):
    x, wq, wk = tables.activations(spark, SF), [0.5 + d / 64 for d in range(64)], [2.0 - d / 64 for d in range(64)]
    a, b = ({r["vec_id"]: (r["q"], r["k"]) for r in adaln.qk_norm(x, "x", "dy", kind=kind, impl=i, weight_q=wq, weight_k=wk).collect()} for i in ("arrow", "discrete"))
    assert a.keys() == b.keys() and all(np.allclose(a[i], b[i], atol=1e-9) for i in a)


def test_gate_before_norm(spark):
    x, p = tables.activations(spark, SF), tables.modulation(spark, SF)
    a, b = ({r["vec_id"]: r["y"] for r in adaln.gate_norm(x, "dy", p, "gate_then_norm", impl=i).collect()} for i in ("arrow", "discrete"))
    assert a.keys() == b.keys() and all(np.allclose(a[i], b[i], atol=1e-9) for i in a)


def test_slots_hold_both_bounds(spark):
    b = Bounds(100.0, 1000.0, 2.0)
    groups = spark.createDataFrame([(i, n) for i, n in enumerate([1, 2, 3, 5, 8, 13, 21, 34, 55, 500] * 20)], "group_id long, rows long")
    out = schedule.balance_tasks(groups, b).toPandas()
    assert out.groupby("group_id")["size"].sum().tolist() == [r["rows"] for r in groups.orderBy("group_id").collect()]
    per = out.groupby("slot").agg({"size": "sum", "load": "sum"})
    assert (per["size"] <= b.m_mem).all() and (per["load"] <= b.m_comp).all()
    assert len(per) <= 2 * out["size"].sum() / b.m_mem + 2 * out["load"].sum() / b.m_comp + 1
    assert schedule.balance_tasks(groups.where("false"), b).count() == 0


def test_longest_processing_time_first(spark):
    """Placement against a plain loop over windows of 8 steps."""
    got = schedule.schedule(tables.clips(spark, "/root/testdata/sf0.01"), n_ranks=4, steps="lpt").toPandas()
    key = lambda x: hashlib.md5(f"42:{x}".encode()).hexdigest()
    rows = sorted((key(r.batch_id), r.b * float(r.s) ** 2, r.batch_id) for r in got.itertuples())
    want = {}
    for w in range(0, len(rows), 32):
        total, used = [0.0] * 4, [0] * 4
        for _, load, i in sorted(rows[w : w + 32], key=lambda x: (-x[1], x[0])):
            r = min((r for r in range(4) if used[r] < 8), key=lambda r: (total[r], r))
            want[i] = (w // 32 * 8 + used[r], r)
            total[r] += load
            used[r] += 1
    assert {r.batch_id: (r.step, r.rank) for r in got.itertuples()} == want


def test_loss_measures(spark):
    """Gap and spikes against pandas."""
    import pandas as pd

    rng = np.random.default_rng(2)
    a, b = (pd.DataFrame({"step": range(60), "loss": 2 * 0.97 ** np.arange(60) + rng.normal(0, 0.01, 60)}) for _ in range(2))
    b.loc[[40, 45], "loss"] += 1.0
    smooth = lambda x: x["loss"].rolling(10, min_periods=1).mean()
    gap = (smooth(a) - smooth(b)).abs() / smooth(a)
    got = metrics.loss_gap(spark.createDataFrame(a), spark.createDataFrame(b)).first()
    assert math.isclose(got["max_gap"], gap.max()) and math.isclose(got["mean_gap"], gap.mean())
    assert sorted(r["step"] for r in metrics.spikes(spark.createDataFrame(b), 30, 60).collect()) == [40, 45]
    assert metrics.spikes(spark.createDataFrame(b), 0, 40).where("step > 20").count() == 0


def test_ladder_holds_its_samples(spark):
    df = spark.createDataFrame([(i, s) for i, s in enumerate((1, 256, 257, 30_000, 52_800, 52_801, 200_000))], "sample_id long, s long")
    got = [r["s_pad"] for r in batching.assign_buckets(df, "ladder").orderBy("sample_id").collect()]
    assert got == [256, 256, 640, 36_000, 52_800, 105_600, 211_200]


def test_ranks_are_those_of_a_plain_window(spark):
    from shapebalance.operators.ranks import key, ranked

    df = spark.range(3000).select("id", (F.col("id") % 7).alias("v"), (F.col("id") % 3).alias("w")).withColumn("k", key(5, "id"))
    for within, order in (((), ()), (("w",), ()), ((), (("v", False),)), (("w",), (("v", True),))):
        got = {r["id"]: r["g"] for r in ranked(df, "g", "k", within, order).collect()}
        rows = sorted(df.collect(), key=lambda r: (*(r[c] for c in within), *(r[c] if up else -r[c] for c, up in order), r["k"]))
        seen: dict = {}
        for r in rows:
            at = tuple(r[c] for c in within)
            assert got[r["id"]] == seen.setdefault(at, 0)
            seen[at] += 1


def test_measured_times_grow_with_load(spark):
    plan = costmodel.sweep_plan(spark, [4000, 24_000, 48_000], [1, 3], 3)
    m = costmodel.sync_matrix(costmodel.run_benchmark(plan, executor="arrow"), "median").toPandas().set_index(["b", "s"])["t"]
    assert len(m) == 6 and m[(1, 48_000)] > 2 * m[(1, 4000)] and m[(3, 48_000)] > 1.5 * m[(1, 48_000)]


def test_published_tables(spark):
    k = graphmem.kernel_table(spark).toPandas().set_index("n_k")
    assert round(k.loc[8, "fwd_speedup"], 2) == 3.12 and round(k.loc[64, "fwd_speedup"], 2) == 3.39  # prose starts at 3.21
    assert k.loc[48, "bwd_speedup"] < k.loc[40, "bwd_speedup"] and k.loc[8, "bwd_speedup"] < 1  # it does not grow steadily
    assert round(k.loc[8, "saved_share"], 3) == 0.649 and round(k.loc[64, "saved_share"], 3) == 0.619
    s = graphmem.system_table(spark).toPandas().set_index("arm")
    assert (abs(s["tokens_per_s"] - s["printed"]) < 2).all()
    assert round(1 - 56 / 62, 3) == 0.097  # printed as 10.7 %, which is the throughput's gain


def test_collapse(spark):
    g = graphmem.nodes(spark)
    one = graphmem.collapse(g, [x[0] for x in graphmem.CHAIN]).collect()
    assert len(one) == 1 and one[0]["inputs"] == ["scale", "shift", "x"] and g.count() == 5


def test_slots_keep_their_partitions(spark):
    df = spark.range(1000).withColumn("slot", (F.col("id") % 16).cast("int"))
    out = schedule.to_slots(df, "slot", 16).select(F.spark_partition_id().alias("p"), "slot").distinct()
    assert out.count() == 16 and out.where("p != slot").count() == 0
