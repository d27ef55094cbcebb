"""Queries that once made their data up, on hand-made tables: three clips of 4,800, 256 and 52,800 tokens."""

import pandas as pd
import pytest

from shapebalance.plans import registry


@pytest.fixture(scope="module")
def few(spark, tmp_path_factory):
    d = tmp_path_factory.mktemp("few")
    pd.DataFrame({"o_orderkey": [1, 2, 3], "o_orderstatus": ["O", "P", "O"], "o_orderpriority": ["1-URGENT", "5-LOW", "1-URGENT"]}).to_parquet(d / "orders.parquet")
    pd.DataFrame({"l_orderkey": [1, 2, 3], "l_quantity": [16.0, 50.0, 300.0]}).to_parquet(d / "lineitem.parquet")
    return lambda name: registry.QUERIES[name](spark, str(d)).toPandas()


CELLS = {4000: [1, 2, 4, 8], 8000: [1, 2, 4, 8], 56_000: [1, 2]}


def test_sweep_plan_grid(few):
    got = few("sweep_plan_grid")
    assert sorted(zip(got["s"], got["b"], got["rep"], strict=True)) == [(s, b, rep) for s, bs in CELLS.items() for b in bs for rep in range(3)]
    assert set(got["priority"]) == {0, 56_000, 112_000}


def test_sweep_plan_throughput(few):
    got = few("sweep_plan_throughput")
    assert sorted(zip(got["s"], got["b"], got["rep"], strict=True)) == [(s, b, rep) for s, bs in CELLS.items() for b in (bs[0], bs[-1]) for rep in range(3)]


def test_benchmark_model(few):
    got = few("benchmark_model").set_index(["s", "b"])
    assert sorted(got.index) == [(s, b) for s, bs in CELLS.items() for b in bs] and set(got["n"]) == {3}
    assert got.loc[(56_000, 2), "t"] == pytest.approx(2 + 1.2 * 2 * 5.6**2.1, abs=1e-6)


def test_fit_measured(few):
    got = few("fit_measured")
    assert list(got["n"]) == [sum(map(len, CELLS.values()))] and (got["slope"] > 0).all()


def test_max_frames(few):
    got = {tuple(r)[:4]: tuple(r)[4:] for r in few("max_frames")[["m_mem", "b", "h", "w", "frames", "clips", "longer"]].itertuples(index=False)}
    assert len(got) == 8
    assert got[(144_000, 3, 640, 640)] == (233, 2, 1) and got[(158_400, 3, 640, 640)] == (257, 2, 0) and got[(144_000, 1, 256, 256)] == (4489, 1, 0)


def test_crossover(few):
    got = few("crossover").set_index("p")
    assert got.loc[2.0, "s"] == pytest.approx(16_666.6667) and list(got.index.sort_values()) == [2.0, 2.1]
    assert (got["memory"] == 2).all() and (got["compute"] == 1).all()


def test_memory_bound(few):
    got = few("memory_bound")
    assert set(zip(got["capacity"], got["tokens"], strict=True)) == {(80e9, 80_000.0), (139e9, 198_000.0)}
    assert sorted(zip(got["s"], got["fit"], got["n"], strict=True)) == [(256, 312, 1), (256, 773, 1), (4800, 16, 1), (4800, 41, 1), (52_800, 1, 1), (52_800, 3, 1)]


#: Tokens of the dual plan's batches.
BATCHES = {"1x256x256": 562 * 256, "17x640x640": 30 * 4800, "257x640x640": 52_800}


def test_activation_bytes(few):
    got = few("activation_bytes")
    assert dict(zip(got["bucket_id"], got["tokens"], strict=True)) == BATCHES
    assert list(got["discrete"]) == list(got["tokens"] * 5120 * 10) and list(got["fused"]) == list(got["tokens"] * 5120 * 2)


def test_traffic_bytes(few):
    got = few("traffic_bytes").set_index(["arm", "bucket_id"])["bytes"].to_dict()
    assert got == {(arm, k): vectors * n * 5120 * 40 * 2 * 2 for arm, vectors in (("discrete", 8), ("fused", 2)) for k, n in BATCHES.items()}


def test_graph_collapse(few):
    got = few("graph_collapse").set_index(["bucket_id", "op"])
    assert got["moved"].to_dict() == {(b, op): n * k for b, n in BATCHES.items() for op, k in (("mean", 1), ("var", 1), ("fused", 2))}
    assert set(got.xs("fused", level="op")["inputs"]) == {"mean,scale,shift,var,x"}


def test_published_system_check(few):
    got = few("published_system_check").set_index("arm")
    assert got["clips"].to_dict() == {"unfused": 2, "fused_same": 2, "fused_max": 3}
    assert got["tokens"].to_dict() == {"unfused": 5056, "fused_same": 5056, "fused_max": 57_856}
    assert got.loc["fused_same", "tokens_per_s"] == 2571.4 and got.loc["fused_max", "seconds"] == pytest.approx(57_856 * 68 / 158_400, abs=1e-6)


def test_published_tables_check(few):
    got = few("published_tables_check").set_index("n_k")
    assert got["clips"].to_dict() == {8: 2, 16: 0, 24: 0, 32: 0, 40: 0, 48: 0, 56: 1, 64: 0}
    assert got.loc[8, "fwd"] == 3.12 and got.loc[8, "fwd_gain"] == pytest.approx(2 * 0.482) and got.loc[56, "bwd_gain"] == pytest.approx(1.326)
