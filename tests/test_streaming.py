"""Replays of events in several files whose order is not that of ts."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from shapebalance.operators import costmodel
from shapebalance.plans import registry
from shapebalance.plans.model import Bounds
from shapebalance.sources import tables
from shapebalance.streaming import loop

from .conftest import SF, plain


@pytest.fixture(scope="module")
def shuffled(spark, tmp_path_factory):
    folder = tmp_path_factory.mktemp("shuffled")
    spark.read.parquet(f"{SF}/events.parquet").repartition(5, F.xxhash64("event_id")).write.parquet(f"{folder}/events.parquet")
    assert len(list((folder / "events.parquet").glob("part-*.parquet"))) == 5
    return str(folder)


def test_stream_waits_of_shuffled_files(spark, duck, shuffled):
    got, want = registry.QUERIES["stream_waits"](spark, shuffled).toPandas(), duck.execute(registry.ORACLES["stream_waits"]).df()
    assert len(want) > 0
    assert plain(got) == plain(want)


def test_stream_loop_counts_every_event_of_shuffled_files(spark, shuffled, tmp_path):
    loop.start_loop(loop.event_stream(spark, f"{shuffled}/events.parquet"), str(tmp_path), 20.0, Bounds()).awaitTermination()
    n = loop.latest_cells(spark, str(tmp_path)).agg(F.sum("n")).first()[0]
    assert n == spark.read.parquet(f"{SF}/events.parquet").select("event_id").distinct().count()


def test_stream_loop_goes_on_after_a_restart(spark, shuffled, tmp_path):
    """Four batches, the loop ended and started anew between them: all events count once, and a version needs a move from the last one."""
    events = spark.read.parquet(f"{SF}/events.parquet").orderBy("ts")
    ids = [r["event_id"] for r in events.select("event_id").collect()]
    versions = []
    for k in range(4):
        own = events.where(F.col("event_id").isin(ids[k * len(ids) // 4 : (k + 1) * len(ids) // 4]))
        own.coalesce(1).write.mode("append").parquet(f"{tmp_path}/events.parquet")
        loop.start_loop(loop.event_stream(spark, f"{tmp_path}/events.parquet"), f"{tmp_path}/loop", 20.0).awaitTermination()
        versions.append(loop._folders(spark, f"{tmp_path}/loop/bounds", "version"))
    cells = loop.latest_cells(spark, f"{tmp_path}/loop")
    assert cells.agg(F.sum("n")).first()[0] == len(ids)
    want = costmodel.cells(tables.trace(spark, SF)).toPandas().sort_values(["b", "s"])
    got = cells.toPandas().sort_values(["b", "s"])
    assert np.allclose(got[["b", "s", "n", "sum_t", "sum_t2"]], want[["b", "s", "n", "sum_t", "sum_t2"]])
    assert len(versions[-1]) < 4 and len(loop._folders(spark, f"{tmp_path}/loop/cells", "batch")) <= 2
