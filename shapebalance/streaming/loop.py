"""Live telemetry: waits per window, sessions, and bounds that a running job refits."""

from __future__ import annotations

import json

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery

from ..operators.costmodel import S_REF, compute_bound, fit_weighted, to_model
from ..plans.model import Bounds
from ..sources.tables import trace_columns

EVENTS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def event_stream(spark: SparkSession, path: str, files_per_trigger: int | None = None) -> DataFrame:
    """events, a folder or one file, as a stream of files, with a time that watermarks accept.

    Files come in the order of their modification times. A replay takes all present files in one micro-batch, so no order
    of theirs makes an event late; state then holds the ids of the whole replay. files_per_trigger cuts the replay, and is
    right only for files whose times are in order to within the watermark: what is older than that is dropped.
    """
    reader = spark.readStream.schema(EVENTS)
    if files_per_trigger is not None:
        reader = reader.option("maxFilesPerTrigger", files_per_trigger)
    where = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    fs = where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())
    if not fs.getFileStatus(where).isDirectory():  # file streams take folders, so the file is picked out of its own
        reader, path = reader.option("pathGlobFilter", where.getName()), where.getParent().toString()
    rows = reader.parquet(path)
    return rows.withColumn("ts", F.col("ts").cast("timestamp"))


def distinct_events(stream: DataFrame, late: str = "1 day") -> DataFrame:
    """Drops repeats of event_id within the watermark; state holds the ids of that span."""
    return stream.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def stream_waits(stream: DataFrame, n_ranks: int = 8, width: str = "6 hours", late: str = "1 day") -> DataFrame:
    """Per closed window: slowest rank's time, ranks seen, waiting of the others. Two chained aggregates; state: ranks times open windows."""
    per = distinct_events(stream, late).groupBy(F.window("ts", width), (F.col("user_id") % n_ranks).alias("rank")).agg(F.sum("value").alias("t"))
    out = per.groupBy(F.window(F.window_time("window"), width)).agg(F.max("t").alias("t_sync"), F.count("*").alias("ranks_seen"), (F.count("*") * F.max("t") - F.sum("t")).alias("wait"))
    return out.select(F.col("window.start").alias("window_start"), F.col("window.end").alias("window_end"), "t_sync", "ranks_seen", "wait")


def sessions(events: DataFrame, gap: str = "2 hours", late: str | None = None) -> DataFrame:
    """Bursts of a user's events apart by less than `gap`; batch, or streaming with a watermark."""
    rows = events.withWatermark("ts", late) if late else events
    out = rows.groupBy(F.session_window("ts", gap), "user_id").agg(F.count("*").alias("n"), F.sum("value").alias("busy"))
    return out.select("user_id", F.col("session_window.start").alias("started"), F.col("session_window.end").alias("ended"), "n", "busy")


SUMS = "b long, s long, n long, sum_t double, sum_t2 double"
BOUNDS = "batch long, m_mem double, m_comp double, p double, a double, b double, r2 double"


def _exists(spark: SparkSession, folder: str) -> bool:
    path = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(folder)
    return path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).exists(path)


def _folders(spark: SparkSession, folder: str, name: str) -> list[int]:
    """Numbers of the subfolders name=<n> that were written to their end."""
    path = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(folder)
    if not _exists(spark, folder):
        return []
    found = path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).listStatus(path)
    own = [x.getPath().getName() for x in found if x.getPath().getName().startswith(f"{name}=")]
    return sorted(int(x.partition("=")[2]) for x in own if _exists(spark, f"{folder}/{x}/_SUCCESS"))


def start_loop(stream: DataFrame, folder: str, target: float, bounds: Bounds = Bounds(), n_ranks: int = 8, least_r2: float = 0.9, least_gain: float = 0.01, trigger: dict | None = None) -> StreamingQuery:
    """Per micro-batch, adds its cell sums to those so far, refits, and writes a new version of the bounds.

    A batch's folder holds the sums of all batches up to it, read from the last batch before it, so a batch costs one
    table of cells whatever came before, and another try of a batch replaces what the first one wrote. A version is
    written when the fit is good enough and the bound moves by least_gain from the last version in the folder, or from
    `bounds` if there is none; a restart thus goes on where the loop stopped. trigger: arguments of the stream's trigger,
    by default availableNow; {"processingTime": "1 minute"} watches a live run. The two last batches' sums are kept.
    Folder: cells/batch=<n>, bounds/version=<n>; checkpoint beside them.
    """

    def on_batch(rows: DataFrame, number: int) -> None:
        spark = rows.sparkSession
        own = rows.select(*trace_columns(n_ranks)).groupBy("b", "s").agg(F.count("*").alias("n"), F.sum("t").alias("sum_t"), F.sum(F.col("t") * F.col("t")).alias("sum_t2"))
        done = [k for k in _folders(spark, f"{folder}/cells", "batch") if k < number]
        if done:
            before = spark.read.schema(SUMS).parquet(f"{folder}/cells/batch={done[-1]}")
            own = own.unionByName(before).groupBy("b", "s").agg(*[F.sum(c).alias(c) for c in ("n", "sum_t", "sum_t2")])
        own.coalesce(1).write.mode("overwrite").parquet(f"{folder}/cells/batch={number}")
        path = spark.sparkContext._jvm.org.apache.hadoop.fs.Path
        for old in done[:-1]:
            gone = path(f"{folder}/cells/batch={old}")
            gone.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(gone, True)
        try:
            model = to_model(fit_weighted(spark.read.schema(SUMS).parquet(f"{folder}/cells/batch={number}")))
            new = compute_bound(model, target)
        except ValueError:
            return
        versions = [k for k in _folders(spark, f"{folder}/bounds", "version") if k < number]
        last = spark.read.schema(BOUNDS).parquet(f"{folder}/bounds/version={versions[-1]}").first()["m_comp"] if versions else bounds.m_comp
        if model.r2 >= least_r2 and abs(new / last - 1) >= least_gain:
            row = [(number, bounds.m_mem, new, model.p, model.a, model.b, model.r2)]
            spark.createDataFrame(row, BOUNDS).coalesce(1).write.mode("overwrite").parquet(f"{folder}/bounds/version={number}")

    return distinct_events(stream).writeStream.foreachBatch(on_batch).option("checkpointLocation", f"{folder}/checkpoint").trigger(**(trigger or {"availableNow": True})).start()


def latest_cells(spark: SparkSession, folder: str) -> DataFrame:
    """The sums of all events that the loop has seen."""
    done = _folders(spark, f"{folder}/cells", "batch")
    return spark.read.schema(SUMS).parquet(f"{folder}/cells/batch={done[-1]}") if done else spark.createDataFrame([], SUMS)


def latest_bounds(spark: SparkSession, folder: str) -> DataFrame:
    return spark.read.parquet(f"{folder}/bounds").orderBy(F.desc("version")).limit(1)


def waits_listener(query: StreamingQuery) -> str:
    """The last progress of a query as JSON: rows, late rows dropped by the watermark, state size."""
    p = query.lastProgress
    return json.dumps({"rows": p["numInputRows"], "state": [{"rows": s["numRowsTotal"], "late": s["numRowsDroppedByWatermark"]} for s in p["stateOperators"]]} if p else {})


__all__ = ["S_REF", "distinct_events", "event_stream", "latest_bounds", "latest_cells", "sessions", "start_loop", "stream_waits", "waits_listener"]
