"""Readers with fixed schemas, and the catalogues derived from the given tables.

Only the columns that a catalogue needs reach the scan; payloads (text, html, vectors) are read where lengths or
values come from them and never shuffled.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.shapes import token_len, with_seq_len

#: Priority of an order -> height and width of its clip.
RESOLUTIONS = {"1-URGENT": (640, 640), "2-HIGH": (480, 832), "3-MEDIUM": (384, 640), "4-NOT SPECIFIED": (320, 512), "5-LOW": (256, 256)}
TRACE_SCHEMA = "run int, rep int, rank int, b long, s long, t double"
#: Generator of the trace: constant, slope, exponent, with S in units of S_REF.
A0, B0, P0, S_REF = 2.0, 1.2, 2.1, 1e4


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read_trace(spark: SparkSession, path: str, kind: str = "parquet") -> DataFrame:
    """A benchmark trace in parquet, orc, json or csv, by its declared schema."""
    reader = spark.read.schema(TRACE_SCHEMA)
    return reader.option("header", True).csv(path) if kind == "csv" else getattr(reader, kind)(path)


def write_plan(plan: DataFrame, path: str, by: str = "bound") -> None:
    """A batch plan as parquet, partitioned by its binding constraint; a rerun replaces the partitions it writes."""
    plan.write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy(by).parquet(path)


def clips(spark: SparkSession, sf_dir: str, text_mode: str = "none", **text) -> DataFrame:
    """The clip catalogue: sample_id, modality, f, h, w, s_text, s_visual, s.

    Quantities are summed per order before the join, so the join moves one short row per order.
    """
    q = table(spark, sf_dir, "lineitem").groupBy(F.col("l_orderkey").alias("o_orderkey")).agg(F.sum("l_quantity").alias("q"))
    orders = table(spark, sf_dir, "orders").select("o_orderkey", "o_orderstatus", "o_orderpriority")
    k = F.least(F.lit(32), F.floor(F.coalesce("q", F.lit(0.0)) / 8).cast("int"))
    size = lambda i: F.create_map(*[F.lit(x) for p, hw in RESOLUTIONS.items() for x in (p, hw[i])])[F.col("o_orderpriority")]
    raw = orders.join(q, "o_orderkey", "left").select(
        F.col("o_orderkey").alias("sample_id"),
        F.when((F.col("o_orderstatus") == "P") | (k <= 0), 1).otherwise(1 + 8 * k).alias("f"), size(0).alias("h"), size(1).alias("w"),
    )
    if text_mode == "caption":
        text["captions"] = text_samples(spark, sf_dir, "documents").select(F.col("sample_id").alias("caption_id"), F.col("s").alias("s_text"))
    out = with_seq_len(raw, text_mode, **text)
    return out.select("sample_id", F.when(F.col("f") == 1, "image").otherwise("video").alias("modality"), "f", "h", "w", "s_text", "s_visual", "s")


def text_samples(spark: SparkSession, sf_dir: str, corpus: str) -> DataFrame:
    """Text-only samples: sample_id, corpus, s (words, at least 1). Conversations add up their turns; pages lose their markup."""
    if corpus == "conversations":
        turns = table(spark, sf_dir, "conversations").select("conv_id", token_len("text").alias("n"))
        out = turns.groupBy(F.col("conv_id").alias("sample_id")).agg(F.sum("n").alias("s"))
    elif corpus == "pages":
        out = table(spark, sf_dir, "pages").select(F.col("page_id").alias("sample_id"), token_len(F.regexp_replace("html", "<[^>]*>", " ")).alias("s"))
    else:
        key = {"documents": "doc_id", "benchmark": "item_id"}[corpus]
        out = table(spark, sf_dir, corpus).select(F.col(key).alias("sample_id"), token_len("text").alias("s"))
    return out.select("sample_id", F.lit(corpus).alias("corpus"), "s")


def trace_columns(n_ranks: int = 8) -> list:
    k = F.from_json("props", "k int")["k"]
    s, b = 512 * (F.coalesce(k, F.lit(0)) + 1), 1 + F.col("user_id") % 4
    noise = 1 + 0.05 * (F.least(F.col("value"), F.lit(200.0)) - 50) / 50
    return [(F.col("event_id") % 7).cast("int").alias("rep"), (F.col("user_id") % n_ranks).cast("int").alias("rank"), b.alias("b"), s.cast("long").alias("s"), (A0 + B0 * b * F.pow(s / S_REF, F.lit(P0)) * noise).alias("t")]


def trace(spark: SparkSession, sf_dir: str, n_ranks: int = 8) -> DataFrame:
    """The benchmark trace read from events: event_id, ts, rep, rank, b, s, t."""
    return table(spark, sf_dir, "events").select("event_id", F.col("ts").cast("timestamp").alias("ts"), *trace_columns(n_ranks))


def activations(spark: SparkSession, sf_dir: str, repeat: int = 1) -> DataFrame:
    """Token rows: vec_id, label, x (doubles), dy from its formula. repeat > 1 copies the rows under new ids."""
    e = table(spark, sf_dir, "embeddings").select(F.col("vec_id").cast("long").alias("vec_id"), "label", F.col("embedding").cast("array<double>").alias("x"))
    if repeat > 1:
        n = e.count()
        e = e.withColumn("_copy", F.explode(F.sequence(F.lit(0), F.lit(repeat - 1)))).withColumn("vec_id", F.col("vec_id") + F.col("_copy") * n).drop("_copy")
    return e.withColumn("dy", F.transform("x", lambda x, d: ((31 * F.col("vec_id") + 17 * d) % 101 - 50) / 128))


def modulation(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One row per label: shift, scale, gate by their formulas. As many rows as labels: broadcast after Spark's size check."""
    labels = table(spark, sf_dir, "embeddings").groupBy("label").agg(F.max(F.size("embedding")).alias("n"))
    d = F.sequence(F.lit(0), F.col("n") - 1)
    of = lambda add, mod, less, by: F.transform(d, lambda i: ((64 * F.col("label") + add * i) % mod - less) / by)
    return labels.select("label", of(11, 19, 9, 32).alias("shift"), of(7, 17, 8, 64).alias("scale"), of(5, 13, 0, 16).alias("gate"))
