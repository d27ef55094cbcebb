"""Lengths of samples after compression and tokenisation (M1-M3), as columns in generated code."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def _c(x) -> Column:
    return x if isinstance(x, Column) else F.col(x) if isinstance(x, str) else F.lit(x)


def _div(a: Column, b: int, rounding: str) -> Column:
    """Whole division of non-negative columns, down or up."""
    up = F.lit(b - 1 if rounding == "ceil" else 0)
    return ((a + up - (a + up) % b) / b).cast("long")


def visual_len(f="f", h="h", w="w", lam: int = 8, eta: int = 16, gamma: int = 16, rounding: str = "floor") -> Column:
    """M1: latent frames times latent pixels. The first frame stays alone; a single frame is one latent frame. Null dimensions give null."""
    f, h, w = (_c(x).cast("long") for x in (f, h, w))
    return (_div(f - 1, lam, rounding) + 1) * _div(h, eta, rounding) * _div(w, gamma, rounding)


def token_len(text, mode: str = "words", chars: int = 4) -> Column:
    """M3: words between spaces, tabs and line ends, or characters by `chars` rounded up; at least 1, null counts as empty."""
    text = F.coalesce(_c(text), F.lit(""))
    if mode == "chars":
        return F.greatest(F.lit(1).cast("long"), _div(F.length(text).cast("long"), chars, "ceil"))
    return F.greatest(F.lit(1).cast("long"), F.size(F.filter(F.split(text, "[ \\t\\n\\r]+"), lambda x: x != "")).cast("long"))


def with_seq_len(df: DataFrame, text_mode: str = "none", fixed: int = 0, captions: DataFrame | None = None, cap: int | None = None) -> DataFrame:
    """M2: adds s_text, s_visual and s = s_text + s_visual, at least 1.

    text_mode: none; fixed (a constant); actual (column s_text is there); caption (`captions`: caption_id, s_text, joined
    by sample_id modulo their number; whole, or cut at `cap` words when that is given). Narrow but for captions, a join that Spark broadcasts when small.
    """
    df = df.withColumn("s_visual", visual_len())
    if text_mode == "caption":
        n = captions.count()
        length = F.col("s_text") if cap is None else F.least("s_text", F.lit(cap))
        caps = captions.select(F.col("caption_id").alias("_cap"), length.alias("s_text"))
        df = df.withColumn("_cap", F.col("sample_id") % F.lit(max(n, 1))).join(caps, "_cap", "left").drop("_cap").withColumn("s_text", F.coalesce("s_text", F.lit(0)))
    elif text_mode != "actual":
        df = df.withColumn("s_text", F.lit(fixed if text_mode == "fixed" else 0).cast("long"))
    return df.withColumn("s", F.greatest(F.lit(1).cast("long"), F.col("s_text") + F.col("s_visual")))
