"""Captions count with all their words."""

from pyspark.sql import functions as F

from shapebalance.functions.shapes import with_seq_len


def test_long_captions_are_whole(spark):
    clips = spark.createDataFrame([(0, 1, 256, 256), (1, 1, 256, 256)], "sample_id long, f int, h int, w int")
    captions = spark.createDataFrame([(0, 2000), (1, 5)], "caption_id long, s_text long")
    lengths = lambda **cap: [tuple(r) for r in with_seq_len(clips, "caption", captions=captions, **cap).select("s_text", "s").orderBy(F.col("sample_id")).collect()]
    assert lengths() == [(2000, 2256), (5, 261)]
    assert lengths(cap=512) == [(512, 768), (5, 261)]
