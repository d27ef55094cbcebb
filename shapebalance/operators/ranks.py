"""Exact global ranks without a single-task sort.

Rows are ordered by columns and then by a hexadecimal key. The key's first digits keep its order, so rows are numbered
inside (columns, digits); counts are summed up in order in two levels, over the columns' values and over the digits of
one value, and each row adds the offset of both.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def key(seed: int, *cols) -> Column:
    """md5 of 'seed:value', the same on every engine and for every partitioning."""
    return F.md5(F.concat_ws(":", F.lit(str(seed)), *[F.col(c).cast("string") if isinstance(c, str) else c.cast("string") for c in cols]).cast("binary"))


def ranked(df: DataFrame, name: str, key_col: str, within: tuple[str, ...] = (), order: tuple[tuple[str, bool], ...] = (), digits: int = 3) -> DataFrame:
    """Adds `name`, a row's number from 0 inside `within` by `order` ((column, ascending)) and then key_col.

    Rows with equal order columns are sorted in up to 16^digits tasks (4,096). The windows over summary rows see one row
    for each distinct value of the order columns, and at most 16^digits for one value.
    """
    cols = [c for c, _ in order]
    df = df.withColumn("_chunk", F.substring(key_col, 1, digits))
    cell = [*within, *cols, "_chunk"]
    local = df.withColumn("_local", F.row_number().over(Window.partitionBy(*cell).orderBy(key_col)) - 1)
    counts = df.groupBy(*cell).agg(F.count("*").alias("_n"))

    def before(keys: list, sort: list):
        return F.coalesce(F.sum("_n").over(Window.partitionBy(*(keys or [F.lit(0)])).orderBy(*sort).rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))

    offsets = counts.withColumn("_offset", before([*within, *cols], ["_chunk"]))
    if cols:
        values = counts.groupBy(*within, *cols).agg(F.sum("_n").alias("_n"))
        first = values.withColumn("_first", before(list(within), [F.col(c).asc() if up else F.col(c).desc() for c, up in order])).drop("_n")
        offsets = offsets.join(first, [*within, *cols]).withColumn("_offset", F.col("_offset") + F.col("_first")).drop("_first")
    return local.join(offsets.drop("_n"), cell).withColumn(name, (F.col("_local") + F.col("_offset")).cast("long")).drop("_chunk", "_local", "_offset")
