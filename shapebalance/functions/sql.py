"""SQL functions of the engine, as expressions that the optimizer inlines, and a table function of sweep cells."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf

_FUNCTIONS = (
    "visual_len(f BIGINT, h BIGINT, w BIGINT) RETURNS BIGINT RETURN ((f - 1) DIV 8 + 1) * (h DIV 16) * (w DIV 16)",
    "seq_len(text_tokens BIGINT, f BIGINT, h BIGINT, w BIGINT) RETURNS BIGINT RETURN greatest(1, text_tokens + ((f - 1) DIV 8 + 1) * (h DIV 16) * (w DIV 16))",
    "dual_batch(s BIGINT, m_mem DOUBLE, m_comp DOUBLE, p DOUBLE) RETURNS BIGINT RETURN greatest(1, least(CAST(floor(m_mem / s) AS BIGINT), CAST(floor(m_comp / pow(CAST(s AS DOUBLE), p)) AS BIGINT)))",
    "range_ratio(top DOUBLE, low DOUBLE) RETURNS DOUBLE RETURN (top - low) / top",
)


@udtf(returnType="p double")
class CandidateExponents:
    """Exponents from lo to hi by step."""

    def eval(self, lo: float, hi: float, step: float) -> Iterator[tuple[float]]:
        for i in range(round((hi - lo) / step) + 1):
            yield (round(lo + i * step, 6),)


def register(spark: SparkSession) -> None:
    for f in _FUNCTIONS:
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {f}")
    spark.udtf.register("candidate_exponents", CandidateExponents)
