"""SQL functions: graded weights and session numbers for use in queries, and Python ones where a loop is needed."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F


@F.pandas_udf("double")
def purity_udaf(label: pd.Series) -> float:
    """The share of the commonest label of a group."""
    return float(label.value_counts().iloc[0] / len(label)) if len(label) else 0.0


@F.udtf(returnType="position int, url_id int, dwell_s double")
class WalkSession:
    """Rows (position, url, page time) of a session given as arrays of URLs and of times in seconds."""

    def eval(self, urls: list, seconds: list) -> Iterator[tuple]:
        for i, u in enumerate(urls):
            yield i, u, float(seconds[i + 1] - seconds[i]) if i + 1 < len(seconds) else 0.0


def register(spark: SparkSession) -> None:
    """ramp_weight(size, lb, ub), step_weight(size, least), session_starts(seconds, beta), walk_session, purity_of."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION ramp_weight(size BIGINT, lb BIGINT, ub BIGINT) RETURNS DOUBLE RETURN CASE WHEN lb = ub THEN CAST(size > lb AS DOUBLE) ELSE greatest(0D, least(1D, CAST(size - lb AS DOUBLE) / (ub - lb))) END")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION step_weight(size BIGINT, fewest BIGINT) RETURNS DOUBLE RETURN CAST(size >= fewest AS DOUBLE)")
    spark.sql(
        "CREATE OR REPLACE TEMPORARY FUNCTION session_starts(seconds ARRAY<DOUBLE>, beta DOUBLE) RETURNS ARRAY<DOUBLE> RETURN "
        "aggregate(array_sort(seconds), CAST(array() AS ARRAY<DOUBLE>), (a, t) -> CASE WHEN size(a) = 0 OR t - element_at(a, -1) > beta THEN array_append(a, t) ELSE a END)"
    )
    spark.udtf.register("walk_session", WalkSession)
    spark.udf.register("purity_of", purity_udaf)
