"""SQL functions, a table function and views, for users of SQL. Functions are inlined by Catalyst."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from channelalign.functions import dtw as kernels

FUNCTIONS = {
    "time_bin": "(us BIGINT, origin BIGINT, width BIGINT) RETURNS BIGINT RETURN (us - origin - pmod(us - origin, width)) DIV width",
    "rayleigh_log_ratio": "(s DOUBLE, s1 DOUBLE, s0 DOUBLE) RETURNS DOUBLE RETURN 2 * ln(s0 / s1) + s * s / 2 * (1 / (s0 * s0) - 1 / (s1 * s1))",
    "rayleigh_cdf": "(s DOUBLE, sigma DOUBLE) RETURNS DOUBLE RETURN 1 - exp(-s * s / (2 * sigma * sigma))",
}


@F.udtf(returnType=T.StructType([T.StructField("bin", T.LongType()), T.StructField("cnt", T.LongType())]))
class DenseSeries:
    """Rows of every bin of a sparse vector, zeros too."""

    def eval(self, bins: list, cnts: list, n_bins: int) -> Iterator[tuple[int, int]]:
        known = dict(zip(bins or [], cnts or [], strict=True))
        for b in range(n_bins or 0):
            yield b, known.get(b, 0)


@F.pandas_udf(T.DoubleType())
def dtw(x: pd.Series, y: pd.Series) -> pd.Series:
    """Elastic distance of two arrays of counts."""
    return pd.Series([kernels.distance(np.asarray(a, float), np.asarray(b, float)) for a, b in zip(x, y, strict=True)])


@F.pandas_udf(T.DoubleType())
def fit_rayleigh_agg(s: pd.Series) -> float:
    """The fit as an aggregate function."""
    return float(np.sqrt((s.to_numpy() ** 2).sum() / (2 * len(s)))) if len(s) else float("nan")


def register(spark: SparkSession, views: dict[str, DataFrame] | None = None) -> None:
    """Makes the functions known to the session, and frames as temporary views (ca_events, ca_binned, ca_pairs, ca_labels, ca_state by custom)."""
    for name, body in FUNCTIONS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}{body}")
    spark.udtf.register("dense_series", DenseSeries)
    spark.udf.register("dtw", dtw)
    spark.udf.register("fit_rayleigh_agg", fit_rayleigh_agg)
    for name, frame in (views or {}).items():
        frame.createOrReplaceTempView(name)
