"""Unusually long intervals, kept apart because they would flatten the staircase."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def length_threshold(df: DataFrame, q: float = 0.99, exact: bool = False, col: str = "zlen") -> int:
    """The value at rank ceil(q * N), exactly or from a sketch. Any threshold gives right answers.

    The exact value is ranked among the rows between two sketched quantiles only.
    """
    n = df.count()
    if not n:
        return 0
    if not exact:
        return int(df.agg(F.percentile_approx(col, q, 10_000)).first()[0])
    lo, hi = df.agg(F.percentile_approx(col, F.lit([max(0.0, q - 0.002), min(1.0, q + 0.002)]), 10_000)).first()[0]
    slack = 1 << 10  # the sketch works on doubles
    below = df.where(F.col(col) < lo - slack).count()
    k = max(1, math.ceil(round(q * n, 9)))
    near = df.where(F.col(col).between(lo - slack, hi + slack)).select(col)
    return int(near.orderBy(col).offset(k - below - 1).first()[0])


def split_outliers(df: DataFrame, threshold: int) -> tuple[DataFrame, DataFrame]:
    """(usual, longer than the threshold)."""
    return df.where(F.col("zlen") <= threshold), df.where(F.col("zlen") > threshold)
