"""The user-function surface: Arrow functions and a table function, registered for SQL."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T


@F.pandas_udf(T.DoubleType())
def ewma_last(values: pd.Series, lam: pd.Series) -> pd.Series:
    """The exponential average at the end of each array of values; nulls are skipped."""

    def one(v, w):
        state = None
        for x in () if v is None else v:
            if x is not None and x == x:
                state = x if state is None else w * x + (1 - w) * state
        return state

    return pd.Series([one(v, w) for v, w in zip(values, lam, strict=True)], dtype="float64")


@F.udtf(returnType=T.StructType([T.StructField(c, T.IntegerType()) for c in ("first", "last", "peak")]))
class FaultsOfSeries:
    """Faults of one series of verdicts: runs of positions where at least x of the last y are abnormal."""

    def eval(self, flags: list, x: int, y: int):
        first, peak = None, 0
        for i in range(len(flags)):
            hits = sum(bool(f) for f in flags[max(0, i - y + 1) : i + 1])
            if hits >= x:
                first, peak = (i if first is None else first), max(peak, hits)
            elif first is not None:
                yield first, i - 1, peak
                first, peak = None, 0
        if first is not None:
            yield first, len(flags) - 1, peak


def register(spark: SparkSession) -> None:
    """SQL: ewma_last(values, lambda), faults_of(flags, x, y), and the SQL function signal_ratio_db(own, others)."""
    spark.udf.register("ewma_last", ewma_last)
    spark.udtf.register("faults_of", FaultsOfSeries)
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION signal_ratio_db(own DOUBLE, others DOUBLE) RETURNS DOUBLE RETURN 10 * log10(try_divide(own, others))")
