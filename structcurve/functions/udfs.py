"""The user-defined surface: SQL functions, Arrow functions, table functions and side metrics."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Observation, SparkSession
from pyspark.sql import functions as F


def register_sql_functions(spark: SparkSession) -> None:
    """``morton4(q0, q1, q2, q3)`` as a SQL function; the optimiser inlines it."""
    body = " | ".join(f"((shiftright(q{d}, {b}) & 1L) << {b * 4 + 3 - d})" for d in range(4) for b in range(4))
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION morton4(q0 BIGINT, q1 BIGINT, q2 BIGINT, q3 BIGINT) RETURNS BIGINT RETURN {body}")


def eigenvalues_udf():
    """Largest eigenvalue of symmetric 3x3 matrices given by their six entries: vectorised numpy."""

    @F.pandas_udf("double")
    def top(xx: pd.Series, yy: pd.Series, ww: pd.Series, xy: pd.Series, xw: pd.Series, yw: pd.Series) -> pd.Series:
        m = np.empty((len(xx), 3, 3))
        m[:, 0, 0], m[:, 1, 1], m[:, 2, 2] = xx, yy, ww
        m[:, 0, 1] = m[:, 1, 0] = xy
        m[:, 0, 2] = m[:, 2, 0] = xw
        m[:, 1, 2] = m[:, 2, 1] = yw
        return pd.Series(np.linalg.eigvalsh(m)[:, 2])

    return top


def mean_vector_udf():
    """Grouped aggregate: the mean of vectors."""

    @F.pandas_udf("array<double>")
    def mean(v: pd.Series) -> list:
        return np.mean(np.array(v.tolist(), np.float64), axis=0).tolist()

    return mean


def image_offsets_udtf():
    """Table function: the shifts of periodic images, ``n`` cells each way."""

    @F.udtf(returnType="na int, nb int, nc int")
    class Offsets:
        def eval(self, n: int):
            for i in range(-n, n + 1):
                for j in range(-n, n + 1):
                    for k in range(-n, n + 1):
                        yield i, j, k

    return Offsets


def box_ranges_udtf():
    """Table function: index ranges of a grid box (three dimensions)."""

    @F.udtf(returnType="first bigint, last bigint")
    class Ranges:
        def eval(self, lo: int, hi: int, bits: int):
            from structcurve.operators.zorder import decompose_box

            yield from decompose_box([lo] * 3, [hi] * 3, bits)

    return Ranges


def observed(df: DataFrame, name: str, **metrics) -> tuple[DataFrame, Observation]:
    """Metrics that a run leaves beside its result: no second pass."""
    seen = Observation(name)
    return df.observe(seen, *(v.alias(k) for k, v in metrics.items())), seen
