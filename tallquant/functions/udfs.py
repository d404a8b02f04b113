"""User-defined functions: scalar, grouped, table-valued, and their SQL registration."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import DoubleType, IntegerType, LongType, StringType, StructField, StructType


@F.arrow_udf(DoubleType())
def dot_udf(x: pa.Array, beta: pa.Array) -> pa.Array:
    """Dot product of two array columns of equal lengths on Arrow data."""
    length = x.value_lengths().to_numpy(zero_copy_only=False)
    products = x.flatten().to_numpy(zero_copy_only=False) * beta.flatten().to_numpy(zero_copy_only=False)
    if len(length) and (length == length[0]).all():
        return pa.array(products.reshape(len(length), length[0]).sum(axis=1))
    return pa.array(np.bincount(np.repeat(np.arange(len(length)), length), weights=products, minlength=len(length)))


@F.arrow_udf(DoubleType())
def l1_norm_udf(x: pa.Array) -> pa.Array:
    """l1 norm of an array column on Arrow data."""
    ends = x.offsets.to_numpy()
    total = np.concatenate(([0.0], np.cumsum(np.abs(x.values.to_numpy(zero_copy_only=False)))))
    return pa.array(total[ends[1:]] - total[ends[:-1]])


@F.pandas_udf(DoubleType())
def weighted_quantile_udf(v: pd.Series, w: pd.Series, tau: pd.Series) -> float:
    """Grouped aggregate: smallest value whose running weight reaches tau of the total."""
    from tallquant.operators.solvers import weighted_quantile

    return weighted_quantile(v.to_numpy(dtype=float), w.to_numpy(dtype=float), float(tau.iloc[0]))


@F.pandas_udf(DoubleType())
def pinball_sum_udf(z: pd.Series, tau: pd.Series) -> float:
    return float(np.maximum(tau * z, (tau - 1) * z).sum())


@F.udtf(returnType=StructType([StructField("grp", StringType()), StructField("tau", DoubleType()), StructField("j", IntegerType()), StructField("beta", DoubleType()), StructField("n_rows", LongType())]))
class QuantileFit:
    """``quantile_fit(TABLE(rows) PARTITION BY (grp), tau)`` over columns grp, b, x: one exact fit for each partition."""

    def __init__(self):
        self.grp, self.tau, self.b, self.x = None, None, [], []

    def eval(self, row, tau: float):
        self.grp, self.tau = row["grp"], tau
        self.b.append(row["b"])
        self.x.append(row["x"])

    def terminate(self) -> Iterator[tuple]:
        if not self.b:
            return
        from tallquant.operators.solvers import solve_weighted

        fit = solve_weighted(np.array(self.x, dtype=float), np.array(self.b), np.ones(len(self.b)), self.tau)
        for j, v in enumerate(fit.beta):
            yield self.grp, float(self.tau), j, None if np.isnan(v) else float(v), len(self.b)


def register(spark: SparkSession) -> None:
    """Register everything for SQL; ``pinball`` is a SQL function, inlined by the optimizer."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION pinball(z DOUBLE, tau DOUBLE) RETURNS DOUBLE RETURN greatest(tau * z, (tau - 1) * z)")
    spark.udf.register("dot_product", dot_udf)
    spark.udf.register("weighted_quantile", weighted_quantile_udf)
    spark.udtf.register("quantile_fit", QuantileFit)
