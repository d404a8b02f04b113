"""The quantile (pinball) loss, its laws, and full-data objectives."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def pinball(z: Column, tau: float | Column) -> Column:
    """tau * z above zero, (tau - 1) * z below: the larger of both lines."""
    tau = tau if isinstance(tau, Column) else F.lit(float(tau))
    return F.greatest(tau * z, (tau - 1.0) * z)


def skew_ratio(tau: float) -> float:
    """The larger of tau and 1 - tau over the smaller."""
    return max(tau, 1 - tau) / min(tau, 1 - tau)


def dot(x: Column, beta: list[float] | Column) -> Column:
    beta = F.array(*[F.lit(float(v)) for v in beta]) if isinstance(beta, list) else beta
    return F.aggregate(F.zip_with(x, beta, lambda a, b: a * b), F.lit(0.0), lambda s, v: s + v)


def norm(x: Column, p: str = "l1") -> Column:
    """l1, l2 or linf norm of an array column."""
    size = F.transform(x, lambda v: F.abs(v))
    if p == "linf":
        return F.array_max(size)
    if p == "l2":
        return F.sqrt(F.aggregate(x, F.lit(0.0), lambda s, v: s + v * v))
    return F.aggregate(size, F.lit(0.0), lambda s, v: s + v)


def entry_l1(design: DataFrame) -> DataFrame:
    """Sum of absolute entries of the whole matrix."""
    return design.agg(F.sum(norm(F.col("x"))).alias("entry_l1"))


def augment(design: DataFrame) -> DataFrame:
    """Adds ``a``, the row of [b, -x], whose product with (1, beta) is the residual."""
    return design.withColumn("a", F.concat(F.array("b"), F.transform("x", lambda v: -v)))


def strip(augmented: np.ndarray) -> np.ndarray:
    """Coefficients from a vector of the augmented problem: scale the first entry to one and drop it."""
    return np.asarray(augmented[1:], dtype=float) / augmented[0]


def reflect(design: DataFrame, tau: float) -> tuple[DataFrame, float]:
    """The same problem at 1 - tau, by negating response and covariates."""
    return design.withColumns({"b": -F.col("b"), "x": F.transform("x", lambda v: -v)}), 1 - tau


def fold_weights(design: DataFrame) -> DataFrame:
    """Multiply each row by its weight: the loss is positively homogeneous."""
    return design.withColumns({"b": F.col("w") * F.col("b"), "x": F.transform("x", lambda v: F.col("w") * v), "w": F.lit(1.0)})


def objective(design: DataFrame, beta: list[float], tau: float) -> DataFrame:
    """Total weighted loss of one coefficient vector: one pass, partial sums."""
    return design.agg(F.sum(F.col("w") * pinball(F.col("b") - dot(F.col("x"), beta), tau)).alias("objective"))


def batch_matrix(column: pa.Array) -> np.ndarray:
    """Rows of a list column of equal lengths as a matrix, without a copy of the values."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    n = len(column)
    values = column.flatten().to_numpy(zero_copy_only=False)
    return values.reshape(n, -1) if n else np.empty((0, 0))


def objective_many(design: DataFrame, candidates: list[tuple[int, list[float], float]]) -> DataFrame:
    """``cand, objective`` of many (id, beta, tau) in one pass.

    The candidate matrix is broadcast; its size is the number of fits times
    columns and does not depend on the data.
    """
    ids = np.array([c[0] for c in candidates], dtype=np.int64)
    betas = np.array([c[1] for c in candidates], dtype=float).reshape(len(candidates), -1)
    taus = np.array([c[2] for c in candidates], dtype=float)
    cast = design.sparkSession.sparkContext.broadcast((ids, betas, taus))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids, betas, taus = cast.value
        total = np.zeros(len(ids))
        for batch in batches:
            b, w, x = batch.column(0).to_numpy(), batch.column(1).to_numpy(), batch_matrix(batch.column(2))
            for start in range(0, len(b), 4096):
                r = b[start : start + 4096, None] - x[start : start + 4096] @ betas.T
                total += w[start : start + 4096] @ np.maximum(taus * r, (taus - 1) * r)
        yield pa.RecordBatch.from_arrays([pa.array(ids), pa.array(total)], names=["cand", "part"])

    return design.select("b", "w", "x").mapInArrow(run, "cand long, part double").groupBy("cand").agg(F.sum("part").alias("objective"))


def check_loss_laws(pairs: DataFrame, tau: float) -> DataFrame:
    """Subadditivity, l1 bounds, homogeneity and the Lipschitz law over columns ``y1, y2``."""
    y1, y2 = F.col("y1"), F.col("y2")
    f = lambda z: F.sum(pinball(z, tau))
    low, high = min(tau, 1 - tau), max(tau, 1 - tau)
    slack = 1e-9 * (1.0 + F.sum(F.abs(y1)) + F.sum(F.abs(y2)))
    return pairs.agg(
        (f(y1 + y2) <= f(y1) + f(y2) + slack).alias("subadditive"),
        ((f(y1) >= low * F.sum(F.abs(y1)) - slack) & (f(y1) <= high * F.sum(F.abs(y1)) + slack)).alias("bounded_by_l1"),
        (F.abs(f(4.0 * y1) - 4.0 * f(y1)) <= slack).alias("homogeneous"),
        (F.abs(f(y1) - f(y2)) <= high * F.sum(F.abs(y1 - y2)) + slack).alias("lipschitz"),
    )
