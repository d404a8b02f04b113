"""Seven ways to an R that makes A R^-1 well behaved in l1, and two that do not try."""

from __future__ import annotations

import time
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tallquant.functions.loss import batch_matrix
from tallquant.operators import linalg, sampling, sizing, sketch


@dataclass
class Conditioner:
    """An R with its inverse, the passes over the data it took, and seconds."""

    method: str
    r: np.ndarray
    rinv: np.ndarray
    passes: int
    seconds: float
    kappa_bound: float
    notes: dict = field(default_factory=dict)

    def rows(self) -> list[tuple]:
        return [(self.method, i, j, float(self.r[i, j]), float(self.rinv[i, j]), float(self.kappa_bound)) for i in range(len(self.r)) for j in range(len(self.r))]


def usable(r: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Columns without a pivot get a unit one, so R can be inverted; they are reported by rank_report."""
    keep = linalg.rank_report(r)
    r = r.copy()
    for j in np.flatnonzero(~keep):
        r[j, :] = 0.0
        r[j, j] = 1.0
    return r, keep


def rounded(a: np.ndarray, rounding: str = "density") -> np.ndarray:
    """R of the rounding of a small matrix; columns without a pivot, such as those that no row holds, stay out and are zero."""
    _, keep = usable(linalg.positive_r(a))
    r, a = np.zeros((len(keep), len(keep))), a[:, keep]
    if keep.any():
        r0 = linalg.positive_r(a)
        r[np.ix_(keep, keep)], _ = linalg.round_slab(lambda rinv: linalg.local_slab_stats(a, rinv), r0) if rounding == "slab" else linalg.round_density(linalg.local_density_gram(a), r0.T @ r0 / np.sqrt(len(r0)))
    return r


def _finish(method: str, r: np.ndarray, passes: int, start: float, n: int, **notes) -> Conditioner:
    r, keep = usable(r)
    return Conditioner(method, r, np.linalg.inv(r), passes, time.time() - start, sizing.kappa_bound(method, len(r), n), {"independent": keep.tolist(), **notes})


def collect_rows(frame: DataFrame, column: str = "a") -> np.ndarray:
    """Weighted rows of a sample of bounded size on the driver."""
    table = frame.select(column, "w").toArrow()
    return batch_matrix(table.column(0)) * table.column(1).to_numpy()[:, None]


def condition(
    frame: DataFrame, method: str = "sparse_qr_qr", *, seed: int = 0, column: str = "a", engine: str = "fast", sketch_rows: int | None = None, l1_sample: int | None = None,
    rounding: str = "density", factor: str = "qr", n: int | None = None, local_bytes: float = 2e8,
) -> Conditioner:
    """R of the rows in ``column`` by one of the methods.

    Sketches have a height that is a parameter; their R comes from a tree of QR
    factors.  The l1 sample of the two-step methods is rounded or factorised
    locally if it fits ``local_bytes``, else by passes over the distributed sample.
    """
    start, d = time.time(), linalg.width_of(frame, column)
    if n is None:  # two of the bounds depend on the number of rows
        n = frame.count() if method in ("dense_qr", "fast_qr") else 0
    r1 = sketch_rows or sketch.practical_rows(d)
    if method in ("identity", "uniform"):
        return _finish(method, np.eye(d), 0, start, n)
    if method in ("round_full", "round_fast"):
        how = "slab" if method == "round_fast" else rounding
        r, rounds = linalg.round_full(frame, column, how)
        return _finish(method, r, rounds + 1, start, n, rounds=rounds)
    build = {"dense_qr": sketch.dense_cauchy, "fast_qr": sketch.fast_cauchy, "exponential_qr": sketch.sparse_exponential}.get(method, sketch.sparse_cauchy)
    options = {} if method == "fast_qr" else {"engine": engine}
    r1 = (sketch_rows or sketch.dense_rows(d)) if method == "dense_qr" else r1
    first = sketch.factor(build(frame, r1, seed, column=column, **options), factor)
    if method in ("sparse_qr", "dense_qr", "fast_qr", "exponential_qr"):
        return _finish(method, first, 1, start, n, sketch_rows=r1)
    first, _ = usable(first)
    s1 = l1_sample or max(2000, 20 * d * d)
    normed = sampling.row_norms(frame, np.linalg.inv(first), how="exact", column=column)
    part = sampling.sample_rows(normed, s1, seed + 1, engine=engine)
    part = part.withColumn(column, F.transform(column, lambda v: v * F.col("w"))).select("row_id", column, F.lit(1.0).alias("w"))
    if s1 * d * 8 <= local_bytes:
        a = collect_rows(part, column)
        if method == "sparse_qr_qr":
            r = linalg.positive_r(a)
        else:
            r = rounded(a, rounding)
    else:
        part = part.persist()
        r = linalg.tall_qr(part, column) if method == "sparse_qr_qr" else linalg.round_full(part, column, rounding)[0]
        part.unpersist()
    return _finish(method, r, 3, start, n, sketch_rows=r1, l1_sample=s1)


def measure_kappa(frame: DataFrame, rinv: np.ndarray, directions: int = 200, seed: int = 1, column: str = "a") -> tuple[float, float]:
    """alpha = sum |A R^-1| and a lower bound of beta over axes and random directions (one pass)."""
    d = len(rinv)
    u = np.column_stack([np.eye(d), np.random.default_rng(seed).normal(size=(d, directions))])
    size = sketch.l1_along(frame, rinv @ u, column)
    return float(size[:d].sum()), float((np.abs(u).max(axis=0) / np.maximum(size, 1e-300)).max())


def basis_l1(frame: DataFrame, rinv: np.ndarray, column: str = "a") -> DataFrame:
    """Column l1 norms of A R^-1, row by row, without forming it."""
    cast = frame.sparkSession.sparkContext.broadcast(rinv)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(len(cast.value))
        for batch in batches:
            if len(batch):
                total += np.abs(batch_matrix(batch.column(0)) @ cast.value).sum(axis=0)
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(len(total))), pa.array(total)], names=["j", "l1"])

    return frame.select(column).mapInArrow(run, "j long, l1 double").groupBy("j").agg(F.sum("l1").alias("l1"))
