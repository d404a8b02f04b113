"""Embeddings of a tall matrix into few rows, and their measured distortion.

A sketch is linear, so partial sums of partitions, batches or micro-batches add up.
Returned frames have ``bucket`` and one column ``v0 .. v(d-1)`` for each column.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tallquant.functions import randomness as rnd
from tallquant.functions.loss import batch_matrix
from tallquant.operators.linalg import svd_r, tall_qr, width_of
from tallquant.sources.blocks import matrices

#: Columns up to which the sketch is one SQL aggregate; beyond, Arrow blocks.
SQL_WIDTH = 60
#: Rows that a worker holds before it adds up those of one bucket, in bytes: the whole sketch need not fit.
HELD_BYTES = 64 << 20


def practical_rows(d: int) -> int:
    """Sketch rows used in practice: 20 d^2, a thousand at least."""
    return max(1000, 20 * d * d)


def theory_rows(d: int, omega: float = 1.0) -> int:
    """Sketch rows of the sparse transform's guarantee."""
    return math.ceil(omega * d**5 * math.log(d) ** 5) if d > 1 else 1


def _sum_columns(frame: DataFrame, d: int) -> DataFrame:
    return frame.groupBy("bucket").agg(*[F.sum(f"v{j}").alias(f"v{j}") for j in range(d)])


def _bucketed(frame: DataFrame, column: str, r: int, multiplier, seed: int, engine: str, d: int) -> DataFrame:
    rows = frame.select(rnd.bucket(rnd.unit(seed, "bucket", F.col("row_id"), engine), r).alias("bucket"), multiplier.alias("c"), F.col(column).alias("x"))
    if d <= SQL_WIDTH:
        return rows.groupBy("bucket").agg(*[F.sum(F.col("c") * F.col("x")[j]).alias(f"v{j}") for j in range(d)])

    names = ["bucket", *[f"v{j}" for j in range(d)]]

    def summed(buckets: np.ndarray, x: np.ndarray) -> pa.RecordBatch:
        order = np.argsort(buckets, kind="stable")
        starts = np.flatnonzero(np.diff(buckets[order], prepend=-1))
        total = np.add.reduceat(x[order], starts, axis=0)
        return pa.RecordBatch.from_arrays([pa.array(buckets[order][starts], pa.int64()), *[pa.array(total[:, j]) for j in range(d)]], names=names)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple[np.ndarray, np.ndarray]] = []
        size = 0
        for batch in batches:
            if len(batch):
                held.append((batch.column(0).to_numpy(), batch.column(1).to_numpy()[:, None] * batch_matrix(batch.column(2))))
                size += held[-1][1].nbytes
            if size >= HELD_BYTES:
                yield summed(*map(np.concatenate, zip(*held, strict=True)))
                held, size = [], 0
        if held:
            yield summed(*map(np.concatenate, zip(*held, strict=True)))

    return _sum_columns(rows.mapInArrow(run, "bucket long, " + ", ".join(f"v{j} double" for j in range(d))), d)


def sparse_cauchy(frame: DataFrame, r: int, seed: int, column: str = "a", engine: str = "fast") -> DataFrame:
    """Each row goes to one bucket, multiplied by its own Cauchy number: one pass, input-sparsity cost."""
    c = rnd.cauchy(rnd.unit(seed, "cauchy", F.col("row_id"), engine))
    return _bucketed(frame, column, r, c, seed, engine, width_of(frame, column))


def sparse_exponential(frame: DataFrame, r: int, seed: int, column: str = "a", engine: str = "fast") -> DataFrame:
    """The variant with signed reciprocal exponentials in place of Cauchy numbers."""
    sign = F.when(rnd.unit(seed, "sign", F.col("row_id"), engine) < 0.5, -1.0).otherwise(1.0)
    c = sign / rnd.exponential(rnd.unit(seed, "exponential", F.col("row_id"), engine))
    return _bucketed(frame, column, r, c, seed, engine, width_of(frame, column))


def _counter_units(keys: np.ndarray, lanes: int, seed: int) -> np.ndarray:
    """Uniforms of a counter-based generator: one row for each key, one column for each lane."""
    with np.errstate(over="ignore"):
        z = keys.view(np.uint64)[:, None] + (np.arange(1, lanes + 1, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15))[None, :] + np.uint64(seed)
        z = (z ^ (z >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
        z = (z ^ (z >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
        z ^= z >> np.uint64(31)
    return ((z >> np.uint64(12)).astype(np.float64) + 0.5) / rnd.TWO52


def dense_rows(d: int) -> int:
    return max(2 * d, math.ceil(2 * d * math.log(max(d, 2))))


def dense_cauchy(frame: DataFrame, r: int | None, seed: int, column: str = "a", engine: str = "fast") -> DataFrame:
    """Every row hits all sketch rows with independent Cauchy numbers."""
    d = width_of(frame, column)
    r = r or dense_rows(d)
    if engine == "portable":
        rows = frame.select("row_id", F.col(column).alias("x"), F.explode(F.sequence(F.lit(0), F.lit(r - 1))).alias("k"))
        c = rnd.cauchy(rnd.unit(seed, "dense", F.concat_ws("#", "row_id", "k"), engine))
        return rows.select(F.col("k").cast("long").alias("bucket"), *[(c * F.col("x")[j]).alias(f"v{j}") for j in range(d)]).groupBy("bucket").agg(*[F.sum(f"v{j}").alias(f"v{j}") for j in range(d)])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        block = np.zeros((r, d))
        for batch in batches:
            keys, x = batch.column(0).to_numpy(), batch_matrix(batch.column(1))
            for a in range(0, len(keys), 2048):
                c = np.tan(np.pi * (_counter_units(keys[a : a + 2048], r, seed) - 0.5))
                block += c.T @ x[a : a + 2048]
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(r)), *[pa.array(block[:, j]) for j in range(d)]], names=["bucket", *[f"v{j}" for j in range(d)]])

    rows = frame.select(F.xxhash64("row_id").alias("key"), column)
    return _sum_columns(rows.mapInArrow(run, "bucket long, " + ", ".join(f"v{j} double" for j in range(d))), d)


def hadamard(x: np.ndarray) -> np.ndarray:
    """Fast Walsh-Hadamard transform of columns, scaled to keep l2 norms; rows must be a power of two."""
    y, h, n = x.astype(float).copy(), 1, len(x)
    while h < n:
        y = y.reshape(n // (2 * h), 2, h, -1)
        y = np.concatenate([y[:, :1] + y[:, 1:], y[:, :1] - y[:, 1:]], axis=1).reshape(n, -1)
        h *= 2
    return y / math.sqrt(n)


def fast_cauchy(frame: DataFrame, r: int, seed: int, column: str = "a", block: int = 256) -> DataFrame:
    """Rows mixed in blocks by a Hadamard matrix on top of the identity, then bucketed with Cauchy numbers.

    Blocks are runs of one partition, so the data is not shuffled; the result
    depends on the partitioning and is checked statistically.
    """
    d = width_of(frame, column)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        out, rest_x, rest_k = np.zeros((r, d)), np.zeros((0, d)), np.zeros(0, dtype=np.int64)

        def mix(x: np.ndarray, key: int) -> None:
            nonlocal out
            padded = np.vstack([x, np.zeros((block - len(x), d))]) if len(x) < block else x
            both = np.vstack([hadamard(padded), padded])
            u = _counter_units(np.array([key]), 4 * block, seed)[0]
            np.add.at(out, (u[: 2 * block] * r).astype(np.int64), np.tan(np.pi * (u[2 * block :] - 0.5))[:, None] * both)

        for batch in batches:
            rest_k = np.concatenate([rest_k, batch.column(0).to_numpy()])
            rest_x = np.vstack([rest_x, batch_matrix(batch.column(1))]) if len(batch) else rest_x
            while len(rest_x) >= block:
                mix(rest_x[:block], int(rest_k[0]))
                rest_x, rest_k = rest_x[block:], rest_k[block:]
        if len(rest_x):
            mix(rest_x, int(rest_k[0]))
        some = np.flatnonzero(np.abs(out).sum(axis=1))
        yield pa.RecordBatch.from_arrays([pa.array(some, pa.int64()), *[pa.array(out[some, j]) for j in range(d)]], names=["bucket", *[f"v{j}" for j in range(d)]])

    rows = frame.select(F.xxhash64("row_id").alias("key"), column)
    return _sum_columns(rows.mapInArrow(run, "bucket long, " + ", ".join(f"v{j} double" for j in range(d))), d)


def as_matrix(sketch: DataFrame) -> np.ndarray:
    """The sketch on the driver: its height is a parameter, not a function of the data."""
    table = sketch.orderBy("bucket").toArrow()
    return np.column_stack([table.column(j).to_numpy() for j in range(1, table.num_columns)])


def factor(sketch: DataFrame, how: str = "qr") -> np.ndarray:
    """R of the sketch by a tree of QR factors, so the driver sees columns by columns; ``svd`` gives singular values times right vectors."""
    d = len(sketch.columns) - 1
    r = tall_qr(sketch.select(F.array(*[f"v{j}" for j in range(d)]).alias("a")), "a", d)
    return svd_r(r) if how == "svd" else r


def probe_distortion(frame: DataFrame, sketch: np.ndarray, n_dirs: int = 64, seed: int = 1, column: str = "a") -> tuple[float, float]:
    """Smallest and largest |sketch x|_1 / |A x|_1 over random directions and axes: one pass."""
    d = sketch.shape[1]
    dirs = np.column_stack([np.random.default_rng(seed).normal(size=(d, n_dirs)), np.eye(d)])
    ratio = np.abs(sketch @ dirs).sum(axis=0) / l1_along(frame, dirs, column)
    return float(ratio.min()), float(ratio.max())


def l1_along(frame: DataFrame, dirs: np.ndarray, column: str = "a") -> np.ndarray:
    """|A x|_1 for each column x of ``dirs``."""
    cast = frame.sparkSession.sparkContext.broadcast(dirs)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(cast.value.shape[1])
        for batch in batches:
            for m in matrices(batch.column(0)):
                total += np.abs(m @ cast.value).sum(axis=0)
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(len(total))), pa.array(total)], names=["k", "v"])

    rows = frame.select(column).mapInArrow(run, "k long, v double").groupBy("k").agg(F.sum("v").alias("v")).orderBy("k").collect()
    return np.array([r.v for r in rows])
