"""Triangular factors and ellipsoid roundings of tall matrices.

State is columns by columns; rows are visited by passes over the DataFrame and
never gathered.  ``D`` has an array column of the matrix row, ``a`` by default.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tallquant.sources import blocks
from tallquant.sources.blocks import matrices


def positive_r(a: np.ndarray) -> np.ndarray:
    """R of a QR factorisation with a positive diagonal; columns are scaled first."""
    p = a.shape[1]
    if not len(a):
        return np.zeros((p, p))
    scale = np.maximum(np.abs(a).max(axis=0), 1e-300)
    r = np.linalg.qr(a / scale, mode="r")
    if len(r) < p:
        r = np.vstack([r, np.zeros((p - len(r), p))])
    sign = np.where(np.diag(r) < 0, -1.0, 1.0)
    return sign[:, None] * r * scale


def svd_r(a: np.ndarray) -> np.ndarray:
    """Another R of the same matrix: singular values times the right vectors."""
    _, s, vt = np.linalg.svd(a, full_matrices=False)
    return s[:, None] * vt


def rank_report(r: np.ndarray) -> np.ndarray:
    """Mask of columns that are independent of those before them, by the diagonal of R."""
    diag = np.abs(np.diag(r))
    size = np.linalg.norm(r, axis=0)
    return diag > 1e-10 * np.maximum(size, 1e-300)


def _blocks(frame: DataFrame, column: str, kernel: Callable, init: Callable, width: int) -> DataFrame:
    """One row ``part, blob`` of each partition: the kernel folded over its batches."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        state = init()
        for batch in batches:
            for m in matrices(batch.column(0)):
                state = kernel(state, m)
        yield pa.RecordBatch.from_arrays([pa.array([TaskContext.get().partitionId()], pa.int64()), pa.array([state.astype("<f8").tobytes()], pa.binary())], names=["part", "blob"])

    return frame.select(column).mapInArrow(run, "part long, blob binary")


def _merge(blobs: DataFrame, join: Callable[[list[np.ndarray]], np.ndarray], shape: tuple[int, int], fan: int = 1024) -> np.ndarray:
    """Tree merge: runs of ``fan`` partitions in tasks, what is left (a thousandth of them) on the driver."""

    def step(table: pa.Table) -> pa.Table:
        parts = [np.frombuffer(x).reshape(shape) for x in table.column("blob").to_pylist()]
        return pa.Table.from_arrays([pa.array([table.column("part")[0].as_py()], pa.int64()), pa.array([join(parts).astype("<f8").tobytes()], pa.binary())], names=["part", "blob"])

    blobs = blobs.withColumn("part", F.floor(F.col("part") / fan)).groupBy("part").applyInArrow(step, "part long, blob binary")
    return join([np.frombuffer(r.blob).reshape(shape) for r in blobs.orderBy("part").collect()] or [np.zeros(shape)])


def width_of(frame: DataFrame, column: str = "a") -> int:
    if blocks.is_packed(frame, column):
        return blocks.width(frame, column)
    row = frame.select(F.size(column).alias("n")).first()
    return row.n if row else 0


def tall_qr(frame: DataFrame, column: str = "a", d: int | None = None) -> np.ndarray:
    """R of a matrix of any height: QR in each partition, then QR of stacked factors in a tree.

    With its width ``d`` given the frame is evaluated once.
    """
    d = d or width_of(frame, column)
    blobs = _blocks(frame, column, lambda s, x: positive_r(np.vstack([s, x])), lambda: np.zeros((d, d)), d)
    return _merge(blobs, lambda parts: positive_r(np.vstack(parts)), (d, d))


def gram(frame: DataFrame, column: str = "a", weigh: Callable[[np.ndarray], np.ndarray] | None = None) -> np.ndarray:
    """Sum of (weighted) outer products of rows."""
    d = width_of(frame, column)

    def kernel(s: np.ndarray, x: np.ndarray) -> np.ndarray:
        return s + (x.T @ x if weigh is None else (x * weigh(x)[:, None]).T @ x)

    return _merge(_blocks(frame, column, kernel, lambda: np.zeros((d, d)), d), lambda parts: np.sum(parts, axis=0), (d, d))


def gram_cholesky(frame: DataFrame, column: str = "a") -> np.ndarray:
    """R by Cholesky of the Gram matrix; squares the condition number, so for well-conditioned input."""
    return np.linalg.cholesky(gram(frame, column)).T


def slab_stats(frame: DataFrame, rinv: np.ndarray, column: str = "a") -> tuple[np.ndarray, np.ndarray]:
    """In the coordinates of R: l1 norms of columns, and the subgradient of each."""
    d = len(rinv)

    def kernel(s: np.ndarray, x: np.ndarray) -> np.ndarray:
        y = x @ rinv
        return s + np.vstack([np.abs(y).sum(axis=0), np.sign(y).T @ y])

    out = _merge(_blocks(frame, column, kernel, lambda: np.zeros((d + 1, d)), d), lambda parts: np.sum(parts, axis=0), (d + 1, d))
    return out[0], out[1:]


def local_slab_stats(a: np.ndarray, rinv: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    y = a @ rinv
    return np.abs(y).sum(axis=0), np.sign(y).T @ y


def round_slab(stats: Callable[[np.ndarray], tuple[np.ndarray, np.ndarray]], r: np.ndarray, most: int = 400) -> tuple[np.ndarray, int]:
    """2d-rounding by slab cuts from an R whose ellipsoid holds the l1 ball.

    ``stats(rinv)`` gives column norms and subgradients.  Each round shrinks the
    ellipsoid to the smallest one around its part inside the slab of the worst
    axis, until every axis point at radius 1 / (2 sqrt d) is inside the ball.
    """
    d = len(r)
    if d == 1:
        return np.array([[stats(np.eye(1))[0][0]]]), 1
    r, cuts = r.copy(), 0
    while cuts < most:
        rinv = np.linalg.inv(r)
        size, grad = stats(rinv)
        worst = int(size.argmax())
        if size[worst] <= 2 * np.sqrt(d):
            break
        g = grad[worst]
        half = 1.0 / np.linalg.norm(g)
        if half >= 1 / np.sqrt(d):
            break
        along, across = np.sqrt(d) * half, np.sqrt(d * (1 - half**2) / (d - 1))
        e = g / np.linalg.norm(g)
        shape = np.eye(d) / across + (1 / along - 1 / across) * np.outer(e, e)
        r = positive_r(shape @ r)
        cuts += 1
    return r, cuts


def round_density(gram_of: Callable[[np.ndarray], np.ndarray], m: np.ndarray, most: int = 60, tol: float = 1e-6) -> tuple[np.ndarray, int]:
    """sqrt(d)-rounding by the fixed point M = sum of a a' / sqrt(a M^-1 a'); ``gram_of(M^-1)`` is one pass."""
    for k in range(1, most + 1):
        new = gram_of(np.linalg.inv(m))
        change = np.linalg.norm(new - m) / np.linalg.norm(m)
        m = new
        if change < tol:
            break
    return np.linalg.cholesky(m).T, k


def local_density_gram(a: np.ndarray) -> Callable[[np.ndarray], np.ndarray]:
    def gram_of(minv: np.ndarray) -> np.ndarray:
        q = np.einsum("ij,jk,ik->i", a, minv, a)
        return (a * (1 / np.sqrt(np.maximum(q, 1e-300)))[:, None]).T @ a

    return gram_of


def round_full(frame: DataFrame, column: str = "a", how: str = "density", most: int = 25) -> tuple[np.ndarray, int]:
    """Rounding of the whole matrix, one pass a round over its blocks; no state is kept for rows."""
    if not blocks.is_packed(frame, column):
        packed = blocks.pack(frame.select(column), column)
        try:
            return round_full(packed, column, how, most)
        finally:
            blocks.forget(packed)
    r = tall_qr(frame, column)
    if how == "slab":
        return round_slab(lambda rinv: slab_stats(frame, rinv, column), r)
    gram_of = lambda minv: gram(frame, column, lambda x: 1 / np.sqrt(np.maximum(np.einsum("ij,jk,ik->i", x, minv, x), 1e-300)))
    return round_density(gram_of, r.T @ r / np.sqrt(len(r)), most=most)


def sandwich(a: np.ndarray, r: np.ndarray, directions: int = 2000, seed: int = 1) -> tuple[float, float]:
    """Smallest and largest of |A R^-1 u|_1 over random unit u: their ratio bounds the rounding."""
    rng = np.random.default_rng(seed)
    u = rng.normal(size=(len(r), directions))
    u = np.column_stack([u / np.linalg.norm(u, axis=0), np.eye(len(r))])
    size = np.abs(a @ np.linalg.inv(r) @ u).sum(axis=0)
    return float(size.min()), float(size.max())
