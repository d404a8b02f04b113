"""The interior-point method with the iterates of rows in a table.

Rows stay packed in blocks, and what an iterate holds of a row is two numbers beside
them: the dual and the smaller multiplier (the other one is larger by the absolute
residual, since steps keep the residual equal to the multipliers' difference).  Each
iteration is three passes over the blocks: one moves the iterates, writes them to the
shared folder, which also cuts the lineage, and sums the Newton matrix with the
predictor's right-hand side; one gives the predictor's step lengths with everything
that the corrector needs (its right-hand side is linear in the centring parameter);
one the corrector's step lengths.  A task returns one row of sums and minima, so the
driver holds columns by columns only.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tallquant.operators.solvers import Fit
from tallquant.sources import blocks
from tallquant.sources.storage import discard, scratch

STATE = "rows binary, state binary, sums binary"
SHRINK = 0.99995


def _step(v: np.ndarray, dv: np.ndarray) -> float:
    with np.errstate(divide="ignore", invalid="ignore"):
        ratio = np.where(dv < 0, -v / dv, np.inf)
    return float(ratio.min())


class _Block:
    """Row-local quantities of one block (response and covariates) at the current coefficients."""

    def __init__(self, m: np.ndarray, a: np.ndarray, least: np.ndarray, beta: np.ndarray):
        self.x, self.a, self.room = m[:, 1:], a, 1.0 - a
        self.r = m[:, 0] - self.x @ beta
        self.low, self.high = least + np.maximum(-self.r, 0.0), least + np.maximum(self.r, 0.0)
        self.q = 1.0 / (self.low / self.a + self.high / self.room)

    def move(self, xd: np.ndarray, c_low: np.ndarray, c_high: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Changes of the dual and of both multipliers for complementarity targets, where the fit moves by ``xd``."""
        da = self.q * (c_low / self.a - c_high / self.room - xd)
        return da, (c_low - self.low * da) / self.a, (c_high + self.high * da) / self.room

    def predictor(self, dbeta: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        return self.move(self.x @ dbeta, -self.low * self.a, -self.high * self.room)

    def corrector(self, first: np.ndarray, dbeta: np.ndarray, mu: float) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        da, dlow, dhigh = self.predictor(first)
        return self.move(self.x @ dbeta, mu - self.low * self.a - da * dlow, mu - self.high * self.room + da * dhigh)

    def steps(self, da: np.ndarray, dlow: np.ndarray, dhigh: np.ndarray) -> np.ndarray:
        return np.array([_step(self.a, da), _step(self.room, -da), _step(self.low, dlow), _step(self.high, dhigh)])


def _reduce(frame: DataFrame, columns: list[str], kernel: Callable[..., tuple[np.ndarray, np.ndarray]]) -> tuple[np.ndarray, np.ndarray]:
    """Sums and minima of what the kernel gives for the cells of each block; one row a task."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums, least = None, None
        for batch in batches:
            for cells in zip(*batch.columns, strict=True):
                s, m = kernel(*cells)
                sums, least = (s, m) if sums is None else (sums + s, np.minimum(least, m))
        if sums is not None:
            yield pa.RecordBatch.from_arrays([pa.array([sums.tobytes()], pa.binary()), pa.array([least.tobytes()], pa.binary())], names=["sums", "least"])

    found = frame.select(*columns).mapInArrow(run, "sums binary, least binary").collect()
    return np.sum([np.frombuffer(r.sums) for r in found], axis=0), np.min([np.frombuffer(r.least) for r in found], axis=0)


def _pair(cell: pa.Scalar) -> np.ndarray:
    return np.frombuffer(cell.as_buffer()).reshape(2, -1)


def distributed_interior_point(design: DataFrame, tau: float, *, tol: float = 1e-8, most: int = 60) -> Fit:
    """Exact fit up to the tolerance on the duality gap, ``optimal`` if that was reached; weights are folded into the rows.

    A design that :func:`quantreg.packed_rows` gave is taken as it is, any other is packed first.
    """
    own = "rows" not in design.columns
    packed = blocks.pack(design.select(F.lit(0.0).alias("coin"), "b", "w", "x"), "rows") if own else design
    try:
        return _solved(packed, tau, tol, most)
    finally:
        if own:
            blocks.forget(packed)


def _folded(cell: pa.Scalar) -> np.ndarray:
    """Response and covariates of the rows that have a weight, times that."""
    m = blocks.decode(cell.as_buffer())
    m, w = np.column_stack([m[:, 1], m[:, 3:]]), m[:, 2]
    return m if (w == 1.0).all() else m[w > 0] * w[w > 0, None]


def _moments(cell: pa.Scalar) -> tuple[np.ndarray, np.ndarray]:
    m = blocks.decode(cell.as_buffer())
    a = np.column_stack([m[:, 1], m[:, 3:]])
    return np.append(((a * m[:, 2:3]).T @ a).ravel(), len(m)), np.zeros(0)


def _solved(packed: DataFrame, tau: float, tol: float, most: int) -> Fit:
    spark, d = packed.sparkSession, blocks.width(packed, "rows") - 3
    if d < 0:
        raise ValueError("a design without rows has no fit")
    s, _ = _reduce(packed, ["rows"], _moments)
    g, n = s[:-1].reshape(d + 1, d + 1), s[-1]
    beta = np.linalg.solve(g[1:, 1:], g[1:, 0])  # least squares

    def sizes(cell: pa.Scalar, beta: np.ndarray = beta) -> tuple[np.ndarray, np.ndarray]:
        m = _folded(cell)
        return np.array([np.abs(m[:, 0] - m[:, 1:] @ beta).sum(), len(m)]), np.zeros(0)

    (size, live), _ = _reduce(packed, ["rows"], sizes)
    tiny = 1e-3 * (size / max(live, 1.0) + 1e-12)
    path = scratch(spark, "ipm")

    def newton(k: _Block) -> np.ndarray:
        m = (k.x * k.q[:, None]).T @ k.x
        f = np.maximum(tau * k.r, (tau - 1) * k.r).sum()
        return np.concatenate((m.ravel(), k.x.T @ (k.q * k.r), k.x.T @ k.a, k.x.sum(axis=0), [k.low @ k.a + k.high @ k.room, f]))

    def write(frame: DataFrame, it: int, moved: Callable[..., tuple[pa.Scalar, np.ndarray, np.ndarray, np.ndarray]], beta: np.ndarray) -> tuple[DataFrame, np.ndarray]:
        """The iterate of number ``it`` as a table, with the Newton sums of each task beside it."""

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            sums = None
            for batch in batches:
                for cells in zip(*batch.columns, strict=True):
                    rows, m, a, least = moved(*cells)
                    if len(m):
                        s = newton(_Block(m, a, least, beta))
                        sums = s if sums is None else sums + s
                        yield out(rows, np.concatenate((a, least)).tobytes(), None)
            if sums is not None:
                yield out(None, None, sums.tobytes())

        def out(rows: pa.Scalar | bytes | None, state: bytes | None, sums: bytes | None) -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([pa.array([v], pa.binary()) for v in (rows, state, sums)], names=["rows", "state", "sums"])

        frame.mapInArrow(run, STATE).write.option("parquet.block.size", 16 << 20).option("parquet.enable.dictionary", "false").parquet(f"{path}/{it}")
        table = spark.read.schema(STATE).parquet(f"{path}/{it}")
        found = table.where("sums is not null").select("sums").collect()
        return table.where("rows is not null").select("rows", "state"), np.sum([np.frombuffer(r.sums) for r in found], axis=0)

    def first(cell: pa.Scalar, beta: np.ndarray = beta) -> tuple[bytes, np.ndarray, np.ndarray, np.ndarray]:
        m = _folded(cell)
        return blocks.encode(m), m, np.full(len(m), 1.0 - tau), np.full(len(m), tiny)

    state, s = write(packed.select("rows"), 0, first, beta)
    total, it, done = 0.0, 0, not live
    for it in range(1, most + 1) if live else ():
        m, rhs, xa, ones = s[: d * d].reshape(d, d), s[d * d : d * d + d], s[d * d + d : d * d + 2 * d], s[d * d + 2 * d : d * d + 3 * d]
        gap, total = s[-2], s[-1]
        done = bool(gap <= tol * (1 + abs(total)))
        if done:
            break
        ask = (1 - tau) * ones - xa
        solve = lambda v: np.linalg.lstsq(m, v, rcond=None)[0]  # noqa: E731, B023
        ahead = solve(rhs - ask)

        def block(rows: pa.Scalar, pair: pa.Scalar, beta: np.ndarray = beta) -> _Block:
            return _Block(blocks.decode(rows.as_buffer()), *_pair(pair), beta)

        def predict(rows: pa.Scalar, pair: pa.Scalar, block=block, ahead: np.ndarray = ahead) -> tuple[np.ndarray, np.ndarray]:
            k = block(rows, pair)
            da, dlow, dhigh = k.predictor(ahead)
            sums = [k.low @ da, dlow @ k.a, dlow @ da, -(k.high @ da), dhigh @ k.room, -(dhigh @ da)]
            centre = k.x.T @ (k.q * (1 / k.a - 1 / k.room))
            second = k.x.T @ (k.q * (da * dlow / k.a + da * dhigh / k.room))
            return np.concatenate((sums, centre, second)), k.steps(da, dlow, dhigh)

        s, least = _reduce(state, ["rows", "state"], predict)
        up, down = min(1.0, SHRINK * min(least[:2])), min(1.0, SHRINK * min(least[2:]))
        after = gap + up * (s[0] + s[3]) + down * (s[1] + s[4]) + up * down * (s[2] + s[5])
        mu = (after / gap) ** 3 * gap / (2 * n)
        turn = solve(rhs + mu * s[6 : 6 + d] - s[6 + d : 6 + 2 * d] - ask)

        def correct(rows: pa.Scalar, pair: pa.Scalar, block=block, ahead: np.ndarray = ahead, turn: np.ndarray = turn, mu: float = mu) -> tuple[np.ndarray, np.ndarray]:
            k = block(rows, pair)
            return np.zeros(1), k.steps(*k.corrector(ahead, turn, mu))

        _, least = _reduce(state, ["rows", "state"], correct)
        up, down = min(1.0, SHRINK * min(least[:2])), min(1.0, SHRINK * min(least[2:]))

        def advance(rows: pa.Scalar, pair: pa.Scalar, beta=beta, ahead=ahead, turn=turn, mu=mu, up=up, down=down) -> tuple[pa.Scalar, np.ndarray, np.ndarray, np.ndarray]:
            m = blocks.decode(rows.as_buffer())
            k = _Block(m, *_pair(pair), beta)
            da, dlow, dhigh = k.corrector(ahead, turn, mu)
            return rows, m, k.a + up * da, np.minimum(k.low + down * dlow, k.high + down * dhigh)

        beta = beta + down * turn
        state, s = write(state, it, advance, beta)
        discard(spark, f"{path}/{it - 1}")
    return Fit(beta, float(total), it, done)
