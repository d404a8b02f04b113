"""The main algorithm on the sparse layout, with work that follows the nonzeros.

Rows are ``row_id, b, x struct<idx, val>, w`` as ``design.to_sparse`` gives them.  The
sketch adds up entries by (bucket, column), norms gather the rows of R^-1 that a
row's entries name, and only sampled rows are ever written out in full.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tallquant.functions import randomness as rnd
from tallquant.operators import linalg, quantreg, sampling, sketch
from tallquant.sources.design import sparse_to_dense

#: Cells of gathered rows of R^-1 that a worker holds at a time.
CELLS = 4_000_000


def augmented(design: DataFrame) -> DataFrame:
    """``row_id, idx, val`` of the rows [b, -x], without zeros but b."""
    idx = F.concat(F.array(F.lit(0)), F.transform("x.idx", lambda j: (j + 1).cast("int")))
    return design.select("row_id", idx.alias("idx"), F.concat(F.array("b"), F.transform("x.val", lambda v: -v)).alias("val"))


def sparse_cauchy(rows: DataFrame, r: int, seed: int, engine: str = "fast") -> DataFrame:
    """``bucket, j, v``: the sparse Cauchy sketch of augmented rows, one multiplication for each entry."""
    unit = lambda stream: rnd.unit(seed, stream, F.col("row_id"), engine)
    entries = rows.select(rnd.bucket(unit("bucket"), r).alias("bucket"), rnd.cauchy(unit("cauchy")).alias("c"), F.explode(F.arrays_zip("idx", "val")).alias("e"))
    return entries.groupBy("bucket", F.col("e.idx").alias("j")).agg(F.sum(F.col("c") * F.col("e.val")).alias("v"))


def factor(entries: DataFrame, d: int) -> np.ndarray:
    """R of a sketch in entries: its rows are written out in full, which their number allows, and reduced by a tree."""
    cells = F.map_from_entries(F.collect_list(F.struct("j", "v")))
    rows = entries.groupBy("bucket").agg(cells.alias("m")).select(F.transform(F.sequence(F.lit(0), F.lit(d - 1)), lambda j: F.coalesce(F.try_element_at("m", j), F.lit(0.0))).alias("a"))
    return linalg.tall_qr(rows, "a", d)


def _products(b: pa.Array, x: pa.Array, matrix: np.ndarray) -> Iterator[np.ndarray]:
    """[b, -x] times a matrix, some rows at a time."""
    b, idx, val = b.to_numpy(), x.field("idx"), x.field("val")
    ends = np.concatenate(([0], np.cumsum(idx.value_lengths().to_numpy(zero_copy_only=False))))
    at, v = idx.flatten().to_numpy(zero_copy_only=False), val.flatten().to_numpy(zero_copy_only=False)
    start, most = 0, max(1, CELLS // matrix.shape[1])
    while start < len(b):
        stop = max(start + 1, int(np.searchsorted(ends, ends[start] + most, side="right")) - 1)
        stop = min(stop, start + most)
        out, first, last = b[start:stop, None] * matrix[0], ends[start], ends[stop]
        some = np.flatnonzero(np.diff(ends[start : stop + 1]))
        if len(some):
            out[some] -= np.add.reduceat(v[first:last, None] * matrix[1 + at[first:last]], ends[start + some] - first, axis=0)
        yield out
        start = stop


def _norms(b: pa.Array, x: pa.Array, rinv: np.ndarray) -> np.ndarray:
    parts = [np.abs(y).sum(axis=1) for y in _products(b, x, rinv)]
    return np.concatenate(parts) if parts else np.empty(0)


def sample(design: DataFrame, rinv: np.ndarray, sizes: list[float], trials: int, seed: int, engine: str = "fast") -> DataFrame:
    """The importance samples of :func:`sampling.sample_design` from sparse rows: a pass of sums, a pass that returns survivors."""
    cast = design.sparkSession.sparkContext.broadcast(rinv)

    def add(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = sum(float(_norms(x.column(0), x.column(1), cast.value).sum()) for x in batches)
        yield pa.RecordBatch.from_arrays([pa.array([total], pa.float64())], names=["lam"])

    total = design.select("b", "x").mapInArrow(add, "lam double").agg(F.coalesce(F.sum("lam"), F.lit(0.0))).first()[0]
    if not total > 0:
        return sampling.sample_trials(design.where("false").withColumn("lam", F.lit(0.0)), sizes, trials, seed, total=0.0, engine=engine).drop("lam")
    least = sampling.least_coin(seed, trials, engine)
    names, factor_ = design.columns, max(sizes) / total
    b, x = names.index("b"), names.index("x")

    def keep(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            lam = _norms(batch.column(b), batch.column(x), cast.value)
            alive = pa.array(batch.column(len(names)).to_numpy() < np.minimum(1.0, lam * factor_))
            yield pa.RecordBatch.from_arrays([*batch.columns[:-1], pa.array(lam, pa.float64())], names=[*names, "lam"]).filter(alive)

    schema = design.select(*names, F.lit(0.0).alias("lam")).schema
    normed = design.select(*names, least.alias("_least")).mapInArrow(keep, schema)
    return sampling.sample_trials(normed, sizes, trials, seed, total=total, engine=engine).drop("lam")


def objective_many(design: DataFrame, candidates: list[tuple[int, list[float], float]]) -> DataFrame:
    """``cand, objective`` of many (id, beta, tau) in one pass over the entries."""
    ids, taus = np.array([c[0] for c in candidates]), np.array([c[2] for c in candidates])
    matrix = np.vstack([np.ones(len(ids)), np.array([c[1] for c in candidates], dtype=float).T])
    cast = design.sparkSession.sparkContext.broadcast(matrix)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(len(ids))
        for batch in batches:
            w, at = batch.column(1).to_numpy(), 0
            for z in _products(batch.column(0), batch.column(2), cast.value):
                total += w[at : at + len(z)] @ np.maximum(taus * z, (taus - 1) * z)
                at += len(z)
        yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(total)], names=["cand", "part"])

    return design.select("b", "w", "x").mapInArrow(run, "cand long, part double").groupBy("cand").agg(F.sum("part").alias("objective"))


def quantile_fit(design: DataFrame, d: int, taus: list[float], *, s: float, conditioning: str = "sparse_qr_qr", seed: int = 0, trials: int = 1, solver: str = "auto", engine: str = "fast") -> DataFrame:
    """``quantreg.quantile_fit`` of a sparse design with d columns, by ``sparse_qr`` or ``sparse_qr_qr``."""
    spark, width = design.sparkSession, d + 1
    rinv = np.linalg.inv(_usable(factor(sparse_cauchy(augmented(design), sketch.practical_rows(width), seed, engine), width)))
    if conditioning == "sparse_qr_qr":
        part = sparse_to_dense(sample(design, rinv, [float(max(2000, 20 * width * width))], 1, seed + 1, engine), d)
        a = F.concat(F.array("b"), F.transform("x", lambda v: -v))
        rows = part.select(F.transform(a, lambda v: v * F.col("w")).alias("a"))
        rinv = np.linalg.inv(_usable(linalg.tall_qr(rows, "a", width)))
    elif conditioning != "sparse_qr":
        raise ValueError("sparse rows are conditioned by sparse_qr or sparse_qr_qr")
    samples = sparse_to_dense(sample(design, rinv, [float(s)], trials, seed + 2, engine), d)
    rows = quantreg.solve_grid(samples, taus, conditioning, solver).collect()  # trials x levels
    losses = {r.cand: r.objective for r in objective_many(design, [(k, [0.0 if v is None else v for v in r.beta], r.tau) for k, r in enumerate(rows)]).collect()} if rows else {}
    return spark.createDataFrame([(*r, losses[k]) for k, r in enumerate(rows)], quantreg.FIT_SCHEMA + ", objective double")


def _usable(r: np.ndarray) -> np.ndarray:
    from tallquant.operators.conditioning import usable

    return usable(r)[0]
