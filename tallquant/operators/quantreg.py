"""Quantile regression of a tall design: sampled fits, exact distributed fits and baselines."""

from __future__ import annotations

import functools
import math
import time
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from tallquant.functions import randomness as rnd
from tallquant.functions.loss import augment, batch_matrix, dot, objective_many, pinball
from tallquant.operators import sampling, sizing
from tallquant.operators.conditioning import Conditioner, condition
from tallquant.operators.linalg import gram, width_of
from tallquant.operators.solvers import Fit, interior_point, solve_weighted
from tallquant.sources import blocks

FIT_SCHEMA = "method string, s double, trial int, tau double, beta array<double>, sample_objective double, rows_kept long, sum_w double, iterations int, seconds double"
_FIT_KINDS = [pa.string(), pa.float64(), pa.int32(), pa.float64(), pa.list_(pa.float64()), pa.float64(), pa.int64(), pa.float64(), pa.int32(), pa.float64()]


def solve_group(rows: pa.Table, taus: list[float], solver: str, method: str) -> pa.Table:
    """The fits of one sample, a row a level."""
    start = time.time()
    x, b, w = batch_matrix(rows.column("x")), rows.column("b").to_numpy(), rows.column("w").to_numpy()
    out = []
    for tau in taus:
        fit = solve_weighted(x, b, w, tau, solver)
        out.append((method, rows.column("s")[0].as_py(), rows.column("trial")[0].as_py(), tau, fit.beta.tolist(), float(fit.objective), len(b), float(w.sum()), int(fit.iterations), time.time() - start))
    columns = zip(*out, strict=True)
    return pa.Table.from_arrays([pa.array(c, k, from_pandas=True) for c, k in zip(columns, _FIT_KINDS, strict=True)], names=[c.split()[0] for c in FIT_SCHEMA.split(", ")])


def solve_grid(samples: DataFrame, taus: list[float], method: str, solver: str = "auto") -> DataFrame:
    """Subproblems of every (s, trial), all levels each, solved on executors.

    A group has about s rows, which the caller checks with ``sizing.fits_memory``.
    """
    return samples.select("s", "trial", "b", "x", "w").groupBy("s", "trial").applyInArrow(lambda rows: solve_group(rows, taus, solver, method), FIT_SCHEMA)


def sampled(design: DataFrame, method: str, sizes: list[float], trials: int, seed: int, engine: str = "fast", norms: str = "auto", conditioner: Conditioner | None = None) -> tuple[DataFrame, Conditioner | None]:
    """Weighted samples of each size and trial by one of the samplers."""
    if method == "uniform":
        flat = design.withColumn("lam", F.lit(1.0))
        return sampling.sample_trials(flat, sizes, trials, seed, engine=engine), None
    conditioner = conditioner or condition(augment(design), method, seed=seed, engine=engine)
    return sampling.sample_design(design, conditioner.rinv, sizes, trials, seed + 2, norms, engine), conditioner


def quantile_fit(
    design: DataFrame, taus: list[float], *, s: float | list[float] | None = None, eps: float | None = None, conditioning: str = "sparse_qr_qr", norms: str = "auto", solver: str = "auto",
    seed: int = 0, trials: int = 1, engine: str = "fast", evaluate: bool = True,
) -> DataFrame:
    """The main algorithm: condition, row norms, one weighted sample for all levels, solve, and score on the full data.

    With ``eps`` the size comes from the guarantee; where that is as large as the
    data, the fit is exact instead.  Levels below one half need no reflection
    here: probabilities do not depend on the level and the solver takes any.
    ``conditioning="auto"`` leaves norms, conditioner and solver to the planner.  A
    design without rows has no fits.
    """
    spark, width = design.sparkSession, width_of(design, "x")
    if not width:
        return spark.createDataFrame([], FIT_SCHEMA + ", passes int" + ", objective double" * evaluate)
    if s is None:
        n, d = design.count(), width + 1
        s = max(sizing.size_quantile(sizing.kappa_bound(conditioning, d, n), d, eps or 0.1, t, estimated=norms == "median") for t in taus)
        if s >= n:
            return exact_fit(design, taus)
    sizes = [float(v) for v in (s if isinstance(s, list) else [s])]
    if conditioning == "auto":
        from tallquant.plans import planner

        plan = planner.choose(design.count(), width, max(sizes))
        if plan.solver == "merge_rows_exact":
            return exact_fit(design, taus)
        conditioning, norms = plan.conditioning, plan.norms
    samples, cond = sampled(design, conditioning, sizes, trials, seed, engine, norms)
    passes = (cond.passes if cond else 0) + 2 + evaluate
    rows = [(*r, passes) for r in solve_grid(samples, taus, conditioning, solver).collect()]  # methods x sizes x trials x levels: a grid of parameters
    fits = spark.createDataFrame(rows, FIT_SCHEMA + ", passes int")
    return with_objective(design, fits) if evaluate else fits


def with_objective(design: DataFrame, fits: DataFrame) -> DataFrame:
    """Adds the full-data loss of every fit, all in one pass; coefficients that were not estimable count as 0."""
    rows = fits.collect()  # a grid of parameters
    candidates = [(k, [0.0 if v is None or math.isnan(v) else v for v in r.beta], r.tau) for k, r in enumerate(rows)]
    losses = {r.cand: r.objective for r in objective_many(design, candidates).collect()} if rows else {}
    return design.sparkSession.createDataFrame([(*r, losses[k]) for k, r in enumerate(rows)], fits.schema.add("objective", "double"))


def exact_fit(design: DataFrame, taus: list[float]) -> DataFrame:
    """Exact fits of every level; none without rows."""
    rows, packed = [], packed_rows(design)
    for tau in taus if not packed.isEmpty() else []:
        start = time.time()
        fit, info = preprocess_exact(packed, tau)
        rows.append(("exact", 0.0, 0, tau, [float(v) for v in fit.beta], fit.objective, info["middle"], float(info["n"]), fit.iterations, time.time() - start, info["passes"], fit.objective))
    blocks.forget(packed)
    return design.sparkSession.createDataFrame(rows, FIT_SCHEMA + ", passes int, objective double")


def local_matrix(design: DataFrame) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """A small design on the driver; callers bound its rows."""
    table = design.select("b", "w", "x").toArrow()
    return batch_matrix(table.column("x")), table.column("b").to_numpy(), table.column("w").to_numpy()


#: Cells of a design that the driver may hold: bounds the rough fit's sample and the fits without merging.
DRIVER_CELLS = 10_000_000


def packed_rows(design: DataFrame, seed: int = 23, engine: str = "fast") -> DataFrame:
    """The design in blocks of coin, response, weight and covariates: exact fits of several levels read it once."""
    return blocks.pack(design.select(rnd.unit(seed, "coin0", F.col("row_id"), engine).alias("coin"), "b", "w", "x"), "rows")


def _split(m: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    return m[:, 3:], m[:, 1], m[:, 2]


def _list_column(x: np.ndarray) -> pa.ListArray:
    return pa.ListArray.from_arrays(pa.array(np.arange(len(x) + 1, dtype=np.int32) * x.shape[1]), pa.array(np.ascontiguousarray(x, dtype=float).ravel()))


def sample_table(m: np.ndarray, s: float, trial: int = 0) -> pa.Table:
    """Packed rows on the driver as the group that :func:`solve_group` takes."""
    x, b, w = _split(m)
    return pa.table({"s": np.full(len(b), float(s)), "trial": np.full(len(b), trial, dtype=np.int32), "b": np.ascontiguousarray(b), "x": _list_column(x), "w": np.ascontiguousarray(w)})


def preprocess_exact(design: DataFrame, tau: float, *, seed: int = 23, middle_rows: int = 200_000, rounds: int = 12, engine: str = "fast") -> tuple[Fit, dict]:
    """Exact fit of any number of rows by merging those that are surely above or below the fit.

    The design is read once, into blocks that all passes visit; one that :func:`packed_rows` gave is taken as it is.
    A uniform sample gives a rough fit and the scale of its error; rows outside a
    band around it are summed into one row above and one below.  The loss of the
    merged problem never exceeds the full loss and equals it where no merged row
    has the wrong sign, so a fit without wrong signs is optimal for all data.

    At most ``middle_rows`` rows stay unmerged.  Where the band and the rows of
    wrong sign need more, the distributed interior point solves all rows, and a
    thin band around its solution gives the vertex; if even that band holds too
    many rows (many equal ones), its solution stands, exact up to its tolerance.
    A design without rows is an error.
    """
    if "rows" not in design.columns:
        packed = packed_rows(design, seed, engine)
        try:
            return preprocess_exact(packed, tau, middle_rows=middle_rows, rounds=rounds)
        finally:
            blocks.forget(packed)
    n, d = blocks.height(design), blocks.width(design, "rows") - 3
    if not n:
        raise ValueError("a design without rows has no fit")
    m = min(n, math.ceil((d * n) ** (2 / 3)) + 50 * d, max(50 * d, DRIVER_CELLS // d))
    if n <= 4 * m and n * d <= DRIVER_CELLS:
        x, b, w = _split(blocks.gathered(design, "rows"))
        return solve_weighted(x, b, w, tau), {"passes": 2, "middle": n, "n": n, "wrong": 0}
    x, b, w = _split(blocks.gathered(blocks.mapped(design, "rows", lambda rows: rows[rows[:, 0] < min(1.0, m / n)]), "rows"))
    rough = interior_point(x, b, tau, w)
    spread = np.linalg.pinv(x.T @ x) * len(x)
    size = np.sqrt(np.maximum(np.einsum("ij,jk,ik->i", x, spread, x), 1e-300))

    def around_rough(half: float) -> tuple[float, float]:
        z = (b - x @ rough.beta) / size
        return np.quantile(z, tau - half) if tau - half > 0 else -np.inf, np.quantile(z, tau + half) if tau + half < 1 else np.inf

    def around(beta: np.ndarray):
        def band(half: float) -> tuple[float, float]:
            far = float(np.quantile(np.abs(b - x @ beta) / size, min(1.0, 2 * half)))
            return -far, far

        return band

    thin = min(0.45, 0.25 * middle_rows / n)
    fit, passes, middle = _fit_merged(design, tau, rough.beta, spread, around_rough, min(0.45, max(0.4 * m / n, 2.5 / math.sqrt(m))), middle_rows, rounds, (around, thin))
    passes += 3
    if fit is None:
        from tallquant.operators.distributed_ipm import distributed_interior_point

        centre = distributed_interior_point(design, tau)
        passes += 3 + 3 * centre.iterations

        fit, more, middle = _fit_merged(design, tau, centre.beta, spread, around(centre.beta), thin, middle_rows, rounds, (around, thin))
        passes += more
        if fit is None:
            if not centre.optimal:
                raise RuntimeError(f"no exact fit at level {tau}: the band overflows and the interior point did not converge")
            fit = centre
    return fit, {"passes": passes, "middle": middle, "n": n, "wrong": 0}


def _fit_merged(design: DataFrame, tau: float, beta: np.ndarray, spread: np.ndarray, band, half: float, middle_rows: int, rounds: int, closer: tuple) -> tuple[Fit | None, int, int]:
    """The fit with rows outside ``band(half)`` around ``beta`` merged, passes and middle rows; None if the middle does not fit.

    Of a band of too many rows a weighted share gives a better centre, around which a thinner band (``closer``: its
    function and width) does: rows outside count in full there, so that centre errs by the share alone.  Merged rows of
    the wrong sign join the middle.
    """
    passes, past, narrowed = 0, [], 0
    for _ in range(rounds):
        cut = (beta, spread, *band(half), past)
        up, down, mid, held = _merge_rows(design, cut, middle_rows)
        passes += 1
        share = mid is None
        if share:
            if past or narrowed == 3:
                break
            up, down, mid, _ = _merge_rows(design, cut, middle_rows, 0.5 * middle_rows / held)
            passes += 1
            if mid is None:
                break
        mx, mb, mw = mid
        for row in (up, down):
            if row is not None:
                mx, mb, mw = np.vstack([mx, row[1:]]), np.append(mb, row[0]), np.append(mw, 1.0)
        keep = interior_point(mx, mb, tau, mw)
        if share:
            beta, band, half, narrowed = keep.beta, closer[0](keep.beta), closer[1] * 0.5**narrowed, narrowed + 1
            continue
        wrong, full = _check_signs(design, keep.beta, cut, tau)
        passes += 1
        if wrong == 0:
            return Fit(keep.beta, full, keep.iterations, True), passes, len(mb)
        past.append(keep.beta)
    return None, passes, 0


def _banded(beta: np.ndarray, spread: np.ndarray, low: float, high: float, past: list[np.ndarray], b: np.ndarray, x: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Rows above and below the band that kept their sign at the ``past`` fits, and all others."""
    z = (b - x @ beta) / np.sqrt(np.maximum(np.einsum("ij,jk,ik->i", x, spread, x), 1e-300))
    above, below = z > high, z < low
    for other in past:
        r = b - x @ other
        above, below = above & (r >= 0), below & (r <= 0)
    return above, below, ~above & ~below


def _merge_rows(design: DataFrame, cut: tuple, most: int, share: float = 1.0):
    """Sums of the rows above and below the band, the rows inside (None if those exceed ``most``) and their number.

    With a ``share`` below one, so many of the rows inside by a coin, weighted up.  No task returns more than ``most`` rows.
    """
    cast = design.sparkSession.sparkContext.broadcast(cut)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums: dict[int, np.ndarray] = {}
        held = 0

        def rows(side: int, b: np.ndarray, w: np.ndarray, x: np.ndarray) -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([pa.array(np.full(len(b), side, dtype=np.int32)), pa.array(b), pa.array(w), _list_column(x)], names=["side", "b", "w", "x"])

        for m in (m for batch in batches for m in blocks.matrices(batch.column(0))):
            x, b, w = _split(m)
            above, below, inside = _banded(*cast.value, b, x)
            for side, mask in ((1, above), (-1, below)):
                if mask.any():
                    sums[side] = sums.get(side, 0) + np.append(w[mask] @ b[mask], w[mask] @ x[mask])
            if share < 1:
                inside &= m[:, 0] * 2.0**20 % 1.0 < share  # low bits: the high ones chose the rough fit's sample
            held += int(inside.sum())
            if inside.any() and held <= most:
                yield rows(0, b[inside], w[inside] / share, x[inside])
        for side, row in sums.items():
            yield rows(side, row[:1], np.ones(1), row[None, 1:])
        yield rows(2, np.array([float(held)]), np.ones(1), np.zeros((1, 0)))

    rows = design.select("rows").mapInArrow(run, "side int, b double, w double, x array<double>").persist()
    try:
        d = len(cut[0])
        merged = {}
        for r in rows.where("side <> 0").groupBy("side").agg(F.sum("b").alias("b"), *[F.sum(F.get("x", F.lit(j))).alias(f"x{j}") for j in range(d)]).collect():
            merged[r.side] = np.array(r[1:], dtype=float)
        held = int(merged[2][0]) if 2 in merged else 0
        if held > most:
            return None, None, None, held
        return merged.get(1), merged.get(-1), local_matrix(rows.where("side = 0")) if held else (np.zeros((0, d)), np.zeros(0), np.zeros(0)), held
    finally:
        rows.unpersist()


def _check_signs(design: DataFrame, beta: np.ndarray, cut: tuple, tau: float) -> tuple[int, float]:
    """Merged rows whose residual at the new fit has the wrong sign, and the full loss there."""
    cast = design.sparkSession.sparkContext.broadcast(cut)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        wrong, total = 0, 0.0
        for batch in batches:
            for m in blocks.matrices(batch.column(0)):
                x, b, w = _split(m)
                above, below, _ = _banded(*cast.value, b, x)
                r = b - x @ beta
                wrong += int((r[above] < 0).sum() + (r[below] > 0).sum())
                total += float(w @ np.maximum(tau * r, (tau - 1) * r))
        yield pa.RecordBatch.from_arrays([pa.array([wrong], pa.int64()), pa.array([total])], names=["wrong", "total"])

    row = design.select("rows").mapInArrow(run, "wrong long, total double").agg(F.sum("wrong"), F.sum("total")).first()
    return int(row[0]), float(row[1])


def certify_full(design: DataFrame, beta: list[float], tau: float, basis: list[tuple[list[float], float, float]]) -> bool:
    """Optimality on all data from one aggregate: the pull of non-basis rows against the multipliers of basis rows (x, b, w)."""
    d = len(beta)
    r = F.col("b") - dot(F.col("x"), [float(v) for v in beta])
    psi = F.when(F.abs(r) <= 1e-9, 0.0).when(r > 0, F.lit(tau)).otherwise(F.lit(tau - 1.0)) * F.col("w")
    pull = np.array(design.agg(*[F.sum(psi * F.col("x")[j]).alias(f"g{j}") for j in range(d)]).first())
    x = np.array([row[0] for row in basis])
    u = -np.linalg.solve(x.T, pull)
    w = np.array([row[2] for row in basis])
    return bool(np.all(u <= w * tau + 1e-6) and np.all(u >= w * (tau - 1) - 1e-6))


# --- one nonzero in each row ------------------------------------------------------


def group_quantile_exact(rows: DataFrame, key: str, value: str, weight: str, tau: float, how: str = "bracket") -> DataFrame:
    """``key, q``: the weighted tau-quantile of each group, exact.

    ``window`` runs a weighted running sum in each group; ``bracket`` first finds
    an interval around it from partial sketches, sums the weight below, and
    orders only the rows inside, so a group of any size is no single task's sort.
    """
    own = Window.partitionBy(key)
    order = own.orderBy(value).rangeBetween(Window.unboundedPreceding, 0)
    if how == "window":
        run = rows.withColumn("_run", F.sum(weight).over(order)).withColumn("_all", F.sum(weight).over(own.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)))
        return run.where(F.col("_run") >= tau * F.col("_all") * (1 - 1e-15)).groupBy(key).agg(F.min(value).alias("q"))
    values = rows.groupBy(key, value).agg(F.sum(weight).alias("_w"))
    salted = values.withColumn("_w", F.col("_w").cast("double"))
    ends = salted.groupBy(key).agg(F.sum("_w").alias("_all"), F.percentile_approx(value, [0.0, max(0.0, tau - 0.02), min(1.0, tau + 0.02), 1.0], 2000).alias("_c"))
    out, lo, hi = None, 1, 2
    at = salted.join(ends, key)
    below = at.groupBy(key).agg(F.sum(F.when(F.col(value) < F.col("_c")[lo], F.col("_w")).otherwise(0.0)).alias("_below"), F.sum(F.when(F.col(value) <= F.col("_c")[hi], F.col("_w")).otherwise(0.0)).alias("_upto"), F.first("_all").alias("_all"), F.first("_c").alias("_c"))
    target = tau * F.col("_all") * (1 - 1e-15)
    inside_ok = (F.col("_below") < target) & (F.col("_upto") >= target)
    span = below.withColumns({"_lo": F.when(inside_ok, F.col("_c")[lo]).when(F.col("_below") >= target, F.col("_c")[0]).otherwise(F.col("_c")[hi]), "_hi": F.when(inside_ok, F.col("_c")[hi]).when(F.col("_below") >= target, F.col("_c")[lo]).otherwise(F.col("_c")[3]), "_start": F.when(inside_ok, F.col("_below")).when(F.col("_below") >= target, 0.0).otherwise(F.lit(None))})
    inner = salted.join(span.select(key, "_lo", "_hi", "_all"), key)
    start = inner.groupBy(key).agg(F.sum(F.when(F.col(value) < F.col("_lo"), F.col("_w")).otherwise(0.0)).alias("_start"))
    part = inner.where((F.col(value) >= F.col("_lo")) & (F.col(value) <= F.col("_hi"))).join(start, key)
    run = part.withColumn("_run", F.col("_start") + F.sum("_w").over(order))
    out = run.where(F.col("_run") >= tau * F.col("_all") * (1 - 1e-15)).groupBy(key).agg(F.min(value).alias("q"))
    return out


def _one_positive() -> Column:
    """Whether a row has one nonzero, and that is positive."""
    return (F.size(F.filter("x", lambda v: v != 0)) == 1) & (F.array_max("x") > 0)


def onehot_cells(design: DataFrame, *keep: str) -> DataFrame:
    """``j, t, w`` of rows with one positive nonzero: its column, the quotient it fits, and its weight."""
    at = F.array_position(F.transform("x", lambda v: v > 0), F.lit(True)) - 1
    rows = design.select(*keep, at.cast("int").alias("j"), "b", "w", F.array_max("x").alias("v"))
    return rows.select(*keep, "j", (F.col("b") / F.col("v")).alias("t"), (F.col("w") * F.col("v")).alias("w"))


def onehot_fit(design: DataFrame, tau: float, how: str = "bracket") -> DataFrame:
    """``j, q`` of a design whose rows have one positive nonzero: the problem splits into grouped quantiles."""
    return group_quantile_exact(onehot_cells(design), "j", "t", "w", tau, how)


# --- baselines and derived fits ---------------------------------------------------


def fit_ls(design: DataFrame) -> np.ndarray:
    """Least squares from one pass of Gram sums."""
    rows = design.withColumn("a", F.concat(F.array("b"), "x")).withColumn("a", F.transform("a", lambda v: v * F.sqrt("w")))
    g = gram(rows, "a")
    return np.linalg.solve(g[1:, 1:], g[1:, 0])


def fit_lad(design: DataFrame) -> Fit:
    """The l1 line: the median fit."""
    return preprocess_exact(design, 0.5)[0]


def quantile_fit_by(design: DataFrame, taus: list[float], solver: str = "auto", group_rows: int = 500_000) -> DataFrame:
    """One model for each ``grp``, of all its rows.

    Groups up to ``group_rows`` are solved in one task each.  Larger ones are
    fitted over the cluster: by grouped quantiles where every row has one positive
    nonzero, else by merging rows.
    """
    schema = "grp string, tau double, beta array<double>, objective double, rows long"

    def fit(part: pd.DataFrame) -> pd.DataFrame:
        x, b, w = np.array(part.x.tolist(), dtype=float), part.b.to_numpy(), part.w.to_numpy()
        out = []
        for tau in taus:
            f = solve_weighted(x, b, w, tau, solver)
            out.append((part.grp.iloc[0], tau, f.beta.tolist(), f.objective, len(b)))
        return pd.DataFrame(out, columns=["grp", "tau", "beta", "objective", "rows"])

    sizes = design.groupBy("grp").agg(F.count("*").alias("n"), F.max(F.size("x")).alias("d"), F.min(_one_positive()).alias("split"))
    large = sizes.where(F.col("n") > group_rows).collect()  # at most one for every group_rows rows
    of = lambda groups: F.coalesce(F.col("grp").isin([r.grp for r in groups if r.grp is not None]), F.lit(any(r.grp is None for r in groups)))
    small = design.where(~of(large)) if large else design
    fits = small.select("grp", "b", "x", "w").groupBy("grp").applyInPandas(fit, schema)
    if not large:
        return fits
    rows, spark = [], design.sparkSession
    split = [r for r in large if r.split]
    beta = {(r.grp, tau): [float("nan")] * r.d for r in split for tau in taus}
    for tau in taus if split else []:
        cells = onehot_cells(design.where(of(split)), "grp").withColumn("g", F.struct("grp", "j"))
        for q in group_quantile_exact(cells, "g", "t", "w", tau, "bracket").collect():
            beta[q.g.grp, tau][q.g.j] = q.q
    if split:
        fitted = spark.createDataFrame([(g, tau, v) for (g, tau), v in beta.items()], "grp string, tau double, beta array<double>")
        pairs = design.where(of(split)).alias("d").join(F.broadcast(fitted.alias("f")), F.expr("d.grp <=> f.grp"))
        resid = F.col("b") - dot(F.col("x"), F.transform("beta", lambda v: F.nanvl(v, F.lit(0.0))))
        loss = {(r.grp, r.tau): r.loss for r in pairs.groupBy("f.grp", "tau").agg(F.sum(F.col("w") * pinball(resid, F.col("tau"))).alias("loss")).collect()}
        rows += [(r.grp, tau, beta[r.grp, tau], loss[r.grp, tau], r.n) for r in split for tau in taus]
    for r in large:
        for tau in taus if not r.split else []:
            f = preprocess_exact(design.where(F.col("grp").eqNullSafe(F.lit(r.grp))), tau)[0]
            rows.append((r.grp, tau, [float(v) for v in f.beta], float(f.objective), r.n))
    return fits.unionByName(spark.createDataFrame(rows, schema))


def best_of(fits: DataFrame) -> DataFrame:
    """Of repeated trials, the fit of lowest full-data loss."""
    return fits.groupBy("method", "s", "tau").agg(F.min_by("beta", "objective").alias("beta"), F.min("objective").alias("objective"), F.min_by("trial", "objective").alias("trial"))


def coef_median(fits: DataFrame) -> DataFrame:
    """Median over trials of each coefficient."""
    return fits.select("method", "s", "tau", F.posexplode("beta").alias("j", "v")).groupBy("method", "s", "tau", "j").agg(F.percentile("v", 0.5).alias("median"))


def predict(design: DataFrame, fits: DataFrame) -> DataFrame:
    """Fitted quantiles and residuals of every row under every fit (the fits are a parameter grid)."""
    return design.crossJoin(F.broadcast(fits.select("tau", "beta"))).withColumn("fitted", dot(F.col("x"), F.col("beta"))).withColumn("residual", F.col("b") - F.col("fitted")).drop("beta")


def coverage(design: DataFrame, fits: DataFrame) -> DataFrame:
    """Share of rows at or below each fitted quantile, and mean loss."""
    return predict(design, fits).groupBy("tau").agg(F.avg((F.col("residual") <= 1e-9).cast("double")).alias("coverage"), F.avg(pinball(F.col("residual"), F.col("tau"))).alias("mean_loss"))


def crossing(design: DataFrame, fits: DataFrame) -> DataFrame:
    """Share of rows whose fitted quantiles fall from one level to the next."""
    lower = F.lag("fitted").over(Window.partitionBy("row_id").orderBy("tau"))
    return predict(design, fits).withColumn("below", lower).where("below is not null").groupBy("tau").agg(F.avg((F.col("fitted") < F.col("below") - 1e-9).cast("double")).alias("crossing"))


def bootstrap_ci(design: DataFrame, taus: list[float], replicates: int = 50, level: float = 0.9, seed: int = 41, engine: str = "fast", rows: int = 200_000) -> DataFrame:
    """Point-wise intervals from resampling n of n rows: Poisson(1) weights on every row.

    Where every row has one positive nonzero, all replicates are grouped quantiles
    of one job.  Else designs up to ``rows`` are solved in one task a replicate, and
    larger ones over the cluster, one replicate after the other.
    """
    n, split = design.agg(F.count("*"), F.min(_one_positive())).first()
    draw = lambda t: rnd.poisson_one(rnd.unit(seed, F.concat(F.lit("boot"), t.cast("string")), F.col("row_id"), engine))
    copies = F.filter(F.transform(F.sequence(F.lit(0), F.lit(replicates - 1)), lambda t: F.struct(t.alias("trial"), draw(t).alias("k"))), lambda c: c["k"] > 0)
    drawn = lambda: design.withColumn("c", F.explode(copies)).select("b", "x", (F.col("w") * F.col("c.k")).alias("w"), F.col("c.trial").alias("trial"), F.lit(float(n)).alias("s"))
    if split:
        cells = onehot_cells(drawn(), "trial").withColumn("g", F.struct("trial", "j"))
        parts = [group_quantile_exact(cells, "g", "t", "w", tau, "window" if n <= rows else "bracket").select(F.lit(tau).alias("tau"), F.col("g.j").alias("j"), F.col("q").alias("v")) for tau in taus]
        coefs = functools.reduce(DataFrame.unionByName, parts)
    elif n <= rows:
        coefs = solve_grid(drawn(), taus, "bootstrap").select("tau", F.posexplode("beta").alias("j", "v"))
    else:
        fits = []
        for t in range(replicates):
            own = design.withColumn("k", draw(F.lit(t))).where("k > 0").withColumn("w", F.col("w") * F.col("k")).drop("k").persist()
            fits += [(tau, [float(v) for v in preprocess_exact(own, tau)[0].beta]) for tau in taus]
            own.unpersist()
        coefs = design.sparkSession.createDataFrame(fits, "tau double, beta array<double>").select("tau", F.posexplode("beta").alias("j", "v"))
    return intervals(coefs, level)


def intervals(coefs: DataFrame, level: float = 0.9) -> DataFrame:
    """Point-wise intervals of coefficients ``tau, j, v`` over replicates."""
    half = (1 - level) / 2
    return coefs.groupBy("tau", "j").agg(F.percentile("v", half).alias("lo"), F.percentile("v", 1 - half).alias("hi"), F.percentile("v", 0.5).alias("median"), F.count("*").alias("n_rep"))


def enumerate_pairs(design: DataFrame, tau: float, most: int = 3000) -> DataFrame:
    """Optimum of two columns over lines through pairs of rows, in SQL operators.

    Up to ``most`` rows every pair is tried.  Beyond, only pairs that can be optimal are: the loss is convex,
    so the best lines go through rows that the exact fit meets, and pairs of those are scored on all rows.
    """
    rows = design.select("b", "x", "w")
    if design.count() <= most:
        i, j = design.select(F.col("b").alias("b1"), F.col("x").alias("x1"), F.col("row_id").alias("r1")), design.select(F.col("b").alias("b2"), F.col("x").alias("x2"), F.col("row_id").alias("r2"))
        return _best_line(_lines(i, j, F.col("r1") < F.col("r2")).crossJoin(F.broadcast(rows)), tau)  # at most ``most`` rows
    fit, _ = preprocess_exact(design, tau)
    z, scale = F.abs(F.col("b") - dot(F.col("x"), [float(v) for v in fit.beta])), 1.0 + (design.agg(F.max(F.abs("b"))).first()[0] or 0.0)
    for k in range(9, 0, -2):  # rounding of the fit decides how near its rows are
        met = design.where(z <= scale * 10.0**-k).select("b", "x").distinct()
        i, j = met.select(F.col("b").alias("b1"), F.col("x").alias("x1")), met.select(F.col("b").alias("b2"), F.col("x").alias("x2"))
        lines = _lines(i, j, F.struct("b1", "x1") < F.struct("b2", "x2")).select("c0", "c1").distinct()
        best = _best_line(rows.crossJoin(F.broadcast(lines)), tau)
        found = best.first()
        if found.objective is not None and found.objective <= fit.objective * (1 + 1e-9) + 1e-9:
            return design.sparkSession.createDataFrame([tuple(found)], best.schema)
    raise RuntimeError(f"no line through two rows reaches the optimal loss {fit.objective}")


def _lines(i: DataFrame, j: DataFrame, once: Column) -> DataFrame:
    """``c0, c1`` of the lines through rows ``b1, x1`` and ``b2, x2``."""
    det = F.col("x1")[0] * F.col("x2")[1] - F.col("x1")[1] * F.col("x2")[0]
    c0, c1 = (F.col("b1") * F.col("x2")[1] - F.col("b2") * F.col("x1")[1]) / det, (F.col("x1")[0] * F.col("b2") - F.col("x2")[0] * F.col("b1")) / det
    return i.join(j, once).where(F.abs(det) > 1e-12).select(c0.alias("c0"), c1.alias("c1"))


def _best_line(pairs: DataFrame, tau: float) -> DataFrame:
    scored = pairs.groupBy("c0", "c1").agg(F.sum(F.col("w") * pinball(F.col("b") - F.col("c0") * F.col("x")[0] - F.col("c1") * F.col("x")[1], tau)).alias("f"))
    return scored.agg(F.min("f").alias("objective"), F.min_by("c0", "f").alias("beta0"), F.min_by("c1", "f").alias("beta1"))


