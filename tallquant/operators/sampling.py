"""Row norms in a conditioned basis, inclusion probabilities and row samples.

Every coin is a function of (seed, trial, row id), so samples of different sizes are
nested, one pass serves every trial and level, and a retried task repeats itself.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from tallquant.functions import randomness as rnd
from tallquant.functions.loss import batch_matrix, dot
from tallquant.operators.sizing import estimator_width, norms_choice


class NormKernel:
    """Row norms of a batch in the basis of R^-1: exact, or by the median estimator (l1 or l2)."""

    def __init__(self, rinv: np.ndarray, how: str, n: int | None, r2: int | None, p: int, seed: int):
        self.how, self.p, self.matrix = how, p, rinv
        if how == "median":
            d, r2 = len(rinv), r2 or estimator_width(n)
            rng = np.random.default_rng(seed)
            self.matrix = rinv @ (rng.standard_cauchy((d, r2)) if p == 1 else rng.normal(size=(d, r2)))

    def __call__(self, a: np.ndarray) -> np.ndarray:
        y = a @ self.matrix if len(a) else np.zeros((0, 1))
        if self.how == "median":
            return np.median(np.abs(y), axis=1) / (1.0 if self.p == 1 else 0.6744897501960817)
        return np.abs(y).sum(axis=1) if self.p == 1 else np.sqrt((y**2).sum(axis=1))


def norm_kernel(frame: DataFrame, rinv: np.ndarray, how: str = "auto", n: int | None = None, r2: int | None = None, p: int = 1, seed: int = 17) -> NormKernel:
    """``auto`` takes the cheaper kind; rows are counted only where that or the estimator's width depends on their number."""
    d = len(rinv)
    if how == "auto" and d <= estimator_width(1):
        how = "exact"
    if n is None and (how == "auto" or how == "median" and not r2):
        n = frame.count()
    return NormKernel(rinv, norms_choice(d, n) if how == "auto" else how, n, r2, p, seed)


def row_norms(frame: DataFrame, rinv: np.ndarray, how: str = "auto", column: str = "a", n: int | None = None, r2: int | None = None, p: int = 1, seed: int = 17) -> DataFrame:
    """Adds ``lam``: the l1 (or l2) norm of the row times R^-1, exact or by the median estimator."""
    cast = frame.sparkSession.sparkContext.broadcast(norm_kernel(frame, rinv, how, n, r2, p, seed))
    names = frame.columns
    at = names.index(column)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            lam = cast.value(batch_matrix(batch.column(at)))
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(lam, pa.float64())], names=[*names, "lam"])

    schema = frame.select(*names, F.lit(0.0).alias("lam")).schema
    return frame.mapInArrow(run, schema)


def sample_design(design: DataFrame, rinv: np.ndarray, sizes: list[float], trials: int, seed: int, norms: str = "auto", engine: str = "fast", n: int | None = None) -> DataFrame:
    """Samples of a design by the norms of its augmented rows: one pass for their sum, one that returns only surviving rows.

    Columns of the design, and ``trial, s, p`` with ``w`` divided by p, as :func:`sample_trials` gives them.
    """
    cast = design.sparkSession.sparkContext.broadcast(norm_kernel(design, rinv, norms, n))

    def norms_of(b: pa.Array, x: pa.Array) -> np.ndarray:
        cells = batch_matrix(x)
        return cast.value(np.column_stack([b.to_numpy(), -cells])) if len(cells) else np.empty(0)

    def add(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = 0.0
        for batch in batches:
            total += float(norms_of(batch.column(0), batch.column(1)).sum())
        yield pa.RecordBatch.from_arrays([pa.array([total])], names=["lam"])

    total = design.select("b", "x").mapInArrow(add, "lam double").agg(F.coalesce(F.sum("lam"), F.lit(0.0))).first()[0]
    if not total > 0:
        return sample_trials(design.where("false").withColumn("lam", F.lit(0.0)), sizes, trials, seed, total=0.0, engine=engine).drop("lam")
    factor, names = max(sizes) / total, design.columns
    b, x = names.index("b"), names.index("x")
    least = least_coin(seed, trials, engine)

    def keep(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            lam = norms_of(batch.column(b), batch.column(x))
            alive = pa.array(batch.column(len(names)).to_numpy() < np.minimum(1.0, lam * factor))
            yield pa.RecordBatch.from_arrays([*batch.columns[:-1], pa.array(lam, pa.float64())], names=[*names, "lam"]).filter(alive)

    schema = design.select(*names, F.lit(0.0).alias("lam")).schema
    normed = design.select(*names, least.alias("_least")).mapInArrow(keep, schema)
    return sample_trials(normed, sizes, trials, seed, total=total, engine=engine).drop("lam")


def row_norms_sql(frame: DataFrame, rinv: np.ndarray, column: str = "a") -> DataFrame:
    """The exact norms as one expression: stays in generated code, for few columns."""
    terms = [F.abs(dot(F.col(column), [float(v) for v in rinv[:, k]])) for k in range(rinv.shape[1])]
    total = terms[0]
    for t in terms[1:]:
        total = total + t
    return frame.withColumn("lam", total)


def row_norms_coo(coo: DataFrame, rinv: np.ndarray) -> DataFrame:
    """``row_id, lam`` from entries (row_id, j, v): the product with R^-1 as a join on j."""
    entries = [(j, k, float(rinv[j, k])) for j in range(rinv.shape[0]) for k in range(rinv.shape[1])]
    r = F.broadcast(coo.sparkSession.createDataFrame(entries, "j int, k int, r double"))  # columns by columns
    return coo.join(r, "j").groupBy("row_id", "k").agg(F.sum(F.col("v") * F.col("r")).alias("y")).groupBy("row_id").agg(F.sum(F.abs("y")).alias("lam"))


def total_norm(frame: DataFrame) -> float:
    return frame.agg(F.coalesce(F.sum("lam"), F.lit(0.0))).first()[0]


def probability(s: float, total: float, lam: Column | str = "lam") -> Column:
    lam = F.col(lam) if isinstance(lam, str) else lam
    return F.least(F.lit(1.0), lam * (float(s) / total)) if total > 0 else F.lit(0.0)


def sample_rows(frame: DataFrame, s: float, seed: int, trial: int = 0, total: float | None = None, engine: str = "fast", passes: int = 2) -> DataFrame:
    """Keep each row with p = min(1, s lam / sum lam) and divide its weight by p.

    ``passes=1`` finds the same sample while lam is being summed: a row stays if
    its coin / lam is below s over the sum of its partition so far, which is never
    larger than the sum of all; what each partition kept, about s rows, is written
    once and cut at the whole sum.
    """
    coin = rnd.unit(seed, f"coin{trial}", F.col("row_id"), engine)
    if passes == 1 and total is None:
        frame, total = _candidates(frame.withColumn("coin", coin), s)
        p = probability(s, total)
        return frame.withColumn("p", p).where(F.col("coin") < F.col("p")).drop("coin").withColumn("w", F.col("w") / F.col("p"))
    total = total if total is not None else total_norm(frame)
    p = probability(s, total)
    return frame.withColumn("p", p).where(coin < F.col("p")).withColumn("w", F.col("w") / F.col("p"))


def _candidates(frame: DataFrame, s: float) -> tuple[DataFrame, float]:
    """Rows that the coin may keep, and the sum of lam, in one pass over the frame."""
    from tallquant.sources.storage import scratch

    names = frame.columns
    lam_at, coin_at = names.index("lam"), names.index("coin")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, waiting, total = [], 0, 0.0

        def alive() -> pa.Table:
            table = pa.Table.from_batches(held)
            return table.filter(pa.array(table.column(coin_at).to_numpy() * total < s * table.column(lam_at).to_numpy()))

        for batch in batches:
            total += float(batch.column(lam_at).to_numpy().sum())
            held.append(batch)
            waiting += len(batch)
            if waiting > 4 * s + 100_000:
                held = alive().to_batches()
                waiting = sum(map(len, held))
        for batch in alive().to_batches() if held else []:
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.nulls(len(batch), pa.float64())], names=[*names, "part_total"])
        if held:
            yield pa.RecordBatch.from_arrays([*(pa.nulls(1, c.type) for c in held[0].columns), pa.array([total])], names=[*names, "part_total"])

    schema = T.StructType([T.StructField(f.name, f.dataType) for f in frame.schema] + [T.StructField("part_total", T.DoubleType())])
    path = scratch(frame.sparkSession, "candidates")
    frame.mapInArrow(run, schema).write.parquet(path)
    kept = frame.sparkSession.read.schema(schema).parquet(path)
    total = kept.agg(F.coalesce(F.sum("part_total"), F.lit(0.0))).first()[0]
    return kept.where("part_total is null").drop("part_total"), total


def _coin(seed: int, trial: Column, engine: str) -> Column:
    return rnd.unit(seed, F.concat(F.lit("coin"), trial.cast("string")), F.col("row_id"), engine)


def least_coin(seed: int, trials: int, engine: str) -> Column:
    """The smallest coin of a row over all trials: no trial keeps the row if this one does not."""
    return F.least(*[_coin(seed, F.lit(t), engine) for t in range(trials)]) if trials > 1 else _coin(seed, F.lit(0), engine)


def sample_trials(frame: DataFrame, sizes: list[float], trials: int, seed: int, total: float | None = None, engine: str = "fast") -> DataFrame:
    """Samples of every size and trial in one pass: adds ``trial, s, p`` and divides ``w``; only survivors are exploded."""
    total = total if total is not None else total_norm(frame)
    most = max(sizes)
    coins = F.transform(F.sequence(F.lit(0), F.lit(trials - 1)), lambda t: F.struct(t.alias("trial"), _coin(seed, t, engine).alias("u")))
    alive = F.filter(coins, lambda c: c["u"] < probability(most, total))
    kept = frame.withColumn("c", F.explode(alive)).withColumns({"trial": F.col("c.trial"), "u": F.col("c.u")}).drop("c")
    grid = F.array(*[F.lit(float(s)) for s in sizes])
    out = kept.withColumn("s", F.explode(F.filter(grid, lambda s: F.col("u") < F.least(F.lit(1.0), F.col("lam") * s / total))))
    p = F.least(F.lit(1.0), F.col("lam") * F.col("s") / total)
    return out.withColumn("p", p).withColumn("w", F.col("w") / F.col("p")).drop("u")


def sample_uniform(frame: DataFrame, s: float, seed: int, trial: int = 0, n: int | None = None, replace: bool = False, engine: str = "fast") -> DataFrame:
    """Every row with p = s / n; with replacement by Poisson counts of mean s / n (weights count the draws)."""
    n = n if n is not None else frame.count()
    u = rnd.unit(seed, f"{'draw' if replace else 'coin'}{trial}", F.col("row_id"), engine)
    if replace:
        counts = rnd.poisson_one(u) if s == n else rnd.poisson(u, s / n if n else 0.0)
        return frame.withColumn("draws", counts).where("draws > 0").withColumn("w", F.col("w") * F.col("draws") * (n / s)).drop("draws")
    p = min(1.0, s / n) if n else 0.0
    return frame.where(u < p).withColumns({"p": F.lit(p), "w": F.col("w") / F.lit(p if p else 1.0)})


def sample_report(sample: DataFrame) -> DataFrame:
    """Rows kept, clipped rows, and sums of probabilities and weights."""
    return sample.agg(F.count("*").alias("rows_kept"), F.count(F.when(F.col("p") >= 1, 1)).alias("rows_clipped"), F.sum("p").alias("sum_p"), F.sum("w").alias("sum_w"))


def expected_size(frame: DataFrame, s: float, total: float | None = None) -> DataFrame:
    total = total if total is not None else total_norm(frame)
    return frame.agg(F.sum(probability(s, total)).alias("expected_rows"))


def sample_rank(sample: DataFrame, column: str = "a") -> int:
    from tallquant.operators.linalg import rank_report, tall_qr

    return int(rank_report(tall_qr(sample, column)).sum())


def probe_preservation(frame: DataFrame, sample: DataFrame, taus: list[float], n_dirs: int = 32, seed: int = 1) -> DataFrame:
    """Largest deviation from 1 of sampled over full loss along random directions of the augmented space."""
    from tallquant.functions.loss import objective_many

    d = len(frame.select("x").first().x)
    rng = np.random.default_rng(seed)
    dirs = [(k, rng.normal(size=d).tolist(), t) for k, t in enumerate(t for t in taus for _ in range(n_dirs))]
    full = objective_many(frame, dirs).withColumnRenamed("objective", "full")
    part = objective_many(sample, dirs).withColumnRenamed("objective", "part")
    level = F.array(*[F.lit(t) for _, _, t in dirs])[F.col("cand").cast("int")]
    return full.join(part, "cand").groupBy(level.alias("tau")).agg(F.max(F.abs(F.col("part") / F.col("full") - 1)).alias("worst"))
