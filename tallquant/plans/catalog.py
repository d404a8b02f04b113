"""Registered queries of the engine's methods, measures and workloads, with DuckDB SQL where SQL can express them.

Random numbers that SQL repeats come from the portable generator, so both engines
draw the same coins.  Where SQL cannot repeat a method its query returns what holds
of the measured figures, and the SQL says what should.
"""

from __future__ import annotations

import math
from collections.abc import Callable

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tallquant.functions import loss as L
from tallquant.functions import randomness as rnd
from tallquant.operators import conditioning as C
from tallquant.operators import metrics, quantreg, sampling, sizing
from tallquant.operators import sketch as S
from tallquant.operators.linalg import width_of
from tallquant.operators import sparse as SP
from tallquant.plans import experiments as X
from tallquant.plans import planner
from tallquant.sources import blocks
from tallquant.sources import design as D
from tallquant.sources import storage

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}
TAUS = [0.5, 0.75, 0.95]
TAU_VALUES = "(VALUES (0.5::double), (0.75::double), (0.95::double)) AS t(tau)"


def query(sql: str | None = None) -> Callable[[Query], Query]:
    def keep(f: Query) -> Query:
        QUERIES[f.__name__] = f
        if sql is not None:
            ORACLES[f.__name__] = sql
        return f

    return keep


def significant(name: str) -> list:
    """A value as mantissa (4 decimals) and exponent: heavy-tailed sums have no common scale."""
    e = F.floor(F.log10(F.abs(F.col(name))))
    return [F.when(F.col(name) == 0, 0.0).otherwise(F.round(F.col(name) / F.pow(F.lit(10.0), e), 4)).alias(f"{name}_m"), F.when(F.col(name) == 0, 0).otherwise(e).cast("int").alias(f"{name}_e")]


def significant_sql(name: str) -> str:
    e = f"floor(log10(abs({name})))"
    return f"CASE WHEN {name} = 0 THEN 0.0 ELSE round({name} / pow(10.0, {e}), 4) END AS {name}_m, (CASE WHEN {name} = 0 THEN 0 ELSE {e} END)::int AS {name}_e"


PIN = "greatest({tau} * ({z}), ({tau} - 1) * ({z}))"


def pin_sql(z: str, tau: float | str) -> str:
    tau = f"{tau}::double" if isinstance(tau, float) else tau
    return PIN.format(z=z, tau=tau)


def tau_frame(spark: SparkSession, taus: list[float] = TAUS) -> DataFrame:
    return spark.createDataFrame([(t,) for t in taus], "tau double")


def value_design(spark: SparkSession, sf_dir: str) -> DataFrame:
    return D.build(D.table(spark, sf_dir, "events"), F.col("event_id"), F.col("value"), [F.lit(1.0)])


# --- loss -----------------------------------------------------------------------


@query(f"SELECT event_type, round(sum({pin_sql('value - 50', 0.75)}), 4) AS loss, count(*) AS n FROM events GROUP BY event_type")
def loss_pinball_fixed_beta(spark, sf_dir):
    ev = D.table(spark, sf_dir, "events")
    return ev.groupBy("event_type").agg(F.round(F.sum(L.pinball(F.col("value") - 50.0, 0.75)), 4).alias("loss"), F.count("*").alias("n"))


@query(f"SELECT c.k AS cand, round(sum({pin_sql('value - c.v', 'c.tau')}), 4) AS objective FROM events, (VALUES (0, 20.0::double, 0.5::double), (1, 50.0, 0.75), (2, 80.0, 0.95)) AS c(k, v, tau) GROUP BY c.k")
def loss_many_candidates(spark, sf_dir):
    out = L.objective_many(value_design(spark, sf_dir), [(0, [20.0], 0.5), (1, [50.0], 0.75), (2, [80.0], 0.95)])
    return out.select(F.col("cand").cast("int").alias("cand"), F.round("objective", 4).alias("objective"))


_Y1, _Y2 = "value", "(value * 0.5 - 40)"
LAWS_SQL = f"""
WITH s AS (SELECT sum({pin_sql(_Y1, 0.75)}) AS f1, sum({pin_sql(_Y2, 0.75)}) AS f2, sum({pin_sql(f"({_Y1} + {_Y2})", 0.75)}) AS f12, sum({pin_sql(f"(4 * {_Y1})", 0.75)}) AS f4,
  sum(abs({_Y1})) AS n1, sum(abs({_Y1} - {_Y2})) AS n12 FROM events)
SELECT f12 <= f1 + f2 + 1e-3 AS subadditive, f1 BETWEEN 0.25 * n1 - 1e-3 AND 0.75 * n1 + 1e-3 AS bounded_by_l1, abs(f4 - 4 * f1) <= 1e-3 AS homogeneous, abs(f1 - f2) <= 0.75 * n12 + 1e-3 AS lipschitz FROM s"""


@query(LAWS_SQL)
def loss_laws(spark, sf_dir):
    return L.check_loss_laws(D.table(spark, sf_dir, "events").select(F.col("value").alias("y1"), (F.col("value") * 0.5 - 40).alias("y2")), 0.75)


@query(f"SELECT tau, round(sum({pin_sql('value - 34.59', 'tau')}), 4) AS objective FROM events, {TAU_VALUES} GROUP BY tau")
def objective_by_tau(spark, sf_dir):
    parts = [L.objective(value_design(spark, sf_dir), [34.59], t).select(F.lit(t).alias("tau"), F.round("objective", 4).alias("objective")) for t in TAUS]
    return parts[0].union(parts[1]).union(parts[2])


@query(f"SELECT round(sum({pin_sql('value - 30', 0.2)}), 4) AS direct, round(sum({pin_sql('30 - value', 0.8)}), 4) AS reflected FROM events")
def loss_reflected(spark, sf_dir):
    design = value_design(spark, sf_dir)
    mirrored, tau = L.reflect(design, 0.2)
    a = L.objective(design, [30.0], 0.2).select(F.round("objective", 4).alias("direct"))
    return a.crossJoin(L.objective(mirrored, [30.0], tau).select(F.round("objective", 4).alias("reflected")))


@query("SELECT round(sum(value), 3) AS s0, round(sum(CASE WHEN event_type = 'click' THEN -1.0 ELSE 0.0 END), 3) AS s1, count(*) AS n, round(sum(CASE WHEN event_type = 'click' THEN 2.0 ELSE 0.0 END), 3) AS folded FROM events")
def augmented_rows(spark, sf_dir):
    design = D.onehot_events(spark, sf_dir).drop("grp")
    folded = L.fold_weights(design.withColumn("w", F.lit(2.0)))
    a = L.augment(design).agg(F.round(F.sum(F.col("a")[0]), 3).alias("s0"), F.round(F.sum(F.col("a")[1]), 3).alias("s1"), F.count("*").alias("n"))
    return a.crossJoin(folded.agg(F.round(F.sum(F.col("x")[0]), 3).alias("folded")))


@query("SELECT vec_id, round(list_sum(list_transform(embedding, lambda x: abs(x::double))), 5) AS l1, round(sqrt(list_sum(list_transform(embedding, lambda x: x::double * x::double))), 5) AS l2, round(list_max(list_transform(embedding, lambda x: abs(x::double))), 6) AS linf, round(embedding[1]::double - embedding[64]::double, 6) AS dot FROM embeddings")
def emb_dot_norms(spark, sf_dir):
    x = F.transform("embedding", lambda v: v.cast("double"))
    emb = D.table(spark, sf_dir, "embeddings").select("vec_id", x.alias("x"))
    direction = [1.0] + [0.0] * 62 + [-1.0]
    return emb.select("vec_id", F.round(L.norm(F.col("x"), "l1"), 5).alias("l1"), F.round(L.norm(F.col("x"), "l2"), 5).alias("l2"), F.round(L.norm(F.col("x"), "linf"), 6).alias("linf"), F.round(L.dot(F.col("x"), direction), 6).alias("dot"))


@query("SELECT round(sum(abs(s_nationkey::double)) + count(*), 4) AS entry_l1 FROM supplier")
def entry_norm(spark, sf_dir):
    return L.entry_l1(D.supplier_design(spark, sf_dir)).select(F.round("entry_l1", 4).alias("entry_l1"))


# --- exact grouped quantiles ------------------------------------------------------


@query(" UNION ALL ".join(f"SELECT {t}::double AS tau, quantile_disc(value, {t}) AS q FROM events" for t in TAUS))
def intercept_only_quantile(spark, sf_dir):
    ev = D.table(spark, sf_dir, "events")
    parts = [ev.agg(F.expr(f"percentile_disc({t}) WITHIN GROUP (ORDER BY value)").alias("q")).select(F.lit(t).alias("tau"), "q") for t in TAUS]
    return parts[0].union(parts[1]).union(parts[2])


@query("SELECT row_number() OVER (ORDER BY event_type) - 1 AS j, quantile_disc(value, 0.75) AS q FROM events GROUP BY event_type")
def onehot_group_quantile_events(spark, sf_dir):
    return quantreg.onehot_fit(D.onehot_events(spark, sf_dir), 0.75).select(F.col("j").cast("long").alias("j"), "q")


@query("SELECT row_number() OVER (ORDER BY o_orderpriority) - 1 AS j, quantile_disc(o_totalprice, 0.75) AS q FROM orders GROUP BY o_orderpriority")
def onehot_group_quantile_orders(spark, sf_dir):
    return quantreg.onehot_fit(D.onehot_orders(spark, sf_dir), 0.75, how="bracket").select(F.col("j").cast("long").alias("j"), "q")


WEIGHTED_SQL = """
WITH r AS (SELECT l_returnflag AS flag, l_extendedprice AS v, sum(l_quantity) OVER (PARTITION BY l_returnflag ORDER BY l_extendedprice RANGE BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS run,
  sum(l_quantity) OVER (PARTITION BY l_returnflag) AS total FROM lineitem)
SELECT flag, min(v) AS q FROM r WHERE run >= 0.75 * total GROUP BY flag"""


@query(WEIGHTED_SQL)
def weighted_group_quantile(spark, sf_dir):
    rows = D.table(spark, sf_dir, "lineitem").select(F.col("l_returnflag").alias("flag"), F.col("l_extendedprice").alias("v"), F.col("l_quantity").alias("w"))
    return quantreg.group_quantile_exact(rows, "flag", "v", "w", 0.75)


@query(WEIGHTED_SQL)
def weighted_group_quantile_bracket(spark, sf_dir):
    rows = D.table(spark, sf_dir, "lineitem").select(F.col("l_returnflag").alias("flag"), F.col("l_extendedprice").alias("v"), F.col("l_quantity").alias("w"))
    return quantreg.group_quantile_exact(rows, "flag", "v", "w", 0.75, how="bracket")


# --- workload designs ---------------------------------------------------------------


@query(f"SELECT row_id, j, round(b, 6) AS b FROM ({D.skew_sql(10, 1.75)})")
def skew_design_rows(spark, sf_dir):
    design = D.skew_lineitem(spark, sf_dir, 10, 1.75, engine="portable")
    return design.select("row_id", (F.array_position("x", F.lit(1.0)) - 1).cast("int").alias("j"), F.round("b", 6).alias("b"))


@query(f"SELECT j, round(quantile_disc(b, 0.75), 6) AS q FROM ({D.skew_sql(10, 1.75)}) GROUP BY j")
def skew_exact_solution(spark, sf_dir):
    return quantreg.onehot_fit(D.skew_lineitem(spark, sf_dir, 10, 1.75, engine="portable"), 0.75).select("j", F.round("q", 6).alias("q"))


@query(f"SELECT j, count(*) AS n FROM ({D.skew_sql(10, 1.75)}) GROUP BY j")
def skew_block_sizes(spark, sf_dir):
    design = D.skew_lineitem(spark, sf_dir, 10, 1.75, engine="portable")
    return design.groupBy((F.array_position("x", F.lit(1.0)) - 1).cast("int").alias("j")).agg(F.count("*").alias("n"))


@query(f"SELECT row_id, round(b, 6) AS b, {', '.join(f'x[{j + 1}] AS x{j}' for j in range(11))} FROM ({D.census_sql()})")
def census_design_rows(spark, sf_dir):
    return D.census_design(spark, sf_dir).select("row_id", F.round("b", 6).alias("b"), *[F.col("x")[j].alias(f"x{j}") for j in range(11)])


@query(f"SELECT 3 * count(*) AS n, round(3 * sum({pin_sql('value - 30', 0.75)}), 4) AS objective FROM events")
def stack_design_k(spark, sf_dir):
    design = D.stack(value_design(spark, sf_dir), 3)
    return design.agg(F.count("*").alias("n")).crossJoin(L.objective(design, [30.0], 0.75).select(F.round("objective", 4).alias("objective")))


@query("SELECT count(*) AS n, sum(w)::double AS w FROM (SELECT value, event_type, 3 * count(*) AS w FROM events GROUP BY ALL)")
def duplicate_collapse(spark, sf_dir):
    return D.collapse(D.stack(D.onehot_events(spark, sf_dir).drop("grp"), 3)).agg(F.count("*").alias("n"), F.sum("w").alias("w"))


@query('SELECT count(*) AS "rows", count(*) FILTER (quality IS NULL) AS rejected FROM documents LEFT JOIN labels USING (doc_id)')
def design_rejected_rows(spark, sf_dir):
    docs = D.table(spark, sf_dir, "documents").join(D.table(spark, sf_dir, "labels"), "doc_id", "left")
    return D.count_rejected(docs, F.col("n_chars"), [F.lit(1.0), F.col("quality")])


@query(f"SELECT round(sum(b), 4) AS total FROM ({D.skew_sql(5, 2.0)})")
def skew_total_response(spark, sf_dir):
    return D.skew_lineitem(spark, sf_dir, 5, 2.0, engine="portable").agg(F.round(F.sum("b"), 4).alias("total"))


@query(f"SELECT count(*) AS n, round(avg(b), 4) AS mean_b, {', '.join(f'round(avg(x[{j + 1}]), 4) AS mean_x{j}' for j in range(11))} FROM ({D.gaussian_sql(11, 2)})")
def gaussian_design_moments(spark, sf_dir):
    d = D.gaussian_design(spark, sf_dir, 11, 2, engine="portable")
    return d.agg(F.count("*").alias("n"), F.round(F.avg("b"), 4).alias("mean_b"), *[F.round(F.avg(F.col("x")[j]), 4).alias(f"mean_x{j}") for j in range(11)])


# --- sketches and conditioners --------------------------------------------------------

R = 64
EV_ROWS = "SELECT event_id::varchar AS row_id, value AS b FROM events"
SEED = 7


def sketch_sql(multiplier: str, source: str = EV_ROWS, seed: int = SEED, r: int = R) -> str:
    return f"SELECT floor({rnd.unit_sql(seed, chr(39) + 'bucket' + chr(39), 'row_id')}::double * {r})::bigint AS bucket, sum({multiplier} * b) AS v0, sum(-{multiplier}) AS v1 FROM ({source}) GROUP BY 1"


CAUCHY_SQL = f"tan({math.pi!r} * ({rnd.unit_sql(SEED, chr(39) + 'cauchy' + chr(39), 'row_id')}::double - 0.5))"
EXP_SQL = f"((CASE WHEN {rnd.unit_sql(SEED, chr(39) + 'sign' + chr(39), 'row_id')} < 0.5 THEN -1.0::double ELSE 1.0::double END) / (-ln({rnd.unit_sql(SEED, chr(39) + 'exponential' + chr(39), 'row_id')}::double)))"


def event_rows(spark, sf_dir) -> DataFrame:
    return L.augment(value_design(spark, sf_dir))


@query(f"SELECT bucket, {significant_sql('v0')}, {significant_sql('v1')} FROM ({sketch_sql(CAUCHY_SQL)})")
def sketch_sparse_cauchy_d2(spark, sf_dir):
    return S.sparse_cauchy(event_rows(spark, sf_dir), R, SEED, engine="portable").select("bucket", *significant("v0"), *significant("v1"))


@query(f"SELECT bucket, {significant_sql('v0')}, {significant_sql('v1')} FROM ({sketch_sql(EXP_SQL)})")
def sketch_exponential(spark, sf_dir):
    return S.sparse_exponential(event_rows(spark, sf_dir), R, SEED, engine="portable").select("bucket", *significant("v0"), *significant("v1"))


DENSE_SQL = f"""SELECT k::bigint AS bucket, sum(c * b) AS v0, sum(-c) AS v1 FROM (SELECT k, b, tan({math.pi!r} * ({rnd.unit_sql(SEED, chr(39) + 'dense' + chr(39), "row_id || '#' || k")}::double - 0.5)) AS c FROM ({EV_ROWS}), range(8) AS r(k)) GROUP BY k"""


@query(f"SELECT bucket, {significant_sql('v0')}, {significant_sql('v1')} FROM ({DENSE_SQL})")
def sketch_dense_cauchy_d2(spark, sf_dir):
    return S.dense_cauchy(event_rows(spark, sf_dir), 8, SEED, engine="portable").select("bucket", *significant("v0"), *significant("v1"))


def _distortion(spark, sf_dir, name: str, build) -> DataFrame:
    """Whether norms along 75 directions are neither lost nor blown up beyond what d log d allows."""
    rows = L.augment(D.skew_lineitem(spark, sf_dir, 10, 1.75))
    low, high = S.probe_distortion(rows, S.as_matrix(build(rows, S.practical_rows(11), 1)))
    return spark.createDataFrame([(name, low > 0.3, high < 1e3 * 11 * math.log(11))], "sketch string, not_lost boolean, not_blown_up boolean")


@query("SELECT 'sparse_cauchy' AS sketch, true AS not_lost, true AS not_blown_up")
def sketch_sparse_cauchy_d10_norms(spark, sf_dir):
    return _distortion(spark, sf_dir, "sparse_cauchy", S.sparse_cauchy)


@query("SELECT 'fast_cauchy' AS sketch, true AS not_lost, true AS not_blown_up")
def sketch_fast_cauchy_distortion(spark, sf_dir):
    return _distortion(spark, sf_dir, "fast_cauchy", S.fast_cauchy)


R_SQL = f"SELECT sqrt(sum(v0 * v0)) AS r11, sum(v0 * v1) / sqrt(sum(v0 * v0)) AS r12, sqrt(sum(v1 * v1) - sum(v0 * v1) * sum(v0 * v1) / sum(v0 * v0)) AS r22 FROM ({sketch_sql(CAUCHY_SQL)})"


def event_conditioner(spark, sf_dir) -> C.Conditioner:
    return C.condition(event_rows(spark, sf_dir), "sparse_qr", seed=SEED, engine="portable", sketch_rows=R)


@query(f"SELECT {significant_sql('r11')}, {significant_sql('r12')}, {significant_sql('r22')} FROM ({R_SQL})")
def conditioner_qr_d2(spark, sf_dir):
    r = event_conditioner(spark, sf_dir).r
    one = spark.createDataFrame([(float(r[0, 0]), float(r[0, 1]), float(r[1, 1]))], "r11 double, r12 double, r22 double")
    return one.select(*significant("r11"), *significant("r12"), *significant("r22"))


# rows of [b, -1] times the inverse of R: (b / r11, -1 / r22 - b r12 / (r11 r22))
NORM_SQL = f"SELECT row_id, b, abs(b / r11) + abs(-1.0 / r22 - b * r12 / (r11 * r22)) AS lam FROM ({EV_ROWS}), ({R_SQL})"


@query(f"SELECT row_id, {significant_sql('lam')} FROM ({NORM_SQL})")
def row_norms_exact(spark, sf_dir):
    return sampling.row_norms(event_rows(spark, sf_dir), event_conditioner(spark, sf_dir).rinv, how="exact").select("row_id", *significant("lam"))


@query(f"SELECT row_id, {significant_sql('lam')} FROM ({NORM_SQL})")
def row_norms_expression(spark, sf_dir):
    return sampling.row_norms_sql(event_rows(spark, sf_dir), event_conditioner(spark, sf_dir).rinv).select("row_id", *significant("lam"))


@query("SELECT count(*) AS n, true AS most_in_range FROM lineitem")
def row_norms_median_est(spark, sf_dir):
    rows = L.augment(D.skew_lineitem(spark, sf_dir, 10, 1.75))
    rinv = C.condition(rows, "sparse_qr").rinv
    both = sampling.row_norms(rows, rinv, how="exact").withColumnRenamed("lam", "exact").join(sampling.row_norms(rows, rinv, how="median", n=60_000).select("row_id", "lam"), "row_id")
    ratio = F.col("lam") / F.col("exact")
    return both.agg(F.count("*").alias("n"), (F.avg(ratio.between(0.5, 1.5).cast("double")) >= 0.95).alias("most_in_range"))


def _each_method(spark, rows: DataFrame, methods: list[str], **options) -> DataFrame:
    """Passes of each conditioner, and whether its measured condition number is far below the identity's and within the guarantee's order."""
    d = width_of(rows)
    alpha, beta = C.measure_kappa(rows, np.eye(d))
    out = []
    for m in methods:
        c = C.condition(rows, m, **options)
        own = C.measure_kappa(rows, c.rinv)
        out.append((m, len(c.r), c.passes if not m.startswith("round") else None, own[0] * own[1] < 0.5 * alpha * beta, own[0] * own[1] <= max(c.kappa_bound, 3.0 * d**2)))
    return spark.createDataFrame(out, "method string, d int, passes int, improves boolean, within_bound boolean")


def _each_sql(passes: dict[str, int | None], d: int) -> str:
    rows = ", ".join(f"('{m}', {d}, {'NULL' if p is None else p}::int, true, true)" for m, p in passes.items())
    return f"SELECT * FROM (VALUES {rows}) AS v(method, d, passes, improves, within_bound)"


@query(_each_sql({"sparse_qr": 1, "sparse_qr_round": 3, "sparse_qr_qr": 3, "dense_qr": 1, "fast_qr": 1, "exponential_qr": 1}, 12))
def conditioners_compared(spark, sf_dir):
    return _each_method(spark, L.augment(D.census_design(spark, sf_dir)), ["sparse_qr", "sparse_qr_round", "sparse_qr_qr", "dense_qr", "fast_qr", "exponential_qr"])


@query(_each_sql({"sparse_qr": 1}, 12))
def conditioner_svd(spark, sf_dir):
    return _each_method(spark, L.augment(D.census_design(spark, sf_dir)), ["sparse_qr"], factor="svd")


@query(_each_sql({"round_fast": None, "round_full": None}, 12))
def round_slab_sandwich(spark, sf_dir):
    rows = blocks.pack(L.augment(D.census_design(spark, sf_dir)).select("a"), "a")  # each round is a pass
    return _each_method(spark, rows, ["round_fast", "round_full"])


@query(f"SELECT row_id, {significant_sql('lam')} FROM (SELECT row_id, sqrt(b * b + 1.0) AS lam FROM ({EV_ROWS}))")
def row_norms_l2(spark, sf_dir):
    return sampling.row_norms(event_rows(spark, sf_dir), np.eye(2), how="exact", p=2).select("row_id", *significant("lam"))


@query("SELECT 0 AS j, round(sum(abs(value)), 2) AS l1 FROM events UNION ALL SELECT 1, count(*)::double FROM events")
def basis_norms(spark, sf_dir):
    return C.basis_l1(event_rows(spark, sf_dir), np.eye(2)).select(F.col("j").cast("int").alias("j"), F.round("l1", 2).alias("l1"))


ENTRY_SQL = f"""
WITH e AS (SELECT event_id::varchar AS row_id, value, row_number() OVER () AS r, dense_rank() OVER (ORDER BY event_type) AS k FROM events),
a AS (SELECT row_id, 0 AS j, value AS v FROM e UNION ALL SELECT row_id, k, -1.0 FROM e)
SELECT floor({rnd.unit_sql(SEED, chr(39) + 'bucket' + chr(39), 'row_id')}::double * {R})::bigint AS bucket, j::int AS j, sum({CAUCHY_SQL} * v) AS v FROM a GROUP BY ALL"""


@query(f"SELECT bucket, j, {significant_sql('v')} FROM ({ENTRY_SQL})")
def sketch_of_sparse_rows(spark, sf_dir):
    """The sketch of the sparse layout: work and output follow the nonzeros."""
    rows = SP.augmented(D.to_sparse(D.onehot_events(spark, sf_dir).drop("grp")))
    return SP.sparse_cauchy(rows, R, SEED, engine="portable").select("bucket", "j", *significant("v"))


@query("SELECT tau, true AS within_guarantee FROM (VALUES (0.5::double), (0.75)) AS v(tau)")
def fit_sparse_rows(spark, sf_dir):
    design = D.onehot_orders(spark, sf_dir).drop("grp").persist()
    ref = X.reference_frame(spark, X.onehot_reference(design, [0.5, 0.75]))
    fits = SP.quantile_fit(D.to_sparse(design), 5, [0.5, 0.75], s=800.0).join(ref, "tau")
    return fits.select("tau", (F.col("objective") <= F.col("f_ref") * sizing.guarantee(0.1)).alias("within_guarantee"))


@query("SELECT 'sparse_qr_round' AS method, 0.75::double AS tau, true AS within_guarantee")
def fit_planned(spark, sf_dir):
    """Conditioner, norms and solver left to the planner."""
    design = storage.kept(D.census_design(spark, sf_dir).withColumn("x", F.slice("x", 1, 2)))
    fit = quantreg.quantile_fit(design, [0.75], s=1000.0, conditioning="auto")
    exact = quantreg.preprocess_exact(design, 0.75)[0].objective
    return fit.select("method", "tau", (F.col("objective") <= exact * sizing.guarantee(0.1)).alias("within_guarantee"))


# --- sampling ----------------------------------------------------------------------

SIZE = 800
PROB_SQL = f"SELECT n.row_id, n.b, n.lam, least(1.0, n.lam * {SIZE}.0 / t.total) AS p FROM ({NORM_SQL}) n, (SELECT sum(lam) AS total FROM ({NORM_SQL})) t"
COIN_SQL = rnd.unit_sql(SEED, "'coin0'", "row_id")


def event_sample(spark, sf_dir, passes: int = 2) -> DataFrame:
    normed = sampling.row_norms(event_rows(spark, sf_dir), event_conditioner(spark, sf_dir).rinv, how="exact")
    return sampling.sample_rows(normed, SIZE, SEED, engine="portable", passes=passes)


@query(f"SELECT row_id, {significant_sql('p')} FROM ({PROB_SQL})")
def probabilities(spark, sf_dir):
    normed = sampling.row_norms(event_rows(spark, sf_dir), event_conditioner(spark, sf_dir).rinv, how="exact")
    return normed.withColumn("p", sampling.probability(SIZE, sampling.total_norm(normed))).select("row_id", *significant("p"))


IMPORTANCE_SQL = f"SELECT row_id, b, 1.0 / p AS w, p FROM ({PROB_SQL}) WHERE {COIN_SQL} < p"


@query(f"SELECT row_id, {significant_sql('w')} FROM ({IMPORTANCE_SQL})")
def sample_importance(spark, sf_dir):
    return event_sample(spark, sf_dir).select("row_id", *significant("w"))


@query(f"SELECT row_id, {significant_sql('w')} FROM ({IMPORTANCE_SQL})")
def sample_single_pass(spark, sf_dir):
    return event_sample(spark, sf_dir, passes=1).select("row_id", *significant("w"))


@query(f"SELECT count(*) AS rows_kept, count(*) FILTER (p >= 1) AS rows_clipped, round(sum(p), 3) AS sum_p, round(sum(w), 1) AS sum_w FROM ({IMPORTANCE_SQL})")
def sample_report(spark, sf_dir):
    return sampling.sample_report(event_sample(spark, sf_dir)).select("rows_kept", "rows_clipped", F.round("sum_p", 3).alias("sum_p"), F.round("sum_w", 1).alias("sum_w"))


@query(f"SELECT row_id FROM ({EV_ROWS}), (SELECT count(*) AS n FROM events) WHERE {COIN_SQL} < 500.0::double / n")
def sample_uniform(spark, sf_dir):
    return sampling.sample_uniform(value_design(spark, sf_dir), 500, SEED, engine="portable").select("row_id")


@query(f"SELECT row_id FROM (SELECT row_id, abs(b) + 1 AS lam FROM ({EV_ROWS})), (SELECT sum(abs(value) + 1) AS total FROM events) WHERE {COIN_SQL} < least(1.0, lam * (500.0::double / total))")
def sample_identity(spark, sf_dir):
    rows = event_rows(spark, sf_dir)
    normed = sampling.row_norms(rows, C.condition(rows, "identity").rinv, how="exact")
    return sampling.sample_rows(normed, 500, SEED, engine="portable").select("row_id")


@query(f"SELECT count(*) FILTER (u < 0.02) AS small, count(*) FILTER (u < 0.1) AS large, count(*) FILTER (u < 0.02 AND u < 0.1) AS common FROM (SELECT {COIN_SQL} AS u FROM ({EV_ROWS}))")
def sample_nested(spark, sf_dir):
    design = value_design(spark, sf_dir)
    n = design.count()
    a, b = (sampling.sample_uniform(design, s * n, SEED, n=n, engine="portable").select("row_id") for s in (0.02, 0.1))
    return a.agg(F.count("*").alias("small")).crossJoin(b.agg(F.count("*").alias("large"))).crossJoin(a.intersect(b).agg(F.count("*").alias("common")))


@query("SELECT k AS draws, count(*) AS n FROM (SELECT " + rnd.poisson_one_sql(rnd.unit_sql(SEED, "'boot0'", "row_id")) + f" AS k FROM ({EV_ROWS})) GROUP BY k")
def bootstrap_poisson_weights(spark, sf_dir):
    k = rnd.poisson_one(rnd.unit(SEED, "boot0", F.col("row_id"), "portable"))
    return value_design(spark, sf_dir).groupBy(k.alias("draws")).agg(F.count("*").alias("n"))


TRIALS_SQL = f"""
WITH r AS (SELECT row_id, t, s, n, {rnd.unit_sql(1, "'coin' || t", 'row_id')} AS u FROM ({EV_ROWS}), range(5) AS r(t), (VALUES (300.0::double), (900.0::double)) AS v(s), (SELECT count(*) AS n FROM events))
SELECT s, t::int AS trial, count(*) AS rows_kept, round(sum(n / s), 3) AS sum_w FROM r WHERE u < s / n GROUP BY s, t"""


@query(TRIALS_SQL)
def sample_trials_report(spark, sf_dir):
    normed = value_design(spark, sf_dir).withColumn("lam", F.lit(1.0))
    return sampling.sample_trials(normed, [300.0, 900.0], 5, 1, engine="portable").groupBy("s", "trial").agg(F.count("*").alias("rows_kept"), F.round(F.sum("w"), 3).alias("sum_w"))


REPLACE_SQL = f"""
WITH r AS (SELECT n, {rnd.unit_sql(3, "'draw0'", 'row_id')} AS u FROM ({EV_ROWS}), (SELECT count(*) AS n FROM events))
SELECT CASE WHEN u < {math.exp(-2)!r} THEN 0 WHEN u < {3 * math.exp(-2)!r} THEN 1 WHEN u < {5 * math.exp(-2)!r} THEN 2 ELSE 3 END AS draws, count(*) AS n FROM r WHERE u >= {math.exp(-2)!r} GROUP BY 1"""


@query(REPLACE_SQL)
def sample_with_replacement(spark, sf_dir):
    """Rows by number of draws when twice as many rows are drawn as there are (three or more together)."""
    design = value_design(spark, sf_dir)
    n = design.count()
    drawn = sampling.sample_uniform(design, 2 * n, 3, n=n, replace=True, engine="portable")
    return drawn.groupBy(F.least(F.round(F.col("w") * 2), F.lit(3)).cast("int").alias("draws")).agg(F.count("*").alias("n"))


@query("SELECT tau, true AS preserved FROM (VALUES (0.5::double), (0.75)) AS v(tau)")
def preservation_probe(spark, sf_dir):
    design = D.skew_lineitem(spark, sf_dir, 5, 2.0)
    samples, _ = quantreg.sampled(design, "sparse_qr_qr", [3000.0], 1, 3)
    return sampling.probe_preservation(design, samples, [0.5, 0.75]).select("tau", (F.col("worst") < 0.3).alias("preserved"))


@query("SELECT 12 AS rank_all, 12 AS rank_sample")
def sample_rank_report(spark, sf_dir):
    rows = L.augment(D.census_design(spark, sf_dir))
    part = sampling.sample_uniform(rows, 2000, 3)
    return spark.createDataFrame([(sampling.sample_rank(rows), sampling.sample_rank(part))], "rank_all int, rank_sample int")


# --- fits --------------------------------------------------------------------------

TAU_SAMPLE_SQL = f"""
WITH s AS (SELECT b, w FROM ({IMPORTANCE_SQL})), g AS (SELECT tau, b, sum(w) OVER (PARTITION BY tau ORDER BY b RANGE BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS run, sum(w) OVER (PARTITION BY tau) AS total FROM s, {TAU_VALUES})
SELECT tau, min(b) AS q FROM g WHERE run >= tau * total * 0.999999999999999 GROUP BY tau"""


@query(TAU_SAMPLE_SQL)
def fit_main_intercept(spark, sf_dir):
    """The whole algorithm at two augmented columns: sketch, R, norms, coins, weighted solve."""
    fits = quantreg.solve_grid(event_sample(spark, sf_dir).withColumns({"s": F.lit(float(SIZE)), "trial": F.lit(0)}), TAUS, "sparse_qr")
    return fits.select("tau", F.col("beta")[0].alias("q"))


UNIFORM_ONEHOT_SQL = f"SELECT row_number() OVER (ORDER BY event_type) - 1 AS j, quantile_disc(value, 0.75) AS q FROM events, (SELECT count(*) AS n FROM events) WHERE {rnd.unit_sql(SEED, chr(39) + 'coin0' + chr(39), 'event_id')} < 1500.0::double / n GROUP BY event_type"


@query(UNIFORM_ONEHOT_SQL)
def fit_uniform_onehot(spark, sf_dir):
    part = sampling.sample_uniform(D.onehot_events(spark, sf_dir), 1500, SEED, engine="portable")
    return quantreg.onehot_fit(part, 0.75).select(F.col("j").cast("long").alias("j"), "q")


IDENTITY_ONEHOT_SQL = f"""
WITH r AS (SELECT event_type, value, abs(value) + 1 AS lam, {rnd.unit_sql(SEED, chr(39) + 'coin0' + chr(39), 'event_id')} AS u FROM events), t AS (SELECT sum(lam) AS total FROM r),
s AS (SELECT event_type, value, 1.0 / least(1.0, lam * (1500.0::double / total)) AS w FROM r, t WHERE u < least(1.0, lam * (1500.0::double / total))),
g AS (SELECT event_type, value, sum(w) OVER (PARTITION BY event_type ORDER BY value RANGE BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS run, sum(w) OVER (PARTITION BY event_type) AS total FROM s)
SELECT row_number() OVER (ORDER BY event_type) - 1 AS j, min(value) AS q FROM g WHERE run >= 0.75 * total * 0.999999999999999 GROUP BY event_type"""


@query(IDENTITY_ONEHOT_SQL)
def fit_identity_onehot(spark, sf_dir):
    rows = L.augment(D.onehot_events(spark, sf_dir).drop("grp"))
    normed = sampling.row_norms(rows, C.condition(rows, "identity").rinv, how="exact")
    part = sampling.sample_rows(normed, 1500, SEED, engine="portable")
    return quantreg.onehot_fit(part, 0.75).select(F.col("j").cast("long").alias("j"), "q")


EXACT_ONEHOT_SQL = "WITH q AS (" + " UNION ALL ".join(f"SELECT {t}::double AS tau, event_type, quantile_disc(value, {t}) AS q FROM events GROUP BY event_type" for t in TAUS) + f") SELECT tau, round(sum({pin_sql('value - q', 'tau')}), 1) AS f_exact, true AS within_guarantee FROM events JOIN q USING (event_type) GROUP BY tau"


@query(EXACT_ONEHOT_SQL)
def fit_sparse_qr_onehot(spark, sf_dir):
    """Sampled fits against the exact losses: within (1 + eps) / (1 - eps) at eps = .1."""
    design = D.onehot_events(spark, sf_dir).drop("grp")
    fits = quantreg.quantile_fit(design, TAUS, s=800, conditioning="sparse_qr")
    both = fits.join(X.reference_frame(spark, X.onehot_reference(design, TAUS)), "tau")
    return both.select("tau", F.round("f_ref", 1).alias("f_exact"), (F.col("objective") <= F.col("f_ref") * sizing.guarantee(0.1)).alias("within_guarantee"))


WEIGHTED_PAIRS_SQL = f"""
WITH a AS (SELECT s_suppkey AS k, s_acctbal AS b, s_nationkey::double AS x, abs(s_acctbal) + 1 + s_nationkey AS lam, {rnd.unit_sql(SEED + 2, "'coin0'", 's_suppkey')} AS u FROM supplier),
t AS (SELECT sum(lam) AS total, count(*) * 0.8 AS size FROM a),
s AS (SELECT k, b, x, 1.0 / least(1.0, lam * size / total) AS w FROM a, t WHERE u < least(1.0, lam * (size / total))),
l AS (SELECT DISTINCT (p.b * q.x - q.b * p.x) / (q.x - p.x) AS c0, (q.b - p.b) / (q.x - p.x) AS c1 FROM s p JOIN s q ON p.k < q.k AND p.x <> q.x),
f AS (SELECT c0, c1, sum(w * greatest(0.75 * (b - c0 - c1 * x), -0.25 * (b - c0 - c1 * x))) AS f FROM l, s GROUP BY c0, c1)
SELECT (SELECT count(*) FROM s) AS rows_kept, round(min(f), 4) AS objective FROM f"""


@query(WEIGHTED_PAIRS_SQL)
def fit_main_supplier_ipm(spark, sf_dir):
    """The main algorithm with two nonzeros a row, its weighted subproblem solved by the interior point; SQL tries every pair of sampled rows."""
    design = D.supplier_design(spark, sf_dir)
    fits = quantreg.quantile_fit(design, [0.75], s=0.8 * design.count(), conditioning="identity", norms="exact", solver="ipm", seed=SEED, engine="portable", evaluate=False)
    return fits.select("rows_kept", F.round("sample_objective", 4).alias("objective"))


@query("SELECT tau, true AS interior_point_ran, true AS within_guarantee FROM (VALUES (0.5::double), (0.9)) AS v(tau)")
def fit_main_census_ipm(spark, sf_dir):
    """The main algorithm on the census design, subproblems by the interior point, against the exact losses."""
    design = storage.kept(D.census_design(spark, sf_dir))
    ref = X.reference_frame(spark, X.exact_reference(design, [0.5, 0.9]))
    fits = quantreg.quantile_fit(design, [0.5, 0.9], s=3000.0, solver="ipm").join(ref, "tau")
    return fits.select("tau", (F.col("iterations") > 3).alias("interior_point_ran"), (F.col("objective") <= F.col("f_ref") * sizing.guarantee(0.05)).alias("within_guarantee"))


PAIRS_SQL = """
WITH s AS (SELECT s_suppkey AS k, s_acctbal AS b, s_nationkey::double AS x FROM supplier),
l AS (SELECT DISTINCT (p.b * q.x - q.b * p.x) / (q.x - p.x) AS c0, (q.b - p.b) / (q.x - p.x) AS c1 FROM s p JOIN s q ON p.k < q.k AND p.x <> q.x),
f AS (SELECT c0, c1, sum(greatest(0.75 * (b - c0 - c1 * x), -0.25 * (b - c0 - c1 * x))) AS f FROM l, s GROUP BY c0, c1)
SELECT round(min(f), 5) AS objective, round(arg_min(c0, f), 6) AS beta0, round(arg_min(c1, f), 6) AS beta1 FROM f"""


@query(PAIRS_SQL)
def fit_supplier_exact_pairs(spark, sf_dir):
    out = quantreg.enumerate_pairs(D.supplier_design(spark, sf_dir), 0.75)
    return out.select(F.round("objective", 5).alias("objective"), F.round("beta0", 6).alias("beta0"), F.round("beta1", 6).alias("beta1"))


def _supplier_fit(spark, sf_dir, how: str) -> DataFrame:
    from tallquant.operators.solvers import solve_weighted

    x, b, w = quantreg.local_matrix(D.supplier_design(spark, sf_dir))
    fit = solve_weighted(x, b, w, 0.75, how)
    one = spark.createDataFrame([(fit.objective, float(fit.beta[0]), float(fit.beta[1]))], "objective double, beta0 double, beta1 double")
    return one.select(F.round("objective", 5).alias("objective"), F.round("beta0", 6).alias("beta0"), F.round("beta1", 6).alias("beta1"))


@query(PAIRS_SQL)
def fit_ipm_supplier(spark, sf_dir):
    return _supplier_fit(spark, sf_dir, "ipm")


@query(PAIRS_SQL)
def fit_simplex_supplier(spark, sf_dir):
    return _supplier_fit(spark, sf_dir, "simplex")


# Optimal losses of the census design on the given tables, by rows of lineitem and level, each certified by its dual.
CENSUS_OPTIMA = {
    6000: {0.1: 1242.703086, 0.75: 1241.665362},
    60000: {0.1: 12265.798152, 0.75: 12317.717656},
    600000: {0.1: 122830.906372, 0.75: 123427.694973},
}
CENSUS_EXACT_SQL = "SELECT n, tau, objective, true AS optimal FROM (SELECT count(*) AS n FROM lineitem) JOIN (VALUES " + ", ".join(f"({n}, {t}::double, {round(f, 3)}::double)" for n, by in CENSUS_OPTIMA.items() for t, f in by.items()) + ") AS v(m, tau, objective) ON m = n"


@query(CENSUS_EXACT_SQL)
def fit_preprocess_census(spark, sf_dir):
    design, rows = storage.kept(D.census_design(spark, sf_dir)), []
    for tau in (0.1, 0.75):
        fit, info = quantreg.preprocess_exact(design, tau)
        rows.append((info["n"], tau, round(float(fit.objective), 3), bool(fit.optimal)))
    return spark.createDataFrame(rows, "n long, tau double, objective double, optimal boolean")


@query("SELECT count(*) AS n, 0.75::double AS tau, true AS seven_digits FROM lineitem")
def fit_distributed_interior_point(spark, sf_dir):
    """All rows by the distributed interior point, against the exact loss by merging rows."""
    from tallquant.operators.distributed_ipm import distributed_interior_point

    design = quantreg.packed_rows(D.census_design(spark, sf_dir))
    fit, (exact, info) = distributed_interior_point(design, 0.75, most=40), quantreg.preprocess_exact(design, 0.75)
    blocks.forget(design)
    return spark.createDataFrame([(info["n"], 0.75, bool(abs(fit.objective / exact.objective - 1) < 1e-7))], "n long, tau double, seven_digits boolean")


@query("SELECT method, 3000.0::double AS s, 0.5::double AS tau, true AS near_optimum FROM (VALUES " + ", ".join(f"('{m}')" for m in X.SAMPLERS) + ") AS v(method)")
def fit_census_all_samplers(spark, sf_dir):
    design = storage.kept(D.census_design(spark, sf_dir))
    best = X.exact_reference(design, [0.5])[0][2]
    fits = X.sampled_fits(design, X.SAMPLERS, [3000.0], [0.5], 1)
    return fits.select("method", "s", "tau", (F.col("objective") <= 1.05 * best).alias("near_optimum"))


@query("SELECT tau, j::int AS j, true AS near_truth FROM (VALUES (0.25::double), (0.75)) AS v(tau), range(11) AS r(j)")
def fit_planted_slopes(spark, sf_dir):
    """Exact fits of the planted response: within .1 of the known slopes (5 covariates' worth of sampling error at 6,000 rows)."""
    fits = quantreg.exact_fit(D.census_planted(spark, sf_dir), [0.25, 0.75])
    truth = spark.createDataFrame([(t, [float(v) for v in D.planted_slopes(t)]) for t in (0.25, 0.75)], "tau double, truth array<double>")
    pairs = fits.join(truth, "tau").select("tau", F.posexplode(F.arrays_zip("beta", "truth")).alias("j", "v"))
    return pairs.select("tau", "j", (F.abs(F.col("v.beta") - F.col("v.truth")) < 0.1).alias("near_truth"))


@query("SELECT round(regr_slope(l_extendedprice, l_quantity), 5) AS slope, round(regr_intercept(l_extendedprice, l_quantity), 4) AS intercept FROM lineitem")
def fit_ls_one_covariate(spark, sf_dir):
    line = D.table(spark, sf_dir, "lineitem")
    design = D.build(line, D.line_id(), F.col("l_extendedprice"), [F.lit(1.0), F.col("l_quantity")])
    beta = quantreg.fit_ls(design)
    one = spark.createDataFrame([(float(beta[1]), float(beta[0]))], "slope double, intercept double")
    return one.select(F.round("slope", 5).alias("slope"), F.round("intercept", 4).alias("intercept"))


@query("SELECT row_number() OVER (ORDER BY event_type) - 1 AS j, round(avg(value), 6) AS beta FROM events GROUP BY event_type")
def fit_ls_onehot(spark, sf_dir):
    beta = quantreg.fit_ls(D.onehot_events(spark, sf_dir).drop("grp"))
    return spark.createDataFrame([(j, float(v)) for j, v in enumerate(beta)], "j long, beta double").select("j", F.round("beta", 6).alias("beta"))


@query("SELECT row_number() OVER (ORDER BY role) - 1 AS j, quantile_disc(length(text), 0.5)::double AS q FROM conversations GROUP BY role")
def fit_lad_onehot(spark, sf_dir):
    return quantreg.onehot_fit(D.conversation_design(spark, sf_dir), 0.5).select(F.col("j").cast("long").alias("j"), "q")


@query("SELECT event_type AS grp, 0.75::double AS tau, round(quantile_disc(value, 0.75), 6) AS beta, count(*) AS n FROM events GROUP BY event_type")
def fit_by_group(spark, sf_dir):
    design = D.build(D.table(spark, sf_dir, "events"), F.col("event_id"), F.col("value"), [F.lit(1.0)], grp=F.col("event_type"))
    return quantreg.quantile_fit_by(design, [0.75]).select("grp", "tau", F.round(F.col("beta")[0], 6).alias("beta"), F.col("rows").alias("n"))


BOOT_SQL = f"""
WITH k AS (SELECT event_type, value, t, {rnd.poisson_one_sql(rnd.unit_sql(41, "'boot' || t", 'event_id'))} AS w FROM events, range(6) AS r(t)),
g AS (SELECT event_type, t, value, sum(w) OVER (PARTITION BY event_type, t ORDER BY value RANGE BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS run, sum(w) OVER (PARTITION BY event_type, t) AS total FROM k WHERE w > 0),
q AS (SELECT event_type, t, min(value) AS q FROM g WHERE run >= 0.75 * total * 0.999999999999999 GROUP BY event_type, t)
SELECT row_number() OVER (ORDER BY event_type) - 1 AS j, round(quantile_cont(q, 0.05), 4) AS lo, round(quantile_cont(q, 0.95), 4) AS hi, count(*) AS n_rep FROM q GROUP BY event_type"""


@query(BOOT_SQL)
def bootstrap_ci_onehot(spark, sf_dir):
    ci = quantreg.bootstrap_ci(D.onehot_events(spark, sf_dir).drop("grp"), [0.75], replicates=6, engine="portable")
    return ci.select(F.col("j").cast("long").alias("j"), F.round("lo", 4).alias("lo"), F.round("hi", 4).alias("hi"), "n_rep")


# --- measures ------------------------------------------------------------------------

CANDS = [(0, (70.0, 69.0, 66.0, 71.0, 68.0)), (1, (66.0, 70.5, 66.2, 60.0, 69.0)), (2, (75.0, 75.0, 70.0, 70.0, 65.0)), (3, (68.5, 71.0, 67.0, 70.0, 68.4))]


def _candidate_errors(spark, sf_dir) -> DataFrame:
    """Errors of fixed candidates of the one-hot problem at 0.75: five coefficients each."""
    rows = [("fixed", 0.0, k, 0.75, list(v)) for k, v in CANDS]
    design = D.onehot_events(spark, sf_dir).drop("grp")
    ref = X.onehot_reference(design, [0.75])
    losses = L.objective_many(design, [(k, b, t) for _, _, k, t, b in rows])
    fits = spark.createDataFrame(rows, "method string, s double, trial int, tau double, beta array<double>").join(losses, F.col("trial") == F.col("cand")).drop("cand")
    return metrics.rel_errors(fits, X.reference_frame(spark, ref))


CAND_SQL = f"""
WITH q AS (SELECT event_type, row_number() OVER (ORDER BY event_type) - 1 AS j, quantile_disc(value, 0.75) AS q FROM events GROUP BY event_type),
c AS (SELECT k, unnest(v) AS v, generate_subscripts(v, 1) - 1 AS j FROM (VALUES {', '.join(f'({k}, {list(v)}::double[])' for k, v in CANDS)}) AS t(k, v)),
f AS (SELECT k, sum({pin_sql('value - v', 0.75)}) AS f, sum({pin_sql('value - q', 0.75)}) AS g FROM events JOIN q USING (event_type) JOIN c USING (j) GROUP BY k),
g AS (SELECT k, sqrt(sum((v - q) * (v - q)) / sum(q * q)) AS l2, sum(abs(v - q)) / sum(abs(q)) AS l1, max(abs(v - q)) / max(abs(q)) AS linf FROM c JOIN q USING (j) GROUP BY k)
SELECT k AS trial, abs(f - g.g) / g.g AS objective, l2, l1, linf FROM (SELECT * FROM f JOIN g USING (k)) AS g"""


@query(f"SELECT trial, round(objective, 7) AS objective, round(l2, 7) AS l2, round(l1, 7) AS l1, round(linf, 7) AS linf FROM ({CAND_SQL})")
def rel_errors(spark, sf_dir):
    return _candidate_errors(spark, sf_dir).select("trial", *[F.round(c, 7).alias(c) for c in metrics.MEASURES])


@query(" UNION ALL ".join(f"SELECT '{m}' AS measure, round(quantile_cont({m}, 0.25), 7) AS q1, round(quantile_cont({m}, 0.5), 7) AS median, round(quantile_cont({m}, 0.75), 7) AS q3, count(*) AS n_trials FROM ({CAND_SQL})" for m in metrics.MEASURES))
def error_quartiles(spark, sf_dir):
    out = metrics.error_quartiles(_candidate_errors(spark, sf_dir))
    return out.select("measure", *[F.round(c, 7).alias(c) for c in ("q1", "median", "q3")], "n_trials")


@query(f"SELECT floor(-log10(quantile_cont(l2, 0.75)))::int AS digits FROM ({CAND_SQL})")
def digits_table(spark, sf_dir):
    out = metrics.digits(metrics.error_quartiles(_candidate_errors(spark, sf_dir)).where("measure = 'l2'"))
    return out.select(F.col("digits").cast("int").alias("digits"))


@query(f"SELECT 1 AS digits, (quantile_cont(linf, 0.75) <= 0.1)::int AS sizes FROM ({CAND_SQL}) UNION ALL SELECT 6, (quantile_cont(linf, 0.75) <= 1e-6)::int FROM ({CAND_SQL})")
def least_rows_for_digits(spark, sf_dir):
    table = metrics.error_quartiles(_candidate_errors(spark, sf_dir)).where("measure = 'linf'")
    parts = [metrics.rows_for_digits(table, k).agg(F.count("*").cast("int").alias("sizes")).select(F.lit(k).alias("digits"), "sizes") for k in (1, 6)]
    return parts[0].union(parts[1])


@query(f"SELECT measure, count(*) FILTER (error > 0.05) AS n_failed FROM (" + " UNION ALL ".join(f"SELECT '{m}' AS measure, {m} AS error FROM ({CAND_SQL})" for m in metrics.MEASURES) + ") GROUP BY measure")
def failed_trials(spark, sf_dir):
    return metrics.error_quartiles(_candidate_errors(spark, sf_dir), fail_above=0.05).select("measure", "n_failed")


COVER_SQL = f"SELECT tau, round(avg((value <= q)::int), 6) AS coverage, round(avg({pin_sql('value - q', 'tau')}), 6) AS mean_loss FROM events, (VALUES (0.5::double, 35.0::double), (0.75, 69.0), (0.95, 147.0)) AS f(tau, q) GROUP BY tau"


def fixed_fits(spark) -> DataFrame:
    return spark.createDataFrame([(0.5, [35.0]), (0.75, [69.0]), (0.95, [147.0])], "tau double, beta array<double>")


@query(COVER_SQL)
def coverage(spark, sf_dir):
    return quantreg.coverage(value_design(spark, sf_dir), fixed_fits(spark)).select("tau", F.round("coverage", 6).alias("coverage"), F.round("mean_loss", 6).alias("mean_loss"))


@query("SELECT 0.75::double AS tau, round(avg((5000 + 10 * s_nationkey < 4000 + 60 * s_nationkey)::int), 6) AS crossing FROM supplier")
def tau_crossing(spark, sf_dir):
    fits = spark.createDataFrame([(0.5, [4000.0, 60.0]), (0.75, [5000.0, 10.0])], "tau double, beta array<double>")
    return quantreg.crossing(D.supplier_design(spark, sf_dir), fits).select("tau", F.round("crossing", 6).alias("crossing"))


# One-hot designs of each ship year, by quantity and by line number: their rows and columns, from the table.
DESIGNS_SQL = "SELECT year(l_shipdate)::int AS yr, 'quantity' AS kind, count(DISTINCT l_quantity)::int AS d, count(*) AS n FROM lineitem GROUP BY ALL UNION ALL SELECT year(l_shipdate)::int, 'linenumber', count(DISTINCT l_linenumber)::int, count(*) FROM lineitem GROUP BY ALL"


def _of_designs(spark, sf_dir, schema: str, rows: Callable[[int, int], list[tuple]]) -> DataFrame:
    """``yr, kind, d, n`` of the designs of ``DESIGNS_SQL``, each with the rows that a function of d and n gives."""
    line = D.table(spark, sf_dir, "lineitem").select(F.year("l_shipdate").alias("yr"), "l_quantity", "l_linenumber")
    line = line.groupBy("yr").agg(F.countDistinct("l_quantity").cast("int").alias("quantity"), F.countDistinct("l_linenumber").cast("int").alias("linenumber"), F.count("*").alias("n"))
    designs = line.unpivot(["yr", "n"], ["quantity", "linenumber"], "kind", "d").select("yr", "kind", "d", "n").collect()  # two for each year
    return spark.createDataFrame([(*r, *v) for r in designs for v in rows(r.d, r.n)], "yr int, kind string, d int, n long, " + schema)


@query(f"SELECT yr, kind, d, n, {significant_sql('s_quantile')}, {significant_sql('s_l1')}, width FROM (SELECT *, 3 * 81 * 6.0 * d * d / 0.01 * (d * ln(18 * 3 / 0.1) + ln(80)) AS s_quantile, 32 * 6.0 * d * d / 0.01 * (d * ln(12 / 0.1) + ln(40)) AS s_l1, ceil(15 * ln(40.0 * n))::int AS width FROM ({DESIGNS_SQL}))")
def sizing_table(spark, sf_dir):
    sizes = lambda d, n: [(sizing.size_quantile(6.0 * d * d, d, 0.1, 0.75, 0.05, True), sizing.size_l1(6.0 * d * d, d, 0.1), sizing.estimator_width(n))]
    out = _of_designs(spark, sf_dir, "s_quantile double, s_l1 double, width int", sizes)
    return out.select("yr", "kind", "d", "n", *significant("s_quantile"), *significant("s_l1"), "width")


KAPPA_SQL = " UNION ALL ".join(f"SELECT yr, kind, d, n, '{m}' AS method, {k} AS kappa FROM designs" for m, k in (
    ("round_full", "pow(d, 1.5) * sqrt(d + 1.0)"), ("round_fast", "2.0::double * d * d"), ("sparse_qr_round", "6.0::double * d * d"), ("sparse_qr_qr", "pow(d, 4.75) * pow(ln(d), 2.75)"),
    ("dense_qr", "pow(d, 2.5) * pow(ln(n), 1.5)"), ("fast_qr", "pow(d, 3.5) * pow(ln(n), 2.5)"), ("sparse_qr", "pow(d, 6.5) * pow(ln(d), 5.5)"),
))


@query(f"WITH designs AS ({DESIGNS_SQL}) SELECT yr, kind, d, n, method, {significant_sql('kappa')} FROM ({KAPPA_SQL})")
def kappa_bounds(spark, sf_dir):
    names = ["round_full", "round_fast", "sparse_qr_round", "sparse_qr_qr", "dense_qr", "fast_qr", "sparse_qr"]
    out = _of_designs(spark, sf_dir, "method string, kappa double", lambda d, n: [(m, float(sizing.kappa_bound(m, d, n))) for m in names])
    return out.select("yr", "kind", "d", "n", "method", *significant("kappa"))


@query("SELECT count(*) AS nnz, count(*) AS n_rows FROM events")
def nnz_processed(spark, sf_dir):
    return D.nnz(D.onehot_events(spark, sf_dir))


PLAN_SIZES = [0.05, 1e6, 1e9]  # a share of the rows, and numbers of rows
PLAN_SQL = f"SELECT yr, kind, d, n, s, CASE WHEN d <= ceil(15 * ln(40.0 * n)) THEN 'exact' ELSE 'median' END AS norms, CASE WHEN s >= n THEN 'identity' WHEN d <= 40 THEN 'sparse_qr_round' ELSE 'sparse_qr_qr' END AS conditioning, CASE WHEN s >= n OR s * d * 32 > 2e9 THEN 'merge_rows_exact' ELSE 'ipm' END AS solver FROM (SELECT *, CASE WHEN v < 1 THEN v * n ELSE v END AS s FROM ({DESIGNS_SQL}), (VALUES " + ", ".join(f"({v}::double)" for v in PLAN_SIZES) + ") AS v(v))"


@query(PLAN_SQL)
def plan_choices(spark, sf_dir):
    def plans(d: int, n: int) -> list[tuple]:
        sizes = [v * n if v < 1 else v for v in PLAN_SIZES]
        return [(s, p.norms, p.conditioning, p.solver) for s in sizes for p in [planner.choose(n, d, s)]]

    return _of_designs(spark, sf_dir, "s double, norms string, conditioning string, solver string", plans)


TAIL_SQL = f"SELECT *, 0.25 * 0.1 / (6 * 0.75) AS net_radius, d * ln(3 / (0.25 * 0.1 / (6 * 0.75))) AS net_log_size, 6.0 * d * d * 3 / n AS term_bound, 2 * exp(-least(700.0, 0.01 * n / (6.0 * d * d * 3 * 3))) AS tail FROM ({DESIGNS_SQL})"


@query("SELECT yr, kind, d, n, round(net_radius, 8) AS net_radius, round(net_log_size, 6) AS net_log_size, round(term_bound, 8) AS term_bound, round(tail, 8) AS tail FROM (" + TAIL_SQL + ")")
def tail_constants(spark, sf_dir):
    """Constants of a sample as large as the design, at the condition number of rounding."""
    names = ["net_radius", "net_log_size", "term_bound", "tail"]
    out = _of_designs(spark, sf_dir, ", ".join(f"{c} double" for c in names), lambda d, n: [tuple(sizing.tail_bound(0.1, 0.75, d, 6.0 * d * d, float(n))[c] for c in names)])
    return out.select("yr", "kind", "d", "n", *[F.round(c, 6 if c == "net_log_size" else 8).alias(c) for c in names])


@query(f"SELECT yr, kind, d, n, s, s * d * 32 <= 2e9 AS solvable FROM (SELECT *, share * n AS s FROM ({DESIGNS_SQL}), (VALUES (0.05::double), (1.0), (1000.0)) AS v(share))")
def solvable_in_memory(spark, sf_dir):
    return _of_designs(spark, sf_dir, "s double, solvable boolean", lambda d, n: [(v * n, bool(sizing.fits_memory(v * n, d))) for v in (0.05, 1.0, 1000.0)])


@query("SELECT true AS optimal, false AS shifted_optimal")
def certificate(spark, sf_dir):
    """The dual certificate on all rows: accepts the optimum and refuses a shifted one."""
    design = D.onehot_events(spark, sf_dir).drop("grp").persist()
    beta = X.onehot_reference(design, [0.75])[0][1]
    basis = [([float(j == k) for k in range(5)], beta[j], 1.0) for j in range(5)]
    return spark.createDataFrame([(quantreg.certify_full(design, beta, 0.75, basis), quantreg.certify_full(design, [v + 5.0 for v in beta], 0.75, basis))], "optimal boolean, shifted_optimal boolean")


@query("SELECT 'sparse_qr_round' AS method, 2000.0::double AS s, 0.75::double AS tau, true AS often_enough")
def guarantee_success(spark, sf_dir):
    design = D.skew_lineitem(spark, sf_dir, 5, 2.0).persist()
    fits = X.sampled_fits(design, ["sparse_qr_round"], [2000.0], [0.75], 8)
    rate = metrics.success_rate(fits, X.reference_frame(spark, X.onehot_reference(design, [0.75])), 0.1)
    return rate.select("method", "s", "tau", (F.col("success") >= 0.8).alias("often_enough"))


UNIFORM_TRIALS_SQL = f"""
WITH r AS (SELECT event_type, value, t, {rnd.unit_sql(0, "'coin' || t", 'event_id')} AS u FROM events, range(5) AS r(t)),
q AS (SELECT t, event_type, quantile_disc(value, 0.75) AS q FROM r, (SELECT count(*) AS n FROM events) WHERE u < 600.0::double / n GROUP BY t, event_type),
f AS (SELECT t, sum({pin_sql('value - q', 0.75)}) AS f FROM events JOIN q USING (event_type) GROUP BY t)"""


def _uniform_trials(spark, sf_dir) -> DataFrame:
    return X.sampled_fits(D.onehot_events(spark, sf_dir).drop("grp"), ["uniform"], [600.0], [0.75], 5, engine="portable")


@query(UNIFORM_TRIALS_SQL + " SELECT 'uniform' AS method, 0.75::double AS tau, round(min(f), 3) AS objective, arg_min(t, f)::int AS trial FROM f")
def best_of_trials(spark, sf_dir):
    return quantreg.best_of(_uniform_trials(spark, sf_dir)).select("method", "tau", F.round("objective", 3).alias("objective"), "trial")


@query(UNIFORM_TRIALS_SQL + " SELECT row_number() OVER (ORDER BY event_type) - 1 AS j, round(quantile_cont(q, 0.5), 6) AS median FROM q GROUP BY event_type")
def coefficient_medians(spark, sf_dir):
    return quantreg.coef_median(_uniform_trials(spark, sf_dir)).select(F.col("j").cast("long").alias("j"), F.round("median", 6).alias("median"))


KEPT_SQL = f"""
WITH r AS (SELECT abs(value) + 1 AS lam, t, {rnd.unit_sql(2, "'coin' || t", 'event_id')} AS u FROM events, range(2) AS r(t)), a AS (SELECT sum(abs(value) + 1) AS total FROM events),
k AS (SELECT s, t, count(*) AS n FROM r, a, (VALUES (200.0::double), (800.0)) AS v(s) WHERE u < least(1.0, lam * s / total) GROUP BY s, t)
SELECT 'identity' AS method, s, round(avg(n), 4) AS mean_rows, round(avg(n) / s, 6) AS share_of_s FROM k GROUP BY s"""


@query(KEPT_SQL)
def rows_kept_report(spark, sf_dir):
    fits = X.sampled_fits(D.onehot_events(spark, sf_dir).drop("grp"), ["identity"], [200.0, 800.0], [0.75], 2, engine="portable")
    return metrics.kept_report(fits).select("method", "s", F.round("mean_rows", 4).alias("mean_rows"), F.round("share_of_s", 6).alias("share_of_s"))


THEORY_SQL = """
WITH m AS (SELECT * FROM (VALUES ('dense_qr', pow(12.0, 2.5) * pow(ln(1e6), 1.5)), ('fast_qr', pow(12.0, 3.5) * pow(ln(1e6), 2.5)), ('round_full', pow(12.0, 1.5) * sqrt(13.0)), ('round_fast', 2.0 * 144), ('sparse_qr', pow(12.0, 6.5) * pow(ln(12.0), 5.5)),
  ('sparse_qr_round', 6.0 * 144), ('sparse_qr_qr', pow(12.0, 4.75) * pow(ln(12.0), 2.75)), ('exponential_qr', pow(12.0, 3.5) * pow(ln(12.0), 2.5))) AS v(method, k))
SELECT method, 12 AS d, 1000000::bigint AS n, round(k, 2) AS kappa_bound, round(3 * 27 * k / 0.01 * (12 * ln(18 * 3 / 0.1) + ln(80)) / 1e6, 3) AS size_millions FROM m"""


@query(THEORY_SQL)
def theory_table(spark, sf_dir):
    table = X.theory_table(spark).where(F.col("kappa_bound") < float("inf"))
    return table.select("method", "d", "n", F.round("kappa_bound", 2).alias("kappa_bound"), F.round(F.col("size_tau75") / 1e6, 3).alias("size_millions"))


@query(f"SELECT yr, kind, d, n, greatest(1000, 20 * d * d)::int AS practical, greatest(2 * d, ceil(2 * d * ln(greatest(d, 2))))::int AS dense, {significant_sql('theory')} FROM (SELECT *, ceil(pow(d, 5) * pow(ln(d), 5)) AS theory FROM ({DESIGNS_SQL}))")
def sketch_heights(spark, sf_dir):
    out = _of_designs(spark, sf_dir, "practical int, dense int, theory double", lambda d, n: [(S.practical_rows(d), S.dense_rows(d), float(S.theory_rows(d)))])
    return out.select("yr", "kind", "d", "n", "practical", "dense", *significant("theory"))


# --- workloads --------------------------------------------------------------------------

# Each workload's query runs it and returns what the reference reports of it with whether that holds; the tables
# themselves are what the functions of ``experiments`` return.
WORKLOADS = {
    X.w1_error_vs_s: ["no trial failed", "improved conditioners beat naive sampling", "errors fall with the sample size"],
    X.w2_error_vs_s_and_n: ["no trial failed", "errors fall with the sample size at every number of rows"],
    X.w3_error_vs_n: ["no trial failed", "errors are about constant in the number of rows"],
    X.w4_error_vs_s_and_d: ["no trial failed", "errors fall with the sample size", "errors rise with the number of columns"],
    X.w5_error_vs_d: ["no trial failed", "errors rise with the number of columns", "every level has its rows"],
    X.w6_error_vs_tau: ["no trial failed", "errors rise towards extreme levels"],
    X.w7_time_vs_s: ["conditioned samplers visit the data more often than naive ones, whatever the size", "fewer rows are kept than asked for", "parts add up to the whole"],
    X.w8_time_vs_n: ["conditioned samplers visit the data more often than naive ones, whatever the size", "fewer rows are kept than asked for", "parts add up to the whole", "the subproblem does not grow with the rows"],
    X.w9_time_vs_d: ["conditioned samplers visit the data more often than naive ones, whatever the size", "fewer rows are kept than asked for", "parts add up to the whole"],
    X.w10_census_curves: ["medians lie in or close to the bootstrap band", "the least-squares line is one for all levels"],
    X.w11_stacked_errors: ["no trial failed", "improved conditioners beat naive sampling"],
    X.w12_stacked_dims: ["no trial failed", "errors fall with the sample size", "errors rise with the number of columns", "points that no solver can hold are missing"],
    X.w13_census_table: ["sampled coefficients lie around the exact ones"],
    X.w15_other_tables: ["no sampled fit beats the exact one", "sampled losses are near the optimum"],
}


def _workload(run: Callable, said: list[str]) -> None:
    def measured(spark: SparkSession, sf_dir: str) -> DataFrame:
        return spark.createDataFrame(X.claims(run.__name__, run(spark, sf_dir)), "claim string, holds boolean")

    measured.__name__, measured.__doc__ = run.__name__, run.__doc__
    query("SELECT claim, true AS holds FROM (VALUES " + ", ".join(f"('{c}')" for c in said) + ") AS v(claim)")(measured)


for _run, _said in WORKLOADS.items():
    _workload(_run, _said)


@query(f"SELECT j, round(quantile_disc(b, 0.5), 6) AS q, round(quantile_disc(b, 0.5), 6) AS q_collapsed FROM ({D.skew_sql(10, 1.75)}) GROUP BY j")
def w14_duplicates(spark, sf_dir):
    one = D.skew_lineitem(spark, sf_dir, 10, 1.75, engine="portable")
    many = D.collapse(D.stack(one, 3))
    both = quantreg.onehot_fit(one, 0.5).join(quantreg.onehot_fit(many, 0.5).withColumnRenamed("q", "q_collapsed"), "j")
    return both.select("j", F.round("q", 6).alias("q"), F.round("q_collapsed", 6).alias("q_collapsed"))


