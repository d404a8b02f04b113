"""The distributed engine: determinism, exactness, guarantees, trends and plans."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from tallquant.functions import loss as L
from tallquant.operators import conditioning as C
from tallquant.operators import linalg, metrics, quantreg, sampling
from tallquant.operators import sketch as S
from tallquant.plans import experiments as X
from tallquant.plans import planner
from tallquant.sources import design as D
from tallquant.sources import storage


@pytest.fixture(scope="module")
def skew(spark, medium):
    design = D.skew_lineitem(spark, medium, 10, 1.75).persist()
    return design, X.onehot_reference(design, [0.75])


def test_portable_coins(spark):
    from tallquant.functions.randomness import unit

    rows = spark.range(3).select(unit(7, "coin", F.col("id"), "portable").alias("u")).collect()
    assert [r.u for r in rows] == [0.8114196905860244, 0.23381025349195317, 0.3146979558522912]


def test_coins_do_not_depend_on_partitioning(spark, small):
    design = D.onehot_events(spark, small).withColumn("lam", F.lit(1.0))
    a = {r.row_id for r in sampling.sample_rows(design, 100, 5).collect()}
    b = {r.row_id for r in sampling.sample_rows(design.repartition(7), 100, 5).collect()}
    c = {r.row_id for r in sampling.sample_rows(design, 100, 5, passes=1).collect()}
    assert a == b == c and 60 < len(a) < 140


def test_probabilities_hand_value(spark):
    lam = spark.createDataFrame([("a", 1.0), ("b", 1.0), ("c", 8.0)], "row_id string, lam double")
    p = [r.p for r in lam.select(sampling.probability(2, 10.0).alias("p")).collect()]
    assert p == pytest.approx([0.2, 0.2, 1.0])
    assert sampling.expected_size(lam, 2).first()[0] == pytest.approx(1.4)


def test_row_norms_hand_value(spark):
    rows = spark.createDataFrame([("1", [1.0, 2.0]), ("2", [3.0, -4.0])], "row_id string, a array<double>")
    rinv = np.array([[1.0, 0.0], [0.0, 0.5]])
    for f in (lambda: sampling.row_norms(rows, rinv, how="exact"), lambda: sampling.row_norms_sql(rows, rinv)):
        assert {r.row_id: r.lam for r in f().collect()} == {"1": 2.0, "2": 5.0}


def test_tall_qr_equals_local(spark, small):
    rows = L.augment(D.census_design(spark, small)).repartition(9)
    a = np.array([r.a for r in rows.select("a").collect()])
    assert linalg.tall_qr(rows) == pytest.approx(linalg.positive_r(a), rel=1e-8, abs=1e-8)
    assert linalg.gram(rows) == pytest.approx(a.T @ a, rel=1e-9)
    assert linalg.gram_cholesky(rows) == pytest.approx(linalg.positive_r(a), rel=1e-5, abs=1e-4)


def test_sketches_are_linear(spark, small):
    rows = L.augment(D.onehot_events(spark, small).drop("grp"))
    half = F.pmod(F.xxhash64("row_id"), F.lit(2)) == 0
    whole, a, b = (S.sparse_cauchy(x, 32, 1) for x in (rows, rows.where(half), rows.where(~half)))
    both = a.unionByName(b).groupBy("bucket").agg(*[F.sum(f"v{j}").alias(f"v{j}") for j in range(6)])
    assert S.as_matrix(both) == pytest.approx(S.as_matrix(whole), rel=1e-9)


def test_hadamard():
    x = np.random.default_rng(0).normal(size=(8, 3))
    h = np.array([[1.0]])
    for _ in range(3):
        h = np.block([[h, h], [h, -h]])
    assert S.hadamard(x) == pytest.approx(h @ x / np.sqrt(8))


@pytest.mark.parametrize("method", ["sparse_qr", "sparse_qr_round", "sparse_qr_qr", "dense_qr", "fast_qr", "exponential_qr", "round_full", "round_fast"])
def test_conditioners_condition(spark, small, method):
    rows = L.augment(D.census_design(spark, small))
    identity = C.measure_kappa(rows, np.eye(12))
    alpha, beta = C.measure_kappa(rows, C.condition(rows, method).rinv)
    assert alpha * beta < identity[0] * identity[1] / 2


def test_conditioner_round_trip(spark, small):
    c = C.condition(L.augment(D.supplier_design(spark, small)), "sparse_qr")
    path = storage.scratch(spark, "cond")
    storage.save_conditioner(spark, c, path)
    assert storage.load_conditioner(spark, path).r == pytest.approx(c.r)


def test_estimated_norms_in_range(spark, small):
    rows = L.augment(D.skew_lineitem(spark, small, 5, 2.0))
    rinv = C.condition(rows, "sparse_qr").rinv
    both = sampling.row_norms(rows, rinv, how="exact").withColumnRenamed("lam", "exact").join(sampling.row_norms(rows, rinv, how="median", n=6000).select("row_id", "lam"), "row_id")
    assert both.agg(F.avg((F.col("lam") / F.col("exact")).between(0.5, 1.5).cast("double"))).first()[0] >= 0.95


@pytest.mark.parametrize("tau, best", [(0.1, 12265.798152), (0.5, 19654.026669), (0.95, 2791.451547)])
def test_merge_rows_exact(spark, medium, tau, best):
    fit, info = quantreg.preprocess_exact(D.census_design(spark, medium), tau)
    assert fit.optimal and fit.objective == pytest.approx(best, rel=1e-9)
    assert info["wrong"] == 0 and info["middle"] < 0.3 * info["n"]


def test_onehot_exact_both_ways(spark, medium):
    design = D.onehot_orders(spark, medium)
    want = [377470.76, 381987.62, 370101.54, 373312.83, 366508.24]
    for how in ("window", "bracket"):
        assert [r.q for r in quantreg.onehot_fit(design, 0.75, how).orderBy("j").collect()] == want


@pytest.mark.parametrize("tau", [0.001, 0.02, 0.37, 0.999])
def test_bracket_quantile_at_any_level(spark, small, tau):
    rows = D.table(spark, small, "lineitem").select("l_returnflag", "l_extendedprice", "l_quantity")
    a, b = ({r.l_returnflag: r.q for r in quantreg.group_quantile_exact(rows, "l_returnflag", "l_extendedprice", "l_quantity", tau, how).collect()} for how in ("window", "bracket"))
    assert a == b


def test_guarantee(spark, skew):
    design, ref = skew
    fits = X.sampled_fits(design, ["sparse_qr_round"], [3000.0], [0.75], 8)
    assert metrics.success_rate(fits, X.reference_frame(spark, ref), 0.05).first().success >= 0.8


def test_conditioned_samplers_beat_naive_ones(spark, skew):
    design, ref = skew
    table = X.error_table(design, ref, ["sparse_qr_round", "sparse_qr_qr", "identity", "uniform"], [3000.0], [0.75], 8)
    m = {r.method: r["median"] for r in table.where("measure = 'l2'").collect()}
    assert max(m["sparse_qr_round"], m["sparse_qr_qr"]) < 0.8 * min(m["identity"], m["uniform"])


def test_error_falls_with_sample_size(spark, skew):
    design, ref = skew
    table = X.error_table(design, ref, ["sparse_qr_qr"], [600.0, 6000.0], [0.75], 6)
    small, large = (r["median"] for r in table.where("measure = 'l2'").orderBy("s").collect())
    assert large < 0.7 * small


def test_kept_rows_are_fewer_than_asked_for(spark, skew):
    report = metrics.kept_report(X.sampled_fits(skew[0], ["sparse_qr_qr"], [600.0, 50000.0], [0.75], 2)).orderBy("s").collect()
    assert report[1].share_of_s < report[0].share_of_s < 1.2 and report[1].share_of_s < 0.9


def test_preservation(spark, skew):
    samples, _ = quantreg.sampled(skew[0], "sparse_qr_qr", [6000.0], 1, 3)
    assert all(r.worst < 0.15 for r in sampling.probe_preservation(skew[0], samples, [0.5, 0.75]).collect())


def test_planted_slopes(spark, medium):
    fit, _ = quantreg.preprocess_exact(D.census_planted(spark, medium), 0.75)
    assert fit.beta == pytest.approx(D.planted_slopes(0.75), abs=0.05)


def test_stack_and_collapse(spark, small):
    one = D.onehot_events(spark, small).drop("grp")
    many = D.collapse(D.stack(one, 5))
    a, b = ({r.j: r.q for r in quantreg.onehot_fit(x, 0.75).collect()} for x in (one, many))
    assert a == b


def test_bad_rows(spark):
    df = spark.createDataFrame([(1, 1.0), (2, None), (3, float("nan")), (4, float("inf"))], "id int, v double")
    assert D.build(df, F.col("id"), F.col("v"), [F.lit(1.0)]).count() == 1
    with pytest.raises(Exception, match="non-finite"):
        D.build(df, F.col("id"), F.col("v"), [F.lit(1.0)], on_bad="fail").collect()


def test_empty_design(spark, small):
    empty = D.onehot_events(spark, small).drop("grp").where("false")
    assert L.objective(empty, [0.0] * 5, 0.5).first()[0] is None
    assert quantreg.onehot_fit(empty, 0.5).count() == 0
    assert quantreg.quantile_fit(empty, [0.5], s=10.0).count() == 0 and quantreg.quantile_fit(empty, [0.5], eps=0.1).count() == 0 and quantreg.exact_fit(empty, [0.5]).count() == 0
    with pytest.raises(ValueError, match="without rows"):
        quantreg.preprocess_exact(empty, 0.5)


def test_standardise_back(spark, small):
    line = D.table(spark, small, "lineitem")
    design = D.build(line, D.line_id(), F.col("l_extendedprice"), [F.lit(1.0), F.col("l_quantity")])
    scaled, mean, scale = D.standardise(design)
    assert D.unscale(list(quantreg.fit_ls(scaled)), mean, scale) == pytest.approx(list(quantreg.fit_ls(design)), rel=1e-6)


def test_planner():
    assert planner.choose(10**12, 12, 1e5).norms == "exact"
    assert planner.choose(10**4, 11, 1e6).solver == "merge_rows_exact"
    assert planner.choose(10**9, 150, 1e8).solver == "merge_rows_exact"


def plan_of(df) -> str:
    return df._jdf.queryExecution().toString()


def test_sketch_plan_has_one_exchange_of_partial_sums(spark, small):
    plan = plan_of(S.sparse_cauchy(L.augment(D.onehot_events(spark, small).drop("grp")), 64, 1)).split("== Physical Plan ==")[1]
    assert plan.count("Exchange hashpartitioning") == 1 and "partial_sum" in plan


def test_scan_reads_only_design_columns(spark, small):
    plan = plan_of(D.skew_lineitem(spark, small, 5, 2.0).agg(F.sum("b")))
    assert "l_shipdate" not in plan.split("ReadSchema")[1].split("\n")[0]


def test_no_cartesian_product_in_a_fit(spark, small):
    rows = L.augment(D.onehot_events(spark, small).drop("grp"))
    assert "CartesianProduct" not in plan_of(sampling.sample_rows(sampling.row_norms(rows, np.eye(6), how="exact"), 50, 1, total=1.0))


def test_distributed_interior_point(spark, small):
    from tallquant.operators.distributed_ipm import distributed_interior_point

    design = D.census_design(spark, small)
    exact, _ = quantreg.preprocess_exact(design, 0.75)
    fit = distributed_interior_point(design, 0.75)
    assert fit.objective == pytest.approx(exact.objective, rel=1e-6)
    assert fit.iterations < 40


@pytest.mark.parametrize("middle_rows", [4000, 1000])
def test_exact_fit_when_the_band_overflows(spark, medium, middle_rows):
    design = D.census_design(spark, medium).persist()
    want, _ = quantreg.preprocess_exact(design, 0.75)
    fit, info = quantreg.preprocess_exact(design, 0.75, middle_rows=middle_rows)
    design.unpersist()
    assert fit.optimal and 0 < info["middle"] <= middle_rows + 2
    assert fit.objective == pytest.approx(want.objective, rel=1e-9) and list(fit.beta) == pytest.approx(list(want.beta), abs=1e-7)


def interval_rows(frame):
    return [(r.tau, r.j, r.lo, r.hi, r.median, r.n_rep) for r in frame.orderBy("tau", "j").collect()]


def test_bootstrap_resamples_every_row_at_any_size(spark, small):
    onehot = D.onehot_events(spark, small).drop("grp").persist()
    assert interval_rows(quantreg.bootstrap_ci(onehot, [0.75], replicates=6, rows=300)) == interval_rows(quantreg.bootstrap_ci(onehot, [0.75], replicates=6))
    census = D.census_design(spark, small).persist()
    got, want = (interval_rows(quantreg.bootstrap_ci(census, [0.5], replicates=2, rows=rows)) for rows in (3000, 200_000))
    assert [r[:2] for r in got] == [r[:2] for r in want] and np.array(got) == pytest.approx(np.array(want), abs=1e-7)


@pytest.mark.parametrize("columns", [1, 2])
def test_large_groups_are_fitted_on_all_rows(spark, small, columns):
    events = D.table(spark, small, "events")
    grp = F.when(F.col("event_type") != "view", F.col("event_type"))
    design = D.build(events, F.col("event_id"), F.col("value"), [F.lit(1.0), F.col("event_id") % 7][:columns], grp=grp).persist()
    got, want = ({(r.grp, r.tau): r for r in quantreg.quantile_fit_by(design, [0.5, 0.75], group_rows=n).collect()} for n in (10, 500_000))
    assert got.keys() == want.keys() and None in {g for g, _ in got}
    for k, r in got.items():
        assert r.rows == want[k].rows and r.objective == pytest.approx(want[k].objective, rel=1e-9)
        assert columns > 1 or r.beta == want[k].beta


@pytest.mark.parametrize("share", [0.5, 3.0])
def test_sample_with_replacement_keeps_the_total_weight(spark, share):
    n = 40_000
    frame = spark.range(n).select(F.col("id").alias("row_id"), F.lit(1.0).alias("w"))
    total, most = sampling.sample_uniform(frame, share * n, 3, n=n, replace=True).agg(F.sum("w"), F.max(F.col("w") * share)).first()
    assert total == pytest.approx(n, rel=0.03) and most > 1.5


def test_light_passes_give_the_same_sample(spark, small):
    """Sums first, then only surviving rows: the rows of the general functions."""
    design = D.census_design(spark, small)
    rinv = C.condition(L.augment(design), "sparse_qr").rinv
    got = {(r.row_id, r.s, r.trial): r.w for r in sampling.sample_design(design, rinv, [100.0, 400.0], 3, 5).collect()}
    normed = sampling.row_norms(L.augment(design), rinv, how="exact")
    want = {(r.row_id, r.s, r.trial): r.w for r in sampling.sample_trials(normed, [100.0, 400.0], 3, 5).collect()}
    assert got.keys() == want.keys() and len(got) > 1000 and all(got[k] == pytest.approx(want[k], rel=1e-6) for k in got)
    assert sampling.sample_design(design.where("false"), rinv, [100.0], 2, 5).count() == 0


def test_one_pass_sample_scans_once(spark, small):
    """The pass that sums also keeps; every partition keeps about s rows at most."""
    design = D.onehot_events(spark, small).drop("grp").repartition(7).withColumn("lam", F.abs("b") + 1.0)
    seen = spark.sparkContext.accumulator(0)

    def count(batches):
        for batch in batches:
            seen.add(len(batch))
            yield batch

    counted = design.mapInArrow(count, design.schema)
    one = {r.row_id: r.w for r in sampling.sample_rows(counted, 50, 5, passes=1).collect()}
    assert seen.value == design.count()
    assert one == pytest.approx({r.row_id: r.w for r in sampling.sample_rows(design, 50, 5).collect()})


def test_solvers_by_name(spark, small):
    from tallquant.operators.solvers import solve_weighted

    x, b, w = quantreg.local_matrix(D.onehot_events(spark, small))
    fits = {how: solve_weighted(x, b, w, 0.75, how) for how in ("auto", "quantile", "ipm")}
    assert fits["ipm"].iterations > 3 and fits["quantile"].iterations == fits["auto"].iterations == 0
    assert fits["ipm"].objective == pytest.approx(fits["quantile"].objective, rel=1e-9)
    x, b, w = quantreg.local_matrix(D.supplier_design(spark, small))
    assert solve_weighted(x, b, w, 0.75).iterations > 3
    with pytest.raises(ValueError, match="several nonzeros"):
        solve_weighted(x, b, w, 0.75, "quantile")


def test_wide_sketch_in_bounded_blocks(spark, small, monkeypatch):
    """Beyond the width of one SQL aggregate rows are added up in blocks, whatever the height: the sketch is the same."""
    rows = L.augment(D.census_design(spark, small))
    want = S.as_matrix(S.sparse_cauchy(rows, 500, 3))
    monkeypatch.setattr(S, "SQL_WIDTH", 5)
    monkeypatch.setattr(S, "HELD_BYTES", 5000)
    assert S.as_matrix(S.sparse_cauchy(rows, 500, 3)) == pytest.approx(want, rel=1e-9, abs=1e-6)
    assert S.factor(S.sparse_cauchy(rows, 500, 3)) == pytest.approx(linalg.positive_r(want), rel=1e-6, abs=1e-6)


def test_conditioning_of_many_columns(spark, medium):
    """A sketch far taller than the driver would like: R is columns by columns."""
    design = D.skew_lineitem(spark, medium, 120, X.grown(120, 60_000))
    c = C.condition(L.augment(design), "sparse_qr", sketch_rows=40_000)
    assert c.r.shape == (121, 121) and np.isfinite(c.rinv).all()


def test_workload_grids():
    assert X.GRIDS["quick"].keys() == X.GRIDS["paper"].keys()
    assert all(X.GRIDS["quick"][k].keys() == X.GRIDS["paper"][k].keys() for k in X.GRIDS["quick"])
    with pytest.raises(ValueError, match="no parameter"):
        X._grid("w1", "quick", {"sizes": 3})
    assert 165 < 60_000 * (X.grown(10, 60_000) - 1) / (X.grown(10, 60_000) ** 10 - 1) < 175


def test_sparse_rows_equal_dense_ones(spark, small):
    from tallquant.operators import sparse

    design = D.document_design(spark, small).persist()
    rows = D.to_sparse(design)
    dense = S.sparse_cauchy(L.augment(design), 300, 4)
    assert sparse.factor(sparse.sparse_cauchy(sparse.augmented(rows), 300, 4), 17) == pytest.approx(S.factor(dense), rel=1e-6, abs=1e-6)
    rinv = C.condition(L.augment(design), "sparse_qr").rinv
    got = {(r.row_id, r.trial): r.w for r in sparse.sample(rows, rinv, [60.0], 2, 5).collect()}
    want = {(r.row_id, r.trial): r.w for r in sampling.sample_design(design, rinv, [60.0], 2, 5).collect()}
    assert got == pytest.approx(want) and len(got) > 30
    cands = [(0, [1.0] * 16, 0.5), (1, [0.0] * 16, 0.9)]
    assert {r.cand: r.objective for r in sparse.objective_many(rows, cands).collect()} == pytest.approx({r.cand: r.objective for r in L.objective_many(design, cands).collect()})
    monkey = sparse.CELLS
    sparse.CELLS = 40
    try:
        assert {(r.row_id, r.trial): r.w for r in sparse.sample(rows, rinv, [60.0], 2, 5).collect()} == pytest.approx(want)
    finally:
        sparse.CELLS = monkey


def test_sparse_work_follows_the_nonzeros(spark, small):
    """Entries that reach the sketch's exchange are those of the layout, not rows times columns."""
    from tallquant.operators import sparse

    rows = sparse.augmented(D.to_sparse(D.skew_lineitem(spark, small, 40, 1.1)))
    out = sparse.sparse_cauchy(rows, 10**6, 1)
    assert out.count() <= 2 * 6000 and rows.agg(F.sum(F.size("idx"))).first()[0] == 2 * 6000


def test_asof_join_across_bins(spark):
    """A value is carried over bins that hold none, for every key, null included."""
    from datetime import datetime, timedelta

    from tallquant.operators.relational import asof_join

    t0 = datetime(2024, 1, 1)
    left = [(k, t0 + timedelta(hours=h), h) for k in (1, 2, None) for h in range(0, 200, 9)]
    right = [(1, t0 + timedelta(hours=5), 10.0), (1, t0 + timedelta(hours=30), None), (1, t0 + timedelta(hours=90), 20.0), (None, t0 + timedelta(hours=9), 7.0), (2, t0 + timedelta(hours=500), 1.0)]
    out = asof_join(spark.createDataFrame(left, "k int, ts timestamp, h int"), spark.createDataFrame(right, "k int, ts timestamp, v double"), "k", "ts", "v", "got").collect()
    for r in out:
        seen = [(t, v) for k, t, v in right if k == r.k and t <= r.ts and v is not None]
        assert r.got == (max(seen)[1] if seen else None)
    assert len(out) == len(left)
