"""Queries at sizes where they failed: the whole job with the same result, in bounded memory and disk."""

import pytest

from tallquant.operators import quantreg
from tallquant.sources import design as D


def test_pairs_beyond_brute_force(spark, small):
    design = D.supplier_design(spark, small)
    brute, met = (quantreg.enumerate_pairs(design, 0.75, **most).first() for most in ({}, {"most": 3}))
    assert tuple(met) == pytest.approx(tuple(brute), rel=1e-9)
    copies = D.stack(design, 3001)
    assert copies.count() > 3000
    assert quantreg.enumerate_pairs(copies, 0.75).first().objective == pytest.approx(3001 * brute.objective, rel=1e-9)


@pytest.mark.parametrize("name", ["stream_late", "stream_repeated", "stream_sessions", "stream_static_join"])
def test_streams_gather_nothing(spark, small, name, monkeypatch):
    """Rows of a stream go to files, not to the driver's memory sink."""
    from tallquant.plans import relational
    from tallquant.streaming import streams

    drained, drain = [], streams.drain
    monkeypatch.setattr(streams, "drain", lambda *a: drained.append(drain(*a)) or drained[-1])
    getattr(relational, name)(spark, small).collect()
    assert drained and all(d.inputFiles() for d in drained)


def test_interior_point_keeps_one_iterate(spark, small, tmp_path, monkeypatch):
    """Iterates of rows go when the next one is written."""
    from tallquant.operators import distributed_ipm

    monkeypatch.setattr(distributed_ipm, "scratch", lambda spark, name: str(tmp_path / name))
    assert distributed_ipm.distributed_interior_point(D.onehot_events(spark, small), 0.5).iterations > 3
    assert len([p for p in (tmp_path / "ipm").iterdir() if p.is_dir()]) == 1


def test_timed_interior_point_over_the_cluster(spark, small, monkeypatch):
    """A design beyond what the driver may hold is not gathered there."""
    from tallquant.plans import experiments

    design = D.onehot_events(spark, small).drop("grp")
    n = design.count()
    monkeypatch.setattr(quantreg, "DRIVER_CELLS", 10)
    monkeypatch.setattr(quantreg, "local_matrix", lambda design: pytest.fail("gathered"))
    (row,) = experiments.timed(spark, design, ["interior_point"], 100.0, [0.5], {"n": n, "d": 5})
    assert row[0] == "interior_point" and row[-1] == n


def test_exact_fits_read_the_design_once(spark, small, monkeypatch):
    """All levels and passes visit packed blocks, and a band of too many rows needs no fit over the cluster."""
    from pyspark.sql import functions as F

    from tallquant.operators import distributed_ipm
    from tallquant.sources import blocks

    design = D.census_planted(spark, small)
    want = {r.tau: r.objective for r in quantreg.exact_fit(design, [0.25, 0.75]).collect()}
    monkeypatch.setattr(quantreg, "DRIVER_CELLS", 12_000)
    monkeypatch.setattr(distributed_ipm, "distributed_interior_point", lambda *a: pytest.fail("whole design"))
    read = spark.sparkContext.accumulator(0)

    def seen(batches):
        for batch in batches:
            read.add(len(batch))
            yield batch

    counted = design.select("row_id", "b", "x", "w").mapInArrow(seen, "row_id string, b double, x array<double>, w double")
    packed = quantreg.packed_rows(counted)
    for tau in want:
        fit, info = quantreg.preprocess_exact(packed, tau, middle_rows=1500)
        assert fit.objective == pytest.approx(want[tau], rel=1e-9) and info["middle"] <= 1502
    assert read.value == blocks.height(packed) == packed.agg(F.sum("n")).first()[0]


def test_rounding_reads_the_rows_once(spark, small, monkeypatch):
    """Rounds of the slab method visit packed blocks, with the same R as rounds over rows gathered on the driver."""
    import numpy as np

    from tallquant.functions.loss import augment, batch_matrix
    from tallquant.operators import linalg
    from tallquant.sources import blocks

    rows = augment(D.onehot_events(spark, small)).select("a")
    read = spark.sparkContext.accumulator(0)

    def seen(batches):
        for batch in batches:
            read.add(len(batch))
            yield batch

    a = batch_matrix(rows.toArrow().column(0))
    packed = blocks.pack(rows.mapInArrow(seen, "a array<double>"), "a")
    r, rounds = linalg.round_full(packed, "a", "slab")
    want, local = linalg.round_slab(lambda rinv: linalg.local_slab_stats(a, rinv), linalg.positive_r(a))
    assert rounds == local and np.allclose(r, want) and read.value == len(a)


def test_large_samples_stay_in_a_table(spark, small, monkeypatch):
    """A timed sample beyond what the driver may hold is solved by merging its rows, to the same number of rows kept."""
    from tallquant.plans import experiments

    design, label = D.onehot_events(spark, small).drop("grp"), {"n": 100, "d": 5}
    (want,) = experiments.timed(spark, design, ["identity"], 60.0, [0.5, 0.75], label)
    fits, exact = [], quantreg.preprocess_exact
    monkeypatch.setattr(quantreg, "DRIVER_CELLS", 10)
    monkeypatch.setattr(quantreg, "solve_group", lambda *a: pytest.fail("gathered"))
    monkeypatch.setattr(quantreg, "preprocess_exact", lambda *a, **k: fits.append(exact(*a, **k)) or fits[-1])
    (row,) = experiments.timed(spark, design, ["identity"], 60.0, [0.5, 0.75], label)
    assert row[-1] == want[-1] and len(fits) == 2


def test_planned_fit_joins_once(spark, small, monkeypatch):
    """The passes of the planned fit read the kept design, not the tables it is joined from."""
    from tallquant.plans import catalog

    read, fit = [], quantreg.quantile_fit
    monkeypatch.setattr(quantreg, "quantile_fit", lambda design, *a, **k: read.extend(design.inputFiles()) or fit(design, *a, **k))
    assert catalog.QUERIES["fit_planned"](spark, small).first().within_guarantee
    assert read and not any("lineitem" in f or "orders" in f for f in read)


def test_arrivals_in_pieces(spark, small, monkeypatch):
    """A large arrival is written and read in pieces, all of them in its own batch."""
    from tallquant.plans import relational
    from tallquant.streaming import streams

    paths, write = [], streams.events_in_files
    monkeypatch.setattr(relational, "PIECE_ROWS", 400)
    monkeypatch.setattr(streams, "events_in_files", lambda *a: paths.append(write(*a)) or paths[-1])
    n = spark.read.parquet(f"{small}/events.parquet").count()
    assert tuple(relational.stream_repeated(spark, small).first()) == (n, n)
    assert len(spark.read.parquet(paths[0]).inputFiles()) == 4 * (1 + n // 400)


def test_levels_share_passes(spark, small, monkeypatch):
    """Exact fits of all levels come from the same passes over blocks, with the losses of one fit after the other."""
    from tallquant.operators import packed

    design, taus = D.census_design(spark, small), [0.1, 0.5, 0.9]
    want = [r.objective for r in quantreg.exact_fit(design, taus).collect()]
    rows = packed.pack(design, 2)
    monkeypatch.setattr(quantreg, "preprocess_exact", lambda *a, **k: pytest.fail("one level after the other"))
    found = packed.fit_many(rows, taus, most=2500, rough_rows=1500)
    assert found.objective[:, 0] == pytest.approx([2 * f for f in want], rel=1e-9) and found.passes <= 13
    assert rows.rows == found.kept[0] == 2 * rows.n


def test_census_table_stores_one_copy(spark, small, monkeypatch):
    from tallquant.plans import catalog

    monkeypatch.setattr(D, "stack", lambda *a: pytest.fail("copies written out"))
    assert all(r.holds for r in catalog.QUERIES["w13_census_table"](spark, small).collect())


def test_replicates_share_passes(spark, small, monkeypatch):
    """Resamples solved by merging rows are those solved with all rows, and the curves fit none on its own."""
    from tallquant.operators import packed
    from tallquant.plans import catalog

    monkeypatch.setattr(quantreg, "preprocess_exact", lambda *a, **k: pytest.fail("one replicate after the other"))
    rows = packed.pack(D.census_design(spark, small))
    centres = packed.fit_many(rows, [0.5, 0.9]).beta[:, 0]
    draws = packed.poisson(rows, [0, 1, 2])
    every = packed.fit_many(rows, [0.5, 0.9], draws, centres.copy(), most=10**6)
    few = packed.fit_many(rows, [0.5, 0.9], draws, centres.copy(), most=4000)
    assert few.own == pytest.approx(every.own, rel=1e-9) and (few.weight == every.weight).all()
    assert few.weight == pytest.approx([rows.n] * 3, rel=0.1)
    assert all(r.holds for r in catalog.QUERIES["w10_census_curves"](spark, small).collect())


def test_stacked_samples(spark, small, monkeypatch):
    """Copies have coins of their own though rows are stored once, and merged samples are solved as with all their rows."""
    from tallquant.operators import packed
    from tallquant.plans import experiments

    design = D.skew_lineitem(spark, small, 4, 2.0)
    rows = packed.pack(design, 3)
    centres = packed.onehot_quantiles(rows, [0.5, 0.75])
    for method in ("uniform", "dense_qr"):
        rinv = None if method == "uniform" else packed.condition(rows, method).rinv
        draws = packed.importance(rows, rinv, [(3000.0, 0), (3000.0, 1)], 5)
        every = packed.fit_many(rows, [0.5, 0.75], draws, centres.copy(), most=10**6)
        few = packed.fit_many(rows, [0.5, 0.75], draws, centres.copy(), most=2500)
        assert few.own == pytest.approx(every.own, rel=1e-9) and few.kept[0] != few.kept[1]
        assert few.weight == pytest.approx([rows.rows] * 2, rel=0.1) and max(few.kept) <= 3300
    monkeypatch.setattr(D, "stack", lambda *a: pytest.fail("copies written out"))
    table = experiments.w11_stacked_errors(spark, small, methods=["sparse_qr", "identity"])
    assert {r.n_trials for r in table.collect()} == {4}


def test_onehot_quantiles_by_brackets(spark, small):
    """Quantiles of packed columns equal grouped quantiles: from a bracket, from a whole column."""
    from tallquant.operators import packed
    from tallquant.plans import experiments

    design, taus = D.skew_lineitem(spark, small, 4, 2.0), [0.0005, 0.5, 0.95]
    want = [tuple(b) for _, b, _ in experiments.onehot_reference(design, taus)]
    rows = packed.pack(design)
    for rough in (400_000, 4000):
        assert [tuple(b) for b in packed.onehot_quantiles(rows, taus, rough)] == want
    (half, whole) = ([loss for *_, loss in experiments.packed_reference(r, [0.5])][0] for r in (rows, packed.Packed(rows.frame, rows.n, rows.d, 2)))
    assert whole == pytest.approx(2 * half, rel=1e-12)


def test_interior_point_reads_the_design_once(spark, small):
    """Iterations visit packed blocks, given or made once, with the loss of the fit that merges rows."""
    from tallquant.operators import distributed_ipm
    from tallquant.plans import catalog

    design, read = D.census_design(spark, small), spark.sparkContext.accumulator(0)

    def seen(batches):
        for batch in batches:
            read.add(len(batch))
            yield batch

    counted = design.select("row_id", "b", "x", "w").mapInArrow(seen, "row_id string, b double, x array<double>, w double")
    packed = quantreg.packed_rows(design)
    want = quantreg.preprocess_exact(packed, 0.75)[0].objective
    for rows in (counted, packed):
        fit = distributed_ipm.distributed_interior_point(rows, 0.75)
        assert fit.optimal and fit.objective == pytest.approx(want, rel=1e-7)
    assert read.value == design.count()
    assert catalog.QUERIES["fit_distributed_interior_point"](spark, small).first().seven_digits


def test_timed_methods_share_packed_rows(spark, small):
    """All timed methods visit the blocks of one design, which is read once; samples keep about the rows asked for."""
    from tallquant.plans import experiments

    design, read = D.onehot_events(spark, small).drop("grp"), spark.sparkContext.accumulator(0)

    def seen(batches):
        for batch in batches:
            read.add(len(batch))
            yield batch

    n = design.count()
    counted = design.select("row_id", "b", "x", "w").mapInArrow(seen, "row_id string, b double, x array<double>, w double")
    rows = experiments.timed(spark, counted, ["sparse_qr", "uniform", "interior_point", "merge_rows_exact"], 200.0, [0.5], {"n": n, "d": 5})
    assert read.value == n and [r[-2] for r in rows[:2]] == [3, 2]
    assert all(100 < r[-1] < 300 for r in rows[:2]) and rows[2][-1] == n


def test_blocks_of_one_task_are_dealt_to_all_cores(spark):
    import numpy as np

    from tallquant.sources import blocks

    packed = blocks.pack(spark.range(0, 45_000, 1, 1).selectExpr("cast(id as double) as v", "1.0D as u"), "rows")
    assert len(packed.inputFiles()) >= 4 and blocks.height(packed) == 45_000
    assert (np.sort(blocks.gathered(packed, "rows")[:, 0]) == np.arange(45_000)).all()


def test_rounding_without_rows_of_a_column():
    """A column that the sample missed stays out of the rounding, as it does out of the second QR."""
    import numpy as np

    from tallquant.operators import conditioning, linalg

    a = np.random.default_rng(0).normal(size=(200, 3))
    want, gap = conditioning.rounded(a), np.insert(a, 1, 0.0, axis=1)
    for rounding in ("density", "slab"):
        r = conditioning.rounded(gap, rounding)
        assert not r[1].any() and not r[:, 1].any() and np.isfinite(conditioning._finish("sparse_qr_round", r, 3, 0.0, 200).rinv).all()
    assert np.allclose(conditioning.rounded(gap)[np.ix_([0, 2, 3], [0, 2, 3])], want)
    r0 = linalg.positive_r(a)
    assert np.allclose(want, linalg.round_density(linalg.local_density_gram(a), r0.T @ r0 / np.sqrt(3))[0])
