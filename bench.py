"""Headline queries of the engine: prints one JSON line.

Environment: BENCH_SF_DIR (default /root/testdata/sf0.1), BENCH_CPUS (default 4).
Each query is run once to warm the session on a small share, then timed once.
"""

from __future__ import annotations

import json
import os
import sys
import time
from pathlib import Path

sys.path.insert(0, str(Path(__file__).resolve().parent))

from pyspark.sql import functions as F  # noqa: E402

from tallquant.functions.loss import augment, objective_many  # noqa: E402
from tallquant.operators import quantreg, sampling  # noqa: E402
from tallquant.operators import sketch as S  # noqa: E402
from tallquant.operators import sparse  # noqa: E402
from tallquant.operators.conditioning import condition  # noqa: E402
from tallquant.plans import experiments as X  # noqa: E402
from tallquant.session import local_session, ship  # noqa: E402
from tallquant.sources import design as D  # noqa: E402

TAUS = [0.5, 0.75, 0.95]
#: Copies of the census rows in the comparison of sampled and exact fits at a size where sampling pays.
STACK = 8


def three_levels(x, b):
    """All rows on the driver, one interior point a level, like the three levels of a sampled fit."""
    return [quantreg.interior_point(x, b, tau) for tau in TAUS]


def main() -> None:
    sf_dir = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    cpus = int(os.environ.get("BENCH_CPUS", "4"))
    spark = local_session(cores=cpus, shuffle_partitions=2 * cpus, memory=os.environ.get("BENCH_MEMORY", "4g"))
    ship(spark)
    d, q = X.shape_for(sf_dir)
    skew = D.skew_lineitem(spark, sf_dir, d, q).persist()
    census = D.census_design(spark, sf_dir).persist()
    n = skew.count()
    census.count()
    s = min(50_000.0, 0.1 * n)

    big, entries = D.stack(census, STACK), D.to_sparse(skew).persist()
    entries.count()

    def fit(design, method, size=s):
        return quantreg.quantile_fit(design, TAUS, s=size, conditioning=method, solver="ipm").collect()

    queries = {
        "sketch_sparse_cauchy": lambda: S.factor(S.sparse_cauchy(augment(skew), S.practical_rows(d + 1), 1)),
        "row_norms_exact": lambda: sampling.row_norms(augment(skew), X.np.eye(d + 1), how="exact").agg(F.sum("lam")).collect(),
        "objective_150_candidates": lambda: objective_many(skew, [(k, [0.01 * k] * d, 0.75) for k in range(150)]).collect(),
        **{f"fit_skew_{m}": (lambda m=m: fit(skew, m)) for m in ("sparse_qr", "sparse_qr_round", "sparse_qr_qr", "dense_qr", "identity", "uniform")},
        "fit_census_sparse_qr_qr": lambda: fit(census, "sparse_qr_qr"),
        "exact_census_merge_rows": lambda: [quantreg.preprocess_exact(census, tau) for tau in TAUS],
        "exact_census_interior_point": lambda: three_levels(*quantreg.local_matrix(census)[:2]),
        "exact_onehot_bracket": lambda: quantreg.onehot_fit(skew, 0.75, how="bracket").collect(),
        "exact_onehot_window": lambda: quantreg.onehot_fit(skew, 0.75, how="window").collect(),
        "condition_round_fast": lambda: condition(augment(census), "round_fast"),
        "condition_round_full": lambda: condition(augment(census), "round_full"),
        "fit_skew_sparse_rows": lambda: sparse.quantile_fit(entries, d, TAUS, s=s, solver="ipm").collect(),
        f"fit_census_x{STACK}_sparse_qr_qr": lambda: fit(big, "sparse_qr_qr", 50_000.0),
        f"exact_census_x{STACK}_merge_rows": lambda: [quantreg.preprocess_exact(big, tau) for tau in TAUS],
        f"exact_census_x{STACK}_interior_point": lambda: three_levels(*quantreg.local_matrix(big)[:2]),
        "samples_50_trials": lambda: sampling.sample_trials(skew.withColumn("lam", F.lit(1.0)), [s / 10], 50, 1).count(),
    }
    fit(D.prefix(skew, 0.05), "sparse_qr_qr")
    seconds = {}
    for name, run in queries.items():
        start = time.time()
        run()
        seconds[name] = round(time.time() - start, 3)
        if os.environ.get("BENCH_VERBOSE"):
            print(name, seconds[name], file=sys.stderr, flush=True)
    print(json.dumps({"metric": "total_seconds", "value": round(sum(seconds.values()), 3), "unit": "sec", "queries": seconds, "sf": os.path.basename(sf_dir.rstrip("/")), "rows": n, "columns": d, "sample_rows": s}))
    sys.stdout.flush()
    os._exit(0)


if __name__ == "__main__":
    main()
