"""Builder-time choices, returned as a record instead of hidden in the code path."""

from __future__ import annotations

from dataclasses import asdict, dataclass

from tallquant.operators import sizing
from tallquant.operators.sketch import SQL_WIDTH, practical_rows


@dataclass
class Plan:
    """What a fit will do, and why."""

    layout: str
    norms: str
    conditioning: str
    sketch_rows: int
    sample_passes: int
    solver: str
    reasons: dict[str, str]

    def record(self) -> dict:
        return asdict(self)


def choose(n: int, d: int, s: float, nnz_share: float = 1.0, one_nonzero: bool = False, memory_bytes: float = 2e9) -> Plan:
    """Layout, norms, conditioner, passes and solver for a design of n rows and d columns."""
    why: dict[str, str] = {}
    if one_nonzero:
        why["solver"] = "one nonzero in each row: the problem is one quantile for each column"
        return Plan("sparse", "exact", "uniform" if s >= n else "sparse_qr_qr", practical_rows(d), 1, "grouped_quantile", why)
    layout = "sparse" if nnz_share < 0.2 else "wide" if d <= SQL_WIDTH else "dense"
    why["layout"] = f"{nnz_share:.0%} of entries, {d} columns"
    norms = sizing.norms_choice(d, n)
    why["norms"] = f"exact costs {d} a nonzero, estimated {sizing.estimator_width(n)}"
    if s >= n:
        why["solver"] = "the sample would be all rows"
        return Plan(layout, norms, "identity", 0, 1, "merge_rows_exact", why)
    conditioning = "sparse_qr_round" if d <= 40 else "sparse_qr_qr"
    why["conditioning"] = "rounding is most accurate while it is cheap; the second QR scales further"
    solver = "ipm" if sizing.fits_memory(s, d, memory_bytes) else "merge_rows_exact"
    why["solver"] = "the subproblem fits one executor" if solver == "ipm" else "the subproblem exceeds one executor"
    passes = 1 if s < 1e6 else 2
    why["passes"] = "rows kept by one ordered pass" if passes == 1 else "a second pass is cheaper than ordering the kept rows"
    return Plan(layout, norms, conditioning, practical_rows(d), passes, solver, why)
