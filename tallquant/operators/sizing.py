"""Sample-size rules, condition-number bounds and tail constants."""

from __future__ import annotations

import math

from tallquant.functions.loss import skew_ratio

METHODS = ("dense_qr", "fast_qr", "round_full", "round_fast", "sparse_qr", "sparse_qr_round", "sparse_qr_qr", "exponential_qr", "identity", "uniform")


def kappa_bound(method: str, d: int, n: int) -> float:
    """Order of the l1 condition number that a conditioner guarantees."""
    ld, ln = math.log(max(d, 2)), math.log(max(n, 2))
    return {
        "dense_qr": d**2.5 * ln**1.5,
        "fast_qr": d**3.5 * ln**2.5,
        "round_full": d**1.5 * (d + 1) ** 0.5,
        "round_fast": 2.0 * d**2,
        "sparse_qr": d**6.5 * ld**5.5,
        "exponential_qr": d**3.5 * ld**2.5,
        "sparse_qr_round": 6.0 * d**2,
        "sparse_qr_qr": d**4.75 * ld**2.75,
    }.get(method, math.inf)


def size_quantile(kappa: float, d: int, eps: float, tau: float, delta: float = 0.05, estimated: bool = False) -> float:
    """Rows for a (1 +- eps) quantile-loss preserving sample; three times as many with estimated row norms."""
    mu = skew_ratio(tau)
    factor = 81.0 if estimated else 27.0
    return mu * factor * kappa / eps**2 * (d * math.log(18 * mu / eps) + math.log(4 / delta))


def size_l1(kappa: float, d: int, eps: float, delta: float = 0.05) -> float:
    """Rows for a (1 +- eps) l1-preserving sample."""
    return 32.0 * kappa / eps**2 * (d * math.log(12 / eps) + math.log(2 / delta))


def guarantee(eps: float) -> float:
    """Loss ratio that holds with probability 0.8."""
    return (1 + eps) / (1 - eps)


def estimator_width(n: int) -> int:
    """Cauchy columns of the median estimator of row norms."""
    return math.ceil(15 * math.log(40 * n))


def norms_choice(d: int, n: int) -> str:
    """Exact norms cost d a nonzero, estimated ones the width of the estimator."""
    return "exact" if d <= estimator_width(n) else "median"


def tail_bound(eps: float, tau: float, d: int, kappa: float, s: float) -> dict[str, float]:
    """Net radius and size, variance bound and Bernstein tail behind the size rule (for tests and teaching)."""
    gamma = (1 - tau) * eps / (6 * tau)
    return {"net_radius": gamma, "net_log_size": d * math.log(3 / gamma), "term_bound": kappa * skew_ratio(tau) / s, "tail": 2 * math.exp(-min(700.0, eps**2 * s / (kappa * skew_ratio(tau) * 3)))}


def fits_memory(s: float, d: int, budget_bytes: float = 2e9) -> bool:
    """Whether the subproblem of s rows can be held (with working copies) by one solver."""
    return s * d * 8 * 4 <= budget_bytes
