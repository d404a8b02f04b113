"""Local exact solvers of the weighted quantile problem, and the certificate of optimality.

All take numpy arrays ``x`` (rows by columns), ``b`` and optional weights ``w``.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np


def loss(x: np.ndarray, b: np.ndarray, w: np.ndarray, tau: float, beta: np.ndarray) -> float:
    r = b - x @ beta
    return float(w @ np.maximum(tau * r, (tau - 1) * r))


@dataclass
class Fit:
    beta: np.ndarray
    objective: float
    iterations: int
    optimal: bool


def _to_boundary(v: np.ndarray, step: np.ndarray) -> float:
    down = step < 0
    return float((-v[down] / step[down]).min()) if down.any() else np.inf


def interior_point(x: np.ndarray, b: np.ndarray, tau: float, w: np.ndarray | None = None, tol: float = 1e-9, most: int = 80) -> Fit:
    """Primal-dual predictor-corrector on the bounded dual: maximise b'a with x'a fixed and 0 <= a <= 1.

    Each iteration solves one system of the size of the columns.  The end point
    is moved to a vertex if that does not raise the loss.
    """
    n, p = x.shape
    w = np.ones(n) if w is None else w
    live = w > 0
    x, b, w = x[live], b[live], w[live]
    scale = np.maximum(np.abs(x).max(axis=0), 1e-300) if len(x) else np.ones(p)
    a_mat, y = x * w[:, None] / scale, b * w
    n = len(y)
    if not n:
        return Fit(np.full(p, np.nan), 0.0, 0, False)
    dual = np.full(n, 1.0 - tau)
    room = 1.0 - dual
    beta = np.linalg.lstsq(a_mat, y, rcond=None)[0]
    r = y - a_mat @ beta
    tiny = 1e-3 * (np.abs(r).mean() + 1e-12)
    high, low = np.maximum(r, 0) + tiny, np.maximum(-r, 0) + tiny  # multipliers of a <= 1 and a >= 0
    it = 0

    def solve(q: np.ndarray, rhs: np.ndarray) -> np.ndarray:
        m = (a_mat * q[:, None]).T @ a_mat
        ridge = 1e-14 * np.trace(m) / p
        try:
            return np.linalg.solve(m + ridge * np.eye(p), rhs)
        except np.linalg.LinAlgError:
            return np.linalg.lstsq(m, rhs, rcond=None)[0]

    for it in range(1, most + 1):
        resid = y - a_mat @ beta - high + low  # dual feasibility of the pair
        gap = float(low @ dual + high @ room)
        total = float(np.maximum(tau * (y - a_mat @ beta), (tau - 1) * (y - a_mat @ beta)).sum())
        if gap <= tol * (1.0 + abs(total)) and np.abs(resid).max() <= 1e-8 * (1 + np.abs(y).max()):
            break
        q = 1.0 / (low / dual + high / room)
        ask = (1.0 - tau) * a_mat.sum(axis=0) - a_mat.T @ dual

        def direction(c_low: np.ndarray, c_high: np.ndarray) -> tuple[np.ndarray, ...]:
            # complementarity targets: low * da + dual * dlow = c_low, and so on
            g = resid + c_low / dual - c_high / room  # noqa: B023
            dbeta = solve(q, a_mat.T @ (q * g) - ask)  # noqa: B023
            da = q * (g - a_mat @ dbeta)  # noqa: B023
            return dbeta, da, (c_low - low * da) / dual, (c_high + high * da) / room  # noqa: B023

        dbeta, da, dlow, dhigh = direction(-low * dual, -high * room)
        up = min(1.0, 0.99995 * min(_to_boundary(dual, da), _to_boundary(room, -da)))
        down = min(1.0, 0.99995 * min(_to_boundary(low, dlow), _to_boundary(high, dhigh)))
        after = float((low + down * dlow) @ (dual + up * da) + (high + down * dhigh) @ (room - up * da))
        mu = (after / gap) ** 3 * gap / (2 * n) if gap > 0 else 0.0
        dbeta, da, dlow, dhigh = direction(mu - low * dual - da * dlow, mu - high * room + da * dhigh)
        up = min(1.0, 0.99995 * min(_to_boundary(dual, da), _to_boundary(room, -da)))
        down = min(1.0, 0.99995 * min(_to_boundary(low, dlow), _to_boundary(high, dhigh)))
        dual, room = dual + up * da, room - up * da
        beta, low, high = beta + down * dbeta, low + down * dlow, high + down * dhigh
    beta = beta / scale
    f = loss(x, b, w, tau, beta)
    vertex = to_vertex(x, b, beta)
    if vertex is not None:
        g = loss(x, b, w, tau, vertex)
        if g <= f * (1 + 1e-12) + 1e-12:
            beta, f = vertex, g
    return Fit(beta, f, it, certify(x, b, w, tau, beta))


def basis_rows(x: np.ndarray, r: np.ndarray) -> list[int]:
    """Rows in order of their absolute residual, each kept only if it adds rank."""
    p = x.shape[1]
    basis = np.zeros((0, p))
    rows: list[int] = []
    norms = np.linalg.norm(x, axis=1)
    for i in np.argsort(np.abs(r), kind="stable"):
        if norms[i] == 0:
            continue
        v = x[i] / norms[i]
        for _ in range(2):
            v = v - basis.T @ (basis @ v)
        size = np.linalg.norm(v)
        if size > 1e-6:
            basis = np.vstack([basis, v / size])
            rows.append(int(i))
            if len(rows) == p:
                break
    return rows


def to_vertex(x: np.ndarray, b: np.ndarray, beta: np.ndarray) -> np.ndarray | None:
    rows = basis_rows(x, b - x @ beta)
    return np.linalg.solve(x[rows], b[rows]) if len(rows) == x.shape[1] else None


def certify(x: np.ndarray, b: np.ndarray, w: np.ndarray, tau: float, beta: np.ndarray, slack: float = 1e-6) -> bool:
    """Whether multipliers of the zero-residual rows prove beta optimal (may be False at degenerate optima)."""
    r = b - x @ beta
    rows = basis_rows(x, r)
    if len(rows) < x.shape[1]:
        return False
    rest = np.ones(len(b), dtype=bool)
    rest[rows] = False
    rest &= np.abs(r) > 1e-9 * (1 + np.abs(b).max())
    psi = np.where(r > 0, tau, tau - 1.0)
    pull = (w[rest] * psi[rest]) @ x[rest]
    u = -np.linalg.solve(x[rows].T, pull)
    return bool(np.all(u <= w[rows] * tau + slack * (1 + w[rows])) and np.all(u >= w[rows] * (tau - 1) - slack * (1 + w[rows])))


def weighted_quantile(v: np.ndarray, w: np.ndarray, tau: float) -> float:
    """Smallest value whose running weight reaches tau of the total."""
    order = np.argsort(v, kind="stable")
    total = np.cumsum(w[order])
    if not len(total):
        return float("nan")
    return float(v[order][min(len(v) - 1, int(np.searchsorted(total, tau * total[-1] * (1 - 1e-15), side="left")))])


def simplex(x: np.ndarray, b: np.ndarray, tau: float, w: np.ndarray | None = None, most: int = 2000) -> Fit:
    """Walk from vertex to vertex along the steepest edge with an exact line search; for small problems."""
    n, p = x.shape
    w = np.ones(n) if w is None else w
    rows = basis_rows(x, b - x @ np.linalg.lstsq(x, b, rcond=None)[0])
    beta = np.linalg.solve(x[rows], b[rows])
    it = 0
    for it in range(1, most + 1):
        inverse = np.linalg.inv(x[rows])
        r = b - x @ beta
        r[rows] = 0.0
        best = (-1e-10, None, None)
        for k in range(p):
            for sign in (1.0, -1.0):
                move = -(x @ (sign * inverse[:, k]))  # change of residuals along the edge
                slope = np.where(r > 0, tau * move, np.where(r < 0, (tau - 1) * move, np.maximum(tau * move, (tau - 1) * move)))
                rate = float(w @ slope) / (1e-300 + np.abs(move).sum())
                if rate < best[0]:
                    best = (rate, k, sign)
        if best[1] is None:
            break
        _, k, sign = best
        move = -(x @ (sign * inverse[:, k]))
        cross = (r * move < 0) & (np.abs(move) > 1e-14)
        step = np.where(cross, -r / np.where(cross, move, 1.0), np.inf)
        rate = float(w @ np.where(r > 0, tau * move, np.where(r < 0, (tau - 1) * move, np.maximum(tau * move, (tau - 1) * move))))
        target = None
        for i in np.argsort(step, kind="stable"):
            if not np.isfinite(step[i]):
                break
            rate += w[i] * abs(move[i])
            target = int(i)
            if rate >= 0:
                break
        if target is None:
            break
        beta = beta + step[target] * sign * inverse[:, k]
        rows[k] = target
    return Fit(beta, loss(x, b, w, tau, beta), it, certify(x, b, w, tau, beta))


def enumerate_exact(x: np.ndarray, b: np.ndarray, tau: float, w: np.ndarray | None = None) -> Fit:
    """Every vertex of a tiny problem (some optimum interpolates as many rows as there are columns)."""
    from itertools import combinations

    w = np.ones(len(b)) if w is None else w
    best: tuple[float, np.ndarray] | None = None
    for rows in combinations(range(len(b)), x.shape[1]):
        part = x[list(rows)]
        if abs(np.linalg.det(part)) > 1e-12:
            beta = np.linalg.solve(part, b[list(rows)])
            f = loss(x, b, w, tau, beta)
            if best is None or f < best[0]:
                best = (f, beta)
    if best is None:
        return Fit(np.full(x.shape[1], np.nan), float("nan"), 0, False)
    return Fit(best[1], best[0], 0, True)


def independent_columns(x: np.ndarray) -> np.ndarray:
    """Mask of columns that a sample can estimate; the others are reported as not estimable."""
    p = x.shape[1]
    mask = np.zeros(p, dtype=bool)
    if not len(x):
        return mask
    size = np.linalg.norm(x, axis=0)
    _, r = np.linalg.qr(x / np.where(size > 0, size, 1.0))
    kept: list[int] = []
    if np.all(np.abs(np.diag(r)) > 1e-10) and r.shape[0] == p and np.all(size > 0):
        return np.ones(p, dtype=bool)
    basis = np.zeros((len(x), 0))
    for j in range(p):
        if size[j] == 0:
            continue
        v = x[:, j] / size[j]
        v = v - basis @ (basis.T @ v)
        v = v - basis @ (basis.T @ v)
        if np.linalg.norm(v) > 1e-10:
            basis = np.column_stack([basis, v / np.linalg.norm(v)])
            kept.append(j)
    mask[kept] = True
    return mask


def column_quantiles(x: np.ndarray, b: np.ndarray, w: np.ndarray, tau: float) -> Fit:
    """Rows with one nonzero each: the problem falls apart into one weighted quantile for each column."""
    j = (x != 0).argmax(axis=1)
    v = x[np.arange(len(x)), j]
    beta = np.full(x.shape[1], np.nan)
    for k in range(x.shape[1]):
        rows = j == k
        if rows.any():
            if (v[rows] > 0).all():
                beta[k] = weighted_quantile(b[rows] / v[rows], w[rows] * v[rows], tau)
            else:
                beta[k] = interior_point(v[rows, None], b[rows], tau, w[rows]).beta[0]
    return Fit(beta, loss(x, b, w, tau, np.nan_to_num(beta)), 0, True)


SOLVERS = {"ipm": interior_point, "simplex": simplex, "enumerate": enumerate_exact}


def solve_weighted(x: np.ndarray, b: np.ndarray, w: np.ndarray, tau: float, how: str = "auto") -> Fit:
    """The weighted subproblem of a sample; columns that no row touches come back as NaN (null in a DataFrame).

    ``auto`` takes weighted quantiles where every row has one nonzero and the
    interior point elsewhere; the other names always take that solver.
    """
    p = x.shape[1]
    if how in ("auto", "quantile"):
        if len(x) and ((x != 0).sum(axis=1) == 1).all():
            return column_quantiles(x, b, w, tau)
        if how == "quantile":
            raise ValueError("rows with several nonzeros are no set of quantiles")
        how = "ipm"
    mask = independent_columns(x)
    if not mask.any():
        return Fit(np.full(p, np.nan), float("nan"), 0, False)
    fit = SOLVERS[how](x[:, mask], b, tau, w)
    beta = np.full(p, np.nan)
    beta[mask] = fit.beta
    return Fit(beta, fit.objective, fit.iterations, fit.optimal)
