"""A bounded dual simplex for programs with few rows and very many columns.

Rows are two-sided, ``row_lo <= A x <= row_hi``, columns boxed, ``l <= x <= u``.
Each row has a slack variable; the slack basis is dual feasible at once when
every column starts at the bound its cost prefers, so there is no first phase.
The basis inverse is an explicit m x m matrix (m is the number of rows), and
whole-column work is one matrix-vector product per iteration.  The ratio test
flips bounds: it walks the sorted dual ratios and passes every column whose box
is too small to absorb the remaining infeasibility, so one iteration can move a
large part of all columns at once.
"""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np

#: Tolerances: primal (relative to the row's scale), dual, and the smallest pivot.
PRIMAL, DUAL, PIVOT = 1e-9, 1e-9, 1e-9
REFACTOR = 50


@dataclass
class LinearProgram:
    """Minimise or maximise ``c x`` subject to row and column bounds."""

    c: np.ndarray
    A: np.ndarray
    row_lo: np.ndarray
    row_hi: np.ndarray
    u: np.ndarray
    l: np.ndarray | None = None  # noqa: E741
    sense: str = "min"

    def __post_init__(self):
        self.c = np.asarray(self.c, float)
        self.A = np.atleast_2d(np.asarray(self.A, float)).reshape(len(np.atleast_1d(self.row_lo)), len(self.c))
        self.row_lo, self.row_hi = np.asarray(self.row_lo, float), np.asarray(self.row_hi, float)
        self.u = np.broadcast_to(np.asarray(self.u, float), self.c.shape).copy()
        self.l = np.zeros_like(self.c) if self.l is None else np.broadcast_to(np.asarray(self.l, float), self.c.shape).copy()
        if not (np.isfinite(self.u).all() and np.isfinite(self.l).all()):
            raise ValueError("columns need finite bounds")

    @property
    def cost(self) -> np.ndarray:
        """Costs of the minimisation."""
        return self.c if self.sense == "min" else -self.c

    def columns(self, keep: np.ndarray) -> "LinearProgram":
        return LinearProgram(self.c[keep], self.A[:, keep], self.row_lo, self.row_hi, self.u[keep], self.l[keep], self.sense)

    def with_bounds(self, l, u) -> "LinearProgram":  # noqa: E741
        out = object.__new__(LinearProgram)
        out.c, out.A, out.row_lo, out.row_hi, out.sense = self.c, self.A, self.row_lo, self.row_hi, self.sense
        out.l, out.u = l, u
        return out


@dataclass
class LPResult:
    status: str
    obj: float = float("nan")
    x: np.ndarray | None = None
    y: np.ndarray | None = None
    basis: np.ndarray | None = None
    iters: int = 0
    flips: int = 0
    long_steps: list[int] = field(default_factory=list)


def standardise(lp: LinearProgram) -> tuple[np.ndarray, np.ndarray]:
    """Row bounds made finite by the smallest and largest value each row can take."""
    pos, neg = np.maximum(lp.A, 0), np.minimum(lp.A, 0)
    least, most = pos @ lp.l + neg @ lp.u, pos @ lp.u + neg @ lp.l
    return np.maximum(lp.row_lo, least), np.minimum(lp.row_hi, most)


def bfrt_large(scores: np.ndarray, costs: np.ndarray, budget: float) -> tuple[np.ndarray, int]:
    """Positions passed, and the one that stops the walk (-1: none does).

    All positions are sorted by score and summed up; the stop is the first whose
    cost reaches what is left of the budget.
    """
    order = np.argsort(scores, kind="stable")
    spent = np.cumsum(costs[order])
    stop = int(np.searchsorted(spent, budget, side="left"))
    if stop == len(order):
        return order, -1
    return order[:stop], int(order[stop])


def bfrt_small(scores: np.ndarray, costs: np.ndarray, budget: float, guess: int = 64) -> tuple[np.ndarray, int]:
    """As ``bfrt_large`` for walks that end early: only the lowest scores are sorted.

    The set that is sorted grows fourfold until the walk ends inside it; ties at
    its border belong to it, so the result is the same.
    """
    n = len(scores)
    while guess < n:
        edge = np.partition(scores, guess)[guess]
        near = np.flatnonzero(scores <= edge)
        passed, stop = bfrt_large(scores[near], costs[near], budget)
        if stop >= 0:
            return near[passed], int(near[stop])
        guess *= 4
    return bfrt_large(scores, costs, budget)


def solve_lp(lp: LinearProgram, warm: np.ndarray | None = None, max_iters: int = 20_000) -> LPResult:
    """Optimal solution, or a proof of infeasibility.

    ``warm`` is a basis (column numbers; ``n + i`` is the slack of row i) of a
    program with the same costs and rows: bound changes keep it dual feasible.
    """
    n, m = len(lp.c), len(lp.A)
    if (lp.l > lp.u + PRIMAL).any() or (lp.row_lo > lp.row_hi + PRIMAL).any():
        return LPResult("infeasible")
    row_lo, row_hi = standardise(lp)
    # rows and costs at a common scale
    scale = np.maximum(np.abs(lp.A).max(axis=1, initial=0.0), 1e-300)
    size = max(float(np.abs(lp.c).max(initial=0.0)), 1e-300)
    A, cost = lp.A / scale[:, None], np.concatenate([lp.cost / size, np.zeros(m)])
    row_lo, row_hi = row_lo / scale, row_hi / scale
    slack = PRIMAL * (1 + np.maximum(np.abs(row_lo), np.abs(row_hi)))
    if (row_lo > row_hi + slack).any():
        return LPResult("infeasible")
    row_hi = np.maximum(row_hi, row_lo)
    low, high = np.concatenate([lp.l, row_lo]), np.concatenate([lp.u, row_hi])
    span = high - low
    basis = np.arange(n, n + m) if warm is None else np.array(warm, np.int64)
    basic = np.zeros(n + m, bool)
    basic[basis] = True

    def column(j):
        if j < n:
            return A[:, j]
        out = np.zeros(m)
        out[j - n] = -1.0
        return out

    def times(row):
        """row @ [A, -I]"""
        return np.concatenate([row @ A, -row])

    def factor():
        try:
            inverse = np.linalg.inv(np.column_stack([column(j) for j in basis])) if m else np.zeros((0, 0))
        except np.linalg.LinAlgError:
            return None
        y = cost[basis] @ inverse
        return inverse, cost - times(y)

    start = factor()
    if start is None:
        if warm is not None:
            return solve_lp(lp, None, max_iters)
        raise np.linalg.LinAlgError("singular basis")
    inverse, d = start
    x = np.where(d >= 0, low, high)

    def primal():
        at = x.copy()
        at[basis] = 0.0
        return -(inverse @ (A @ at[:n] - at[n:]))

    x[basis] = primal()
    flips, long_steps, it = 0, [], 0
    tolerance = PRIMAL * (1 + np.maximum(np.abs(low), np.abs(high)))
    shaken = False
    while m:
        xb = x[basis]
        under, over = low[basis] - xb, xb - high[basis]
        gap = np.maximum(under, over)
        weight = 1e-12 + np.sqrt((inverse**2).sum(axis=1))
        bad = gap > tolerance[basis]
        if not bad.any():
            break
        it += 1
        if it > max_iters:
            return LPResult("iteration_limit", iters=it, flips=flips)
        if it > 400 + 30 * m and not shaken:
            # a tiny shift of the costs breaks ties that keep pivots from moving on
            shaken = True
            cost = cost + np.random.default_rng(0).uniform(0, 1e-10, n + m) * (1 + np.abs(cost))
            inverse, d = factor()
            keep = basic | (np.abs(d) <= DUAL)
            x = np.where(keep, x, np.where(d >= 0, low, high))
            x[basis] = primal()
            continue
        r = int(np.argmax(np.where(bad, gap / weight, -1.0)))
        sign = 1.0 if under[r] > over[r] else -1.0
        alpha = times(inverse[r])
        move = sign * alpha
        at_low = x <= low + tolerance
        able = ~basic & (span > 0) & (np.abs(alpha) > PIVOT) & np.where(at_low, move < 0, move > 0)
        index = np.flatnonzero(able)
        if not len(index):
            return LPResult("infeasible", iters=it, flips=flips)
        size_of = np.abs(alpha[index])
        scores, costs = np.abs(d[index]) / size_of, size_of * span[index]
        budget = float(gap[r])
        walk = bfrt_small if it > 1 and len(index) > 512 else bfrt_large
        passed, stop = walk(scores, costs, budget)
        if stop < 0:
            # everything that can move has moved: the row stays short by a real amount
            if budget - costs.sum() > tolerance[basis[r]]:
                return LPResult("infeasible", iters=it, flips=flips)
            stop = int(np.argmax(scores))
            passed = np.setdiff1d(passed, [stop])
        if len(passed):
            j = index[passed]
            to = np.where(at_low[j], high[j], low[j])
            shift = to - x[j]
            x[j] = to
            total = np.zeros(m)
            inside = j < n
            total += A[:, j[inside]] @ shift[inside]
            np.subtract.at(total, j[~inside] - n, shift[~inside])
            x[basis] -= inverse @ total
            flips += len(passed)
        long_steps.append(len(passed))
        q = int(index[stop])
        leaving = int(basis[r])
        bound = low[leaving] if sign > 0 else high[leaving]
        entering = inverse @ column(q)
        step = (x[leaving] - bound) / entering[r]
        x[basis] -= entering * step
        x[q] += step
        x[leaving] = bound
        d -= d[q] / alpha[q] * alpha
        d[q] = 0.0
        basic[leaving], basic[q] = False, True
        basis[r] = q
        pivot = inverse[r] / entering[r]
        inverse = inverse - np.outer(entering, pivot)
        inverse[r] = pivot
        if it % REFACTOR == 0:
            again = factor()
            if again is not None:
                inverse, d = again
                x[basis] = primal()
    value = np.clip(x[:n], lp.l, lp.u)
    y = (cost[basis] @ inverse) * size / scale if m else np.zeros(0)
    return LPResult("optimal", float(lp.c @ value), value, y if lp.sense == "min" else -y, basis.copy(), it, flips, long_steps)


def solve_lp_primal(lp: LinearProgram, max_iters: int = 50_000) -> LPResult:
    """Reference primal simplex (single steps, artificial first phase), for small programs."""
    n, m = len(lp.c), len(lp.A)
    if (lp.l > lp.u).any() or (lp.row_lo > lp.row_hi).any():
        return LPResult("infeasible")
    row_lo, row_hi = standardise(lp)
    if (row_lo > row_hi + PRIMAL * (1 + np.abs(row_lo))).any():
        return LPResult("infeasible")
    row_hi = np.maximum(row_lo, row_hi)
    x = np.concatenate([lp.l, np.zeros(m)])
    activity = lp.A @ lp.l
    x[n:] = np.clip(activity, row_lo, row_hi)
    miss = x[n:] - activity
    sign = np.where(miss >= 0, 1.0, -1.0)
    whole = np.hstack([lp.A, -np.eye(m), np.diag(sign)])
    low = np.concatenate([lp.l, row_lo, np.zeros(m)])
    high = np.concatenate([lp.u, row_hi, np.abs(miss)])
    x = np.concatenate([x, np.abs(miss)])
    basis = np.arange(n + m, n + 2 * m)
    basic = np.zeros(n + 2 * m, bool)
    basic[basis] = True
    total = 0
    for phase in (1, 2):
        cost = np.concatenate([np.zeros(n + m), np.ones(m)]) if phase == 1 else np.concatenate([lp.cost, np.zeros(2 * m)])
        if phase == 2:
            if x[n + m :].sum() > 1e-7 * (1 + np.abs(activity).sum()):
                return LPResult("infeasible", iters=total)
            high[n + m :] = 0.0
            x[n + m :] = 0.0
        for _ in range(max_iters):
            inverse = np.linalg.inv(whole[:, basis])
            d = cost - (cost[basis] @ inverse) @ whole
            up = ~basic & (x < high - 1e-12) & (d < -1e-9)
            down = ~basic & (x > low + 1e-12) & (d > 1e-9)
            able = np.flatnonzero(up | down)
            if not len(able):
                break
            total += 1
            q = int(able[0]) if total > 1000 else int(able[np.argmax(np.abs(d[able]))])
            way = 1.0 if up[q] else -1.0
            change = -(inverse @ whole[:, q]) * way
            with np.errstate(divide="ignore", invalid="ignore"):
                room = np.where(change > 1e-11, (high[basis] - x[basis]) / change, np.where(change < -1e-11, (low[basis] - x[basis]) / change, np.inf))
            r = int(np.argmin(room))
            limit = high[q] - x[q] if way > 0 else x[q] - low[q]
            step = min(float(room[r]), limit)
            x[basis] += change * step
            x[q] += way * step
            if room[r] <= limit:
                leaving = basis[r]
                x[leaving] = high[leaving] if change[r] > 0 else low[leaving]
                basic[leaving], basic[q] = False, True
                basis[r] = q
        else:
            return LPResult("iteration_limit", iters=total)
    value = x[:n]
    return LPResult("optimal", float(lp.c @ value), value, None, None, total)


def check_optimal(lp: LinearProgram, result: LPResult, tol: float = 1e-6) -> dict[str, float]:
    """Residuals that certify an optimum: primal, dual, and the duality gap."""
    row_lo, row_hi = standardise(lp)
    activity = lp.A @ result.x
    scale = 1 + np.maximum(np.abs(row_lo), np.abs(row_hi))
    primal = max(0.0, float(((row_lo - activity) / scale).max(initial=0)), float(((activity - row_hi) / scale).max(initial=0)))
    y = result.y if lp.sense == "min" else -result.y
    d = lp.cost - y @ lp.A
    # the dual value of boxed variables and two-sided rows
    dual = float(np.where(y > 0, y * row_lo, y * row_hi).sum() + np.where(d > 0, d * lp.l, d * lp.u).sum())
    obj = float(lp.cost @ result.x)
    return {"primal": primal, "gap": abs(obj - dual) / (1 + abs(obj)), "ok": float(primal <= tol and abs(obj - dual) <= tol * (1 + abs(obj)))}


def support_bound(lp: LinearProgram, result: LPResult) -> tuple[int, int]:
    """Positive columns, and the most there can be: ceil(m + sum of x) with unit boxes."""
    return int((result.x > 1e-9).sum()), int(np.ceil(len(lp.A) + result.x.sum() - 1e-9))
