"""The solvers against enumeration, and the published bounds and theory."""

import itertools

import numpy as np
import pytest

from bundlery.functions.hardness import bound_pair
from bundlery.functions.lang import parse_package_sql
from bundlery.functions.metrics import integrality_gap
from bundlery.operators.partition import partition_low_variance, ratio_score, scan_line, theory_beta
from bundlery.plans.ilp import feasible, solve_ilp
from bundlery.plans.lp import LinearProgram, bfrt_large, bfrt_small, check_optimal, solve_lp, solve_lp_primal, support_bound
from bundlery.plans.reduced import solve_reduced_ilp


def random_program(seed, n=7, m=3):
    rng = np.random.default_rng(seed)
    A = rng.integers(-3, 6, (m, n)).astype(float)
    mid = A @ rng.integers(0, 2, n)
    return LinearProgram(rng.integers(-5, 9, n).astype(float), A, mid - rng.integers(0, 3, m), mid + rng.integers(0, 3, m), np.ones(n), sense="max" if seed % 2 else "min")


def enumerate_best(lp):
    best = None
    for x in itertools.product((0, 1), repeat=len(lp.c)):
        a = lp.A @ np.array(x)
        if (a >= lp.row_lo - 1e-9).all() and (a <= lp.row_hi + 1e-9).all():
            v = float(lp.c @ np.array(x))
            best = v if best is None else (max if lp.sense == "max" else min)(best, v)
    return best


@pytest.mark.parametrize("seed", range(30))
def test_integer_optimum_is_the_enumerated_one(seed):
    lp = random_program(seed)
    want = enumerate_best(lp)
    assert solve_ilp(lp, gap=1e-9).obj == pytest.approx(want)
    assert solve_reduced_ilp(lp, q=len(lp.c), gap=1e-9).obj == pytest.approx(want)
    assert feasible(lp) is True


@pytest.mark.parametrize("seed", range(30))
def test_dual_simplex_meets_its_certificate_and_the_primal(seed):
    lp = random_program(seed, n=12)
    got = solve_lp(lp)
    assert got.status == "optimal" and check_optimal(lp, got)["ok"] == 1.0
    assert got.obj == pytest.approx(solve_lp_primal(lp).obj, abs=1e-6)
    assert support_bound(lp, got)[0] <= support_bound(lp, got)[1]


def test_infeasible_programs_are_proved():
    lp = LinearProgram(np.ones(4), np.ones((1, 4)), [5], [9], np.ones(4))
    assert solve_lp(lp).status == "infeasible" and solve_ilp(lp).status == "infeasible"


@pytest.mark.parametrize("budget", [0.0, 3.0, 40.0, 1e9])
def test_ratio_walks_agree(budget):
    rng = np.random.default_rng(3)
    scores, costs = rng.integers(0, 50, 500).astype(float), rng.random(500) + 0.1
    a, b = bfrt_large(scores, costs, budget), bfrt_small(scores, costs, budget, guess=4)
    assert a[1] == b[1] and sorted(a[0]) == sorted(b[0])


def test_published_bounds_of_the_order_line_query():
    # fixed values: printed bounds at hardness 1 and 7
    for h, want in ((1, 772.11), (7, 970.61)):
        assert bound_pair(">=", 25.50, 14.43, 30, 10 ** (-h / 3))[0] == pytest.approx(want, abs=0.6)
    lo, hi = bound_pair("between", 1530, 1485, 30, 10 ** (-1 / 3))
    assert (lo, hi) == (pytest.approx(40864.32, abs=5), pytest.approx(50935.68, abs=5))


@pytest.mark.parametrize("n", [39, 100, 1000])
def test_far_pair_is_isolated(n):
    x = np.concatenate([[-1.0, 1.0], np.full(n, 1 + 3 / n)])
    assert ratio_score(x, scan_line(x, None, theory_beta(float(x.var()), n + 2))) == pytest.approx(0, abs=1e-9)


def test_pieces_keep_the_bound_and_boxes_hold_their_rows():
    x = np.random.default_rng(1).normal(size=(800, 2))
    piece = np.searchsorted(cuts := scan_line(x[:, 0], None, 0.05), x[:, 0], side="right")
    assert all(x[piece == p, 0].var() <= 0.05 + 1e-9 for p in range(len(cuts) + 1))
    for unit in (None, [1.0, 100.0]):
        g = partition_low_variance(x, 20, unit=unit)
        assert ((x >= g.lo[g.assign]) & (x < g.hi[g.assign])).all() and len(g.lo) >= 40


@pytest.mark.parametrize("points", [np.zeros((0, 1)), np.zeros((1, 1)), np.ones((9, 1)), np.repeat([[1.0], [2.0]], 5, axis=0)])
def test_degenerate_relations_end(points):
    assert len(partition_low_variance(points, 2).lo) <= max(1, len(np.unique(points))) and len(scan_line(points[:, 0] if len(points) else points.ravel(), None, 0.1)) <= 1


def test_text_queries():
    q = parse_package_sql("SELECT PACKAGE(*) AS P FROM t REPEAT 0 WHERE a BETWEEN 1 AND 2 SUCH THAT COUNT(*) = 3 AND SUM(P.x + y) <= 4.5 MINIMIZE SUM(P.z)")
    assert (q.repeat, q.where, q.objective, q.sense) == (0, "a BETWEEN 1 AND 2", "z", "min")
    assert [c.text for c in q.such_that] == ["COUNT(*)", "SUM(x + y)"] and q.such_that[1].hi == 4.5
    with pytest.raises(ValueError):
        parse_package_sql("SELECT PACKAGE(*) FROM t SUCH THAT MEDIAN(x) = 3")


def test_gap_orientation():
    assert integrality_gap(9.9, 19.9, "max") == pytest.approx(2) and integrality_gap(19.9, 9.9, "min") == pytest.approx(2)
    assert integrality_gap(-1, 2, "max") is None


def test_short_scans_cut_as_long_ones(monkeypatch):
    from bundlery.operators import partition

    rng = np.random.default_rng(11)
    for t in range(300):
        n = int(rng.integers(1, 200))
        v, w = rng.integers(0, 60, n) * 0.37, rng.integers(1, 9, n).astype(float) if t % 2 else None
        beta = v.var() * 10 ** -rng.uniform(0, 3)
        monkeypatch.setattr(partition, "SHORT", 256)
        short = partition.scan_line(v, w, beta)
        monkeypatch.setattr(partition, "SHORT", 0)
        assert (short == partition.scan_line(v, w, beta)).all()
