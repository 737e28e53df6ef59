"""The searches on numpy alone: worked examples, exact methods against each other, invariants."""

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from linseg.kernels import merging, optimal, refine, splits
from linseg.kernels.moments import Absolute, Constant, Linear
from linseg.operators.segment import METHODS, run


def planted(seed, n, k, d, noise=1.0, amp=3.0):
    rng = np.random.default_rng(seed)
    cuts = [0, *sorted(rng.choice(np.arange(5, n - 5), k - 1, replace=False).tolist()), n]
    x = np.zeros((n, d))
    for a, b in zip(cuts, cuts[1:]):
        x[a:b] = rng.normal(0, amp, d) + np.linspace(0, 1, b - a)[:, None] * rng.normal(0, amp, d)
    return np.arange(n, dtype=float), x + rng.normal(0, noise, (n, d)), cuts


def least_squares(t, x):
    a = np.column_stack([np.ones(len(t)), t])
    w, *_ = np.linalg.lstsq(a, x, rcond=None)
    return float(((x - a @ w) ** 2).sum())


def test_two_lines_are_found_exactly():
    x = np.array([0, 1, 2, 3, 10, 9, 8, 7.0])[:, None]
    for method in ("binary_split", "optimal_partition", "brute_force", "penalized_optimal"):
        r = run(np.arange(8.0), x, 2, method)
        assert r["cuts"].tolist() == [0, 4, 8] and r["cost"] < 1e-20, method
        assert np.allclose(r["lines"][1][0], 14) and np.allclose(r["lines"][1][1], -1)


def test_first_sweep_of_the_worked_example():
    s = Linear(np.arange(8.0), np.array([0, 1, 2, 3, 10, 9, 8, 7.0])[:, None])
    cuts, trace = refine.refine(s, np.array([0, 3, 8]), order="left_to_right")
    assert cuts.tolist() == [0, 4, 8] and trace[0] == pytest.approx(25.6) and trace[1] == pytest.approx(0)


def test_one_line_and_merge_gain():
    s = Linear(np.arange(4.0), np.array([0, 0, 1, 1.0])[:, None])
    c, m, e = s.exact(0, 4)
    assert (c[0], m[0], e) == pytest.approx((-0.1, 0.4, 0.2))
    assert s.one(0, 4) - s.one(0, 2) - s.one(2, 4) == pytest.approx(0.2)


def test_partition_counts():
    from itertools import combinations

    count = sum(all(b - a >= 2 for a, b in zip((0, *c), (*c, 12))) for c in combinations(range(1, 12), 2))
    assert refine.partitions(12, 3, 2) == count == 28
    assert refine.partitions(12, 3) == 55 and refine.printed_partitions(12, 3) == 45


@given(st.integers(0, 10_000), st.integers(8, 40), st.integers(1, 3))
@settings(max_examples=40, deadline=None)
def test_range_costs_are_least_squares(seed, n, d):
    rng = np.random.default_rng(seed)
    t, x = np.sort(rng.uniform(1e6, 1e6 + 50, n)), rng.normal(1e3, 10, (n, d))
    s = Linear(t, x)
    a, b = sorted(rng.choice(n + 1, 2, replace=False))
    assert s.one(a, b) == pytest.approx(least_squares(t[a:b] - t[0], x[a:b]) if b - a > 2 else 0.0, rel=1e-6, abs=1e-6)
    c, m, e = s.exact(a, b)
    assert e == pytest.approx(s.one(a, b), rel=1e-6, abs=1e-6)


@given(st.integers(0, 10_000))
@settings(max_examples=15, deadline=None)
def test_exact_methods_agree_and_bound_the_rest(seed):
    t, x, _ = planted(seed, 26, 3, 2)
    s = Linear(t, x)
    best = s.model_cost(optimal.brute_force(s, 3))
    assert s.model_cost(optimal.optimal_partition(s, 3)) == pytest.approx(best)
    cuts, _, _ = optimal.penalized_for_k(s, 3)
    if len(cuts) == 4:
        assert s.model_cost(cuts) == pytest.approx(best)
    for name in METHODS:
        if name not in ("unknown_k", "penalized_optimal", "one_piece"):
            r = run(t, x, 3, name, seed=str(seed))
            assert r["cost"] >= best - 1e-9, name
            assert r["cuts"][0] == 0 and r["cuts"][-1] == 26 and (np.diff(r["cuts"]) > 0).all(), name


@given(st.integers(0, 10_000), st.sampled_from(["seeded_shuffle", "odd_even", "left_to_right"]), st.integers(1, 4))
@settings(max_examples=30, deadline=None)
def test_refinement_never_raises_the_cost_and_ends_where_no_move_helps(seed, order, gamma):
    t, x, _ = planted(seed, 80, 4, 2)
    s = Linear(t, x)
    cuts, trace = refine.refine(s, refine.random_cuts(80, 5, gamma, seed), gamma, tol=0.0, order=order, seed=seed)
    assert all(a >= b - 1e-9 for a, b in zip(trace, trace[1:]))
    assert (np.diff(cuts) >= gamma).all()
    c, m = s.lines(cuts[:-1], cuts[1:])
    err = lambda i, a, b: ((s.x[a:b] - c[i] - s.t[a:b, None] * m[i]) ** 2).sum()
    for p in range(len(cuts) - 2):
        lo, hi = cuts[p], cuts[p + 2]
        now = err(p, lo, cuts[p + 1]) + err(p + 1, cuts[p + 1], hi)
        least = min(err(p, lo, q) + err(p + 1, q, hi) for q in range(lo + gamma, hi - gamma + 1))
        assert now <= least + 1e-6 * (1 + least)


@given(st.integers(1, 6), st.integers(1, 4), st.integers(0, 99))
def test_random_cuts_are_feasible(k, gamma, seed):
    cuts = refine.random_cuts(k * gamma + 7, k, gamma, seed)
    assert len(cuts) == k + 1 and (np.diff(cuts) >= gamma).all()


def test_merging_follows_the_strict_greedy_order():
    t, x, _ = planted(3, 60, 3, 1)
    s = Linear(t, x)
    edges = list(merging.cells(60, 5))
    _, path = merging.merge(s, np.array(edges), 1)
    for cut, gain in path:
        gains = [(s.one(a, c) - s.one(a, b) - s.one(b, c), b) for a, b, c in zip(edges, edges[1:], edges[2:])]
        assert min(gains)[1] == cut and min(gains)[0] == pytest.approx(gain)
        edges.remove(cut)


def test_cells_keep_their_budget_and_polish_never_hurts():
    t, x, _ = planted(5, 400, 4, 2)
    s = Linear(t, x)
    edges = optimal.balanced_cells(s, 12.0)
    assert all(s.one(a, b) <= 12.0 + 1e-9 for a, b in zip(edges, edges[1:]) if b - a > 2)
    coarse = s.model_cost(optimal.optimal_over_cells(s, 4, 10)[0])
    assert s.model_cost(optimal.cells_then_refine(s, 4, 10)[0]) <= coarse + 1e-9
    assert optimal.optimal_over_cells(s, 4, 10, compress="svd")[0].tolist() == optimal.optimal_over_cells(s, 4, 10)[0].tolist()
    scale, pieces = optimal.bicriteria(s, 4)
    assert sum(b - a for a, b in pieces) == 400 and scale >= 0


def test_special_cases():
    assert run(np.arange(1.0), np.ones((1, 1)), 1, "refine_boundaries")["cost"] == 0
    assert "error" in run(np.arange(3.0), np.ones((3, 1)), 2, "refine_boundaries") and run(np.arange(3.0), np.ones((3, 1)), 2, "refine_boundaries", on_infeasible="clamp")["k"] == 1
    t, x, _ = planted(1, 50, 2, 2)
    wide = np.column_stack([x, np.full(50, 7.0)])  # a constant dimension changes nothing
    assert run(t, wide, 2, "optimal_partition")["cuts"].tolist() == run(t, x, 2, "optimal_partition")["cuts"].tolist()
    assert run(t * 3 + 1e9, x * 5, 2, "optimal_partition")["cost"] == pytest.approx(25 * run(t, x, 2, "optimal_partition")["cost"])
    with pytest.raises(ValueError):
        optimal.brute_force(Linear(np.arange(500.0), np.zeros((500, 1))), 6)


def test_other_cost_models():
    t, x, cuts = planted(2, 60, 2, 1, noise=0.2)
    assert abs(splits.binary_split(Absolute(t, x), 2)[1] - cuts[1]) <= 2
    flat = Constant(t, x)
    assert flat.one(0, 10) == pytest.approx(((x[:10] - x[:10].mean(0)) ** 2).sum())


def test_unknown_number_of_pieces():
    rng = np.random.default_rng(11)
    x = np.repeat(rng.normal(0, 5, (4, 3)), 75, axis=0) + rng.normal(0, 0.5, (300, 3))
    found, _ = merging.unknown_k(Linear(np.arange(300.0), x))
    assert found.tolist() == [0, 75, 150, 225, 300]


@pytest.mark.parametrize("gamma", [2, 3, 5, 10])
def test_penalised_search_is_optimal_for_any_least_piece(gamma):
    rng = np.random.default_rng(gamma)
    for _ in range(60):
        x = np.cumsum(rng.normal(size=(rng.integers(2 * gamma, 60), 1)), 0)
        s = Linear(np.arange(len(x), dtype=float), x)
        beta = float(rng.uniform(0.01, 1.0)) * s.one(0, s.n)
        best = min(c + beta * k for k, c, _ in optimal.optimal_path(s, s.n // gamma, gamma))
        cuts = optimal.penalized_optimal(s, beta, gamma)
        assert s.model_cost(cuts) + beta * (len(cuts) - 1) == pytest.approx(best)
        assert min(np.diff(cuts)) >= gamma


@pytest.mark.parametrize("scales", [(1.0, 1.0), (10_000.0, 10.0), (1e-3, 5.0)])
def test_unknown_k_with_dimensions_of_unlike_scale(scales):
    rng = np.random.default_rng(1)
    for _ in range(12):
        x = rng.normal(size=(100, 2)) * scales
        assert len(merging.unknown_k(Linear(np.arange(100.0), x), k_max=6)[0]) == 2
        x[40:] += 8 * np.array(scales)
        cuts = merging.unknown_k(Linear(np.arange(100.0), x), k_max=6)[0]
        assert len(cuts) == 3 and abs(cuts[1] - 40) <= 1


def test_one_range_costs_what_many_cost():
    t, x, _ = planted(3, 80, 3, 4)
    for kind in (Linear, Constant):
        s = kind(t, x)
        for a in range(0, 80, 7):
            for b in range(a, 81, 5):
                assert s.one(a, b) == pytest.approx(float(s.cost(a, b)), rel=1e-9, abs=1e-9)


def test_signals_that_do_not_fit_give_error_rows():
    t, x = np.arange(500.0), np.random.default_rng(0).normal(size=(500, 1))
    assert "absolute" in run(t, x, 2, "binary_split", "l1_linear")["error"]
    assert "too many" in run(t, x, 6, "brute_force")["error"]


def test_cells_are_never_capped():
    rng = np.random.default_rng(0)
    s = Linear(np.arange(30_000.0), rng.normal(size=(30_000, 1)))
    edges, factor = optimal.cell_edges(s, 2, 100_000)
    assert factor == 100_000 and len(edges) > 5001


def test_short_signals_from_one_table_of_costs(monkeypatch):
    """Absolute errors of many ranges at once, and penalties tried on one table, are what one range or run at a time gives."""
    rng = np.random.default_rng(11)
    for n in (5, 40, 90):
        x = np.column_stack([np.round(rng.exponential(3000, n)), rng.integers(0, 100, n)]).astype(float)
        s = Linear(np.arange(n) * 1.0, x)
        table = optimal.all_costs(s)
        at = np.arange(n)
        assert np.allclose(table[n, :n], s.cost(at, n), rtol=1e-9, atol=1e-9 * s.total)
        for gamma in (1, 2, 4):
            k = min(3, n // gamma)
            with monkeypatch.context() as m:
                m.setattr(optimal, "WHOLE", 0)
                want = optimal.penalized_for_k(s, k, gamma)
            got = optimal.penalized_for_k(s, k, gamma)
            assert np.array_equal(got[0], want[0]) and got[1:] == want[1:]
        a = Absolute(np.arange(n) * 1.0, x)
        lo = rng.integers(0, n - 3, 30)
        hi = np.minimum(lo + rng.integers(1, n, 30), n)
        assert np.allclose(a.cost(lo, hi), [a._fit(int(i), int(j))[2] if j - i > 2 else 0.0 for i, j in zip(lo, hi, strict=True)], rtol=1e-7)


def test_table_of_all_costs_is_the_plain_search():
    """Costs of all ranges at once, on repeated times, flat and single columns; the exact search over them evaluates no range by itself."""
    rng = np.random.default_rng(11)
    for d, t in ((1, np.arange(70.0)), (4, np.repeat(np.arange(35.0), 2)), (2, np.zeros(40))):
        for kind in (Linear, Constant):
            s = kind(t, rng.normal(size=(len(t), d)) + (np.arange(len(t)) > 30)[:, None])
            got = s.all_costs(7)
            at = np.arange(s.n + 1)
            for e in range(1, s.n + 1):
                assert got[e, :e] == pytest.approx(s.cost(at[:e], e), abs=1e-9) and np.isinf(got[e, e:]).all()
            before = s.count.evals
            s.cost = s.upto = None
            cuts = optimal.optimal_partition(s, 3)
            assert s.count.evals - before == sum(e - 1 for e in range(2, s.n + 1))
            del s.cost, s.upto
            assert s.model_cost(cuts) <= s.model_cost(refine.uniform(s.n, 3)) + 1e-9


def test_penalized_by_table_is_the_pruned_search():
    for seed in range(6):
        s = Linear(*planted(seed, 90, 4, 2)[:2])
        for beta in (0.0, 5.0, 300.0):
            assert optimal.penalized(s, beta).tolist() == optimal.penalized_optimal(s, beta).tolist()
