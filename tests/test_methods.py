"""The paper's validation: known eigenvalues, bands of counts, rates, optimality, special cases, trends."""

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from ergodica.operators import smalldense as sd
from ergodica.operators.convergence import predicted_iterations
from ergodica.operators.cost import saving, storage
from ergodica.operators.kernel import Operator, solve_arrays, start_block
from ergodica.operators.spectrum import costs, crowding, window_bounds
from ergodica.sources.synthetic import FIVE_STATE

P = np.array(FIVE_STATE)


def edges(p):
    s, d = np.nonzero(p)
    return s, d, p[s, d]


def dense_pi(p):
    n = len(p)
    return np.linalg.lstsq(np.vstack([p.T - np.eye(n), np.ones(n)]), np.append(np.zeros(n), 1), rcond=None)[0]


def random_chain(n, seed, sparsity=0.5):
    rng = np.random.default_rng(seed)
    p = rng.random((n, n)) * (rng.random((n, n)) < sparsity) + np.roll(np.eye(n), 1, axis=1) + 0.1 * np.eye(n)
    return p / p.sum(axis=1, keepdims=True)


def test_eigenvalues():
    got = np.sort(np.abs(np.linalg.eigvals(P)))[::-1]
    assert np.round(got, 4).tolist() == [1.0, 0.9998, 0.9996, 0.5483, 0.5483]


def test_five_state_counts():
    power = solve_arrays(*edges(P), width=1, check_every=100, seed=1, max_iter=300_000)
    two = solve_arrays(*edges(P), width=2, check_every=100, seed=1, max_iter=300_000)
    three = solve_arrays(*edges(P), width=3, check_every=1, seed=1)
    assert power.ledger.iterations > 50_000 and 0.25 < two.ledger.iterations / power.ledger.iterations < 0.7 and three.ledger.iterations < 100
    by_distance = solve_arrays(*edges(P), width=2, check_every=100, seed=1, max_iter=300_000, truth=dense_pi(P))
    assert 50_000 < by_distance.ledger.iterations < 65_000
    assert np.abs(three.pi - dense_pi(P)).max() < 1e-7


@pytest.mark.parametrize("depth,most", [(3, 100), (4, 90), (5, 8)])
def test_five_state_windows(depth, most):
    r = solve_arrays(*edges(P), depth=depth, check_every=1, seed=1)
    assert r.converged and r.ledger.iterations <= most and r.ledger.matvecs_core == r.ledger.iterations


def test_rate_follows_next_eigenvalue():
    p = np.diag([0.0] * 8)
    p = random_chain(8, 3)
    moduli = np.sort(np.abs(np.linalg.eigvals(p)))[::-1]
    for s in (1, 2):
        log = [(r["iteration"], r["residual"]) for r in solve_arrays(*edges(p), width=s, check_every=1, seed=2, tol=1e-12).log if 1e-11 < r["residual"] < 1e-3]
        slope = np.polyfit(*np.array([(k, np.log(x)) for k, x in log]).T, 1)[0]
        assert np.exp(slope) < moduli[s] * 1.15


@given(st.integers(0, 10_000), st.integers(1, 4))
@settings(max_examples=25, deadline=None)
def test_least_residual_is_least(seed, width):
    p = random_chain(9, seed)
    op = Operator(*edges(p), 9)
    w = op.step(op.step(start_block(9, width, seed)))
    z = op.step(w)
    e = sd.extract(w, z)
    rng = np.random.default_rng(seed)
    for c in rng.normal(size=(20, width)):
        v = w @ c
        assert np.linalg.norm(op.step(v[:, None])[:, 0] - v) / np.linalg.norm(v) >= e.residual - 1e-9
    assert sd.extract(w, z, "ritz_eig").residual >= e.residual - 1e-9
    v = w @ e.coefficients
    assert abs(np.linalg.norm(v) - 1) < 1e-8 and abs(np.linalg.norm(p.T @ v - v) - e.residual) < 1e-8


@given(st.integers(0, 10_000))
@settings(max_examples=15, deadline=None)
def test_extraction_ignores_mixing_of_columns(seed):
    p = random_chain(8, seed)
    op = Operator(*edges(p), 8)
    x = start_block(8, 3, seed)
    g = np.random.default_rng(seed).random((3, 3)) + 2 * np.eye(3)
    a, b = sd.extract(x, op.step(x)), sd.extract(x @ g, op.step(x @ g))
    assert abs(a.residual - b.residual) < 1e-8


def test_projected_matrix_is_psd_and_its_least_value_is_the_residual():
    p = random_chain(10, 5)
    w = start_block(10, 4, 1)
    q, _ = np.linalg.qr(w)
    b = ((p.T - np.eye(10)) @ q).T @ ((p.T - np.eye(10)) @ q)
    values = np.linalg.eigvalsh(b)
    assert values[0] > -1e-12 and abs(np.sqrt(values[0]) - sd.extract(w, p.T @ w).residual) < 1e-9


def test_special_cases():
    p = random_chain(6, 9)
    a, b = solve_arrays(*edges(p), width=1, depth=1, seed=4), solve_arrays(*edges(p), width=1, depth=1, seed=4, method="power")
    assert a.ledger.iterations == b.ledger.iterations and np.array_equal(a.pi, b.pi)
    assert solve_arrays(*edges(p), width=6, check_every=1, seed=4).ledger.iterations == 1
    one = solve_arrays(np.array([0]), np.array([0]), np.array([1.0]))
    assert one.converged and one.pi.tolist() == [1.0]


@pytest.mark.parametrize("how", ["ritz_schur", "ritz_eig", "min_residual", "gram"])
def test_extractions_agree_once_converged(how):
    p = random_chain(12, 2)
    r = solve_arrays(*edges(p), width=3, check_every=2, extract=how, tol=1e-7)
    assert r.converged and np.abs(r.pi - dense_pi(p)).max() < 1e-5


def test_window_rank_and_cost():
    p = random_chain(40, 1, 0.1)
    block, window = solve_arrays(*edges(p), width=2, check_every=5, seed=3), solve_arrays(*edges(p), width=2, depth=3, check_every=5, seed=3)
    assert window.ledger.iterations <= block.ledger.iterations + 5
    assert all(2 <= r["rank"] <= 6 for r in window.log)
    assert window.ledger.matvecs_core == 2 * window.ledger.iterations
    explicit = solve_arrays(*edges(p), width=2, depth=3, check_every=5, seed=3, image="explicit")
    assert explicit.ledger.passes > window.ledger.passes


def test_periodic_chain_does_not_converge_by_power():
    n = 6
    p = np.roll(np.eye(n), 1, axis=1)
    start = np.zeros((n, 1))
    start[0] = 1
    assert not solve_arrays(*edges(p), start=start, max_iter=300).converged
    assert solve_arrays(*edges(p), width=1, depth=n, start=start, check_every=8, max_iter=300).converged


def test_near_periodic_choice_of_ritz_value():
    r = sd.ritz_eig(sd.triangle(np.eye(5), P.T), np.ones(5), pick="nearest_one")
    assert abs(r.ritz - 1) < 1e-12
    assert abs(sd.ritz_eig(sd.triangle(np.eye(5), P.T), np.ones(5)).ritz - 1) < 1e-12


def test_subspace_and_adaptive():
    p = random_chain(15, 6)
    assert np.abs(solve_arrays(*edges(p), width=3, method="subspace", check_every=3).pi - dense_pi(p)).max() < 1e-7
    assert np.abs(solve_arrays(*edges(p), width=2, check_every="adaptive").pi - dense_pi(p)).max() < 1e-7


def test_sparse_kernel_equals_dense(monkeypatch):
    from ergodica.operators import kernel

    p = random_chain(30, 8, 0.2)
    dense = solve_arrays(*edges(p), width=3, seed=1)
    monkeypatch.setattr(kernel, "DENSE", 0)
    sparse = solve_arrays(*edges(p), width=3, seed=1)
    assert np.abs(dense.pi - sparse.pi).max() < 1e-12
    follow = solve_arrays(*edges(p), follow=0.85, seed=1)
    monkeypatch.setattr(kernel, "DENSE", 1200)
    assert np.abs(follow.pi - solve_arrays(*edges(p), follow=0.85, seed=1).pi).max() < 1e-9


@pytest.mark.parametrize("width", [1, 3, 8, 9, 40])
def test_gather_lists_equal_the_matrix(width):
    """Hubs with many entries, states with none, repeated pairs."""
    from ergodica.operators.kernel import Slots

    rng = np.random.default_rng(width)
    n, m = 300, 4000
    src, dst, prob = rng.integers(0, n, m), np.where(rng.random(m) < 0.3, rng.integers(0, 3, m), rng.integers(0, 200, m)), rng.random(m)
    p = np.zeros((n, n))
    np.add.at(p, (dst, src), prob)
    x = rng.random((n, width))
    assert np.allclose(Slots(src, dst, prob, n).step(x), p @ x, atol=1e-12)


def test_ritz_extractions_keep_the_rate():
    """A ring of 60 states with long excursions: eigen and Schur extractions need as many steps as the least residual, two checks more at most."""
    p = 0.5 * np.eye(60) + 0.3 * np.roll(np.eye(60), 1, axis=1) + 0.2 * np.roll(np.eye(60), -1, axis=1)
    p[0, 30:] += 0.2 / 30
    p /= p.sum(axis=1, keepdims=True)
    steps = {how: solve_arrays(*edges(p), width=8, extract=how, check_every=10, seed=1, on_limit="raise").ledger.iterations for how in ("min_residual", "ritz_eig", "ritz_schur")}
    assert max(steps.values()) <= steps["min_residual"] + 20
    with pytest.raises(RuntimeError):
        solve_arrays(*edges(p), max_iter=10, on_limit="raise")


def test_costs():
    assert saving(50_910_000, 4_000_000) == pytest.approx(92.14, abs=0.01) and storage(10, 2, 4) == 80
    assert predicted_iterations(0.99980009) == pytest.approx(115_170, rel=1e-3)
    table = costs([1, 0.9998, 0.9996, 0.5483])
    assert min(table, key=lambda r: r["matvecs"])["width"] == 3
    lo, hi = window_bounds([1, 0.99, 0.9, 0.5], 1, 2)
    assert lo < hi
    assert crowding([1 - 0.001 * j**2 for j in range(8)]) == pytest.approx(2, abs=0.01)
