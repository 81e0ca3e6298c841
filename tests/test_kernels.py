import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from nearfield.functions import kernels as k
from nearfield.functions.elements import EDGE, ElementModel, unit_cell


def spd(n, seed, spread=0.5):
    a = np.random.default_rng(seed).normal(size=(n, n)) / np.sqrt(n)
    return np.eye(n) + spread * (a @ a.T)


def gapped(n, seed):
    """Symmetric with eigenvalues away from zero."""
    q = np.linalg.qr(np.random.default_rng(seed).normal(size=(n, n)))[0]
    w = np.where(np.arange(n) % 2, 1.0, -1.0) * np.linspace(0.3, 2, n)
    return (q * w) @ q.T


@settings(max_examples=25, deadline=None)
@given(st.integers(1, 30), st.integers(0, 1000), st.integers(2, 6))
def test_sign_of_every_order_is_the_eigensolver_s(n, seed, order):
    a = gapped(n, seed)
    x = k.sign(a, order)
    assert np.abs(x - k.sign_exact(a)).max() < 1e-9
    assert np.abs(k.sign(3.7 * a, order) - x).max() < 1e-9


@pytest.mark.parametrize("terms", [1, 2, 3])
def test_pade_steps_converge_faster_with_more_poles(terms):
    a, r = gapped(25, 1), k.Report()
    assert np.abs(k.sign_pade(a, terms, report=r) - k.sign_exact(a)).max() < 1e-9
    assert r.steps <= {1: 10, 2: 6, 3: 5}[terms]


def test_convergence_is_quadratic():
    a = gapped(20, 2)
    a = a / np.abs(np.linalg.eigvalsh(a)).max()
    x, misses = a, []
    for _ in range(14):
        x = 1.5 * x - 0.5 * x @ x @ x
        misses.append(np.linalg.norm(x @ x - np.eye(20), 2))
    late = [(b, c) for b, c in zip(misses, misses[1:], strict=False) if 1e-7 < b < 1e-1]
    assert late and all(c <= 0.8 * b * b for b, c in late)


@settings(max_examples=20, deadline=None)
@given(st.integers(1, 25), st.integers(0, 1000))
def test_roots_and_inverses(n, seed):
    s = spd(n, seed)
    y, z = k.coupled_roots(s)
    assert np.abs(y @ y - s).max() < 1e-9 and np.abs(y @ z - np.eye(n)).max() < 1e-9
    for how in ("coupled", "cholesky", "lu"):
        assert np.abs(k.inverse(s, how) @ s - np.eye(n)).max() < 1e-9
    for p in (1, 2, 3):
        assert np.abs(np.linalg.matrix_power(k.inverse_root(s, p), p) @ s - np.eye(n)).max() < 1e-8
    assert np.abs(np.linalg.matrix_power(k.MatFn.root(3)(s), 3) - s).max() < 1e-8


def test_polynomial_and_spectral():
    a = gapped(9, 3)
    assert np.allclose(k.polynomial(a, (1, 0, -2, 1)), np.eye(9) - 2 * a @ a + a @ a @ a)
    assert np.allclose(k.spectral(a, np.square), a @ a)


def test_purification_agrees_over_solvers_and_precisions():
    h, s = gapped(24, 4), spd(24, 5, 0.2)
    exact, w, _ = k.purify(h, s, k.Purification(mu=0.05, solver="eigen"))
    assert np.allclose(exact @ s @ exact, exact, atol=1e-10) and np.allclose(w, exact @ h @ exact, atol=1e-10)
    for how in (k.Purification(mu=0.05), k.Purification(mu=0.05, order=4, inverse="cholesky"), k.Purification(mu=0.05, solver="pade", order=2), k.Purification(mu=0.05, solver="exact", inverse="lu"), k.Purification(mu=0.05, pad=16)):
        d, w2, done = k.purify(h, s, how)
        assert np.abs(d - exact).max() < 1e-9 and np.abs(w2 - w).max() < 1e-9
    error = {p: np.abs(k.purify(h, s, k.Purification(mu=0.05, operand=p, k_inverse=8, k_sign=16))[0] - exact).max() for p in ("fp64", "fp32", "tf32", "half", "bf16")}
    assert error["fp64"] < 1e-10 < error["fp32"] < 1e-4 < error["half"] < 5e-2 and error["tf32"] < error["bf16"] < 0.5


def test_fixed_steps_count_products():
    h, s = gapped(10, 6), spd(10, 7, 0.1)
    from nearfield.operators.observables import gemms

    for ki, ks in ((5, 9), (8, 20)):
        for with_w in (True, False):
            done = k.purify(h, s, k.Purification(k_inverse=ki, k_sign=ks), with_w)[2]
            assert done["gemms"] == gemms(ki, ks, with_w)


def test_rounding_of_narrow_formats():
    x = np.array([1 + 2.0**-9, 1 + 2.0**-8, -3.14159, 1e-3], np.float32)
    assert k.Precision("bf16").round(x)[0] == 1.0 and k.Precision("half").round(x)[1] == np.float32(1 + 2.0**-8)
    assert np.abs(k.Precision("tf32").round(x) - x).max() < 2.0**-9
    stored = k.Precision("half", stored=True)
    assert (stored.gemm(x[None], x[:, None]) == stored.gemm(x[None], x[:, None]).astype(np.float16)).all()


def test_stacks_give_what_single_matrices_give():
    pairs = [(gapped(9, i), spd(9, 50 + i)) for i in range(5)]
    h, s = (np.stack(x) for x in zip(*pairs, strict=True))
    calls = {
        "sign": lambda a: k.sign(a, stop=k.StopRule.fixed(30)),
        "sign5": lambda a: k.sign(a, order=5),
        "pade": lambda a: k.sign_pade(a, 2),
        "exact": k.sign_exact,
        "power": lambda a: k.sign(a, scale="power"),
        "poly": lambda a: k.polynomial(a, (1.0, 0.0, 2.0)),
        "exp": lambda a: k.spectral(a, np.exp),
    }
    for f in calls.values():
        assert f(h) == pytest.approx(np.stack([f(x) for x in h]), abs=1e-9)
    for f in (k.inverse, lambda a: k.inverse(a, "cholesky"), lambda a: k.inverse(a, "lu"), lambda a: k.inverse_root(a, 3), lambda a: k.coupled_roots(a)[0]):
        assert f(s) == pytest.approx(np.stack([f(x) for x in s]), abs=1e-9)
    for how in (k.Purification(solver="eigen"), k.Purification(k_inverse=12, k_sign=20, pad=4), k.Purification(solver="exact", inverse="cholesky")):
        assert how.stacks
        d, w, done = k.purify(h, s, how)
        for i, (a, b) in enumerate(pairs):
            d1, w1, done1 = k.purify(a, b, how)
            assert d[i] == pytest.approx(d1, abs=1e-9) and w[i] == pytest.approx(w1, abs=1e-9) and done["gemms"] == done1["gemms"]
            assert np.broadcast_to(done["residual"], 5)[i] == pytest.approx(done1["residual"], abs=1e-12, nan_ok=True)
    assert not k.Purification().stacks and not k.Purification(k_sign=3).stacks


def test_spectral_weights_count_electrons():
    h, s = gapped(12, 8), spd(12, 9, 0.2)
    e, w = k.spectral_weights(h, s, range(12))
    d = k.purify(h, s, k.Purification(mu=0.1, solver="eigen"))[0]
    assert w[e < 0.1].sum() == pytest.approx(np.trace(d @ s)) and w.sum() == pytest.approx(12)


def test_batches_of_equal_sizes():
    matrices = [gapped(n, n) for n in (4, 7, 4, 9, 7)]
    out = k.batched(k.sign, matrices)
    assert all(np.abs(x - k.sign_exact(m)).max() < 1e-9 for x, m in zip(out, matrices, strict=True))


@pytest.mark.parametrize(
    "call",
    [
        lambda: k.sign(np.diag([1.0, 0.0, -1.0])),
        lambda: k.sign(np.array([[0.0, 1.0], [-1.0, 0.0]])),
        lambda: k.sign(np.eye(3) * 3, scale=None),
        lambda: k.sign(np.full((2, 2), np.nan)),
        lambda: k.sign(np.ones((2, 3))),
        lambda: k.coupled_roots(np.diag([1.0, -1.0])),
        lambda: k.inverse(np.diag([1.0, -1.0]), "cholesky"),
        lambda: k.inverse(np.zeros((2, 2)), "lu"),
        lambda: k.inverse(np.eye(2), "magic"),
        lambda: k.inverse_root(np.diag([1.0, -2.0]), 2),
        lambda: k.spectral(np.array([[0.0, 1.0], [0.0, 0.0]]), np.exp),
        lambda: k.purify(np.eye(2), -np.eye(2), k.Purification(solver="eigen")),
        lambda: k.Precision("fp8"),
    ],
)
def test_bad_input_is_told(call):
    with pytest.raises(k.KernelError):
        call()


def test_one_by_one_and_empty():
    assert k.sign(np.array([[-3.0]]))[0, 0] == -1
    assert k.purify(np.array([[-1.0]]), np.array([[2.0]]), k.Purification())[0][0, 0] == pytest.approx(0.5)
    assert k.sign(np.zeros((0, 0))).shape == (0, 0)


def test_elements_are_periodic_and_their_slope_is_the_derivative():
    cell = unit_cell()
    assert len(cell) == 96 and [c[0] for c in cell[:3]] == ["O", "H", "H"]
    names, xyz, box = [c[0] for c in cell], np.array([c[1:] for c in cell]), np.array([EDGE] * 3)
    m = ElementModel()
    h, s, _ = m.pair(names, xyz, box)
    assert np.allclose(h, h.T) and np.linalg.eigvalsh(s)[0] > 0.5
    h2, s2, _ = m.pair(names, xyz + np.array([3.3, -40.0, 9.9]), box)
    assert np.allclose(h, h2) and np.allclose(s, s2)
    r = np.linspace(0.5, 4.4, 50)
    slope = (m.overlap("O", "H")(r + 1e-6) - m.overlap("O", "H")(r - 1e-6)) / 2e-6
    assert np.allclose(m.overlap_slope("O", "H")(r), slope, atol=1e-8)
    assert m.cost("S", "S") / m.cost("O", "O") == pytest.approx(10, rel=0.02)
