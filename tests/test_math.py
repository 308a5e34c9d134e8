import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from vecboost.config import BoostConfig
from vecboost.functions import losses as L
from vecboost.functions.significance import paired_t, two_sided, unpaired_t
from vecboost.functions.solve import SOLVERS, check_spd, hessian_of
from vecboost.plans.baselines import round_budget
from vecboost.plans.model import Tree
from vecboost.plans.tuning import grown

S = np.array([[0, 0, 0], [1, 0, -1], [0, 2, 0], [0.5, 0.5, -1]], float)
Y = np.array([0, 1, 1, 2])


def sums(rows):
    loss = L.SoftmaxXent()
    g, h = loss.grad(S, Y)[rows].sum(0)[None], loss.full(S, Y)[rows].sum(0)
    return g, h[np.triu_indices(3)][None], np.diag(h)[None], np.array([len(rows)])


def test_worked_example():
    full, diag, pair = (hessian_of(k, 3) for k in ("full", "diagonal", "pair"))
    g, hf, hd, n = sums(range(4))
    np.testing.assert_allclose(g[0], [0.554897, -0.185136, -0.369762], atol=1e-6)
    np.testing.assert_allclose(full.weight(g, hf, n, 1.0)[0], [-0.267016, 0.050653, 0.216362], atol=1e-6)
    np.testing.assert_allclose(diag.weight(g, hd, n, 1.0)[0], [-0.310421, 0.101601, 0.248228], atol=1e-6)
    np.testing.assert_allclose([full.gain(g, hf, n, 1.0)[0], diag.gain(g, hd, n, 1.0)[0], pair.gain(g, hf, n, 1.0)[0]], [0.118773, 0.141424, 0.114544], atol=1e-6)
    a, b = sums([0, 2]), sums([1, 3])
    split = lambda k, i: k.gain(a[0], a[i], a[3], 1.0)[0] + k.gain(b[0], b[i], b[3], 1.0)[0] - k.gain(g, (hf, hd)[i - 1], n, 1.0)[0]
    np.testing.assert_allclose([split(full, 1), split(diag, 2)], [0.716129, 0.791309], atol=1e-6)


@settings(max_examples=30, deadline=None)
@given(st.integers(1, 8), st.integers(0, 10_000))
def test_solvers_agree_and_full_weights_sum_to_zero(c, seed):
    rng = np.random.default_rng(seed)
    a = rng.normal(size=(6, c, c))
    m, v = a @ a.transpose(0, 2, 1) + 0.5 * np.eye(c), rng.normal(size=(6, c))
    want = np.linalg.solve(m, v[:, :, None])[:, :, 0]
    for name, f in SOLVERS.items():
        if name != "closed" or c <= 3:
            np.testing.assert_allclose(f(m, v), want, rtol=1e-7, atol=1e-7)
    s, y = rng.normal(size=(20, max(c, 2))), rng.integers(0, max(c, 2), 20)
    loss = L.SoftmaxXent()
    g, h = loss.grad(s, y), loss.full(s, y)
    np.testing.assert_allclose(g.sum(1), 0, atol=1e-12)
    np.testing.assert_allclose(h.sum(2), 0, atol=1e-12)
    k = hessian_of("full", max(c, 2))
    w = k.weight(g.sum(0)[None], h.sum(0)[k.up][None], np.array([20]), 1.0)
    assert abs(w.sum()) < 1e-9
    pair = hessian_of("pair", max(c, 2))
    args = (g.sum(0)[None], h.sum(0)[k.up][None], np.array([20]), 1.0)
    assert pair.gain(*args)[0] <= k.gain(*args)[0] + 1e-12


def test_singular_systems():
    h = L.SoftmaxXent().full(S, Y).sum(0)[None]
    v = np.array([[1.0, -0.5, -0.5]])
    for f in ("pivoted_qr", "svd"):
        w = SOLVERS[f](h, v)
        np.testing.assert_allclose((h @ w[:, :, None])[:, :, 0], v, atol=1e-9)
    assert not check_spd(h - 1e-9 * np.eye(3), 0.0)[0] and check_spd(h, 1.0)[0]


def test_first_layer_closed_forms():
    n, c, g = 12, 3, np.array([[2.0, -3.0, 1.0]])
    h = np.full((1, c), n * (c - 1) / c**2)
    np.testing.assert_allclose(hessian_of("diagonal", c).weight(g, h, None, 1.0), -g / (1 + n * (c - 1) / c**2))
    full = hessian_of("full", c)
    m = n * (np.eye(c) / c - 1 / c**2)
    np.testing.assert_allclose(full.weight(g, m[full.up][None], None, 1.0), -g / (1 + n / c), atol=1e-12)


@pytest.mark.parametrize("loss,c", [(L.SoftmaxXent(), 3), (L.MultiExp(L.codewords(3, "centered")), 3), (L.MarginExp(L.codewords(3, "simplex")), 3), (L.ZeroSum(L.SoftmaxXent(), 0.7), 3)])
def test_derivatives_by_differences(loss, c):
    e = 1e-5
    for k in range(c):
        d = np.eye(c)[k] * e
        np.testing.assert_allclose((loss.value(S + d, Y) - loss.value(S - d, Y)) / (2 * e), loss.grad(S, Y)[:, k], atol=1e-6)
        np.testing.assert_allclose((loss.grad(S + d, Y) - loss.grad(S - d, Y)) / (2 * e), loss.full(S, Y)[:, k], atol=1e-6)
    np.testing.assert_allclose(np.einsum("ijj->ij", loss.full(S, Y)), loss.diag(S, Y), atol=1e-12)


def test_autodiff_is_exact():
    def xent(s, y):
        total = L.exp(s[0]) + L.exp(s[1]) + L.exp(s[2])
        own = s[0] * (y == 0) + s[1] * (y == 1) + s[2] * (y == 2)
        return L.log(total) - own

    a, b = L.AutoDiff(xent), L.SoftmaxXent()
    for f in ("value", "grad", "diag", "full"):
        np.testing.assert_allclose(getattr(a, f)(S, Y), getattr(b, f)(S, Y), atol=1e-10)


def test_pairwise_ranking():
    s, grade, group = np.array([0.3, -0.2, 1.0, 0.1]), np.array([1, 0, 0, 2]), np.array([0, 0, 1, 1])
    loss, g, h = L.PairwiseLogistic().derivatives(s, grade, group)
    for k in range(4):
        d = np.eye(4)[k] * 1e-5
        up, down = (L.PairwiseLogistic().derivatives(s + x, grade, group)[0] for x in (d, -d))
        assert abs((up - down) / 2e-5 - g[k]) < 1e-6
    assert (h > 0).all()


def test_codes():
    v = L.codewords(4, "simplex")
    np.testing.assert_allclose((v**2).sum(1), 1)
    np.testing.assert_allclose((v @ v.T)[0, 1:], -1 / 3)
    np.testing.assert_allclose(L.codewords(4, "centered").sum(1), 0, atol=1e-12)


def test_t_tests():
    assert abs(two_sided(2.228139, 10) - 0.05) < 1e-6 and abs(two_sided(1.96, 1e7) - 0.05) < 1e-4
    assert unpaired_t(1, 1, 10, 1, 1, 10)[2] == 1.0
    t, df, p = unpaired_t(20.0, 2.0, 8, 22.0, 3.0, 10)
    assert abs(t + 1.6903) < 1e-3 and 15 < df < 16 and 0.1 < p < 0.12
    assert paired_t(0.5, 1.0, 16)[0] == 2.0


def test_round_budget():
    assert [round_budget(*x) for x in ((100, 26), (10, 10), (25, 10), (25, 26), (10, 3), (10, 26))] == [(4, 104, True), (1, 10, True), (3, 30, True), (1, 26, True), (4, 12, True), (1, 26, False)]


def test_grid_grows_only_at_edges():
    assert grown([0.1, 0.3, 1], 0.3) is None and grown([1, 2, 4], 4) == [1, 2, 4, 8] and grown([0, 1, 2], 0) is None and grown([1, 2, 4], 1) == [0.5, 1, 2, 4]


def test_post_pruning_collapses_bottom_up():
    t = Tree(1, 3)
    for n, g in [(1, 5.0), (2, -4.0), (3, -2.0), (4, 3.0), (5, 0.5), (6, 1.0)]:
        t.split(n, 0, 1, True, g)
    t.collapse()
    assert sorted(j for j in t.nodes() if t.feature[j] >= 0) == [1]


def test_config():
    c = BoostConfig(outputs=4, rows_per_layer=(10, 20), blocks=((0, 1), (2, 3)))
    assert BoostConfig.from_json(c.to_json()) == c and c.quota(0) == 10 and c.quota(5) == 20
    with pytest.raises(ValueError):
        BoostConfig(outputs=100, hessian="full")
    with pytest.raises(ValueError):
        BoostConfig(hessian="other")
