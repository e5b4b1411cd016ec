"""Invariants of the tensor-train kernels."""

from math import prod

import numpy as np
import pytest

from traincube.functions import kernels as K
from traincube.functions import ordering, shapes


def smooth(modes):
    x = np.arange(prod(modes)) / prod(modes)
    return -np.log(np.abs(x - 0.5) + 1e-3)


@pytest.mark.parametrize("modes", [[7], [3, 4], [2, 3, 5], [4, 2, 2, 3], [2, 2, 2, 2, 2], [2, 1, 3, 2, 2, 5]])
@pytest.mark.parametrize("tau", [0.0, 1e-8, 1e-4, 1e-2, 1e-1])
def test_error_is_within_the_budget_and_measured(modes, tau):
    rng = np.random.default_rng(0)
    for x in (rng.standard_normal(prod(modes)), smooth(modes)):
        cores, lost = K.decompose(x, modes, tau)
        err = np.linalg.norm(K.expand(cores) - x)
        assert err <= tau * np.linalg.norm(x) * (1 + 1e-10) + 1e-12
        assert abs(err - np.sqrt(lost)) <= 1e-7 * np.linalg.norm(x)
        for c in cores[:-1]:
            u = c.reshape(-1, c.shape[2], order="F")
            assert np.allclose(u.T @ u, np.eye(u.shape[1]), atol=1e-9)


def test_orientation():
    x = np.array([100 * i + 10 * j + k for k in range(1, 6) for j in range(1, 4) for i in range(1, 3)], float)
    cores, _ = K.decompose(x, [2, 3, 5], 1e-13)
    for i in range(2):
        for j in range(3):
            for k in range(5):
                assert np.isclose(K.expand(cores)[i + 2 * j + 6 * k], 100 * (i + 1) + 10 * (j + 1) + k + 1)
                assert np.isclose(K.entries(cores, np.array([[i, j, k]]))[0], 100 * (i + 1) + 10 * (j + 1) + k + 1)


def test_element_eleven_of_sixteen_is_at_3_1_2():
    d = [(10 // s) % n + 1 for n, s in zip([4, 2, 2], shapes.strides([4, 2, 2]))]
    assert d == [3, 1, 2]
    assert shapes.modes_for_vector(4, 3) == [4, 2, 2]
    assert shapes.modes_for_matrix(4, 3) == [4, 4, 2, 2, 2, 2]
    assert shapes.modes_for_matrix(4, 3, merge_pairs=True) == [16, 4, 4]


def test_arithmetic_commutes_with_expansion():
    rng = np.random.default_rng(1)
    modes = [2, 3, 4]
    x, y = rng.standard_normal((2, 24))
    a, b = (K.decompose(v, modes, 0.0)[0] for v in (x, y))
    assert np.allclose(K.expand(K.add(a, b)), x + y)
    assert np.allclose(K.expand(K.sub(a, b)), x - y)
    assert np.allclose(K.expand(K.hadamard(a, b)), x * y)
    assert np.isclose(K.dot(a, b), x @ y) and np.isclose(K.norm(a), np.linalg.norm(x))
    t = x.reshape(modes, order="F")
    assert np.allclose(K.expand(K.fix(a, {1: 2})), t[:, 2].ravel(order="F"))
    assert np.allclose(K.expand(K.contract(a, {0: np.ones(2), 2: np.ones(4)})), t.sum((0, 2)))
    assert np.isclose(K.expand(K.contract(a, {k: np.ones(n) for k, n in enumerate(modes)}))[0], x.sum())
    assert K.ranks(K.recompress(K.add(a, a), 1e-12)[0]) == K.ranks(a)
    assert np.allclose(K.expand(K.delta(modes, [1, 2, 3], 5.0)), np.eye(24)[23] * 5)


def test_concat_and_stack():
    rng = np.random.default_rng(2)
    parts = [[rng.standard_normal((a, n, b)) for a, n, b in ((1, 4, r), (r, 3, s), (s, 2, 1))] for r, s in ((2, 3), (3, 2))]
    joined = K.concat(parts)
    assert K.ranks(joined) == [1, 5, 5, 1] and [c.shape[1] for c in joined] == [8, 3, 2]
    whole = np.concatenate([K.expand(p).reshape(4, 3, 2, order="F") for p in parts]).ravel(order="F")
    assert np.allclose(K.expand(joined), whole)
    rounded, _ = K.recompress(joined, 1e-12)
    assert np.allclose(K.expand(rounded), whole) and max(K.ranks(rounded)) <= 5
    stacked = np.concatenate([K.expand(p) for p in parts])
    assert np.allclose(K.expand(K.stack(parts)), stacked)
    for tau in (1e-12, 0.1, 0.5):
        got, lost = K.stack_rounded(parts, tau)
        err = np.linalg.norm(K.expand(got) - stacked)
        assert err <= tau * np.linalg.norm(stacked) * (1 + 1e-9) + 1e-12 and abs(err - np.sqrt(lost)) < 1e-6 * np.linalg.norm(stacked)


def test_edge_cases():
    cores, lost = K.decompose(np.zeros(12), [3, 4], 0.1)
    assert K.ranks(cores) == [1, 1, 1] and lost == 0
    assert K.ranks(K.decompose(np.full(83, 2.5), [83], 1e-3)[0]) == [1, 1]
    assert K.ranks(K.decompose(np.full(16, 2.5), [2] * 4, 1e-12)[0]) == [1] * 5
    one = K.rank_one([np.array([1.0, 2]), np.array([3.0, 4, 5]), np.array([1.0, -1])])
    assert K.ranks(K.decompose(K.expand(one), [2, 3, 2], 1e-10)[0]) == [1, 1, 1, 1]
    capped, lost = K.decompose(np.random.default_rng(0).standard_normal(64), [4, 4, 4], 0.0, max_rank=2)
    assert max(K.ranks(capped)) <= 2 and lost > 0


def test_published_ratios_of_the_kernel():
    """The sampled kernel at 1024 x 1024: printed ratios and absolute spectral errors, to two digits."""
    n, d = 1024, 10
    x = (np.arange(n) + 0.5) / n
    m = -np.log(np.abs(x[:, None] - x[None, :]) + 1e-5)
    # Ratio and error by (tolerance, level).
    want = {
        (1e-2, 6): (1.6e2, 7.5e-1), (1e-2, 7): (4.9e2, 7.7e-1), (1e-2, 8): (1.0e3, 9.6e-1),
        (1e-5, 6): (1.0e2, 1.1e-3), (1e-5, 7): (2.9e2, 1.3e-3), (1e-5, 8): (4.6e2, 1.1e-3),
        (1e-8, 6): (7.5e1, 9.8e-7), (1e-8, 7): (2.0e2, 1.0e-6), (1e-8, 8): (3.1e2, 1.0e-6),
        (1e-11, 6): (6.3e1, 1.5e-9), (1e-11, 7): (1.6e2, 1.5e-9), (1e-11, 8): (2.2e2, 1.1e-9),
    }
    for (tau, level), (ratio, error) in want.items():
        one = shapes.modes_for_vector(d, level)
        turn = [v for k in range(level) for v in (k, level + k)]
        t = m.reshape(one + one, order="F").transpose(turn)
        cores, _ = K.decompose(t.ravel(order="F"), list(t.shape), tau)
        y = K.expand(cores).reshape(t.shape, order="F").transpose(np.argsort(turn)).reshape(n, n, order="F")
        assert abs(n * n / K.numel(cores) / ratio - 1) < 0.06
        assert abs(np.linalg.norm(m - y, 2) / error - 1) < 0.06


def test_sizes_and_keys():
    assert [shapes.smooth_ceiling(n) for n in (15, 150, 1500, 488376)] == [16, 160, 1600, 500000]
    assert shapes.small_primes(83) == [83] and shapes.small_primes(500) == [2, 2, 5, 5, 5]
    cells = np.stack(np.meshgrid(*[np.arange(8)] * 3, indexing="ij"), -1).reshape(-1, 3)
    assert sorted(ordering.morton_array(cells, 3)) == list(range(512))
    key = ordering.hilbert_array(cells, 3)
    assert sorted(key) == list(range(512))
    walk = cells[np.argsort(key)]
    assert (np.abs(np.diff(walk, axis=0)).sum(1) == 1).all()


def test_distance_is_that_of_the_expanded_train():
    rng = np.random.default_rng(5)
    for modes in ([7], [3, 4], [2, 3, 5, 4]):
        x = rng.standard_normal(int(np.prod(modes)))
        cores, lost = K.decompose(x, modes, 0.4)
        assert np.isclose(K.distance(cores, x), np.linalg.norm(K.expand(cores) - x)) and np.isclose(K.distance(cores, x) ** 2, lost)


def test_loose_cuts_need_no_svd(monkeypatch):
    """At loose tolerances all cuts come from products of the smaller side; ranks and errors are those of the SVD."""
    rng = np.random.default_rng(4)
    x = (np.outer(rng.standard_normal(256), rng.standard_normal(240)) + 0.2 * rng.standard_normal((256, 240))).ravel(order="F")
    modes = [2] * 8 + [2, 2, 2, 2, 5, 3]
    for tau in (0.01, 0.1, 0.5):
        monkeypatch.setattr(K, "GRAM_SQUARE", np.inf)
        monkeypatch.setattr(K, "GRAM_LEAST", np.inf)
        want, off = K.decompose(x, modes, tau)
        monkeypatch.undo()
        with monkeypatch.context() as m:
            m.setattr(np.linalg, "svd", None)
            got, lost = K.decompose(x, modes, tau)
        assert K.ranks(got) == K.ranks(want) and np.isclose(lost, off) and np.allclose(K.expand(got), K.expand(want))
        assert np.isclose(np.linalg.norm(K.expand(got) - x), np.sqrt(lost)) and lost <= (tau * np.linalg.norm(x)) ** 2
        for c in got[:-1]:
            m = c.reshape(-1, c.shape[2], order="F")
            assert np.allclose(m.T @ m, np.eye(c.shape[2]), atol=1e-9)
