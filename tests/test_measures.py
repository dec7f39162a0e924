import brute
import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from clusterfuse.functions import kernels as K
from clusterfuse.functions import packed as P


def pair(rng, dim):
    return int(rng.integers(dim + 2, 500)), rng.normal(size=dim), brute.spd(rng, dim), int(rng.integers(dim + 2, 500)), rng.normal(size=dim), brute.spd(rng, dim, 3.0)


def kernel(n1, m1, s1, n2, m2, s2, **kw):
    return {k: float(v[0]) for k, v in K.pair_measures(np.array([n1]), m1[None], s1[None], np.array([n2]), m2[None], s2[None], **kw).items()}


@pytest.mark.parametrize("dim", [1, 2, 4, 8, 64, 100])
def test_kernels_match_brute_force(dim):
    args = pair(np.random.default_rng(dim), dim)
    want, got = brute.measures(*args), kernel(*args, literal_js=True)
    for m in K.MEASURES:
        assert got[m] == pytest.approx(want[m], rel=1e-8, abs=1e-8), m
        assert K.one_pair(m, *args) == pytest.approx(want[m], rel=1e-8, abs=1e-8), m


@settings(max_examples=30, deadline=None)
@given(st.integers(0, 10_000), st.integers(1, 6))
def test_identities_and_invariants(seed, dim):
    rng = np.random.default_rng(seed)
    n1, m1, s1, n2, m2, s2 = args = pair(rng, dim)
    x = kernel(*args, literal_js=True)
    assert x["js"] == pytest.approx(x["b"], abs=1e-8)
    assert x["o"] == pytest.approx(np.log(2 * x["vr"]), abs=1e-8)
    assert x["ab"] <= x["b"] + 1e-9 and x["b"] >= -1e-9 and x["w"] >= -1e-9
    swapped = kernel(n2, m2, s2, n1, m1, s1)
    for m in K.MEASURES:
        assert swapped[m] == pytest.approx(x[m], rel=1e-7, abs=1e-7)
    a, shift = rng.normal(size=(dim, dim)) + 2 * np.eye(dim), rng.normal(size=dim)
    moved = kernel(n1, a @ m1 + shift, a @ s1 @ a.T, n2, a @ m2 + shift, a @ s2 @ a.T)
    for m in ("b", "js", "vr", "ab", "o"):
        assert moved[m] == pytest.approx(x[m], rel=1e-5, abs=1e-5)
    q, _ = np.linalg.qr(rng.normal(size=(dim, dim)))
    assert kernel(n1, q @ m1, q @ s1 @ q.T, n2, q @ m2, q @ s2 @ q.T, which=("w",))["w"] == pytest.approx(x["w"], rel=1e-6, abs=1e-6)
    scale = np.diag(rng.uniform(0.1, 10, dim))
    assert kernel(n1, scale @ m1, scale @ s1 @ scale, n2, scale @ m2, scale @ s2 @ scale, which=("oh",))["oh"] == pytest.approx(x["oh"], abs=1e-7)
    self_ = kernel(n1, m1, s1, n1, m1, s1)
    assert self_["o"] == pytest.approx(dim * np.log(2 * (n1 - 1) / (2 * n1 - 1)), abs=1e-8)
    l1, l2 = K.lndet(s1[None]), K.lndet(s2[None])
    assert l1[0] <= K.ln_hadamard(np.diag(s1)[None])[0] + 1e-9
    bound = K.o_lower_bound(dim, np.array([n1]), l1, np.linalg.eigvalsh(s1)[-1:], np.array([n2]), l2, np.linalg.eigvalsh(s2)[-1:], np.array([(m1 - m2) @ (m1 - m2)]))
    assert bound[0] <= x["o"] + 1e-8


def test_small_scale_is_stable_in_high_dimension():
    rng = np.random.default_rng(3)
    s = brute.spd(rng, 100) * 1e-12
    assert np.linalg.det(s) == 0.0
    x = kernel(500, np.zeros(100), s, 500, np.zeros(100), s)
    assert np.isfinite(x["o"]) and np.isfinite(x["b"])


def test_singular_sides():
    flat, full = np.array([[1.0, 1.0], [1.0, 1.0]]), np.eye(2)
    one = kernel(10, np.zeros(2), flat, 10, np.zeros(2), full)
    assert np.isnan(one["b"]) and np.isfinite(one["o"]) and np.isfinite(one["ab"])
    both = kernel(10, np.zeros(2), flat, 10, np.zeros(2), flat)
    assert np.isnan(both["o"])


def test_null_bias_is_that_of_samples():
    rng = np.random.default_rng(5)
    values = []
    for _ in range(200):
        x, y = rng.normal(size=(40, 8)), rng.normal(size=(60, 8))
        values.append(kernel(40, x.mean(0), np.cov(x.T), 60, y.mean(0), np.cov(y.T), which=("o",))["o"])
    assert np.mean(values) == pytest.approx(K.null_bias(8, 40, 60), abs=0.05)


def test_packed_round_trip():
    s = brute.spd(np.random.default_rng(0), 5)
    assert np.array_equal(P.dense(P.packed(s)[None], 5)[0], s)
    assert [P.place(i, j, 5) for i, j in P.slots(5)] == list(range(15)) and P.dim_of(15) == 5
