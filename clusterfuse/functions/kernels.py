"""Batched numpy kernels of the pair measures; every argument has a leading batch axis."""

from __future__ import annotations

import math

import numpy as np

MEASURES = ("b", "js", "w", "vr", "ab", "o", "oh")
LN2 = math.log(2.0)


def lndet(s: np.ndarray) -> np.ndarray:
    """Log-determinants by Cholesky; nan where a matrix isn't positive definite."""
    try:
        return 2 * np.log(np.diagonal(np.linalg.cholesky(s), axis1=-2, axis2=-1)).sum(-1)
    except np.linalg.LinAlgError:
        if len(s) == 1:
            return np.array([np.nan])
        half = len(s) // 2
        return np.concatenate([lndet(s[:half]), lndet(s[half:])])


def cluster_lndet(n: np.ndarray, s: np.ndarray) -> np.ndarray:
    """As lndet, and nan where n samples cannot span D axes."""
    out = lndet(s)
    scale = np.log(np.maximum(np.diagonal(s, axis1=-2, axis2=-1), 1e-300)).sum(-1)
    return np.where((n - 1 >= s.shape[-1]) & (out > scale - 27.6 * s.shape[-1]), out, np.nan)


def ln_hadamard(diag: np.ndarray) -> np.ndarray:
    with np.errstate(divide="ignore", invalid="ignore"):
        out = np.log(diag).sum(-1)
    return np.where(np.isfinite(out), out, np.nan)


def lse(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """ln(e^a + e^b); a missing side counts as zero volume."""
    top = np.fmax(a, b)
    with np.errstate(invalid="ignore"):
        both = top + np.log1p(np.exp(-np.abs(a - b)))
    return np.where(np.isnan(a) | np.isnan(b), top, both)


def fused_cov(n1, m1, s1, n2, m2, s2) -> np.ndarray:
    n, d = n1 + n2, m1 - m2
    w1, w2, gap = (n1 - 1) / (n - 1), (n2 - 1) / (n - 1), n1 / n * n2 / (n - 1)
    return w1[:, None, None] * s1 + w2[:, None, None] * s2 + gap[:, None, None] * d[:, :, None] * d[:, None, :]


def mahalanobis(s: np.ndarray, d: np.ndarray) -> np.ndarray:
    try:
        return (d * np.linalg.solve(s, d[..., None])[..., 0]).sum(-1)
    except np.linalg.LinAlgError:
        return np.array([np.nan if np.linalg.matrix_rank(x) < len(x) else float(v @ np.linalg.solve(x, v)) for x, v in zip(s, d)])


def wasserstein2(m1, s1, m2, s2) -> np.ndarray:
    """Squared 2-Wasserstein distance."""
    lam, vec = np.linalg.eigh(s1)
    root = (vec * np.sqrt(np.maximum(lam, 0))[:, None, :]) @ np.swapaxes(vec, -1, -2)
    cross = np.sqrt(np.maximum(np.linalg.eigvalsh(root @ s2 @ root), 0)).sum(-1)
    return ((m1 - m2) ** 2).sum(-1) + np.trace(s1, axis1=-2, axis2=-1) + np.trace(s2, axis1=-2, axis2=-1) - 2 * cross


def kl_to(m, s, mean, avg) -> np.ndarray:
    """Divergence of N(m, s) from N(mean, avg)."""
    inverse = np.linalg.inv(avg)
    return 0.5 * (np.einsum("bij,bji->b", inverse, s) + lndet(avg) - lndet(s) + mahalanobis(avg, mean - m) - s.shape[-1])


def pair_measures(n1, m1, s1, n2, m2, s2, which=MEASURES, literal_js=False, l1=None, l2=None) -> dict[str, np.ndarray]:
    """The asked measures of each pair; nan where one isn't defined. l1, l2: log-determinants if they are known."""
    n1, n2 = np.asarray(n1, float), np.asarray(n2, float)
    out, d = {}, m1 - m2
    if set(which) - {"oh", "w"}:
        l1 = cluster_lndet(n1, s1) if l1 is None else l1
        l2 = cluster_lndet(n2, s2) if l2 is None else l2
    if set(which) & {"b", "ab", "js"}:
        avg = (s1 + s2) / 2
        la, far = lndet(avg), mahalanobis(avg, d) / 8
        if "b" in which or "js" in which:
            b = far + 0.5 * (la - 0.5 * (l1 + l2))
            out["b"] = b
            if "js" in which:
                mid = (m1 + m2) / 2
                out["js"] = (kl_to(m1, s1, mid, avg) + kl_to(m2, s2, mid, avg)) / 2 if literal_js else b
        out["ab"] = far + 0.5 * (la + LN2 - lse(l1, l2))
    if set(which) & {"vr", "o"}:
        ln_vr = cluster_lndet(n1 + n2, fused_cov(n1, m1, s1, n2, m2, s2)) - lse(l1, l2)
        with np.errstate(over="ignore"):
            out["vr"], out["o"] = np.exp(ln_vr), ln_vr + LN2
    if "oh" in which:
        # diagonals are all that it needs: linear in D
        one, two = (np.diagonal(s, axis1=-2, axis2=-1) for s in (s1, s2))
        n = n1 + n2
        fused = ((n1 - 1) / (n - 1))[:, None] * one + ((n2 - 1) / (n - 1))[:, None] * two + (n1 / n * n2 / (n - 1))[:, None] * d * d
        out["oh"] = LN2 + ln_hadamard(fused) - lse(ln_hadamard(one), ln_hadamard(two))
    if "w" in which:
        out["w"] = wasserstein2(m1, s1, m2, s2)
    return {k: out[k] for k in which}


def literal_forms(n1, m1, s1, n2, m2, s2) -> dict[str, np.ndarray]:
    """b and o from determinants themselves, as they are printed: at many axes determinants leave the range of doubles and the values are lost."""
    n1, n2, d = np.asarray(n1, float), np.asarray(n2, float), m1 - m2
    det = np.linalg.det
    with np.errstate(divide="ignore", invalid="ignore"):
        one, two, avg = det(s1), det(s2), (s1 + s2) / 2
        b = mahalanobis(avg, d) / 8 + 0.5 * np.log(det(avg) / np.sqrt(one * two))
        return {"b_literal": b, "o_literal": np.log(det(fused_cov(n1, m1, s1, n2, m2, s2)) / ((one + two) / 2))}


def _ld(s: np.ndarray) -> float:
    if len(s) == 2:
        return math.log(s[0, 0] * s[1, 1] - s[0, 1] * s[1, 0])
    return 2 * float(np.log(np.linalg.cholesky(s).diagonal()).sum())


def _sum_exp(a: float, b: float) -> float:
    return max(a, b) + math.log1p(math.exp(-abs(a - b)))


def one_pair(measure: str, n1, m1, s1, n2, m2, s2) -> float:
    """One measure of one pair without a batch axis, for positive definite clusters; js literally, vr from determinants."""
    d = m1 - m2
    if measure in ("vr", "o", "oh"):
        n = n1 + n2
        w1, w2, gap = (n1 - 1) / (n - 1), (n2 - 1) / (n - 1), n1 / n * n2 / (n - 1)
        if measure == "oh":
            one, two = s1.diagonal(), s2.diagonal()
            return LN2 + float(np.log(w1 * one + w2 * two + gap * d * d).sum()) - _sum_exp(float(np.log(one).sum()), float(np.log(two).sum()))
        fused = w1 * s1 + w2 * s2 + (gap * d)[:, None] * d
        if measure == "vr":
            return float(np.linalg.det(fused) / (np.linalg.det(s1) + np.linalg.det(s2)))
        return LN2 + _ld(fused) - _sum_exp(_ld(s1), _ld(s2))
    if measure == "w":
        return float(wasserstein2(m1[None], s1[None], m2[None], s2[None])[0])
    avg = (s1 + s2) / 2
    if measure == "js":
        inverse, la, half = np.linalg.inv(avg), _ld(avg), d / 2
        far = float(half @ inverse @ half)
        return sum(0.5 * (float((inverse * s).sum()) + la - _ld(s) + far - len(d)) for s in (s1, s2)) / 2
    far, l1, l2 = float(d @ np.linalg.solve(avg, d)) / 8, _ld(s1), _ld(s2)
    return far + 0.5 * (_ld(avg) - ((l1 + l2) / 2 if measure == "b" else _sum_exp(l1, l2) - LN2))


def o_lower_bound(dim, n1, l1, lam1, n2, l2, lam2, gap2) -> np.ndarray:
    """A value that O never falls below, from what is kept of each cluster: log-determinant and largest eigenvalue (or trace)."""
    n = n1 + n2
    w1, w2, c = (n1 - 1) / (n - 1), (n2 - 1) / (n - 1), n1 / n * n2 / (n - 1)
    spread = dim * lse(np.log(w1) + l1 / dim, np.log(w2) + l2 / dim)
    return LN2 + spread + np.log1p(c * gap2 / (w1 * lam1 + w2 * lam2)) - lse(l1, l2)


def digamma(x: float) -> float:
    out = 0.0
    while x < 8:
        out -= 1 / x
        x += 1
    y = 1 / (x * x)
    return out + math.log(x) - 0.5 / x - y * (1 / 12 - y * (1 / 120 - y * (1 / 252 - y / 240)))


def trigamma(x: float) -> float:
    out = 0.0
    while x < 8:
        out += 1 / (x * x)
        x += 1
    y = 1 / (x * x)
    return out + 1 / x + y / 2 + y / x * (1 / 6 - y * (1 / 30 - y / 42))


def null_bias(dim: int, n1: int, n2: int) -> float:
    """Expected O of two samples of one Gaussian.

    Log-determinants of sample covariances are biased by D and n, and the log of the mean volume lies above the mean of
    the logs by an eighth of the variance of their difference."""
    if min(n1, n2) <= dim:
        return math.nan

    def bias(nu: int) -> float:
        return sum(digamma((nu - i) / 2) for i in range(dim)) + dim * math.log(2 / nu)

    spread = sum(trigamma((n - 1 - i) / 2) for n in (n1, n2) for i in range(dim))
    return bias(n1 + n2 - 1) - 0.5 * (bias(n1 - 1) + bias(n2 - 1)) - spread / 8


def flops(measure: str, dim: int) -> float:
    """Rough operation counts of one pair, with the log-determinants of the two clusters at hand."""
    chol, solve, eig = dim**3 / 3, 2 * dim**2, 9 * dim**3
    return {"b": chol + solve + dim**2, "js": 2 * chol + 4 * dim**3, "w": 2 * eig + 4 * dim**3, "vr": chol + 3 * dim**2, "ab": chol + solve + dim**2, "o": chol + 3 * dim**2, "oh": 8.0 * dim}[measure]
