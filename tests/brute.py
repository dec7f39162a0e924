"""Slow, independent versions of the measures, of cliques and of fused clusters."""

from itertools import combinations

import numpy as np


def measures(n1, m1, s1, n2, m2, s2):
    avg, d = (s1 + s2) / 2, m1 - m2
    ld = lambda s: np.linalg.slogdet(s)[1]
    far = d @ np.linalg.inv(avg) @ d / 8
    b = far + 0.5 * (ld(avg) - (ld(s1) + ld(s2)) / 2)
    mid = (m1 + m2) / 2
    kl = lambda m, s: 0.5 * (np.trace(np.linalg.inv(avg) @ s) + ld(avg) - ld(s) + (mid - m) @ np.linalg.inv(avg) @ (mid - m) - len(m))
    lam, v = np.linalg.eigh(s1)
    root = v @ np.diag(np.sqrt(lam)) @ v.T
    w = d @ d + np.trace(s1) + np.trace(s2) - 2 * np.sqrt(np.maximum(np.linalg.eigvalsh(root @ s2 @ root), 0)).sum()
    n = n1 + n2
    mean = (n1 * m1 + n2 * m2) / n
    fused = ((n1 - 1) * s1 + (n2 - 1) * s2 + n1 * np.outer(m1 - mean, m1 - mean) + n2 * np.outer(m2 - mean, m2 - mean)) / (n - 1)
    both = np.logaddexp(ld(s1), ld(s2))
    h = lambda s: np.log(np.diag(s)).sum()
    return {
        "b": b, "js": (kl(m1, s1) + kl(m2, s2)) / 2, "w": w, "vr": np.exp(ld(fused) - both), "ab": far + 0.5 * (ld(avg) + np.log(2) - both),
        "o": np.log(2) + ld(fused) - both, "oh": np.log(2) + h(fused) - np.logaddexp(h(s1), h(s2)),
    }


def spd(rng, dim, scale=1.0):
    a = rng.normal(size=(dim, dim + 3))
    return scale * (a @ a.T) / dim + 0.1 * np.eye(dim)


def maximal_cliques(nodes, edges):
    adjacent = {frozenset(e) for e in edges}
    cliques = [set(c) for k in range(1, len(nodes) + 1) for c in combinations(nodes, k) if all(frozenset(p) in adjacent for p in combinations(c, 2))]
    return sorted(sorted(c) for c in cliques if len(c) > 1 and not any(c < d for d in cliques))


def fused(parts):
    """n, mean, covariance of clusters (n, mean, cov) together."""
    n = sum(p[0] for p in parts)
    mean = sum(p[0] * p[1] for p in parts) / n
    scatter = sum((p[0] - 1) * p[2] + p[0] * np.outer(p[1] - mean, p[1] - mean) for p in parts)
    return n, mean, scatter / (n - 1)


def iterative(clusters, threshold):
    """Fuse the best pair until none lies below the threshold: member lists, rounds, pairs measured."""
    now, rounds = {i: ([i], c) for i, c in enumerate(clusters)}, 1
    value = {(i, j): measures(*now[i][1], *now[j][1])["o"] for i, j in combinations(sorted(now), 2)}
    pairs = len(value)
    while value and min(value.values()) < threshold:
        i, j = min(value, key=lambda p: (value[p], p))
        one, two = now.pop(i), now.pop(j)
        value = {p: v for p, v in value.items() if not {i, j} & set(p)}
        now[i] = (sorted(one[0] + two[0]), fused([one[1], two[1]]))
        for k in now:
            if k != i:
                value[(min(i, k), max(i, k))] = measures(*now[i][1], *now[k][1])["o"]
                pairs += 1
        rounds += 1
    return sorted(m for m, _ in now.values()), rounds, pairs
