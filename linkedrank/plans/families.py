"""Families of networks: k-means on potential times log size decides who may share slots."""

from __future__ import annotations

import math
import random

from linkedrank.plans.networks import Network


def potential(net: Network, best: dict[str, float]) -> float:
    """Sum of the best row ceilings over the size."""
    return sum(best[rel] for rel, matched in net.nodes if matched) / net.size


def weight(net: Network, best: dict[str, float], log_shift: int = 1) -> float:
    return potential(net, best) * math.log(net.size + log_shift)


def kmeans_1d(values: list[float], k: int, seed: int = 0, restarts: int = 5) -> tuple[list[int], float]:
    """Lloyd's iterations from k-means++ starts; the least squared error of all restarts."""
    best, error = [0] * len(values), math.inf
    for r in range(restarts):
        rng = random.Random(seed * 1009 + r)
        centers = [rng.choice(values)]
        while len(centers) < k:
            gaps = [min((v - c) ** 2 for c in centers) for v in values]
            centers.append(rng.choices(values, gaps)[0] if sum(gaps) > 0 else rng.choice(values))
        label = None
        while True:
            new = [min(range(k), key=lambda j: ((v - centers[j]) ** 2, j)) for v in values]
            if new == label:
                break
            label = new
            for j in range(k):
                own = [v for v, a in zip(values, label) if a == j]
                centers[j] = sum(own) / len(own) if own else centers[j]
        e = sum((v - centers[a]) ** 2 for v, a in zip(values, label))
        if e < error - 1e-12:
            best, error = label, e
    return best, error


def exact_error(values: list[float], k: int) -> float:
    """Least squared error of any k clusters of numbers, by dynamic programming."""
    v = sorted(values)
    n = len(v)
    cost = [[0.0] * (n + 1) for _ in range(n + 1)]
    for i in range(n):
        for j in range(i + 1, n + 1):
            m = sum(v[i:j]) / (j - i)
            cost[i][j] = sum((x - m) ** 2 for x in v[i:j])
    best = [cost[0][j] for j in range(n + 1)]
    for _ in range(k - 1):
        best = [0.0] + [min(best[i] + cost[i][j] for i in range(j)) for j in range(1, n + 1)]
    return best[n]


def cluster(networks: list[Network], best: dict[str, float], ratio: float = 0.6, seed: int = 0, restarts: int = 5) -> dict[str, int]:
    """Family of each network: ratio 0 all share, ratio 1 none share."""
    k = max(1, round(ratio * len(networks)))
    if k <= 1 or k >= len(networks):
        return {n.code: (i if k > 1 else 0) for i, n in enumerate(networks)}
    labels, _ = kmeans_1d([weight(n, best) for n in networks], k, seed, restarts)
    return {n.code: a for n, a in zip(networks, labels)}
