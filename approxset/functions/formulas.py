"""Expected rates, sizes and bounds."""

from __future__ import annotations

import math


def qf_eps(n: int, p: int) -> float:
    """1 - (1 - 2^-p)^n."""
    return -math.expm1(n * math.log1p(-(2.0**-p)))


def bloom_eps(n: int, m: int, k: int) -> float:
    return (-math.expm1(-k * n / m)) ** k


def bits_qf(eps: float, load: float, flags: int = 3) -> float:
    return (math.log2(load / eps) + flags) / load


def bits_bloom(eps: float) -> float:
    return math.log2(1 / eps) / math.log(2)


def capacity_qf(size: int, r: int, load: float = 0.9) -> int:
    return int(load * size * 8 / (r + 3))


def capacity_bloom(size: int, eps: float) -> int:
    return int(size * 8 / bits_bloom(eps))


def max_cluster_bound(m: float, load: float, eps: float = 0.0) -> float:
    return (1 + eps) * math.log(m) / (load - math.log(load) - 1)


def mean_cluster_bound(load: float) -> float:
    return 1 / (1 - load * math.exp(1 - load))
