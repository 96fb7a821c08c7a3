"""Bounds on the largest bucket and the conditions under which the cost statements hold."""

from __future__ import annotations

import math


def segment(n: int, p: int, s: int) -> int:
    """Length of a padded segment: lanes of ceil(n/p) cut into s."""
    return max(1, -(-max(1, -(-n // p)) // s))


def regular(n: int, p: int, r: int, form: str = "exact") -> float:
    """Largest bucket of the deterministic sort: exact (s + p - 1) x, safe (1+1/r)n/p + (r+1)p, printed with rp instead."""
    s = r * p
    if form == "exact":
        return (s + p - 1) * segment(n, p, s)
    return (1 + 1 / r) * n / p + (r + 1 if form == "safe" else r) * p


def random(n: int, p: int, omega: float) -> float:
    """(1 + 1/w) n / p, with high probability."""
    return (1 + 1 / omega) * n / p


def claim_probability(n: int, rho: float) -> float:
    """Chance that some bucket passes (1 + eps) times its share, with samples of claim_size."""
    return float(n) ** -rho


def synchronisation_fits(n: int, p: int, l_ops: float) -> bool:
    """L <= 2 n / (p lg^2 p): the work outweighs synchronisation."""
    return p < 2 or l_ops <= 2 * n / (p * math.log2(p) ** 2)


def regular_conditions(n: int, p: int, r: int, lanes: int | None = None, l_ops: float | None = None) -> list[str]:
    """Which conditions of the deterministic method fail: on the sample of all lanes and, given L, on synchronisation."""
    w = lanes or p
    out = []
    if n > 2 and w * p * r * r > n / math.log2(n):
        out.append(f"lanes p r^2 = {w * p * r * r} is over n / lg n = {n / math.log2(n):.0f}: the sample is no longer a small share of the work")
    if l_ops is not None and not synchronisation_fits(n, p, l_ops):
        out.append("L is over 2 n / (p lg^2 p): synchronisation outweighs the work")
    return out


def random_conditions(n: int, p: int, omega: float, l_ops: float | None = None) -> list[str]:
    lg = math.log2(max(2, n))
    out = []
    if 2 * p * omega**2 * lg >= n / 2:
        out.append("the sample is half of the keys or more")
    if p * p > n / (omega * lg):
        out.append("p^2 is over n / (w lg n)")
    if l_ops is not None and not synchronisation_fits(n, p, l_ops):
        out.append("L is over 2 n / (p lg^2 p): synchronisation outweighs the work")
    return out
