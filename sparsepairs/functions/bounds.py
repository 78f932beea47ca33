"""Closed forms: guarantees, sample sizes and errors of the estimators."""

from __future__ import annotations

from math import ceil, comb, inf, log2, sqrt

#: Fixed value: the printed constant of the sampling bound at failure 1/6, where 13.35 follows from the formula.
PRINTED = 14.0


def k_for(eps: float) -> int:
    """Pairs to keep for a relative error ``eps`` < 1/4."""
    if not 0 < eps < 0.25:
        raise ValueError("eps must lie in (0, 1/4)")
    return ceil(9 / eps**2 - 1e-9)


def eps_for(k: int) -> float:
    """Relative error that ``k`` kept pairs give in two of three runs."""
    return 3 / sqrt(k)


def regime(z: float, k: int) -> str:
    """``guarantee`` above k^2 pairs, else only an upper bound."""
    return "guarantee" if z > k * k else "bound"


def overshoot(eps: float, k: int) -> float:
    return (1 + eps) / (k * eps**2)


def undershoot(eps: float, k: int) -> float:
    return (1 - eps) / (k * eps**2)


def unfilled(z: float, p: float, k: int) -> float:
    """Bound of the chance that fewer than k pairs fall below p."""
    return z * p / (z * p - k) ** 2 if z * p > k else 1.0


def runs_for(delta: float) -> int:
    """Smallest odd number of runs whose median fails with at most ``delta``, a run failing with 1/3."""
    r = 1
    while sum(comb(r, i) * 2 ** (r - i) for i in range((r + 1) // 2, r + 1)) / 3**r > delta:
        r += 2
    return r


def expected_hits(p: float, joined: float) -> float:
    return p * joined


def work_ok(p: float, left: int, right: int, doubled: bool = True) -> bool:
    """Whether a group's expected hits stay within its size (twice that for the doubled policy)."""
    return p * left * right <= (2 if doubled else 1) * max(left, right)


def variance_bound(z: float, na: float, nc: float, p1: float, p2: float) -> float:
    return (nc / p1 + na / p2 + 1 / (p1 * p2)) * z


def variance_exact(row_squares: float, col_squares: float, z: float, p1: float, p2: float) -> float:
    """Variance of the scaled sample count from the sums of squared row and column degrees."""
    q1, q2 = p1 - p1 * p1, p2 - p2 * p2
    return (p2 * p2 * q1 * row_squares + p1 * p1 * q2 * col_squares + z * q1 * q2) / (p1 * p2) ** 2


def deviation_bound(n1: float, n2: float, na: float, nc: float, s: float, eps: float, z: float) -> float:
    return (nc * n1 + na * n2 + n1 * n2 / s) / (s * eps**2 * z)


def constant(delta: float = 1 / 6, printed: bool = True) -> float:
    """(1 + 1 / (2 sqrt delta)) / delta, or the printed 14 at 1/6."""
    return PRINTED if printed and abs(delta - 1 / 6) < 1e-12 else (1 + 1 / (2 * sqrt(delta))) / delta


def sample_size(n1: float, n2: float, na: float, nc: float, z_min: float, eps: float, delta: float = 1 / 6, printed: bool = True) -> float:
    return (nc * n1 + na * n2) / z_min * constant(delta, printed) / eps**2


def beta(n1: float, n2: float, na: float, nc: float, s: float, eps: float, printed: bool = True) -> float:
    """Result size from which samples of ``s`` tuples hold the error ``eps`` with 5/6."""
    return constant(printed=printed) / eps**2 * (nc * n1 + na * n2) / s


def sample_eps(z: float, na: float, nc: float, p1: float, p2: float, printed: bool = True) -> float:
    """Error of sampling at the rates p1 and p2, with 5/6."""
    return sqrt(constant(printed=printed) * (nc / p1 + na / p2) / z)


def vacuous(eps: float) -> bool:
    """Errors above 1 say nothing."""
    return eps > 1


def rounds_for(eps: float) -> int:
    """Rounds of the min-rank baseline."""
    return ceil(1 / eps**2 - 1e-9) + 1


def prior_space_bound(n1: float, n2: float, z: float, eps: float) -> float:
    """Lower bound of any sampling sketch, in tuples, below n1 + n2: up to constants n1 n2 / (eps^2 z)."""
    return min(n1 + n2, sqrt(n1 * n2 / (1 / 6 * z)) / eps) if z else inf


def sort_bound(n: float, block: float, memory: float) -> float:
    """Block transfers of an external sort, up to a constant."""
    if n <= block:
        return 1.0
    return n / block * max(1.0, log2(n / block) / log2(max(2.0, memory / block)))


def space_bits(k: int, domain_bits: int = 60) -> int:
    """Bits of a kept set: two attribute hashes for each pair."""
    return 2 * domain_bits * k
