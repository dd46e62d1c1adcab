"""Chi-squared statistics and the parameters of a forest."""

from __future__ import annotations

import math
from dataclasses import dataclass, replace


def chi2_survival(x: float, k: int) -> float:
    """P(chi-squared with k degrees > x): the regularised upper incomplete gamma function, by series or continued fraction."""
    if x <= 0:
        return 1.0
    a, z = k / 2, x / 2
    front = math.exp(-z + a * math.log(z) - math.lgamma(a))
    if z < a + 1:
        term = total = 1 / a
        n = a
        while term > total * 1e-17:
            n += 1
            term *= z / n
            total += term
        return max(0.0, 1 - front * total)
    tiny = 1e-300
    b = z + 1 - a
    c, d = 1 / tiny, 1 / b
    h = d
    for i in range(1, 10_000):
        an = -i * (i - a)
        b += 2
        d = 1 / (an * d + b or tiny)
        c = b + an / c or tiny
        h *= d * c
        if abs(d * c - 1) < 1e-16:
            break
    return front * h


def chi2_upper(alpha: float, k: int) -> float:
    """x with P(chi-squared with k degrees > x) = alpha."""
    if alpha >= 1:
        return 0.0
    lo, hi = 0.0, float(k) + 10
    while chi2_survival(hi, k) > alpha:
        hi *= 2
    for _ in range(200):
        mid = (lo + hi) / 2
        lo, hi = (mid, hi) if chi2_survival(mid, k) > alpha else (lo, mid)
    return (lo + hi) / 2


def derive_params(K: int, c: float, L: int) -> dict[str, float]:
    """epsilon and beta for which a near point is found by some tree and far points stay few.

    alpha1 is the share of near points that one tree may miss, with
    alpha1 ** L = 1 / e; alpha2 the tail at epsilon squared over c squared.
    """
    alpha1 = math.exp(-1 / L)
    eps2 = chi2_upper(alpha1, K)
    alpha2 = chi2_survival(eps2 / c**2, K)
    return {"alpha1": alpha1, "eps2": eps2, "eps": math.sqrt(eps2), "alpha2": alpha2, "beta": 2 - 2 * alpha2**L}


def beta_table(K: int = 16, c: float = 1.5, most: int = 20) -> list[tuple[int, float, float]]:
    return [(L, derive_params(K, c, L)["eps"], derive_params(K, c, L)["beta"]) for L in range(1, most + 1)]


def pick_L(K: int = 16, c: float = 1.5, most: int = 20, flat: float = 0.15) -> int:
    """First L after which one more space lowers beta by less than `flat` of itself."""
    betas = [b for _, _, b in beta_table(K, c, most)]
    return next((i + 1 for i in range(len(betas) - 1) if (betas[i] - betas[i + 1]) / betas[i] < flat), most)


SUCCESS = 0.5 - 1 / math.e


@dataclass(frozen=True)
class ForestParams:
    """What an index and its queries need. beta below its theoretical value, or a cap on candidates that binds, gives no guarantee."""

    K: int = 16
    L: int = 4
    c: float = 1.5
    beta: float = 0.1
    bits: int = 8
    seed: int = 42
    max_size: int = 64
    sample: float = 0.1
    max_candidates: int | None = None

    @property
    def regions(self) -> int:
        return 1 << self.bits

    @property
    def eps(self) -> float:
        return derive_params(self.K, self.c, self.L)["eps"]

    @property
    def beta_theory(self) -> float:
        return derive_params(self.K, self.c, self.L)["beta"]

    def need(self, n: int, k: int) -> int:
        """Candidates after which a query stops: beta * n + k, rounded up alike in every engine."""
        full = math.ceil(round(self.beta * n + k, 9))
        return full if self.max_candidates is None else min(full, self.max_candidates)

    def guaranteed(self, n: int, k: int) -> bool:
        return self.beta >= self.beta_theory and self.need(n, k) >= math.ceil(round(self.beta * n + k, 9))

    def with_(self, **changes) -> ForestParams:
        return replace(self, **changes)
