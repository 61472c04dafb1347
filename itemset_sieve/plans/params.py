"""Parameters of the three hashed methods for one level, from n, m (itemsets), A (largest support), theta, eps, delta."""

from __future__ import annotations

import math
from dataclasses import dataclass


@dataclass(frozen=True)
class Facts:
    """What a level knows: n transactions, s_min, m itemsets, A their largest support, tolerance and error."""

    n: int
    s_min: int
    m: int
    A: int  # noqa: N815
    theta: float
    eps: float
    delta: float

    @property
    def alpha(self) -> float:
        return self.A / self.n

    @property
    def near(self) -> float:
        return (1 - self.eps) * self.theta


def delta_for(eta: float, max_level: int) -> float:
    """The error of one look-up that keeps the miss probability of every itemset up to max_level below eta."""
    return eta / 2**max_level


def bitsample(f: Facts, rounding: str = "strict") -> dict[str, float]:
    """rho, k bits of a key, L tables, p1 and p2 (agreement at one position of a frequent, of an infrequent pair).

    strict: L is chosen for k rounded up, so that a frequent pair is missed with probability of at most delta;
    ceil: both formulas as printed, each rounded up.
    """
    base = (1 + 2 * f.alpha) / (1 + 2 * f.near)
    p1, p2 = (1 + 2 * f.theta) / (1 + 2 * f.alpha), 1 / base
    rho = (f.alpha - f.theta) / (f.alpha - f.near)
    k_real = math.log(f.m) / math.log(base) if f.m > 1 else 0.0
    l_real = f.m**rho * math.log(1 / f.delta)
    k = max(1, math.ceil(k_real - 1e-9))
    hit = min(p1, 1.0) ** k
    tables = math.ceil(l_real) if rounding == "ceil" else 1 if hit >= 1 else math.ceil(math.log(f.delta) / math.log1p(-hit) - 1e-9)
    return {"rho": rho, "k": k, "L": max(1, tables), "p1": p1, "p2": p2, "k_real": k_real, "L_real": l_real}


def minwise(f: Facts) -> dict[str, float]:
    """omega, eps_m, lambda (slots of a summary) and the share of agreeing slots from which a pair is accepted."""
    a, t, e = f.alpha, f.theta, f.eps
    omega = f.near / (2 * a - f.near)
    eps_m = a * e / (a + (a - t) * (1 - e))
    lam = 2 / (omega * eps_m**2) * math.log(1 / f.delta)
    return {"omega": omega, "eps_m": eps_m, "lambda": math.ceil(lam), "lambda_real": lam, "similar": t / (2 * a - t), "accept": (1 - eps_m) * t / (2 * a - t)}


def banding(slots: int, similar: float, delta: float) -> tuple[int, int]:
    """Bands and rows of each: the most rows with which a pair of that similarity meets with probability 1 - delta."""
    rows = 1
    for r in range(1, slots + 1):
        if (1 - similar**r) ** (slots // r) <= delta:
            rows = r
    return slots // rows, rows


def covering(f: Facts, most_radius: int = 10) -> dict[str, float]:
    """Radius r, far radius, c, t, eps_c, nu, and the block design: b blocks of radius r_b, keys of an itemset.

    The radius is the integer 2 (A - s_min): a frequent pair shares at least s_min transactions. One label of
    t * r + 1 bits a position is out of reach for usual r; blocks bring the radius down without losing a pair.
    """
    r, far = 2 * (f.A - f.s_min), 2 * (f.alpha - f.near) * f.n
    t_real = math.log2(max(f.m, 2)) / max(far, 1e-9)
    t = max(1, math.ceil(t_real))
    c = (f.alpha - f.near) / (f.alpha - f.theta) if f.alpha > f.theta else math.inf
    eps_c = t - t_real
    nu = (t + eps_c) / (c * t)
    blocks = max(1, min(r + 1, math.ceil(far / math.log2(max(f.m, 2)))))
    while r // blocks > most_radius:
        blocks += 1
    radius = r // blocks
    return {"r": r, "far": far, "c": c, "t": t, "eps_c": eps_c, "nu": nu, "b": blocks, "r_b": radius, "keys": blocks * (2 ** (radius + 1) - 1), "n_padded": f.n + 2 * f.A}
