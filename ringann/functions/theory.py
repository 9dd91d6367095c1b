"""Formulas: collision probabilities, run-length distribution, candidates of the guarantee, cost table."""

from __future__ import annotations

import math

from pyspark.sql import Column
from pyspark.sql import functions as F


def rp_collision_prob(tau: float, w: float) -> float:
    """Gaussian projections of two points at distance tau fall in one slot of width w."""
    if tau <= 0:
        return 1.0
    r = w / tau
    return math.erf(r / math.sqrt(2)) - 2 / (math.sqrt(2 * math.pi) * r) * (1 - math.exp(-r * r / 2))


def cauchy_collision_prob(tau: float, w: float) -> float:
    if tau <= 0:
        return 1.0
    r = w / tau
    return 2 * math.atan(r) / math.pi - math.log(1 + r * r) / (math.pi * r)


def cp_collision_prob(tau, d: int):
    """Cross-polytope on the unit sphere, leading term; number or Column in (0, 2)."""
    if isinstance(tau, Column):
        return F.exp(-tau * tau / (4 - tau * tau) * math.log(d))
    return math.exp(-tau * tau / (4 - tau * tau) * math.log(d))


def cp_rho(c, r):
    return (4 - c * c * r * r) / (4 - r * r) / (c * c)


def cp_rho_star(c):
    return 1 / (c * c)


def hyperplane_collision_prob(theta: float) -> float:
    return 1 - theta / math.pi


def rho(p1: float, p2: float) -> float:
    return math.log(1 / p1) / math.log(1 / p2)


def shareable(family: str, c: float, radii: list[float]) -> bool:
    """Whether one index serves all radii: its rho stays below a bound under 1 at each of them."""
    return family == "cross_polytope" and all(0 < c * r < 2 and cp_rho(c, r) <= cp_rho_star(c) for r in radii)


def run_cdf_limit(m: int, p: float, x: float) -> float:
    return math.exp(-m * (1 - p) * p**x)


def run_cdf_exact(m: int, p: float, x: int) -> float:
    """P(longest cyclic run of successes <= x) of m independent trials.

    The all-success circle has run m. Otherwise cut the circle after a failure: by the length j of the run
    that wraps round the start, (j + 1) ways to place it, the rest is a line between two failures.
    """
    if x >= m:
        return 1.0
    q = 1 - p
    line = [1.0] + [0.0] * m  # line[n]: n trials that end in a failure, no run over x
    for n in range(1, m + 1):
        line[n] = sum(p**j * q * line[n - j - 1] for j in range(min(x, n - 1) + 1))
    return sum((j + 1) * p**j * q * (line[m - j - 1] if m - j - 1 else 1.0) for j in range(min(x, m - 1) + 1))


def run_quantile(m: int, p: float, level: float) -> float:
    return math.log(-math.log(level) / (m * (1 - p))) / math.log(p)


def run_median(m: int, p: float) -> float:
    return run_quantile(m, p, 0.5)


def run_tail_bounds(m: int, p1: float, p2: float, x: float) -> tuple[float, float]:
    """(least chance that a near object's run exceeds x, least chance that a far object's does not)."""
    return 1 - run_cdf_limit(m, p1, x), run_cdf_limit(m, p2, x)


def lambda_raw(m: int, n: int, p1: float, p2: float) -> float:
    e = 1 / rho(p1, p2)
    return m ** (1 - e) * n * (1 - p1) ** -e * (1 - p2) * math.log(2) ** e / p2


def lambda_guarantee(m, n, p1: float, p2: float):
    """Candidates for success with probability 1/4 or more; m and n are numbers, or n a Column."""
    if isinstance(n, Column):
        return F.least(n, F.greatest(F.lit(1), F.ceil(lambda_raw(m, n, p1, p2)))).cast("long")
    return int(min(n, max(1, math.ceil(lambda_raw(m, n, p1, p2)))))


def plan_parameters(n, p1: float, p2: float, alpha: float) -> tuple:
    """(functions, candidates) for n objects, a number or a Column."""
    if isinstance(n, Column):
        m = F.greatest(F.lit(1), F.round(n ** (alpha * rho(p1, p2)))).cast("long")
    else:
        m = max(1, round(n ** (alpha * rho(p1, p2))))
    return m, lambda_guarantee(m, n, p1, p2)


def static_concat_plan(n: int, p1: float, p2: float) -> tuple[int, int]:
    return math.ceil(math.log(n) / math.log(1 / p2)), math.ceil(n ** rho(p1, p2) / p1)


def concat_prob(p: float, k: int) -> float:
    return p**k


def table_hit(p: float, k: int, tables: int) -> float:
    return 1 - (1 - p**k) ** tables


def combinations_reached(m: int, threshold: int) -> int:
    return math.comb(m, threshold)


def expected_touched(n, m: int, p2: float):
    return n * (1 - (1 - p2) ** m)


def complexity_rows(n, d: float, r: float, eta: float) -> list[tuple]:
    """(method, alpha, functions, candidates, space, build time, query time) for n objects, a number or a Column."""
    ln = F.log(n) if isinstance(n, Column) else math.log(n)
    none = F.lit(None).cast("double") if isinstance(n, Column) else None
    rows = [
        ("static_concat", none, none, none, n ** (1 + r), n ** (1 + r) * eta * ln, n**r * (eta * ln + d)),
        ("collision_count", none, none, none, n * ln, n * ln * (eta + ln), n * ln),
    ]
    for alpha in (0.0, 1.0, 1 / (1 - r)):
        m = n ** (alpha * r)
        lam = n ** (1 + alpha * (r - 1))
        query = m * (eta + ln) + lam * d if alpha else n * d
        rows.append(("ring", alpha, m, lam, n * m, n * m * (eta + ln), query))
    return rows


def hash_cost(family: str, d):
    """Operations of one hash function: a projection, a fast rotation, or one coordinate; d is a number or a Column."""
    wide, log2 = (d.cast("double"), F.log2(d)) if isinstance(d, Column) else (float(d), math.log2(d))
    return {"random_projection": wide, "cross_polytope": wide * log2, "bit_sampling": 1.0}[family]


#: Published parameter grids (fixed values): K from 1 to 10 with KL up to 512; powers of two; thresholds and dimensions.
GRIDS = ("static_concat", "collision_count", "ring", "projected_incremental", "query_aware_blocked")


def grid(method: str) -> list[dict]:
    """All settings of a method's grid."""
    powers = [8 << i for i in range(7)]
    if method == "static_concat":
        return [{"K": k, "L": t} for k in range(1, 11) for t in powers if k * t <= 512]
    if method == "collision_count":
        return [{"m": m, "l": t} for m in powers for t in range(2, 11)]
    if method == "ring":
        return [{"m": m, "probes": p} for m in powers for p in (1, m + 1, 2 * m + 1, 4 * m + 1, 8 * m + 1)]
    if method == "projected_incremental":
        return [{"d": x} for x in range(4, 11)]
    return [{"L": t, "M": n // t, "c": c} for t in (10, 20, 40) for n in (100, 240, 400) if n % t == 0 for c in (2, 3, 4)]


def gamma_cdf(k: float, x: float) -> float:
    """Chi-square distribution with k degrees, by the series of the incomplete gamma function."""
    a, x = k / 2, x / 2
    if x <= 0:
        return 0.0
    term = total = 1 / a
    for i in range(1, 1000):
        term *= x / (a + i)
        total += term
        if term < total * 1e-15:
            break
    return min(1.0, total * math.exp(-x + a * math.log(x) - math.lgamma(a)))
