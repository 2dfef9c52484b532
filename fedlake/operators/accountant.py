"""Rényi privacy accounting of sampled Gaussian and Laplace mechanisms.

A curve maps an integer order to the privacy spent by one mechanism; curves add
under composition and convert to (epsilon, delta) at the best order. The curves
come as plain functions for the driver and as DataFrames for grids.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

ORDERS = tuple(range(2, 257))
GRID_ORDERS = 64


def _logsum(terms: list[float]) -> float:
    top = max(terms)
    return top + math.log(math.fsum(math.exp(t - top) for t in terms))


def _ln_choose(n: int, k: int) -> float:
    return math.lgamma(n + 1) - math.lgamma(k + 1) - math.lgamma(n - k + 1)


def rdp_gaussian(z: float, orders=ORDERS) -> dict[int, float]:
    return {a: a / (2 * z * z) for a in orders}


def rdp_laplace(scale: float, orders=ORDERS) -> dict[int, float]:
    """scale: noise scale over sensitivity."""
    return {a: _logsum([math.log(a / (2 * a - 1)) + (a - 1) / scale, math.log((a - 1) / (2 * a - 1)) - a / scale]) / (a - 1) for a in orders}


def rdp_fixed(q: float, z: float, orders=ORDERS) -> dict[int, float]:
    """Upper bound for a Gaussian mechanism on a fixed-size draw without replacement at rate q."""
    if q >= 1:
        return rdp_gaussian(z, orders)
    eps = lambda j: j / (2 * z * z)
    # ln min(4 (e^x - 1), 2 e^x) without overflow
    second = min(math.log(4) + eps(2) + math.log1p(-math.exp(-eps(2))), math.log(2) + eps(2))
    out = {}
    for a in orders:
        terms = [0.0, _ln_choose(a, 2) + 2 * math.log(q) + second]
        terms += [math.log(2) + _ln_choose(a, j) + j * math.log(q) + (j - 1) * eps(j) for j in range(3, a + 1)]
        out[a] = _logsum(terms) / (a - 1)
    return out


def rdp_fixed_laplace(q: float, scale: float, orders=ORDERS) -> dict[int, float]:
    """The same bound for Laplace noise, whose privacy loss is at most 1 / scale."""
    curve = rdp_laplace(scale, range(2, max(orders) + 1))
    most = math.expm1(1 / scale)
    second = math.log(min(4 * math.expm1(curve[2]), math.exp(curve[2]) * min(2.0, most**2)))
    out = {}
    for a in orders:
        terms = [0.0, _ln_choose(a, 2) + 2 * math.log(q) + second]
        terms += [_ln_choose(a, j) + j * math.log(q) + (j - 1) * curve[j] + min(math.log(2), j * math.log(most)) for j in range(3, a + 1)]
        out[a] = _logsum(terms) / (a - 1)
    return out


def rdp_poisson(q: float, z: float, orders=ORDERS) -> dict[int, float]:
    """Exact integer-order curve of a Poisson-sampled Gaussian mechanism."""
    if q >= 1:
        return rdp_gaussian(z, orders)
    return {a: _logsum([_ln_choose(a, k) + (a - k) * math.log1p(-q) + (k * math.log(q) if k else 0.0) + k * (k - 1) / (2 * z * z) for k in range(a + 1)]) / (a - 1) for a in orders}


def epsilon(curve: dict[int, float], count: float, delta: float) -> float:
    """Epsilon of ``count`` compositions at ``delta``; infinite for delta 0."""
    if delta <= 0:
        return math.inf
    return min(count * r + math.log(1 / delta) / (a - 1) for a, r in curve.items())


@dataclass(frozen=True)
class PrivacyStatement:
    """Epsilon with what it refers to."""

    epsilon: float
    delta: float
    sampling: str
    adjacency: str
    compositions: float
    noise_multiplier: float
    covers: str


def solve(target: float, delta: float, total: int, free: str, *, size: int = 20, z: float = 1.0, rounds: int = 1000) -> float:
    """The noise multiplier ('z'), round size ('M') or number of rounds ('R') that meets an epsilon.

    z is the smallest that keeps it; M and R are the largest that do (0 if none does).
    """

    def spent(size_, z_, rounds_):
        return epsilon(rdp_fixed(size_ / total, z_), rounds_, delta)

    if free == "z":
        low, high = 1e-2, 1.0
        while spent(size, high, rounds) > target:
            high *= 2
            if high > 1e6:
                raise ValueError("no noise meets this budget: the conversion term alone exceeds it")
        for _ in range(60):
            mid = (low + high) / 2
            low, high = (mid, high) if spent(size, mid, rounds) > target else (low, mid)
        return high
    if free == "M":
        return max((m for m in range(1, total + 1) if spent(m, z, rounds) <= target), default=0)
    if free == "R":
        low, high = 0, 1
        while spent(size, z, high) <= target and high < 1 << 40:
            low, high = high, high * 2
        while high - low > 1:
            mid = (low + high) // 2
            low, high = (mid, high) if spent(size, z, mid) <= target else (low, mid)
        return low
    raise ValueError("free is 'z', 'M' or 'R'")


# -- DataFrame curves ----------------------------------------------------
def _ln_factorial(n: Column) -> Column:
    return F.when(n < 1, F.lit(0.0)).otherwise(F.aggregate(F.sequence(F.lit(1), F.greatest(n, F.lit(1)).cast("int")), F.lit(0.0), lambda a, x: a + F.log(x.cast("double"))))


def _choose(n: str, k: str) -> Column:
    return _ln_factorial(F.col(n)) - _ln_factorial(F.col(k)) - _ln_factorial(F.col(n) - F.col(k))


def _summed(terms: DataFrame) -> DataFrame:
    """Log-sum-exp of column t by (q, z, ord), over order minus one."""
    tops = terms.groupBy("q", "z", "ord").agg(F.max("t").alias("top"))
    parts = terms.join(tops, ["q", "z", "ord"]).groupBy("q", "z", "ord", "top").agg(F.sum(F.exp(F.col("t") - F.col("top"))).alias("s"))
    return parts.select("q", "z", "ord", ((F.col("top") + F.log("s")) / (F.col("ord") - 1)).alias("rdp"))


def curve_fixed(rates: DataFrame, orders: int = GRID_ORDERS) -> DataFrame:
    """(q, z) to (q, z, ord, rdp)."""
    grid = rates.withColumn("ord", F.explode(F.sequence(F.lit(2), F.lit(orders)))).withColumn("j", F.explode(F.concat(F.array(F.lit(0)), F.sequence(F.lit(2), F.col("ord")))))
    eps2 = 1.0 / (F.col("z") * F.col("z"))
    second = F.log(F.least(4.0 * F.expm1(eps2), 2.0 * F.exp(eps2)))
    tail = F.log(F.lit(2.0)) + (F.col("j") - 1) * F.col("j") / (2.0 * F.col("z") * F.col("z"))
    t = F.when(F.col("j") == 0, F.lit(0.0)).otherwise(_choose("ord", "j") + F.col("j") * F.log("q") + F.when(F.col("j") == 2, second).otherwise(tail))
    return _summed(grid.withColumn("t", t))


def curve_poisson(rates: DataFrame, orders: int = GRID_ORDERS) -> DataFrame:
    grid = rates.withColumn("ord", F.explode(F.sequence(F.lit(2), F.lit(orders)))).withColumn("j", F.explode(F.sequence(F.lit(0), F.col("ord"))))
    t = _choose("ord", "j") + (F.col("ord") - F.col("j")) * F.log1p(-F.col("q")) + F.col("j") * F.log("q") + F.col("j") * (F.col("j") - 1) / (2.0 * F.col("z") * F.col("z"))
    return _summed(grid.withColumn("t", t))


def epsilon_grid(cells: DataFrame, orders: int = GRID_ORDERS) -> DataFrame:
    """(n_clients, m, delta, compositions) to that plus ``eps``, for noise multiplier 1 and fixed-size draws."""
    keyed = cells.withColumn("q", F.col("m") / F.col("n_clients").cast("double"))
    curve = curve_fixed(keyed.select("q").distinct().withColumn("z", F.lit(1.0)), orders)
    spent = F.col("compositions") * F.col("rdp") + F.log(1.0 / F.col("delta")) / (F.col("ord") - 1)
    return keyed.join(curve, "q").groupBy("n_clients", "m", "delta").agg(F.min(spent).alias("eps"))


def ledger(rates: DataFrame, rounds: int, delta: float, orders: int = GRID_ORDERS) -> DataFrame:
    """(round, eps_cum) at the one rate (q, z) of ``rates``: what is spent after every round; a running sum over the rounds for each order."""
    rows = curve_fixed(rates, orders).select("ord", "rdp").withColumn("round", F.explode(F.sequence(F.lit(1), F.lit(rounds))))
    run = Window.partitionBy("ord").orderBy("round").rowsBetween(Window.unboundedPreceding, 0)
    total = rows.withColumn("total", F.sum("rdp").over(run))
    return total.groupBy("round").agg(F.min(F.col("total") + math.log(1 / delta) / (F.col("ord") - 1)).alias("eps_cum"))


def sql_terms(kind: str, rates: str, orders: int = GRID_ORDERS) -> str:
    """DuckDB CTEs ending in curve(q, z, ord, rdp); ``rates`` selects q and z."""
    lnc = "(lgamma(ord + 1) - lgamma(j + 1) - lgamma(ord - j + 1))"
    if kind == "fixed":
        js = "SELECT q, z, ord, unnest(list_concat([0], range(2, ord + 1)))::BIGINT AS j FROM o"
        term = f"CASE WHEN j = 0 THEN 0.0::DOUBLE ELSE {lnc} + j * ln(q) + CASE WHEN j = 2 THEN ln(least(4.0::DOUBLE * (exp(1 / (z * z)) - 1), 2.0::DOUBLE * exp(1 / (z * z)))) ELSE ln(2.0::DOUBLE) + (j - 1) * j / (2 * z * z) END END"
    else:
        js = "SELECT q, z, ord, unnest(range(0, ord + 1))::BIGINT AS j FROM o"
        term = f"{lnc} + (ord - j) * ln(1 - q) + j * ln(q) + j * (j - 1) / (2 * z * z)"
    return f"""rates AS ({rates}),
o AS (SELECT q, z, unnest(range(2, {orders + 1}))::INTEGER AS ord FROM rates),
j AS ({js}),
t AS (SELECT q, z, ord, {term} AS t FROM j),
top AS (SELECT q, z, ord, max(t) AS top FROM t GROUP BY ALL),
curve AS (SELECT t.q, t.z, t.ord, (any_value(top) + ln(sum(exp(t - top)))) / (t.ord - 1) AS rdp FROM t JOIN top ON t.q = top.q AND t.z = top.z AND t.ord = top.ord GROUP BY t.q, t.z, t.ord)"""
