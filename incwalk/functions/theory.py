"""Closed forms of costs and bounds: Python for planning, and SQL functions for use over columns."""

from __future__ import annotations

import math

from pyspark.sql import SparkSession


def harmonic(m: int) -> float:
    return math.fsum(1 / t for t in range(1, m + 1)) if m < 1_000_000 else math.log(m) + 0.5772156649015329 + 1 / (2 * m)


def update_bound(n: int, r: int, eps: float, m: int, model: str = "random") -> float:
    """Steps over m arrivals. The harmonic number is at least ln m, so it is what a bound needs."""
    base = n * r / eps**2
    return {"random": base * harmonic(m), "alternating": 16 * base * harmonic(m), "dirichlet": base * math.log((m + n) / n), "deletion": base / m, "initial": n * r / eps, "paid_gate": m + n * r * harmonic(m) / eps**2}[model]


def choose_r(n: int, eps: float, rule: str, q: float = 1.0, pi: float | None = None) -> int:
    return {"one": 1, "log": math.ceil(math.log(n / eps)), "fetch": math.floor(q * math.log(n)) + 1, "level": math.ceil(math.log(n) / (n * (pi or 1 / n)))}[rule]


def walk_length(n: float, k: float, c: float, alpha: float) -> float:
    return c / (1 - alpha) * k * (n / k) ** (1 - alpha)


def fetch_bound(n: float, r: float, alpha: float, s: float) -> float | None:
    return 1 + (2 * (1 - alpha) / (n * r)) ** (1 / alpha - 1) * s ** (1 / alpha) if 0 < alpha < 1 else None


def topk_fetch_bound(k: float, r: float, c: float, alpha: float) -> float:
    return 1 + c ** (1 / alpha) * k / ((1 - alpha) * (r / 2) ** (1 / alpha - 1))


def tau(n: float, r: float, alpha: float, s: float) -> float:
    """The rank up to which a walk of ``s`` visits is expected at a node more than half as often as it has segments."""
    return (1 - alpha) ** (1 / alpha) / n ** (1 / alpha - 1) * (2 * s / r) ** (1 / alpha)


def lower_tail_constant(delta: float, eps: float, grid: int = 2000) -> float:
    """Largest 1 - E[exp(-t W)] - t (1 - delta); times n R pi it is the exponent of the lower tail."""
    best = 0.0
    for i in range(1, grid):
        t = 20 * i / grid
        g = eps * math.exp(-t * eps) / (1 - (1 - eps) * math.exp(-t * eps))
        best = max(best, 1 - g - t * (1 - delta))
    return best


def tail_constant(delta: float, eps: float, grid: int = 2000) -> float:
    """Largest t (1 + delta) + 1 - E[exp(t W)], W being eps times a geometric length; times n R pi it is the exponent of the upper tail."""
    top = -math.log(1 - eps) / eps
    best = 0.0
    for i in range(1, grid):
        t = top * i / grid
        g = eps * math.exp(t * eps) / (1 - (1 - eps) * math.exp(t * eps))
        best = max(best, t * (1 + delta) + 1 - g)
    return best


_FUNCTIONS = {
    "walk_length(n DOUBLE, k DOUBLE, c DOUBLE, alpha DOUBLE)": "c / (1 - alpha) * k * pow(n / k, 1 - alpha)",
    "fetch_bound(n DOUBLE, r DOUBLE, alpha DOUBLE, s DOUBLE)": "CASE WHEN alpha > 0 AND alpha < 1 THEN 1 + pow(2 * (1 - alpha) / (n * r), 1 / alpha - 1) * pow(s, 1 / alpha) END",
    "topk_fetch_bound(k DOUBLE, r DOUBLE, c DOUBLE, alpha DOUBLE)": "1 + pow(c, 1 / alpha) * k / ((1 - alpha) * pow(r / 2, 1 / alpha - 1))",
    "fetch_rank(n DOUBLE, r DOUBLE, alpha DOUBLE, s DOUBLE)": "pow(1 - alpha, 1 / alpha) / pow(n, 1 / alpha - 1) * pow(2 * s / r, 1 / alpha)",
    "model_score(j DOUBLE, n DOUBLE, alpha DOUBLE)": "(1 - alpha) * pow(j, -alpha) / pow(n, 1 - alpha)",
    "gate_probability(w DOUBLE, d DOUBLE)": "1 - pow(1 - 1 / d, w)",
}


def register(spark: SparkSession) -> None:
    """The closed forms as temporary SQL functions, which fold over constants and generate code over columns."""
    for head, body in _FUNCTIONS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {head} RETURNS DOUBLE RETURN {body}")
