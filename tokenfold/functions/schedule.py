"""Scalar rules: target lengths, hash bits, thresholds, bounds and costs, as SQL texts and in Python.

Each SQL text is read alike by Spark and DuckDB.
"""

from __future__ import annotations

import math


def half_up(x: float) -> int:
    return math.floor(x + 0.5)


def chunk_width(rho: float) -> int:
    return max(1, half_up(rho))


def target_length(n: int, rho: float, prefix: int = 0, suffix: int = 12) -> int:
    """Tokens after compression: the ratio counts for the body alone."""
    kept = min(n, prefix + suffix)
    body = n - kept
    return n if rho <= 1 or not body else kept + max(1, math.ceil(body / rho))


def bits_for_target(target: int) -> int:
    """Bits that name at least as many codes as groups are wanted; at least one."""
    return max(1, (target - 1).bit_length())


def regions(n: int, prefix: int = 0, suffix: int = 12) -> list[str]:
    """Region of each place; the suffix comes first where both do not fit."""
    kept = min(n, suffix)
    ahead = min(n - kept, prefix)
    return ["prefix"] * ahead + ["body"] * (n - kept - ahead) + ["suffix"] * kept


def budgets(body: int, target: int, window: int) -> list[int]:
    """Groups of each window; they sum to the target."""
    cuts = [*range(0, body, window), body]
    return [b * target // body - a * target // body for a, b in zip(cuts, cuts[1:], strict=False)] if body else []


def tau(rho: float, base: float = 0.70, schedule: str = "linear") -> float:
    """Redundancy from which a window goes to the spectral path."""
    if schedule == "constant":
        return base
    at = (2.0, 8.0, 16.0)
    scale = math.log2 if schedule == "log2" else float
    x, (a, b, c) = scale(min(max(rho, 2.0), 16.0)), map(scale, at)
    value = 0.70 - 0.10 * (x - a) / (b - a) if x <= b else 0.60 - 0.05 * (x - b) / (c - b)
    return value + base - 0.70


def tau_sql(rho: str, schedule: str = "linear") -> str:
    x = f"least(greatest({rho}, 2.0), 16.0)"
    if schedule == "log2":
        return f"(CASE WHEN {x} <= 8 THEN 0.70 - 0.10 * (log2({x}) - 1) / 2 ELSE 0.60 - 0.05 * (log2({x}) - 3) END)"
    return f"(CASE WHEN {x} <= 8 THEN 0.70 - 0.10 * ({x} - 2) / 6 ELSE 0.60 - 0.05 * ({x} - 8) / 8 END)"


def collision_sql(cosine: str, bits: str) -> str:
    return f"pow(1 - acos(greatest(-1.0, least(1.0, {cosine}))) / pi(), {bits})"


def collision(cosine: float, bits: int) -> float:
    """Chance that two vectors agree in all bits of a sign hash."""
    return (1 - math.acos(max(-1.0, min(1.0, cosine))) / math.pi) ** bits


def rff_tail(n: float, dims: float, eps: float) -> float:
    """Bound of the chance that some kernel value is off by more than eps."""
    return min(1.0, 2 * n * n * math.exp(-dims * eps * eps / 8))


def rff_eps(n: float, dims: float, delta: float) -> float:
    return math.sqrt(8 / dims * math.log(2 * n * n / delta))


def matvec_bound(n: float, c: float, dims: float, delta: float) -> float:
    return 2 * n * c * math.sqrt(2 / dims * math.log(2 * n / delta))


def op_count(backend: str, d: int, dims: int = 256, rank: int = 16, bits: int = 8) -> int:
    """Operations for each token."""
    return d if backend == "chunk" else dims * (d + rank) + rank * bits


def prefill_cost(n: float, quadratic: float = 64.0, linear: float = 4096.0) -> float:
    """Work of a reader over n tokens: attention grows with the square, the rest with the length."""
    return quadratic * n * n + linear * n
