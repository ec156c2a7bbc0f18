"""Reward shapes of the tuner, as Python and as SQL. x0: relative gain against the start, x1: against the last step."""

from __future__ import annotations

import math


def delta(now: float, ref: float, metric: str = "latency") -> float:
    return (ref - now) / ref if metric == "latency" else (now - ref) / ref


def reward(x0: float, x1: float, kind: str = "base", lam: float = 1.0, clip: bool = True) -> float:
    """base grows with the square of x0, exp exponentially, log by its logarithm; penalty takes off what the last step lost.
    clip keeps the second factor from growing again once x1 passes -1. *_as_printed: forms kept for comparison only."""
    sign = (x0 > 0) - (x0 < 0)
    inner = 1 + sign * x1
    factor = max(0.0, inner) if clip else abs(inner)
    base = sign * ((1 + abs(x0)) ** 2 - 1) * factor
    return {
        "base": lambda: base,
        "exp": lambda: sign * (math.exp(abs(x0)) - 1) * math.exp(sign * x1),
        "log": lambda: sign * math.log(1 + abs(x0)) * factor,
        "log_as_printed": lambda: base,
        "penalty": lambda: base - lam * max(0.0, -x1),
        "penalty_as_printed": lambda: -lam * max(0.0, -x1) if x0 > 0 else (-lam * max(0.0, x1) if x0 < 0 else 0.0),
    }[kind]()


def reward_sql(x0: str, x1: str, kind: str = "base", lam: float = 1.0) -> str:
    """The clipped shapes, for Spark and DuckDB alike."""
    sign = f"(CASE WHEN {x0} > 0 THEN 1 WHEN {x0} < 0 THEN -1 ELSE 0 END)"
    factor = f"greatest(0, 1 + {sign} * {x1})"
    base = f"{sign} * (pow(1 + abs({x0}), 2) - 1) * {factor}"
    return {"base": base, "exp": f"{sign} * (exp(abs({x0})) - 1) * exp({sign} * {x1})", "log": f"{sign} * ln(1 + abs({x0})) * {factor}", "penalty": f"{base} - {lam} * greatest(0, -({x1}))"}[kind]
