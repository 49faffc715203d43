"""Cap and gain functions, as column expressions and for numbers.

A cap bounds how frequent a value of overall frequency p may be in a group: (1 + beta) p
for the basic bound, (1 + min(beta, -ln p)) p for the capped one, or any increasing function.
"""

from __future__ import annotations

import math
from collections.abc import Callable

from pyspark.sql import Column
from pyspark.sql import functions as F

#: Room for rounding in comparisons of doubles.
EPS = 1e-12
#: Named bounds on the relative gain, besides the basic and capped ones; fixed values.
CUSTOM: dict[str, tuple[Callable[[float, float], float], Callable[[Column, float], Column]]] = {
    "log2": (lambda p, b: min(b, -math.log2(p)) if p > 0 else b, lambda p, b: F.least(F.lit(float(b)), -F.log2(p))),
    "sqrt": (lambda p, b: min(b, 1 / math.sqrt(p) - 1) if p > 0 else b, lambda p, b: F.least(F.lit(float(b)), 1 / F.sqrt(p) - 1)),
}


def cap(p: float, beta: float, kind: str = "capped") -> float:
    if kind == "basic":
        return p * (1 + beta)
    if kind == "capped":
        return p * (1 + min(beta, -math.log(p))) if p > 0 else 0.0
    return p * (1 + CUSTOM[kind][0](p, beta))


def cap_expr(p: Column, beta: float, kind: str | Callable[[Column, float], Column] = "capped") -> Column:
    if callable(kind):
        return kind(p, beta)
    if kind == "basic":
        return p * F.lit(1.0 + beta)
    if kind == "capped":
        return p * (1 + F.least(F.lit(float(beta)), -F.ln(p)))
    return p * (1 + CUSTOM[kind][1](p, beta))


def check_monotone(values: list[float]) -> None:
    """A cap must increase with frequency; values: caps in order of frequency."""
    if any(b < a - EPS for a, b in zip(values, values[1:], strict=False)):
        raise ValueError("the cap function decreases with frequency")


def gain_expr(p: Column, q: Column, kind: str = "relative") -> Column:
    """Distance of a value's frequency q in a group from its overall frequency p."""
    if kind == "relative":
        return (q - p) / p
    if kind == "absolute":
        return q - p
    if kind == "ratio":
        return q / p
    if kind == "logratio":
        return F.when(q > 0, F.abs(F.ln(q / p))).otherwise(F.lit(float("inf")))
    raise ValueError(kind)


def sign_expr(p: Column, q: Column) -> Column:
    return F.when(q > p, "positive").when(q < p, "negative").otherwise("none")
