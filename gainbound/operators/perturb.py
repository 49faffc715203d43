"""The row randomiser: quasi-identifiers stay exact, each sensitive value is kept with its own probability or redrawn.

For a value of frequency p the largest posterior allowed is f(p), the cap. With gamma = f (1 - p) / (p (1 - f)) and
C = 1 / (max gamma + m - 1), a value is kept with probability alpha = (m gamma C - 1) / (m - 1) and else drawn
uniformly from the m values. For a skewed column that alpha can be negative; then every gamma is lowered
to at most 1 + kappa m (min gamma - 1), which is always safe and makes all alphas positive.

Coins are a keyed hash of the row's key, so a retried task, another partitioning or a replayed stream
draws the same value, and nobody without the secret can redraw it.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from gainbound.functions.bounds import cap


@dataclass(frozen=True)
class Randomiser:
    """values in order, and for each its frequency, bound, gamma, alpha, probability to stay and to become any other given value."""

    values: tuple
    p: tuple[float, ...]
    f: tuple[float, ...]
    gamma: tuple[float, ...]
    alpha: tuple[float, ...]
    keep: tuple[float, ...]
    off: tuple[float, ...]
    cap_applied: bool

    @property
    def m(self) -> int:
        return len(self.values)

    def matrix(self) -> np.ndarray:
        """Entry [i, j]: probability that value j is published as value i. Columns sum to 1."""
        out = np.tile(np.array(self.off), (self.m, 1))
        np.fill_diagonal(out, self.keep)
        return out

    def rows(self) -> list[tuple]:
        return [(v, self.p[i], self.f[i], self.gamma[i], self.alpha[i], self.keep[i], self.off[i], self.cap_applied) for i, v in enumerate(self.values)]


def _alphas(gammas: list[float]) -> list[float]:
    m = len(gammas)
    floor = 1 / (max(gammas) + m - 1)
    return [(m * g * floor - 1) / (m - 1) for g in gammas]


def randomiser(counts: list[tuple], beta: float, kind: str = "each", kappa: float = 0.5) -> Randomiser:
    """The randomiser for (value, count) pairs. kind: `each` value its own alpha, `raw` the same without the safe limit on gammas, or `uniform` one alpha for all."""
    pairs = sorted(((v, n) for v, n in counts if n > 0), key=lambda x: (x[0] is None, x[0]))
    m, total = len(pairs), sum(n for _, n in pairs)
    if m < 2:
        raise ValueError("a column of one value has nothing to randomise")
    p = [n / total for _, n in pairs]
    f = [cap(x, beta, "capped") for x in p]
    gamma = [(b / a) * (1 - a) / (1 - b) for a, b in zip(p, f, strict=True)]
    applied = False
    if kind == "uniform":
        least = min(gamma)
        alpha = [(least - 1) / (least + m - 1)] * m
    else:
        alpha = _alphas(gamma)
        if kind == "each" and min(alpha) <= 0:
            limit = 1 + kappa * m * (min(gamma) - 1)
            gamma, applied = [min(g, limit) for g in gamma], True
            alpha = _alphas(gamma)
    return Randomiser(tuple(v for v, _ in pairs), tuple(p), tuple(f), tuple(gamma), tuple(alpha), tuple(a + (1 - a) / m for a in alpha), tuple((1 - a) / m for a in alpha), applied)


def coin(secret: str, key: Column, tag: str) -> Column:
    """A uniform in [0, 1) of 52 bits, from a keyed hash."""
    digest = F.md5(F.concat(F.lit(secret), F.lit("|"), key, F.lit("|" + tag)))
    return F.conv(F.substring(digest, 1, 13), 16, 10).cast("double") / float(1 << 52)


def randomise_expr(r: Randomiser, sa: Column, key: Column, secret: str) -> Column:
    """The published value: stateless, so it serves batches and streams alike."""
    known = [(v, a) for v, a in zip(r.values, r.alpha, strict=True) if v is not None]
    alpha = F.create_map(*[F.lit(x) for pair in known for x in pair])[sa]
    if None in r.values:
        alpha = F.coalesce(alpha, F.lit(r.alpha[r.values.index(None)]))
    drawn = F.element_at(F.array(*[F.lit(v) for v in r.values]), (F.floor(coin(secret, key, "b") * r.m) + 1).cast("int"))
    return F.when(coin(secret, key, "a") < alpha, sa).otherwise(drawn)


def randomise(df: DataFrame, sa: str, key: str, r: Randomiser, secret: str) -> DataFrame:
    """df with the sensitive column replaced; a map over rows, without a shuffle."""
    return df.withColumn(sa, randomise_expr(r, F.col(sa), F.col(key), secret))


def reconstruct(observed: DataFrame, r: Randomiser, by: list[str] | None = None, kind: str = "int") -> DataFrame:
    """Unbiased counts from observed ones. observed: (by..., sa, e). Every value of the domain gets a row for each `by`.

    The transition matrix is a diagonal of alphas plus a rank-one part, so its inverse needs two sums: with T = sum e and
    k = (sum e / alpha - T) / sum 1 / alpha, the estimate is (e - k) / alpha."""
    by = by or []
    spark = observed.sparkSession
    values = F.broadcast(spark.createDataFrame(list(zip(r.values, r.alpha, strict=True)), f"sa {kind}, alpha double"))
    keys = observed.select(*by).distinct() if by else spark.range(1).select(F.lit(0).alias("_one"))
    full = keys.crossJoin(values).join(observed, [*by, "sa"], "left").withColumn("e", F.coalesce("e", F.lit(0)))
    w = Window.partitionBy(*by)
    k = (F.sum(F.col("e") / F.col("alpha")).over(w) - F.sum("e").over(w)) / F.lit(sum(1 / a for a in r.alpha))
    return full.select(*by, "sa", "e", ((F.col("e") - k) / F.col("alpha")).alias("n_hat"))


def reconstruct_dense(r: Randomiser, observed: np.ndarray) -> np.ndarray:
    """The same by solving the linear system; for tests and small domains."""
    return np.linalg.solve(r.matrix(), observed)


def expectation_maximisation(r: Randomiser, observed: np.ndarray, rounds: int = 200) -> np.ndarray:
    """Non-negative counts by iterating Bayes' rule."""
    a, total = r.matrix(), observed.sum()
    x = np.full(r.m, total / r.m)
    for _ in range(rounds):
        expected = a @ x
        x = x * (a.T @ np.divide(observed, expected, out=np.zeros(r.m), where=expected > 0))
    return x


def posterior(r: Randomiser) -> np.ndarray:
    """Entry [i, j]: probability that a row published as i was j."""
    joint = r.matrix() * np.array(r.p)
    return joint / joint.sum(1, keepdims=True)
