"""Approximation predicates and tail bounds, as column expressions."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def _c(x: Column | float) -> Column:
    return x if isinstance(x, Column) else F.lit(x)


def is_cd_approx(estimate: Column, truth: Column, c: float, d: Column | float) -> Column:
    """``truth <= estimate <= c * truth + d``."""
    return (truth <= estimate) & (estimate <= c * truth + _c(d))


def is_eps_approx(estimate: Column, truth: Column, eps: float, d: Column | float) -> Column:
    """``(1 - eps) truth - d <= estimate <= (1 + eps) truth + d``."""
    return ((1 - eps) * truth - _c(d) <= estimate) & (estimate <= (1 + eps) * truth + _c(d))


def budgeted_factor(k: Column | int) -> Column:
    """The budgeted pivot's factor, held with probability 2/3 for k >= 2."""
    return 9 + 24 / (_c(k) - 1)


def chernoff_tail(eps: Column | float, mu: Column | float, t: Column | float) -> Column:
    """Chance that the mean of t values in [0, 1] of mean mu strays by a share eps, at most."""
    return F.least(F.lit(1.0), 2 * F.exp(-_c(eps) * _c(eps) * _c(mu) * _c(t) / 3))


def bernstein_tail(delta: Column | float, mu: Column | float, most: Column | float, t: Column | float) -> Column:
    """Chance that the mean of t values in [0, most] of mean mu strays by delta, at most."""
    return F.least(F.lit(1.0), 2 * F.exp(-_c(t) * _c(delta) * _c(delta) / (2 * _c(most) * (_c(mu) + _c(delta) / 3))))
