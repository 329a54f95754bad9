"""Sample sizes: from theory, or from a budget."""

from __future__ import annotations

import math
from dataclasses import dataclass

#: How a budget of stored nodes is dealt out [our choice]: anchors, first, second, residual sample; the
#: first sample is drawn twice (to classify, and to count), so its share is charged twice.
SPLIT = (1 / 2, 1 / 8, 1 / 8, 1 / 8)


@dataclass(frozen=True)
class Sizes:
    """Anchors ``r``, first and second anchored-part samples, residual sample, cut-off in hits."""

    r: int
    t1: int
    t2: int
    t: int
    cutoff: float


def beta_of(alpha: float) -> float:
    return (1 - alpha) / 4


def cutoff_of(n: int, t1: int, alpha: float = 0.0) -> float:
    return 2 * t1 / n ** (1 - beta_of(alpha)) if n else 0.0


def theory_sizes(n: int, k: int, alpha: float = 0.0, eps: float = 0.1, capped: bool = True) -> Sizes:
    """Natural logarithms; each size is capped at the population unless told otherwise."""
    beta, log = beta_of(alpha), math.log(max(n, 2))
    raw = (48 * k * n ** (1 - beta) * log, 12 * n ** (1 - beta) * log / eps**2, 32 * n ** (alpha + beta) * log / eps**2, 8 * n ** (alpha + 2 * beta) * log / eps**2)
    sized = [min(n, math.ceil(x)) if capped else math.ceil(x) for x in raw]
    return Sizes(*sized, cutoff_of(n, sized[1], alpha))


def budget_sizes(n: int, fraction: float, split: tuple[float, float, float, float] = SPLIT, alpha: float = 0.0) -> Sizes:
    """Sizes that store about ``fraction * n`` nodes in all, each sample at least one node."""
    sized = [min(n, max(1, math.floor(n * fraction * s + 0.5))) for s in split]
    return Sizes(*sized, cutoff_of(n, sized[1], alpha))


def words_stored(sizes: Sizes, k: int, neighbourhoods: int = 0) -> int:
    """Words: a node or a counter is one; the first sample counts twice; a walk holds 2k entries for each neighbourhood member."""
    return sizes.r + 4 * sizes.t1 + 2 * sizes.t2 + sizes.t + neighbourhoods * (1 + 2 * k)


def passes(k: int, fused_outer: bool = False) -> int:
    """Scans that the printed estimate needs at most: one for the anchors, then both parts side by side."""
    return k + 4 - int(fused_outer)


def pairs_for(n: int, fraction: float, stored: int = 0) -> int:
    """Sampled pairs that store ``fraction * n`` nodes in all, less those already stored; two nodes a pair."""
    return max(1, math.floor((n * fraction - stored) / 2 + 0.5))
