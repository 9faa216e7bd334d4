"""Cost and accuracy measures on plain numbers."""

from __future__ import annotations

import math


def poisson_below(mean: float, k: int) -> float:
    """P(X <= k)."""
    return sum(math.exp(-mean + i * math.log(mean) - math.lgamma(i + 1)) for i in range(k + 1)) if k >= 0 else 0.0


def least_reported(c: float, strict: bool) -> int:
    """The smallest sample count that is reported: at least c/2, or more than c/2 (``strict``)."""
    return math.floor(c / 2) + 1 if strict else math.ceil(c / 2)


def fn_probability(c: float, strict: bool = True) -> float:
    """A trace of exactly the threshold's count is not reported."""
    return poisson_below(c, least_reported(c, strict) - 1)


def sfp_probability(c: float, strict: bool = True) -> float:
    """A trace of a quarter of the threshold's count is reported."""
    return 1 - poisson_below(c / 4, least_reported(c, strict) - 1)


def fn_binomial(c: float, count: int, p: float, strict: bool = True) -> float:
    """The same without the Poisson approximation, for ``count`` occurrences kept with ``p``."""
    k = least_reported(c, strict) - 1
    return sum(math.exp(math.lgamma(count + 1) - math.lgamma(i + 1) - math.lgamma(count - i + 1) + i * math.log(p) + (count - i) * math.log1p(-p)) for i in range(min(k, count) + 1)) if 0 < p < 1 else float(p <= 0 or count <= k)


def chernoff_bound(c: float) -> float:
    """Upper bound of the probability that half the expected samples aren't met."""
    return math.exp(-c / 8)


def choose_c(delta: float, strict: bool = True) -> int:
    """The smallest whole C whose false-negative probability, and that of every larger one, is at most delta."""
    if not 0 < delta < 1:
        raise ValueError("an error probability lies between 0 and 1")
    top = 2
    while any(fn_probability(c, strict) > delta for c in range(top, top + 3)):
        top += 1
    return top


def choose_p(c: float, min_count: float) -> float:
    return min(1.0, c / min_count)


def expected_samples(c: float, total: int, min_count: float) -> float:
    return c * total / min_count


def time_ratio(c: float, min_count: float) -> float:
    """Traces of the full enumeration per expected sample."""
    return min_count / c


def space_ratio(distinct: int, total: int, min_count: float) -> float:
    """Distinct traces per counter of the summary."""
    return distinct * min_count / (2 * total)


def summary_capacity(c: float, samples: int) -> int:
    """Counters that keep every trace with c/2 or more of so many samples."""
    return max(1, math.ceil(2 * samples / c))


def blowup(total: int, vertices: int, edges: int) -> float:
    return total / (vertices + edges)
