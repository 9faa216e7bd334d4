"""Column functions: reproducible randomness, trace texts, rolling hashes."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

#: Two primes below 2**31, so that a step of the hash stays within 64 bits.
PRIMES, BASES = (2147483629, 2147483587), (1_000_003, 998_244_353)
SEPARATOR = ">"


def uniform(seed: int, *key: Column | str) -> Column:
    """A number strictly between 0 and 1 that depends on seed and key only: the same in every run, engine and partitioning."""
    text = F.concat_ws("|", F.lit(str(seed)), *[(F.col(k) if isinstance(k, str) else k).cast("string") for k in key])
    return (F.conv(F.substring(F.md5(text.cast("binary")), 1, 13), 16, 10).cast("long") + F.lit(0.5)) / F.lit(float(1 << 52))


def whole_label(label: Column) -> Column:
    """The label, if it can stand in a trace: one that holds the separator would read as several, and is an error."""
    return F.when(F.contains(label, F.lit(SEPARATOR)), F.raise_error(F.lit(f"a label holds {SEPARATOR}")).cast("string")).otherwise(label)


def missing_all(p: float, n: Column) -> Column:
    """Probability that none of ``n`` elements is drawn, each with ``p``; exact for tiny p."""
    import math

    return F.lit(0.0) if p >= 1 else F.exp(n * F.lit(math.log1p(-p)))


def some_drawn(p: float, n: Column) -> Column:
    import math

    return F.when(n > 0, F.lit(1.0)).otherwise(0.0) if p >= 1 else -F.expm1(n * F.lit(math.log1p(-p)))


def hash_step(h: Column, code: Column, which: int) -> Column:
    return (h * F.lit(BASES[which]) + code) % F.lit(PRIMES[which])


def trace_text(labels: Column | str) -> Column:
    return F.array_join(labels, SEPARATOR)


def trace_labels(trace: Column | str = "trace") -> Column:
    return F.split(trace, SEPARATOR)


def trace_length(trace: Column | str = "trace") -> Column:
    return F.size(trace_labels(trace))


def contains_label(label: str, trace: Column | str = "trace") -> Column:
    return F.array_contains(trace_labels(trace), label)


def has_prefix(labels: list[str], trace: Column | str = "trace") -> Column:
    return F.slice(trace_labels(trace), 1, len(labels)) == F.array(*map(F.lit, labels))
