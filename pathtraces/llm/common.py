"""What the corpus operators share: tables, shared storage, word hashing."""

from __future__ import annotations

from itertools import repeat

import numpy as np
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from pathtraces.plans.storage import materialise as spill
from pathtraces.plans.storage import new_path, release

__all__ = ["new_path", "release", "spill"]

#: Word separators of every operator here: space and the five ASCII controls from tab to carriage return. ``bytes.split()``
#: cuts at exactly these, so words are taken from UTF-8 bytes.
WORD = r"[^\x20\x09-\x0D]+"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def fold(column: str, modulus: int):
    """``crc32`` of a number written as text, modulo ``modulus``: the held-out folds."""
    return F.crc32(F.col(column).cast("string").cast("binary")) % modulus


def word_hashes(words: list[bytes]) -> np.ndarray:
    """A 64-bit hash of each word. Hashing again costs less than keeping the words of a large vocabulary."""
    return np.fromiter(map(xxhash.xxh64_intdigest, words, repeat(11)), np.uint64, len(words))


_BASE = 0x9E3779B97F4A7C15
_powers = [np.ones(1, np.uint64), np.ones(1, np.uint64)]


def _grown(n: int) -> tuple[np.ndarray, np.ndarray]:
    """Powers of the base and of its inverse modulo 2**64, at least ``n`` of each."""
    if len(_powers[0]) < n:
        size = max(n, 2 * len(_powers[0]), 1 << 14)
        for k, base in enumerate((_BASE, pow(_BASE, -1, 1 << 64))):
            run = np.full(size, base, np.uint64)
            run[0] = 1
            _powers[k] = np.cumprod(run)
    return _powers[0], _powers[1]


def scramble(x: np.ndarray) -> np.ndarray:
    """Bijective mixing of 64-bit integers."""
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def rolling(hashes: np.ndarray, width: int) -> np.ndarray:
    """A hash of each run of ``width`` neighbours (empty if there are fewer)."""
    n = len(hashes)
    if n < width:
        return np.empty(0, np.uint64)
    up, down = _grown(n + 1)
    sums = np.zeros(n + 1, np.uint64)
    np.cumsum(hashes * down[:n], out=sums[1:])
    return scramble((sums[width:] - sums[:-width]) * up[: n - width + 1])


def texts(column) -> list[bytes | None]:
    """A string column of an Arrow batch as UTF-8 bytes."""
    import pyarrow as pa

    return column.cast(pa.large_binary() if pa.types.is_large_string(column.type) else pa.binary()).to_pylist()


def parts(batch, rows: int = 512):
    """An Arrow batch in pieces of few rows, so that long texts are not all turned to Python objects at once."""
    for at in range(0, batch.num_rows, rows):
        yield batch.slice(at, rows)


def by_exchange(df: DataFrame) -> DataFrame:
    """A side of a join that is never gathered on the driver. Spark guesses its size from the files it comes from: what is exploded or unpacked from
    them weighs many times that, and a broadcast of it does not fit the driver."""
    return df.hint("merge")


def fresh(docs: DataFrame, name: str) -> str:
    """``name``, lengthened until no column of ``docs`` has it, whatever the case."""
    taken = {c.lower() for c in docs.columns}
    while name.lower() in taken:
        name += "_"
    return name
