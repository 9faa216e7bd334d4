"""SimHash near-duplicates by anchor points.

A fingerprint has 64 bits: those set in more than half of the hashes of a text's word shingles. Two fingerprints that differ
in at most 3 bits differ in at most 1 bit in one of their 32-bit halves. Within a half the anchors are the words of a
perfect one-error-correcting code on 31 bits, with the last bit free: covering radius 1. A half is *at home* at its nearest
anchor and *visits* every anchor within 2 (radius plus threshold), 2 or 17 of them. So the home of either of two linked
fingerprints is visited by the other, in at least one half, and only equal anchors are compared.

At an anchor that is home to several fingerprints, all that lie within the threshold of its most frequent one are linked to
that one; of the other pairs only those are emitted that this doesn't already connect. So a group of near copies gives links in
proportion to its size. Equal fingerprints are one node from the start.

Nulls and empty texts have no words and the fingerprint zero, linked like any other. Rows of a null id get a fingerprint, and
the component of the other rows with that fingerprint (null if there are none). Repeated rows share a component. Columns
beside id and text are ignored by ``simhash_components`` and kept by ``simhash_dedup``, which keeps rows of a null id."""

from __future__ import annotations

import numpy as np
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from pathtraces.llm.common import by_exchange, parts, spill, texts
from pathtraces.llm.components import components, drop_ids

SHINGLE, THRESHOLD, SEED = 3, 3, 42
_LOW = (1 << 32) - 1


def fingerprint(text: bytes, shingle: int = SHINGLE, seed: int = SEED) -> int:
    """Unsigned; bit i of the result stands for bit i of the hashes."""
    words = text.lower().split()
    if not words:
        return 0
    grams = map(b" ".join, zip(*(words[k:] for k in range(shingle)))) if len(words) >= shingle else [b" ".join(words)]  # noqa: B905
    digest = xxhash.xxh64_intdigest
    hashes = np.array([digest(g, seed) for g in grams], np.uint64)
    ones = np.zeros(64, np.int64)
    for at in range(0, len(hashes), 1 << 15):
        block = hashes[at : at + (1 << 15)]
        ones += np.unpackbits(block.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    return int(np.packbits(2 * ones > len(hashes), bitorder="little").view("<u8")[0])


def fingerprints(docs: DataFrame, id: str = "doc_id", text: str = "text", shingle: int = SHINGLE) -> DataFrame:
    """``id``, ``fp`` (signed long)."""

    def run(batches):
        import pyarrow as pa

        for batch in batches:
            for piece in parts(batch):
                found = np.array([fingerprint(t or b"", shingle) for t in texts(piece.column(1))], np.uint64).view(np.int64)
                yield pa.RecordBatch.from_arrays([piece.column(0), pa.array(found)], ["id", "fp"])

    return docs.select(F.col(id).alias("id"), F.col(text).alias("text")).mapInArrow(run, f"id {dict(docs.dtypes)[id]}, fp long")


def error_patterns() -> list[list[int]]:
    """For each syndrome of the code, the bit patterns of weight at most 2 that lead to an anchor; the first leads home. Bits
    0 to 30 stand for positions 1 to 31, whose exclusive-or is the syndrome; bit 31 is free."""
    out = []
    for s in range(32):
        home = 1 << (s - 1) if s else 0
        pairs = [1 << (i - 1) | 1 << ((i ^ s) - 1) for i in range(1, 32) if i < i ^ s] if s else []
        out.append([home, home | 1 << 31, *pairs])
    return out


def _syndrome(x: Column) -> Column:
    parity = [F.bit_count(x.bitwiseAND(F.lit(sum(1 << (i - 1) for i in range(1, 32) if i >> j & 1)))) % 2 * (1 << j) for j in range(5)]
    return sum(parity[1:], parity[0])


def visits(nodes: DataFrame) -> DataFrame:
    """Each row of ``nodes`` (with ``fp``) at every anchor it visits: ``anchor``, ``at_home``."""
    table = F.array(*[F.array(*[F.lit(e).cast("long") for e in row]) for row in error_patterns()])
    half = F.explode(F.array(*[F.struct(F.lit(k << 32).cast("long").alias("side"), x.alias("x")) for k, x in enumerate((F.col("fp").bitwiseAND(F.lit(_LOW)), F.shiftrightunsigned("fp", 32)))])).alias("half")
    at = nodes.select("*", half).withColumn("patterns", F.element_at(table, (_syndrome(F.col("half.x")) + 1).cast("int")))
    at = at.select(*nodes.columns, "half", F.posexplode("patterns").alias("k", "e"))
    return at.select(*nodes.columns, F.col("half.side").bitwiseOR(F.col("half.x").bitwiseXOR(F.col("e"))).alias("anchor"), (F.col("k") == 0).alias("at_home"))


def links(nodes: DataFrame, threshold: int = THRESHOLD) -> DataFrame:
    """``a``, ``b``: links between nodes (``fp`` unique, ``first``, ``n``) that connect all within ``threshold`` bits (3 at most)."""
    if not 0 <= threshold <= 3:
        raise ValueError("the anchors cover thresholds from 0 to 3")
    seen = visits(nodes)
    leaders = seen.where("at_home").groupBy("anchor").agg(F.max_by(F.struct("fp", "first"), F.struct("n", -F.col("first"))).alias("leader"), F.count(F.lit(1)).alias("homes"))
    far = F.bit_count(F.col("fp").bitwiseXOR(F.col("leader.fp")))
    met = seen.join(by_exchange(leaders), "anchor").withColumn("far", far).where((F.col("homes") > 1) | F.col("far").between(1, threshold))
    met = spill(met.select("anchor", "fp", "first", "at_home", "homes", "far", F.col("leader.first").alias("leader")), "anchors")
    to_leader = met.where(F.col("far").between(1, threshold)).select(F.col("first").alias("a"), F.col("leader").alias("b"))
    crowded = met.where("homes > 1 and far > 0")
    v, h = crowded.alias("v"), crowded.where("at_home").alias("h")
    near = (F.bit_count(F.col("v.fp").bitwiseXOR(F.col("h.fp"))) <= threshold) & (F.col("v.fp") > F.col("h.fp"))
    other = v.join(by_exchange(h), (F.col("v.anchor") == F.col("h.anchor")) & near & ~((F.col("v.far") <= threshold) & (F.col("h.far") <= threshold)))
    return to_leader.unionByName(other.select(F.col("v.first").alias("a"), F.col("h.first").alias("b")))


def simhash_components(docs: DataFrame, id: str = "doc_id", text: str = "text", shingle: int = SHINGLE, threshold: int = THRESHOLD) -> DataFrame:
    """Per row: ``id``, ``fp``, ``component_id`` (the smallest id that links reach)."""
    marked = spill(fingerprints(docs, id, text, shingle), "fingerprints")
    nodes = spill(marked.groupBy("fp").agg(F.min("id").alias("first"), F.count(F.lit(1)).alias("n")), "nodes")
    found = components(links(nodes.where("first is not null"), threshold))
    named = nodes.join(by_exchange(found), F.col("first") == F.col("node"), "left").select("fp", F.coalesce("component", "first").alias("component_id"))
    return marked.join(by_exchange(named), "fp").select("id", "fp", "component_id").withColumnRenamed("id", id)


def hex_digits(fp: str = "fp") -> Column:
    return F.lpad(F.lower(F.hex(fp)), 16, "0")


def simhash_dedup(docs: DataFrame, id: str = "doc_id", text: str = "text", shingle: int = SHINGLE, threshold: int = THRESHOLD) -> DataFrame:
    """The rows of ``docs`` that stay: of each component the one of the smallest id. Rows of a null id stay."""
    found = simhash_components(docs, id, text, shingle, threshold)
    ids = found.where(F.col(id).isNotNull()).groupBy(F.col(id).alias("id")).agg((F.min("component_id") == F.col("id")).alias("keep"), F.count(F.lit(1)).alias("rows"))
    return drop_ids(docs, spill(ids.where("not keep or rows > 1"), "gone"), id)
