"""Path counts: how many paths of at most i vertices start (or end) in each vertex, for i up to m."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pathtraces.operators.dag import LabeledDag, dag_depth
from pathtraces.plans.storage import materialise

TYPES = {"long": "bigint", "decimal": "decimal(38,0)", "double": "double"}
#: Rounds whose plans are nested before the counts are stored.
UNROLLED = 6


def count_paths(g: LabeledDag, m: int, strategy: str = "join", count_type: str = "long", direction: str = "starting") -> DataFrame:
    """``vid``, ``c``: counts by level, c[0] = 0.

    join: m - 1 rounds, each one join of the edges with the level before and one sum by vertex, combined before it is
    exchanged. grouped: one exchange by session and a sweep backwards in time. Sums of ``long`` that overflow stop the job; ``decimal``
    holds 38 digits."""
    if strategy == "grouped":
        if count_type != "long" or direction != "starting":
            raise ValueError("the sweep counts starting paths in 64 bits")
        return g.pieces().groupBy("tag", "session").applyInArrow(_sweep(g.delta, m), "vid long, c array<long>")
    kind = TYPES[count_type]
    a, b = ("src", "dst") if direction == "starting" else ("dst", "src")
    edges = g.edges.select(F.col(a).alias("near"), F.col(b).alias("far"))
    level = g.vertices.select("vid", F.array(F.lit(0).cast(kind), F.lit(1).cast(kind)).alias("c"))
    for i in range(2, m + 1):
        sums = edges.join(level.select(F.col("vid").alias("far"), F.element_at("c", -1).alias("n")), "far").groupBy("near").agg(F.sum("n").alias("n"))
        level = level.join(sums, F.col("vid") == F.col("near"), "left").select("vid", F.concat("c", F.array((F.coalesce("n", F.lit(0)) + 1).cast(kind))).alias("c"))
        if i % UNROLLED == 0:
            level = materialise(level, "counts")
    return level


def _sweep(delta: int, m: int):
    def run(group):
        import pyarrow as pa

        from pathtraces.operators.kernels import Piece

        piece = Piece.of(group, delta)
        return pa.table({"vid": pa.array(piece.vid, pa.int64()), "c": pa.array(piece.counts(m), pa.list_(pa.int64()))})

    return run


def saturated_counts(g: LabeledDag) -> DataFrame:
    """Counts of paths of any length."""
    return count_paths(g, max(1, dag_depth(g)))


def total_paths(counts: DataFrame, m: int) -> int:
    return int(counts.agg(F.sum(F.element_at("c", m + 1))).first()[0] or 0)


def totals_by_level(counts: DataFrame, m: int) -> DataFrame:
    """``m``, ``n_paths``: one pass over the counts for all levels."""
    sums = counts.agg(F.array(*[F.sum(F.element_at("c", i + 1)) for i in range(1, m + 1)]).alias("n"))
    return sums.select(F.posexplode("n").alias("k", "n_paths")).select((F.col("k") + 1).alias("m"), F.col("n_paths").cast("long").alias("n_paths"))


def spread(counts: DataFrame, m: int) -> DataFrame:
    """``vid``, ``c1``, ..., ``cm``."""
    return counts.select("vid", *[F.element_at("c", i + 1).alias(f"c{i}") for i in range(1, m + 1)])


def counting_cost(g: LabeledDag, m: int) -> DataFrame:
    """Edge visits of the counting phase."""
    return g.edges.agg(F.count(F.lit(1)).alias("n_edges")).select("n_edges", F.lit(m).alias("m"), (F.col("n_edges") * (m - 1)).alias("edge_visits"))
