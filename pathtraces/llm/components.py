"""Connected components of an edge table, without gathering edges or nodes anywhere.

Every round turns the edges into stars around smaller nodes: first each node hands its larger neighbours to its smallest
one, then its smaller neighbours. Rounds grow with the logarithm of the longest chain. Each round is written to shared
storage, so that lineage stays short and a lost executor costs one round's task."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pathtraces.llm.common import by_exchange, spill
from pathtraces.plans.storage import BROADCAST_ROWS


#: Ids alone that may be sent to every task, so that texts stay where they are.
BROADCAST_IDS = 5 * BROADCAST_ROWS


def _state(edges: DataFrame) -> tuple:
    row = edges.agg(F.count(F.lit(1)), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
    return row[0], row[1]


def components(edges: DataFrame, a: str = "a", b: str = "b", max_rounds: int = 60) -> DataFrame:
    """``node``, ``component`` (the smallest node reachable) for every node that has an edge to another node. Edges with a
    null end, loops and repeated edges are allowed and add nothing."""
    now = edges.where(F.col(a) != F.col(b)).select(F.greatest(a, b).alias("u"), F.least(a, b).alias("v")).distinct()
    now = spill(now, "edges")
    state = _state(now)
    for _ in range(max_rounds):
        if not state[0]:
            break
        both = now.unionByName(now.select(F.col("v").alias("u"), F.col("u").alias("v")))
        low = both.groupBy("u").agg(F.min("v").alias("low")).select("u", F.least("u", "low").alias("low"))
        join = by_exchange if state[0] > BROADCAST_ROWS else lambda side: side
        large = both.where("v > u").join(join(low), "u").select(F.col("v").alias("u"), F.col("low").alias("v")).distinct()
        low = large.groupBy("u").agg(F.min("v").alias("low"))
        small = large.join(join(low), "u").where("v != low").select(F.col("v").alias("u"), F.col("low").alias("v"))
        after = spill(small.unionByName(low.withColumnRenamed("low", "v")).distinct(), "edges")
        new = _state(after)
        now, done, state = after, new == state, new
        if done:
            break
    else:
        raise RuntimeError("the components did not settle")
    stars = now.select(F.col("u").alias("node"), F.col("v").alias("component"))
    return stars.unionByName(now.select(F.col("v").alias("node"), F.col("v").alias("component")).distinct())


def drop_ids(docs: DataFrame, ids: DataFrame, id: str) -> DataFrame:
    """``docs`` without the rows whose id is among ``ids`` (column ``id`` and ``rows``, how many rows have it) with ``keep`` false, and one
    row for each other id. ``ids`` may leave out ids that are kept and have one row: so what is joined is what goes, the smaller part.
    Only ids with several rows are brought together by id."""
    several = ids.where("keep and rows > 1").select(F.col("id").alias("__id"))
    gone = ids.where("not keep or rows > 1").select(F.col("id").alias("__id"))
    join = by_exchange if gone.limit(BROADCAST_IDS + 1).count() > BROADCAST_IDS else lambda side: side
    once = docs.join(join(gone), F.col(id) == F.col("__id"), "left_anti")
    return once.unionByName(docs.join(join(several), F.col(id) == F.col("__id"), "left_semi").dropDuplicates([id]))
