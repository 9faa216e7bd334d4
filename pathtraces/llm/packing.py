"""Best-fit packing by minimum bin slack.

Documents become token pieces of at most ``capacity``; a longer document's first piece is the shorter one, the others are full.
Only the lengths decide a packing, and there are at most ``capacity`` different ones, so it is planned on their counts: a bin
takes the longest piece left, then the fullest combination of the rest, found by subset sums over the bits of one integer.
The same combination stays the fullest for as long as its pieces last, so it is repeated that often at once, and the plan has
a few runs for each length, however many documents there are.

Pieces then find their places by rank among the pieces of their length. Ranks come from counts by task of the written piece table
plus running sums over tasks: no length is sorted or gathered in one task.

A null or empty text has only the end id. Rows that share an id, or have none, are packed each. Which of several pieces of one length
stands where, and so its sequence, follows the partitions of the table; how many sequences there are, and the lengths in them, do not. Columns
beside id and text are ignored. An empty table gives no pieces."""

from __future__ import annotations

import zlib

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from pathtraces.llm.common import parts, spill
from pathtraces.llm.tokens import CACHE_BYTES, encoder

CAPACITY, END_ID = 2048, 0


def pieces(docs: DataFrame, tokenizer: str, id: str = "doc_id", text: str = "text", capacity: int = CAPACITY, end_id: int = END_ID, cache_bytes: int = CACHE_BYTES) -> DataFrame:
    """``id``, ``piece``, ``start``, ``length``, ``ids_crc32``, and the piece's ``task`` and ``rank`` among the task's pieces of that length."""

    def run(batches):
        import pyarrow as pa
        from pyspark import TaskContext

        encode, task = encoder(tokenizer, cache_bytes), TaskContext.get().partitionId()
        met = np.zeros(capacity + 1, np.int64)
        end = np.array([end_id], "<u4").tobytes()
        for batch in batches:
            for part in parts(batch):
                rows = []
                for key, ids in zip(part.column(0).to_pylist(), encode(part.column(1).to_pylist()), strict=True):
                    ids += end
                    n = len(ids) // 4
                    at = 0
                    for k in range(-(-n // capacity)):
                        to = at + ((n - 1) % capacity + 1 if k == 0 else capacity)
                        rows.append((key, k, at, to - at, zlib.crc32(ids[4 * at : 4 * to]), task, int(met[to - at])))
                        met[to - at] += 1
                        at = to
                cols = list(zip(*rows, strict=True)) or [[]] * 7
                kinds = [part.column(0).type, pa.int32(), pa.int64(), pa.int64(), pa.int64(), pa.int32(), pa.int64()]
                yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, kinds, strict=True)], names)

    names = ["id", "piece", "start", "length", "ids_crc32", "task", "rank"]
    return docs.select(F.col(id).alias("id"), F.col(text).alias("text")).mapInArrow(run, f"id {dict(docs.dtypes)[id]}, piece int, start long, length long, ids_crc32 long, task int, rank long")


def fullest(counts: dict[int, int], room: int) -> dict[int, int]:
    """A combination of at most the counted pieces that leaves the least room, made of the longest lengths that allow it."""
    layers: list[tuple[int, int, int]] = []  # length, pieces taken at once, sums reachable before
    reach, limit = 1, (1 << (room + 1)) - 1
    for length in sorted((x for x in counts if x <= room and counts[x] > 0), reverse=True):
        left, step = min(counts[length], room // length), 1
        while left > 0:
            step = min(step, left)
            layers.append((length, step, reach))
            reach |= reach << (length * step) & limit
            left, step = left - step, 2 * step
        if reach >> room & 1:
            break
    at, out = reach.bit_length() - 1, {}
    for length, step, before in reversed(layers):
        if not before >> at & 1:
            at -= length * step
            out[length] = out.get(length, 0) + step
    return out


def plan(counts: dict[int, int], capacity: int = CAPACITY) -> list[tuple[int, int, dict[int, int]]]:
    """Runs of equal bins: the first bin's number, how many, and the pieces of each by length."""
    left = {int(k): int(v) for k, v in counts.items() if v > 0}
    runs, at = [], 0
    while left:
        longest = max(left)
        left[longest] -= 1
        combination = fullest(left, capacity - longest)
        left[longest] += 1
        combination[longest] = combination.get(longest, 0) + 1
        times = min(left[x] // n for x, n in combination.items())
        runs.append((at, times, combination))
        at += times
        for x, n in combination.items():
            left[x] -= n * times
            if not left[x]:
                del left[x]
    return runs


def pack(cut: DataFrame, capacity: int = CAPACITY) -> DataFrame:
    """``cut`` (as from ``pieces``, and written: it is read twice) with ``sequence_id`` and ``offset``."""
    spark = cut.sparkSession
    by_task = cut.groupBy("length", "task").agg(F.count(F.lit(1)).alias("n"))
    base = by_task.withColumn("base", F.coalesce(F.sum("n").over(Window.partitionBy("length").orderBy("task").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)))
    base = spill(base, "ranks")
    counts = {r.length: r.n for r in base.groupBy("length").agg(F.sum("n").alias("n")).collect()}  # at most `capacity` rows
    used: dict[int, int] = {}
    rows = []
    for first, times, combination in plan(counts, capacity):
        offset = 0
        for length in sorted(combination, reverse=True):
            n = combination[length]
            low = used.get(length, 0)
            rows.append((length, low, low + n * times, n, first, offset))
            used[length], offset = low + n * times, offset + n * length
    slots = spark.createDataFrame(rows, "length long, low long, high long, each long, first_bin long, at long")
    ranked = cut.join(base.select("length", "task", "base"), ["length", "task"]).withColumn("place", F.col("base") + F.col("rank"))
    placed = ranked.join(F.broadcast(slots), (ranked["length"] == slots["length"]) & (F.col("place") >= F.col("low")) & (F.col("place") < F.col("high"))).drop(slots["length"])
    inside = F.col("place") - F.col("low")
    return placed.select("id", "piece", "start", "length", "ids_crc32", (F.col("first_bin") + F.floor(inside / F.col("each"))).cast("long").alias("sequence_id"), (F.col("at") + inside % F.col("each") * F.col("length")).cast("long").alias("offset"))


def packed(docs: DataFrame, tokenizer: str, id: str = "doc_id", text: str = "text", capacity: int = CAPACITY, end_id: int = END_ID, cache_bytes: int = CACHE_BYTES) -> DataFrame:
    """A row for each piece of every document, with its sequence and its offset there. ``cache_bytes`` bounds the token chunks that a worker keeps, twice."""
    return pack(spill(pieces(docs, tokenizer, id, text, capacity, end_id, cache_bytes), "pieces"), capacity).withColumnRenamed("id", id)
