"""Live edges, path counts, samples and frequent traces from a stream of readings (every reading a vertex).

Readings of a tag are put in order within the allowed lateness: one is released when the watermark has passed it. What comes later than that
finds its place passed: it is reported as ``late``, and takes part in nothing. A released reading looks back at the last readings of its tag. All its predecessors are older, so the
paths that *end* in it, and a sample of them, are final at once. The state of a tag holds the readings not yet released and those of the
last (m - 1) thresholds, and expires when the watermark has left them behind."""

from __future__ import annotations

import json
import math
from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from pathtraces.functions.columns import SEPARATOR

#: Microseconds by which no reading is late: some 142 years.
NEVER = 1 << 52
EVENT = "tag long, kind string, vid long, other long, level int, n long, text string"


def _released(buffer: list, watermark_us: int) -> tuple[list, list]:
    ready = sorted(x for x in buffer if x[0] <= watermark_us)
    return ready, [x for x in buffer if x[0] > watermark_us]


def _sampled_backwards(at: int, kept: list, preds: dict[int, list[int]], m: int, p: float, seed: int):
    """Sampled paths that end in reading ``at``; the descent of the batch sampler on the reversed graph."""
    from pathtraces.operators.kernels import uniform

    rest = math.log1p(-p) if p < 1 else -math.inf
    some = lambda n: -math.expm1(n * rest) if n else 0.0
    by = {x[1]: x for x in kept}
    if uniform(seed, "root", at) >= some(by[at][3][m]):
        return
    work = [([at], m)]
    while work:
        path, i = work.pop()
        key = "-".join(map(str, path))
        left, taken = by[path[-1]][3][i], []
        for j in sorted(preds[path[-1]]):
            n = by[j][3][i - 1]
            if not n:
                continue
            if uniform(seed, "child", key, j) < (some(n) if taken else some(n) / some(left)):
                taken.append(j)
            left -= n
        if not taken or uniform(seed, "self", key) < p:
            yield list(reversed(path))
        work.extend(([*path, j], i - 1) for j in taken)


def live_paths(readings: DataFrame, delta: int, lateness: str, m: int = 2, p: float | None = None, seed: int = 42) -> DataFrame:
    """A row for each event: ``edge`` (other -> vid), ``count`` (n paths of at most ``level`` vertices end in vid), ``sample`` (``text``: a
    sampled trace that ends in vid, with p given), ``late`` (vid came too late)."""

    def step(key, batches, state: GroupState):
        import pandas as pd

        buffer, kept = ([], []) if not state.exists else (json.loads(state.get[0]), json.loads(state.get[1]))
        mark = state.getCurrentWatermarkMs() * 1000
        out = []
        if state.hasTimedOut:
            fresh = []
        else:
            fresh = [(int(t), int(v), str(x)) for pdf in batches for t, v, x in zip(pdf.t_us, pdf.seq, pdf.label, strict=True)]
        for t, v, x in sorted(fresh):
            if t <= mark:  # its place has been passed
                out.append((key[0], "late", v, None, None, None, None))
            else:
                buffer.append([t, v, x])
        ready, buffer = _released(buffer, mark)
        for t, v, x in ready:
            kept = [k for k in kept if t - k[0] <= (m - 1) * delta]
            before = [k for k in kept if t - k[0] <= delta and k[2] != x]
            counts = [0] + [1 + sum(k[3][i - 1] for k in before) for i in range(1, m + 1)]
            kept.append([t, v, x, counts, [k[1] for k in before]])
            out += [(key[0], "edge", v, k[1], None, None, None) for k in before]
            out += [(key[0], "count", v, None, i, counts[i], None) for i in range(1, m + 1)]
            if p is not None:
                names = {k[1]: k[2] for k in kept}
                preds = {k[1]: [j for j in k[4] if j in names] for k in kept}
                out += [(key[0], "sample", v, path[0], len(path), None, SEPARATOR.join(names[j] for j in path)) for path in _sampled_backwards(v, kept, preds, m, p, seed)]
        if not buffer and all(mark - x[0] > (m - 1) * delta for x in kept):
            if state.exists:
                state.remove()
        else:
            state.update((json.dumps(buffer), json.dumps(kept)))
            ends = [x[0] for x in buffer] or [kept[-1][0] + (m - 1) * delta]
            state.setTimeoutTimestamp(max(min(ends) // 1000 + 1, state.getCurrentWatermarkMs() + 1))
        yield pd.DataFrame(out, columns=["tag", "kind", "vid", "other", "level", "n", "text"]).astype({"other": "Int64", "level": "Int32", "n": "Int64"})

    timed = readings.withColumn("at", F.timestamp_micros("t_us")).withWatermark("at", lateness)
    # the engine drops rows that its watermark column calls late before the function sees them, so that column is moved out of reach
    timed = timed.select("tag", "t_us", "seq", "label", F.timestamp_micros(F.col("t_us") + F.lit(NEVER)).alias("never", metadata={"spark.watermarkDelayMs": 0}))
    return timed.groupBy("tag").applyInPandasWithState(step, EVENT, "buffer string, kept string", "append", GroupStateTimeout.EventTimeTimeout)


def live_edges(readings: DataFrame, delta: int, lateness: str) -> DataFrame:
    """``src``, ``dst``."""
    return live_paths(readings, delta, lateness).where("kind = 'edge'").select(F.col("other").alias("src"), F.col("vid").alias("dst"))


def live_frequent(traces: DataFrame, capacity: int, publish: Callable[[dict, int], None]):
    """Keeps a bounded summary of sampled traces over micro-batches. ``publish`` gets the counters after each batch. Each batch is summed up
    in its tasks; only counters come to the driver."""
    from pathtraces.operators.frequent import DecrementSummary, decrement_summary

    summary = DecrementSummary(capacity)

    def each(batch: DataFrame, number: int) -> None:
        summary.merge({r.item: r.n for r in decrement_summary(batch, "text", capacity).collect()})
        publish(dict(summary.counters), number)

    return traces.writeStream.foreachBatch(each)


def windowed_counts(traces: DataFrame, time: str, window: str, slide: str | None = None) -> DataFrame:
    """Counts of sampled traces in tumbling or sliding windows."""
    return traces.groupBy(F.window(time, window, slide or window), "text").agg(F.count(F.lit(1)).alias("n"))


def session_runs(readings: DataFrame, gap: str) -> DataFrame:
    """``tag``, ``label``, ``t_first``, ``t_last``, ``n``: readings of a tag and label no more than ``gap`` apart. Unlike a collapsed run, a session goes on
    across readings elsewhere."""
    timed = readings.withColumn("at", F.timestamp_micros("t_us"))
    return timed.groupBy("tag", "label", F.session_window("at", gap)).agg(F.min("t_us").alias("t_first"), F.max("t_us").alias("t_last"), F.count(F.lit(1)).alias("n")).select("tag", "label", "t_first", "t_last", "n")
