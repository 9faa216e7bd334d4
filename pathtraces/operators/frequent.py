"""Which sampled traces are frequent: exact counts, bounded summaries, verifying second passes, estimates."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from pathtraces.functions.measures import least_reported
from pathtraces.operators.dag import LabeledDag
from pathtraces.operators.enumeration import count_candidates
from pathtraces.plans.storage import materialise, small

#: Places that Spark's own summaries can hold.
BUILT_IN_ROOM = 10_000
METHODS = ("exact", "decrement", "freqitems", "sketch")
SECOND_PASSES = ("stored", "replay", "fresh", "exact", "none")


def enough(c: float, strict: bool, column: str = "n_sample"):
    return F.col(column) >= least_reported(c, strict)


def sample_counts(sample: DataFrame) -> DataFrame:
    return sample.groupBy("trace").agg(F.count(F.lit(1)).alias("n_sample"))


class DecrementSummary:
    """At most ``capacity`` counters. A known item adds one; an unknown one takes a free counter, or, if there is none, takes one off
    all counters and is dropped. Merging adds counters and takes the first one beyond capacity off the rest."""

    def __init__(self, capacity: int):
        self.capacity, self.counters = capacity, {}

    def add(self, item, n: int = 1) -> None:
        """``n`` times the same item at once."""
        counters = self.counters
        if item in counters:
            counters[item] += n
            return
        while n and len(counters) >= self.capacity:
            least = min(n, min(counters.values()))
            for key in [k for k in counters if counters[k] == least]:
                del counters[key]
            for key in counters:
                counters[key] -= least
            n -= least
        if n:
            counters[item] = n

    def merge(self, other: dict) -> None:
        for item, n in other.items():
            self.counters[item] = self.counters.get(item, 0) + n
        if len(self.counters) > self.capacity:
            off = sorted(self.counters.values(), reverse=True)[self.capacity]
            self.counters = {k: n - off for k, n in self.counters.items() if n > off}


def _filled(items: DataFrame, column: str, capacity: int) -> DataFrame:
    """``item``, ``n``, ``most`` (counters held at once): a summary in each task."""

    def fill(batches):
        import pyarrow as pa

        summary, most = DecrementSummary(capacity), 0
        for batch in batches:
            counted = batch.column(0).value_counts()
            for item, n in zip(counted.field(0).to_pylist(), counted.field(1).to_pylist(), strict=True):
                if item is not None:
                    summary.add(item, n)
                    most = max(most, len(summary.counters))
        yield pa.RecordBatch.from_arrays([pa.array(list(summary.counters), pa.string()), pa.array(list(summary.counters.values()), pa.int64()), pa.array([most] * len(summary.counters), pa.int32())], ["item", "n", "most"])

    return items.select(F.col(column).cast("string").alias("item")).mapInArrow(fill, "item string, n long, most int")


def decrement_summary(items: DataFrame, column: str, capacity: int) -> DataFrame:
    """``item``, ``n`` (a lower count), ``most`` (counters that some task held at once): a summary in each task, then one merge of all: their counters are added, and the first one
    beyond capacity is taken off the rest. The sums are by item, so no task holds more than its share."""
    added = materialise(_filled(items, column, capacity).groupBy("item").agg(F.sum("n").alias("n"), F.max("most").alias("most")), "summary")
    top = added.orderBy(F.desc("n")).limit(capacity + 1).agg(F.when(F.count(F.lit(1)) > capacity, F.min("n")).otherwise(0).alias("off"))
    return added.crossJoin(F.broadcast(top)).where(F.col("n") > F.col("off")).select("item", (F.col("n") - F.col("off")).alias("n"), "most")


def merged_maps(summaries: Column, capacity: int) -> Column:
    """An array of summaries, each a map of item to counter, merged one after the other by the same rule into one map."""

    def merge(a: Column, b: Column) -> Column:
        both = F.map_zip_with(a, b, lambda _, x, y: F.coalesce(x, F.lit(0)) + F.coalesce(y, F.lit(0)))
        values = F.sort_array(F.map_values(both), asc=False)
        off = F.when(F.size(values) > capacity, F.element_at(values, F.least(F.size(values), F.lit(capacity + 1)))).otherwise(F.lit(0))
        return F.transform_values(F.map_filter(both, lambda _, n: n > off), lambda _, n: n - off)

    return F.aggregate(summaries, F.create_map().cast("map<string,bigint>"), merge)


def summary_of_parts(counted: DataFrame, part: str, capacity: int) -> DataFrame:
    """``item``, ``n``: from ``counted`` (``part``, ``trace``, ``n``) a summary for each part, such as a day, of which only its ``capacity`` largest counters less the next one are kept; then
    all merged. Parts are few and summaries bounded, so one row holds them."""
    order = Window.partitionBy(part).orderBy(F.desc("n"), "trace")
    ranked = counted.withColumn("place", F.row_number().over(order)).where(F.col("place") <= capacity + 1)
    off = F.max(F.when(F.col("place") == capacity + 1, F.col("n"))).over(Window.partitionBy(part))
    kept = ranked.withColumn("n", F.col("n") - F.coalesce(off, F.lit(0))).where((F.col("place") <= capacity) & (F.col("n") > 0))
    maps = kept.groupBy(part).agg(F.map_from_entries(F.collect_list(F.struct("trace", "n"))).alias("summary"))
    every = maps.agg(F.array_sort(F.collect_list(F.struct(F.col(part), F.map_entries("summary").alias("entries")))).alias("each"))
    merged = merged_maps(F.transform("each", lambda x: F.map_from_entries(x["entries"])), capacity)
    return every.select(F.explode(merged).alias("item", "n"))


def frequent_items(items: DataFrame, column: str, eta: float) -> DataFrame:
    """``item``, ``n``: every item whose share is above ``eta``, and no other: a summary finds at most 1/eta candidates, a second pass counts them."""
    capacity = math.ceil(1 / eta)
    found = small(materialise(decrement_summary(items, column, capacity).select("item"), "candidates"))
    counted = items.select(F.col(column).cast("string").alias("item")).join(found, "item", "left_semi").groupBy("item").agg(F.count(F.lit(1)).alias("n"))
    total = items.agg(F.count(column).alias("total"))
    return counted.crossJoin(F.broadcast(total)).where(F.col("n") > eta * F.col("total")).select("item", "n")


def candidates(sample: DataFrame, c: float, method: str = "exact", capacity: int | None = None, strict: bool = False) -> DataFrame:
    """``trace``, ``n``: all traces that reach C/2 in the sample, perhaps more (``n`` is then a lower count or an estimate). Where Spark's own summaries have too few
    places for that, the decrement summary takes over."""
    if method not in METHODS:
        raise ValueError(f"method is one of {METHODS}")
    if method == "exact":
        return sample_counts(sample).where(enough(c, strict)).select("trace", F.col("n_sample").alias("n"))
    n = sample.count()
    room = capacity or max(1, math.ceil(2 * n / c))
    if method == "decrement" or room > BUILT_IN_ROOM:
        return decrement_summary(sample, "trace", room).select(F.col("item").alias("trace"), "n")
    if method == "freqitems":
        items = sample.select("trace").stat.freqItems(["trace"], 1 / room)
        return items.select(F.explode("trace_freqItems").alias("trace")).withColumn("n", F.lit(None).cast("long"))
    top = sample.agg(F.expr(f"approx_top_k(trace, {room}, {max(1000, 8 * room)})").alias("top"))
    return top.select(F.inline("top")).toDF("trace", "n").select("trace", F.col("n").cast("long").alias("n"))


def with_estimates(counts: DataFrame, p: float) -> DataFrame:
    """Adds ``n_est`` and its standard error ``n_err``."""
    return counts.withColumn("n_est", F.round(F.col("n_sample") / F.lit(p), 6)).withColumn("n_err", F.round(F.sqrt(F.col("n_sample") * F.lit(1 - p)) / F.lit(p), 6))


def second_pass(found: DataFrame, how: str, c: float, p: float, sample: DataFrame | None = None, g: LabeledDag | None = None, m: int | None = None, strict: bool = False) -> DataFrame:
    """``trace``, ``n_sample``, ``n_est``: the candidates that reach C/2 when counted exactly. ``sample`` is the stored sample, the same one drawn again, or a
    fresh one; ``exact`` counts the candidates in the graph instead and reports those that reach the threshold itself."""
    if how == "exact":
        counted = count_candidates(g, found, m)
        return counted.where(F.col("n") >= F.lit(c / p)).select("trace", F.col("n").alias("n_true"))
    wanted = small(materialise(found.select("trace").distinct(), "candidates"))
    counted = sample_counts(sample.join(wanted, "trace", "left_semi")).where(enough(c, strict))
    return with_estimates(counted, p).select("trace", "n_sample", "n_est")
