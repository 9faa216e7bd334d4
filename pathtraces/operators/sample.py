"""Samples of all paths of at most m vertices, each drawn with probability p, without enumerating them."""

from __future__ import annotations

import math
from collections.abc import Callable
from dataclasses import dataclass
from functools import reduce

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from pathtraces.functions import measures
from pathtraces.functions.columns import SEPARATOR, hash_step, missing_all, some_drawn, uniform
from pathtraces.operators.counts import count_paths, total_paths
from pathtraces.operators.dag import LabeledDag
from pathtraces.operators.enumeration import enumerate_traces, label_codes
from pathtraces.plans.storage import BROADCAST_ROWS, materialise

SAMPLERS = ("descend", "printed", "rank", "first_hit", "guide", "bernoulli_full")
KERNELS = ("descend", "printed", "first_hit", "guide")
OUT = "start_vid long, path_key string, trace string"


@dataclass(frozen=True)
class SamplingPlan:
    total: int
    min_count: float
    c: float
    p: float

    @property
    def expected_samples(self) -> float:
        return self.p * self.total

    @property
    def capacity(self) -> int:
        return measures.summary_capacity(self.c, math.ceil(self.expected_samples))


def plan_sampling(counts: DataFrame, m: int, c: float = 10, min_count: float | None = None, min_support: float | None = None) -> SamplingPlan:
    """The threshold is a count, or a share of all paths."""
    if (min_count is None) == (min_support is None):
        raise ValueError("give min_count or min_support")
    total = total_paths(counts, m)
    threshold = min_count if min_count is not None else max(1.0, min_support * total)
    return SamplingPlan(total, threshold, c, measures.choose_p(c, threshold))


def roots(counts: DataFrame, m: int, p: float, seed: int) -> DataFrame:
    """``vid``, ``i``: the vertices with a sampled path. Touches no edge."""
    return counts.where(uniform(seed, F.lit("root"), "vid") < some_drawn(p, F.element_at("c", m + 1))).select("vid", F.lit(m).alias("i"))


def _ways(g: LabeledDag, counts: DataFrame) -> DataFrame:
    """Edges with their child's label and counts."""
    child = g.vertices.join(counts, "vid").select(F.col("vid").alias("dst"), F.col("label").alias("dst_label"), F.col("c").alias("dst_c"))
    return g.edges.join(child, "dst")


def prepare(g: LabeledDag, counts: DataFrame, m: int, guides: bool = False) -> DataFrame:
    """What all samplers descend on, made once and stored: ``vid``, ``kids``. A vertex's children in order of id, each with its label, its counts ``c``
    and, by level, the running sums ``s`` of the counts up to and with it. ``guides`` adds, by level, where a search may begin
    in equal cells of the whole weight."""
    by = Window.partitionBy("src").orderBy("dst").rowsBetween(Window.unboundedPreceding, 0)
    sums = F.array(*[F.sum(F.element_at("dst_c", i)).over(by) for i in range(1, m + 1)])
    summed = _ways(g, counts).withColumn("s", sums)
    lists = summed.groupBy("src").agg(F.array_sort(F.collect_list(F.struct("dst", F.col("dst_label").alias("label"), F.col("dst_c").alias("c"), "s"))).alias("kids"))
    kind = lists.schema["kids"].dataType
    ways = g.vertices.select("vid").join(lists, F.col("vid") == F.col("src"), "left").select("vid", F.coalesce("kids", F.array().cast(kind)).alias("kids"))
    if guides:

        def cells(batches):
            import pyarrow as pa

            from pathtraces.operators.kernels import guide_of

            for batch in batches:
                made = [[guide_of([0, *(k["s"][i] for k in kids), kids[-1]["s"][i] + 1]) if kids else [0] for i in range(m)] for kids in batch.column(1).to_pylist()]
                yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(made, pa.list_(pa.list_(pa.int32())))], ["vid", "kids", "guides"])

        ways = ways.mapInArrow(cells, f"vid long, kids {kind.simpleString()}, guides array<array<int>>")
    return materialise(ways, "ways")


def _sent(now: DataFrame, expected: float) -> DataFrame:
    """A frontier, sent to all tasks if the sample it belongs to is small. It has at most a row for each sampled path and one for each
    visited vertex of such a path, and samples are within ten deviations of their mean."""
    if 2 * (expected + 10 * math.sqrt(expected) + 100) <= BROADCAST_ROWS:
        return F.broadcast(now)
    return materialise(now, "frontier")


def _expected(counts: DataFrame, m: int, p: float, expected: float | None) -> float:
    return p * total_paths(counts, m) if expected is None else expected


def descend(g: LabeledDag, counts: DataFrame, m: int, p: float, seed: int = 42, printed: bool = False, output: str = "trace", ways: DataFrame | None = None, expected: float | None = None) -> DataFrame:
    """``start_vid``, ``path_key``, ``trace`` (or ``h1``, ``h2``), ``scanned`` (edges looked at, each visit's on one row): from each root level by level along
    sampled children.

    Children are considered in order. Until one is taken, each has its chance given that something at or after it is drawn; after
    that, its plain chance. A vertex of whose children none is taken is itself drawn, others with p. Draws are keyed by the path so
    far, so two paths that meet in a vertex are independent. ``printed`` applies the published rule, which is biased.

    Finished paths stay in the frontier, so a level is one join of the prepared children with the frontier, and a row decides on all
    its children at once: no edge is exchanged, and nothing is ordered."""
    hashed = output == "hash"
    codes = F.create_map(*[x for r in label_codes(g).collect() for x in (F.lit(r.label), F.lit(r.code))]) if hashed else None  # one entry a label
    ways, expected = prepare(g, counts, m) if ways is None else ways, _expected(counts, m, p, expected)

    def grown(row: Callable[[str], Column], label: Column, fresh: bool = False) -> list[Column]:
        if hashed:
            return [hash_step(F.lit(0).cast("long") if fresh else row(f"h{k + 1}"), F.element_at(codes, label), k).alias(f"h{k + 1}") for k in (0, 1)]
        return [(label if fresh else F.concat_ws(SEPARATOR, row("trace"), label)).alias("trace")]

    kept = ["h1", "h2"] if hashed else ["trace"]
    start = roots(counts, m, p, seed).join(g.vertices.select("vid", "label"), "vid").join(counts.select("vid", "c"), "vid")
    now = start.select(F.col("vid").alias("start_vid"), F.col("vid").alias("v"), F.col("vid").cast("string").alias("path_key"), *grown(F.col, F.col("label"), True), F.element_at("c", m + 1).cast("long").alias("count"), F.lit(False).alias("done"), F.lit(0).cast("long").alias("scanned"))
    columns = now.columns
    no_kids = F.array().cast(ways.schema["kids"].dataType)

    def level(now: DataFrame, i: int) -> DataFrame:
        n = lambda k: F.element_at(k["c"], i)
        u = lambda k: uniform(seed, F.lit("child"), "path_key", k["dst"])
        here = ways.join(_sent(now, expected), F.col("vid") == F.col("v")).withColumn("kids", F.when(F.col("done"), no_kids).otherwise(F.col("kids")))
        if printed:
            skip = lambda k: F.least(F.lit(1.0), missing_all(p, n(k)) / some_drawn(p, F.col("count")))
            taken = F.filter("kids", lambda k: (n(k) > 0) & (u(k) > skip(k)))
        else:
            left = lambda k: F.col("count") - F.element_at(k["s"], i) + n(k)
            first = F.transform("kids", lambda k: (n(k) > 0) & (u(k) < some_drawn(p, n(k)) / some_drawn(p, left(k))))
            here = here.withColumn("hit", F.array_position(first, F.lit(True)))
            taken = F.filter("kids", lambda k, j: (F.col("hit") > 0) & (j + 1 >= F.col("hit")) & ((j + 1 == F.col("hit")) | ((n(k) > 0) & (u(k) < some_drawn(p, n(k))))))
        here = here.withColumn("taken", taken)
        here = here.withColumn("own", F.col("done") | (F.size("taken") == 0) | (uniform(seed, F.lit("self"), "path_key") < p))
        seen = F.col("scanned") + F.size("kids")
        self_ = F.struct("start_vid", "v", "path_key", *kept, "count", F.lit(True).alias("done"), seen.alias("scanned"))

        def further(k: Column, j: Column) -> Column:
            first_row = F.when(F.col("own") | (j > 0), F.lit(0)).otherwise(seen).cast("long")
            return F.struct(F.col("start_vid"), k["dst"].alias("v"), F.concat_ws("-", "path_key", k["dst"]).alias("path_key"), *grown(F.col, k["label"]), n(k).cast("long").alias("count"), F.lit(False).alias("done"), first_row.alias("scanned"))

        rows = F.transform("taken", further)
        return here.select(F.inline(F.when(F.col("own"), F.concat(F.array(self_), rows)).otherwise(rows))).toDF(*columns)

    for i in range(m, 1, -1):
        now = level(now, i)
    return now.select("start_vid", "path_key", *kept, "scanned")


def hits(g: LabeledDag, counts: DataFrame, m: int, p: float, seed: int = 42, how: str = "first_hit", ways: DataFrame | None = None, expected: float | None = None) -> DataFrame:
    """``start_vid``, ``path_key``, ``trace``, ``draws``, ``steps``: the refined samplers on prepared sums. From a uniform number follows how far the next drawn
    element lies in a vertex's weight; ``first_hit`` finds whose it is by halving, ``guide`` from a stored place on. So work follows
    the sampled children, not a vertex's degree. Draws are those of the tag-local form. ``draws`` and ``steps`` say what the searches took."""
    from pathtraces.operators.kernels import next_hits

    if ways is None or (how == "guide" and "guides" not in ways.columns):
        ways = prepare(g, counts, m, how == "guide")
    expected = _expected(counts, m, p, expected)
    start = roots(counts, m, p, seed).join(g.vertices.select("vid", "label"), "vid")
    zero = F.lit(0).cast("long")
    now = start.select(F.col("vid").alias("start_vid"), F.col("vid").alias("v"), F.col("vid").cast("string").alias("path_key"), F.col("label").alias("trace"), F.lit(False).alias("done"), zero.alias("draws"), zero.alias("steps"))
    columns = now.columns
    kinds = "start_vid long, v long, path_key string, trace string, done boolean, draws long, steps long"

    def level(i: int):
        def run(batches):
            import pyarrow as pa

            for batch in batches:
                out = []
                for row in batch.to_pylist():
                    line = (row["start_vid"], row["v"], row["path_key"], row["trace"])
                    if row["done"]:
                        out.append((*line, True, row["draws"], row["steps"]))
                        continue
                    sums = [0, *(k["s"][i - 1] for k in row["kids"])]
                    found, own, draws, steps = next_hits([*sums, sums[-1] + 1], p, seed, row["path_key"], row["guides"][i - 1] if how == "guide" else None)
                    next_ = [(row["start_vid"], k["dst"], f"{row['path_key']}-{k['dst']}", row["trace"] + SEPARATOR + k["label"], False) for k in map(row["kids"].__getitem__, found)]
                    next_ += [(*line, True)] if own else []
                    out += [(*x, row["draws"] + draws, row["steps"] + steps) if j == 0 else (*x, 0, 0) for j, x in enumerate(next_)]
                types = [pa.int64(), pa.int64(), pa.string(), pa.string(), pa.bool_(), pa.int64(), pa.int64()]
                cols = list(zip(*out, strict=True)) or [[]] * len(types)
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, types, strict=True)], columns)

        return run

    for i in range(m, 1, -1):
        now = ways.join(_sent(now, expected), F.col("vid") == F.col("v")).select(*columns, *ways.columns[1:]).mapInArrow(level(i), kinds)
    return now.select("start_vid", "path_key", "trace", "draws", "steps")


def sample_grouped(g: LabeledDag, m: int, p: float, seed: int = 42, how: str = "descend") -> DataFrame:
    """Counting and sampling of a session in one Arrow call: one exchange in all. ``descend`` draws what the set-based form draws."""
    delta = g.delta

    def run(group):
        import pyarrow as pa

        from pathtraces.operators.kernels import Piece

        found = list(zip(*Piece.of(group, delta).sample(m, p, seed, how), strict=True)) or [[]] * 3
        return pa.table({"start_vid": pa.array(found[0], pa.int64()), "path_key": pa.array(found[1], pa.string()), "trace": pa.array(found[2], pa.string())})

    return g.pieces().groupBy("tag", "session").applyInArrow(run, OUT)


def sample_seeds(g: LabeledDag, m: int, p: float, seeds: list[int], how: str = "first_hit") -> DataFrame:
    """``seed``, ``trace``, ``u``: the samples of many seeds from one exchange by session, for error rates over seeds. ``u`` is uniform and independent of the draw: rows
    below ``q`` are a sample with ``p * q``."""
    delta = g.delta

    def run(group):
        import pyarrow as pa

        from pathtraces.operators.kernels import Piece, uniform

        piece = Piece.of(group, delta)
        found = [(seed, trace, uniform(seed, "thin", key)) for seed in seeds for _, key, trace in piece.sample(m, p, seed, how)]
        kinds = (pa.int64(), pa.string(), pa.float64())
        return pa.table({n: pa.array([f[k] for f in found], t) for k, (n, t) in enumerate(zip(("seed", "trace", "u"), kinds, strict=True))})

    return g.pieces().groupBy("tag", "session").applyInArrow(run, "seed long, trace string, u double")


def sample_ranks(g: LabeledDag, counts: DataFrame, m: int, p: float, seed: int = 42, min_len: int = 1, ways: DataFrame | None = None, expected: float | None = None) -> DataFrame:
    """The paths of a start vertex are numbered: itself first, then the blocks of its children in order. Numbers are drawn, then
    each is resolved by one join a level and a search in the prepared sums. Rows are independent, so prefixes that many samples share make no hot key."""

    def draw(batches):
        import numpy as np
        import pyarrow as pa

        from pathtraces.operators.kernels import ranks

        for batch in batches:
            drawn = [ranks(n, p, seed, v) for v, n in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True)]
            yield pa.RecordBatch.from_arrays([pa.array(np.repeat(batch.column(0).to_numpy(), [len(d) for d in drawn])), pa.array([r for d in drawn for r in d], pa.int64())], ["vid", "rank"])

    chosen = roots(counts, m, p, seed).select("vid").join(counts.select("vid", F.element_at("c", m + 1).cast("long").alias("n")), "vid")
    picked = chosen.mapInArrow(draw, "vid long, rank long")
    picked = picked.where("rank > 0") if min_len == 2 else picked
    start = g.vertices.select("vid", "label").join(picked, "vid")
    now = start.select(F.col("vid").alias("start_vid"), F.col("vid").alias("v"), F.col("vid").cast("string").alias("path_key"), F.col("label").alias("trace"), "rank")
    ways, expected = prepare(g, counts, m) if ways is None else ways, _expected(counts, m, p, expected)
    for i in range(m, 1, -1):
        here = ways.join(_sent(now, expected), F.col("vid") == F.col("v"))
        here = here.withColumn("ends", F.transform("kids", lambda k: F.element_at(k["s"], i)))  # noqa: B023  used at once
        here = here.withColumn("k", F.when(F.col("rank") > 0, _first_at_least("ends", F.col("rank"))))
        kid = F.element_at("kids", F.col("k"))
        here = here.withColumn("kid", kid)
        low = F.element_at(F.col("kid.s"), i) - F.element_at(F.col("kid.c"), i) + 1
        go = F.col("rank") > 0
        now = here.select("start_vid", F.when(go, F.col("kid.dst")).otherwise(F.col("v")).alias("v"), F.when(go, F.concat_ws("-", "path_key", "kid.dst")).otherwise(F.col("path_key")).alias("path_key"), F.when(go, F.concat_ws(SEPARATOR, "trace", "kid.label")).otherwise(F.col("trace")).alias("trace"), F.when(go, F.col("rank") - low).otherwise(F.lit(0)).cast("long").alias("rank"))
    return now.select("start_vid", "path_key", "trace")


def _first_at_least(sums: str, x: Column) -> Column:
    """The place (from 1) of the first of ascending ``sums`` that reaches ``x``, by halving."""
    n = F.size(sums)
    rounds = F.sequence(F.lit(1), F.greatest(F.lit(1), F.ceil(F.log2(n + F.lit(1))).cast("int")))

    def halve(at: Column, _: Column) -> Column:
        middle = F.floor((at["low"] + at["high"]) / 2).cast("int")
        short = F.element_at(sums, middle) < x
        return F.when(at["low"] >= at["high"], at).otherwise(F.struct(F.when(short, middle + 1).otherwise(at["low"]).alias("low"), F.when(short, at["high"]).otherwise(middle).alias("high")))

    return F.aggregate(rounds, F.struct(F.lit(1).alias("low"), n.alias("high")), halve)["low"]


def sample_full(g: LabeledDag, m: int, p: float, seed: int = 42) -> DataFrame:
    """The baseline: every path is made, and kept with p."""
    every = enumerate_traces(g, m).select("start_vid", F.col("path").alias("path_key"), "trace")
    return every.where(uniform(seed, F.lit("path"), "path_key") < p)


def sample_traces(g: LabeledDag, counts: DataFrame, m: int, p: float, seed: int = 42, sampler: str = "descend", strategy: str = "join", ways: DataFrame | None = None, expected: float | None = None) -> DataFrame:
    """``start_vid``, ``path_key``, ``trace`` by any of the samplers. ``ways`` (as from ``prepare``) and ``expected`` samples spare their computation."""
    if sampler not in SAMPLERS:
        raise ValueError(f"sampler is one of {SAMPLERS}")
    if strategy == "grouped":
        if sampler not in KERNELS:
            raise ValueError(f"tag-local samplers are {KERNELS}")
        return sample_grouped(g, m, p, seed, sampler)
    if sampler == "rank":
        return sample_ranks(g, counts, m, p, seed, ways=ways, expected=expected)
    if sampler == "bernoulli_full":
        return sample_full(g, m, p, seed)
    drawn = hits(g, counts, m, p, seed, sampler, ways, expected) if sampler in ("first_hit", "guide") else descend(g, counts, m, p, seed, sampler == "printed", ways=ways, expected=expected)
    return drawn.select("start_vid", "path_key", "trace")


def edge_probabilities(g: LabeledDag, counts: DataFrame, m: int, p: float) -> DataFrame:
    """``src``, ``dst``, ``level``, ``pr``: the chance that the edge is the first taken, given that nothing before it was."""
    own = counts.select(F.col("vid").alias("src"), F.col("c").alias("src_c"))
    rows = _ways(g, counts).join(own, "src").select("src", "dst", F.explode(F.sequence(F.lit(2), F.lit(m))).alias("level"), "src_c", "dst_c") if m > 1 else _ways(g, counts).join(own, "src").select("src", "dst", F.lit(0).alias("level"), "src_c", "dst_c").where("false")
    rows = rows.withColumn("n", F.element_at("dst_c", F.col("level")))
    before = Window.partitionBy("src", "level").orderBy("dst").rowsBetween(Window.unboundedPreceding, -1)
    rows = rows.withColumn("left", F.element_at("src_c", F.col("level") + 1) - F.coalesce(F.sum("n").over(before), F.lit(0)))
    return rows.select("src", "dst", "level", (some_drawn(p, F.col("n")) / some_drawn(p, F.col("left"))).alias("pr"))


def sampler_cost(sample: DataFrame) -> DataFrame:
    """``measure``, ``value``: samples, their labels together, the calls of the descent (distinct prefixes of sampled paths), and the edges that it looked at, as it
    counted them."""
    parts: Column = F.split("path_key", "-")
    prefixes = sample.select(F.explode(F.transform(F.sequence(F.lit(1), F.size(parts)), lambda k: F.array_join(F.slice(parts, 1, k), "-"))).alias("x")).distinct()
    rows = [
        sample.agg(F.count(F.lit(1)).alias("value")).select(F.lit("samples").alias("measure"), "value"),
        sample.agg(F.coalesce(F.sum(F.size(parts)), F.lit(0)).cast("long").alias("value")).select(F.lit("sampled_length").alias("measure"), "value"),
        prefixes.agg(F.count(F.lit(1)).alias("value")).select(F.lit("calls").alias("measure"), "value"),
        sample.agg(F.coalesce(F.sum("scanned"), F.lit(0)).cast("long").alias("value")).select(F.lit("edges_scanned").alias("measure"), "value"),
    ]
    return reduce(DataFrame.unionByName, rows)
