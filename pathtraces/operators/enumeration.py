"""Full enumeration of traces, and exact counts without it."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from pathtraces.functions.columns import SEPARATOR, hash_step, trace_labels, trace_length
from pathtraces.operators.dag import LabeledDag
from pathtraces.plans.storage import materialise, small

UNROLLED = 6


def _levels(start: DataFrame, m: int, step, min_len: int = 1) -> DataFrame:
    """The union of levels min_len to m; long chains are stored now and then."""
    levels, now = [start], start
    for i in range(2, m + 1):
        now = step(now)
        if i % UNROLLED == 0:
            now = materialise(now, "level")
        levels.append(now)
    return reduce(DataFrame.unionByName, levels[min_len - 1 :])


def enumerate_traces(g: LabeledDag, m: int, min_len: int = 1, start: DataFrame | None = None) -> DataFrame:
    """``start_vid``, ``end_vid``, ``path``, ``trace``, ``len``: one row for each path of min_len to m vertices. ``start`` (vid) restricts where
    paths begin."""
    v = g.vertices if start is None else g.vertices.join(start.select("vid"), "vid", "left_semi")
    first = v.select(F.col("vid").alias("start_vid"), F.col("vid").alias("end_vid"), F.col("vid").cast("string").alias("path"), F.col("label").alias("trace"), F.lit(1).alias("len"))
    edges = g.labelled_edges()

    def step(now: DataFrame) -> DataFrame:
        return now.join(edges, now.end_vid == edges.src).select("start_vid", F.col("dst").alias("end_vid"), F.concat_ws("-", "path", "dst").alias("path"), F.concat_ws(SEPARATOR, "trace", "dst_label").alias("trace"), (F.col("len") + 1).alias("len"))

    return _levels(first, m, step, min_len)


def traces_from(g: LabeledDag, m: int, start: DataFrame) -> DataFrame:
    return enumerate_traces(g, m, start=start).groupBy("trace").agg(F.count(F.lit(1)).alias("n"))


def counted(traces: DataFrame) -> DataFrame:
    return traces.groupBy("trace").agg(F.count(F.lit(1)).alias("n")).withColumn("len", trace_length())


def trace_counts(g: LabeledDag, m: int, min_len: int = 1) -> DataFrame:
    """``trace``, ``len``, ``n`` exactly, by suffixes: equal suffixes of one vertex are one row with a count, so the work follows the distinct
    suffixes of each vertex, not the paths."""
    first = g.vertices.select("vid", F.col("label").alias("trace"), F.lit(1).cast("long").alias("n"))
    labels = g.vertices.select(F.col("vid").alias("src"), "label")
    edges = g.edges.join(labels, "src")

    def step(now: DataFrame) -> DataFrame:
        longer = edges.join(now, edges.dst == now.vid).select(F.col("src").alias("vid"), F.concat_ws(SEPARATOR, "label", "trace").alias("trace"), "n")
        return longer.groupBy("vid", "trace").agg(F.sum("n").alias("n"))

    return _levels(first, m, step, min_len).groupBy("trace").agg(F.sum("n").alias("n")).withColumn("len", trace_length())


def skip_pair_counts(rows: DataFrame, labels: str, reach: int) -> DataFrame:
    """``trace``, ``n`` exactly, of paths of one and two vertices, where each row's array ``labels`` is the whole sequence of a tag of its own, at times 0, 1, ...,
    collapsed, and edges look ``reach`` ahead (1 at least). A row is worked out where it is read, and traces are summed before they are exchanged: neither vertices nor edges are stored."""

    def steps(runs: Column) -> Column:
        n = F.size(runs)

        def ahead(run: Column, k: Column) -> Column:
            end = F.when(k + 1 < n, F.get(runs, k + 1)["t"] - 1)  # runs follow each other without a gap
            pairs = []
            for d in range(1, reach + 1):  # each run takes a place at least
                other = F.get(runs, k + d)
                pairs.append(F.when((k + d < n) & (other["t"] - end <= reach) & (other["x"] != run["x"]), F.concat_ws(SEPARATOR, run["x"], other["x"])))
            return F.filter(F.array(run["x"], *pairs), lambda t: t.isNotNull())

        return F.flatten(F.transform(runs, ahead))

    def collapsed(xs: Column) -> Column:
        marked = F.transform(xs, lambda x, t: F.when((t == 0) | (x != F.get(xs, t - 1)), F.struct(t.alias("t"), x.alias("x"))))
        return F.filter(marked, lambda r: r.isNotNull())

    # an array of one, so that its lambda names what would be worked out again at each use
    named = lambda value, use: F.get(F.transform(F.array(value), use), F.lit(0))
    traces = named(F.col(labels), lambda xs: named(collapsed(xs), steps))
    return rows.select(F.explode(traces).alias("trace")).groupBy("trace").agg(F.count(F.lit(1)).alias("n"))


def trace_counts_grouped(g: LabeledDag, m: int) -> DataFrame:
    """The same with one exchange by session: suffix counts in Arrow, summed afterwards."""
    delta = g.delta

    def run(group):
        import pyarrow as pa

        from pathtraces.operators.kernels import Piece

        found = Piece.of(group, delta).traces(m)
        return pa.table({"trace": pa.array(list(found.keys()), pa.string()), "n": pa.array(list(found.values()), pa.int64())})

    return g.pieces().groupBy("tag", "session").applyInArrow(run, "trace string, n long").groupBy("trace").agg(F.sum("n").alias("n")).withColumn("len", trace_length())


def label_codes(g: LabeledDag) -> DataFrame:
    """``label``, ``code``: 1, 2, ... in label order. Labels are numbered within a sorted partition; the labels of the partitions before are added, from one row a
    partition."""
    sorted_ = materialise(g.vertices.select("label").distinct().orderBy("label").select("label", F.spark_partition_id().alias("part")), "labels")
    sizes = sorted_.groupBy("part").agg(F.count(F.lit(1)).alias("n"))
    before = sizes.select("part", (F.sum("n").over(Window.orderBy("part")) - F.col("n")).alias("before"))
    place = F.row_number().over(Window.partitionBy("part").orderBy("label"))
    return sorted_.join(F.broadcast(before), "part").select("label", (place + F.col("before")).cast("long").alias("code"))


def enumerate_hashes(g: LabeledDag, m: int, keep_trace: bool = False) -> DataFrame:
    """``h1``, ``h2`` (``trace``): a row for each path, of constant size: two rolling hashes instead of the labels."""
    codes = label_codes(g)
    v = g.vertices.join(codes, "label")
    zero = F.lit(0).cast("long")
    more = ["trace"] if keep_trace else []
    first = v.select(F.col("vid").alias("end_vid"), hash_step(zero, F.col("code"), 0).alias("h1"), hash_step(zero, F.col("code"), 1).alias("h2"), F.col("label").alias("trace")).select("end_vid", "h1", "h2", *more)
    edges = g.edges.join(v.select(F.col("vid").alias("dst"), "code", "label"), "dst")

    def step(now: DataFrame) -> DataFrame:
        longer = now.join(edges, now.end_vid == edges.src).select(F.col("dst").alias("end_vid"), hash_step(F.col("h1"), F.col("code"), 0).alias("h1"), hash_step(F.col("h2"), F.col("code"), 1).alias("h2"), *([F.concat_ws(SEPARATOR, "trace", "label").alias("trace")] if keep_trace else []))
        return longer

    return _levels(first, m, step).select("h1", "h2", *more)


def hash_counts(g: LabeledDag, m: int) -> DataFrame:
    return enumerate_hashes(g, m).groupBy("h1", "h2").agg(F.count(F.lit(1)).alias("n"))


def resolve_hashes(g: LabeledDag, m: int, wanted: DataFrame) -> DataFrame:
    """``trace``, ``n`` of the wanted hashes, by a second run that carries labels."""
    return enumerate_hashes(g, m, keep_trace=True).join(small(wanted.select("h1", "h2").distinct()), ["h1", "h2"], "left_semi").groupBy("trace").agg(F.count(F.lit(1)).alias("n"))


def count_candidates(g: LabeledDag, candidates: DataFrame, m: int) -> DataFrame:
    """``trace``, ``n`` exactly, for given traces: paths are followed only while their labels begin a candidate, and counted by end
    vertex and prefix."""
    wanted = candidates.select("trace").distinct()
    prefixes = wanted.select(F.explode(F.transform(F.sequence(F.lit(1), trace_length()), lambda k: F.array_join(F.slice(trace_labels(), 1, k), SEPARATOR))).alias("trace")).distinct()
    prefixes = small(materialise(prefixes, "prefixes"))
    first = g.vertices.select(F.col("vid").alias("end_vid"), F.col("label").alias("trace"), F.lit(1).cast("long").alias("n")).join(prefixes, "trace", "left_semi")
    edges = g.labelled_edges()

    def step(now: DataFrame) -> DataFrame:
        longer = now.join(edges, now.end_vid == edges.src).select(F.col("dst").alias("end_vid"), F.concat_ws(SEPARATOR, "trace", "dst_label").alias("trace"), "n")
        return longer.join(prefixes, "trace", "left_semi").groupBy("end_vid", "trace").agg(F.sum("n").alias("n"))

    found = _levels(first.select("end_vid", "trace", "n"), m, step).groupBy("trace").agg(F.sum("n").alias("n"))
    return wanted.join(found, "trace", "left").select("trace", F.coalesce("n", F.lit(0)).cast("long").alias("n"))
