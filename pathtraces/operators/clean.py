"""From readings to vertices: runs at one place become one vertex, alternation between two places becomes one overlap vertex.

Rows are ordered within (tag, time slab), runs within (tag, session). A session ends where a tag is silent for more than the
threshold: no run, block or edge crosses such a gap, so a hot tag falls into many independent pieces."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from pathtraces.operators.slabs import WIDTH, chained

MODES = ("raw", "collapse", "full")


def vertices_of(r: DataFrame) -> DataFrame:
    """Every reading as a vertex of its own."""
    return r.select(F.col("seq").alias("vid"), "tag", F.col("t_us").alias("t_first"), F.col("t_us").alias("t_last"), "label", F.lit(1).alias("n_readings"))


def _merged(v: DataFrame, delta: int, width: int = WIDTH) -> DataFrame:
    """Neighbours of one label, no more than ``delta`` apart, become one vertex, named after its first."""

    def gap(previous: Column, row: Column) -> Column:
        return F.coalesce(row["t_first"] - previous["t_last"] > F.lit(delta), F.lit(True))

    def starts(previous: Column, row: Column) -> Column:
        return gap(previous, row) | (previous["label"] != row["label"])

    runs = chained(v, delta, ["label", "t_first", "t_last"], {"run": starts, "session": gap}, width)
    first = F.min(F.struct("t_first", "vid"))
    out = runs.groupBy("tag", "session", "run").agg(first.alias("first"), F.max("t_last").alias("t_last"), F.first("label").alias("label"), F.sum("n_readings").cast("int").alias("n_readings"))
    return out.select(F.col("first.vid").alias("vid"), "tag", F.col("first.t_first").alias("t_first"), "t_last", "label", "n_readings", "session", "run")


def collapse_runs(v: DataFrame, delta: int, width: int = WIDTH) -> DataFrame:
    return _merged(v, delta, width).drop("session", "run")


def overlap_label(x: Column, y: Column, scheme: str = "text", base: int = 100) -> Column:
    """One label for a pair, whichever comes first. ``numeric``: of whole numbers below ``base``."""
    if scheme == "text":
        return F.concat(F.least(x, y), F.lit("*"), F.greatest(x, y))
    low, high = F.least(x.cast("long"), y.cast("long")), F.greatest(x.cast("long"), y.cast("long"))
    return F.when(high < base, low * base + high).otherwise(F.raise_error(F.lit("a label code reaches the base"))).cast("string")


def merge_overlaps(v: DataFrame, delta: int, scheme: str = "text", respect_gap: bool = True, width: int = WIDTH) -> DataFrame:
    """``v``: runs. Where two labels alternate over four runs or more, the leftmost even number of them becomes one vertex."""
    return _units(v, delta, scheme, respect_gap, width).select(F.col("first.vid").alias("vid"), "tag", F.col("first.t_first").alias("t_first"), "t_last", "label", "n_readings")


def _units(v: DataFrame, delta: int, scheme: str, respect_gap: bool, width: int) -> DataFrame:
    """Blocks and single runs, numbered by ``unit`` in the order of their session.

    Runs equal to the one two before form stretches; neighbouring stretches share one run at most, and who comes first
    takes it, which is a fold over the stretches of a session, a short list."""
    runs = _merged(v, delta, width)
    keys = ["tag", "session"] if respect_gap else ["tag"]  # a session holds no gap; without the rule stretches may run across
    by = Window.partitionBy(*keys).orderBy("run")
    alternates = (F.col("label") == F.lag("label", 2).over(by)) & (F.col("label") != F.lag("label", 1).over(by))
    marked = runs.withColumn("alternates", F.coalesce(alternates, F.lit(False)))
    islands = marked.where("alternates").withColumn("island", F.col("run") - F.row_number().over(Window.partitionBy(*keys).orderBy("run")))
    stretches = islands.groupBy(*keys, "island").agg((F.min("run") - 2).alias("s"), F.max("run").alias("e"))
    taken = stretches.groupBy(*keys).agg(F.array_sort(F.collect_list(F.struct(F.col("s").cast("long").alias("s"), F.col("e").cast("long").alias("e")))).alias("each"))

    def take(done: Column, s: Column) -> Column:
        start = F.greatest(s["s"], done["last"] + 1)
        pairs = F.floor((s["e"] - start + 1) / 2)
        end = start + 2 * pairs - 1
        more = F.concat(done["blocks"], F.array(F.struct(start.alias("s"), end.cast("long").alias("e"))))
        return F.when(pairs >= 2, F.struct(end.cast("long").alias("last"), more.alias("blocks"))).otherwise(done)

    empty = F.struct(F.lit(-1).cast("long").alias("last"), F.array().cast("array<struct<s:bigint,e:bigint>>").alias("blocks"))
    blocks = taken.select(*keys, F.explode(F.aggregate("each", empty, take)["blocks"]).alias("b")).select(*keys, F.explode(F.sequence("b.s", "b.e")).alias("run"), F.col("b.s").alias("block"))
    joined = runs.join(blocks, [*keys, "run"], "left").withColumn("unit", F.coalesce("block", "run"))
    pair = F.col("label").cast("long") if scheme == "numeric" else F.col("label")
    label = F.when(F.max("block").isNotNull(), overlap_label(F.min(pair), F.max(pair), scheme)).otherwise(F.first("label"))
    return joined.groupBy(*keys, "unit").agg(F.min(F.struct("t_first", "vid")).alias("first"), F.max("t_last").alias("t_last"), label.alias("label"), F.sum("n_readings").cast("int").alias("n_readings"))


def _collapsed_again(units: DataFrame) -> DataFrame:
    """Neighbouring units of one label and session, which holds no gap, become one vertex."""
    by = Window.partitionBy("tag", "session").orderBy("unit")
    marked = units.withColumn("starts", F.coalesce(F.col("label") != F.lag("label").over(by), F.lit(True)).cast("int"))
    runs = marked.withColumn("run", F.sum("starts").over(by)).groupBy("tag", "session", "run")
    out = runs.agg(F.min("first").alias("first"), F.max("t_last").alias("t_last"), F.first("label").alias("label"), F.sum("n_readings").cast("int").alias("n_readings"))
    return out.select(F.col("first.vid").alias("vid"), "tag", F.col("first.t_first").alias("t_first"), "t_last", "label", "n_readings")


def clean(r: DataFrame, delta: int, mode: str = "full", scheme: str = "text", respect_gap: bool = True, width: int = WIDTH) -> DataFrame:
    """Vertices of readings. ``full`` collapses again, as an overlap may stand beside its equal; sessions of units are those of readings, unless blocks may
    run across gaps."""
    if mode not in MODES:
        raise ValueError(f"mode is one of {MODES}")
    v = vertices_of(r)
    if mode == "raw":
        return v
    if mode == "collapse":
        return collapse_runs(v, delta, width)
    if respect_gap:
        return _collapsed_again(_units(v, delta, scheme, respect_gap, width))
    return collapse_runs(merge_overlaps(v, delta, scheme, respect_gap, width), delta, width)
