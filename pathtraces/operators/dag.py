"""Labelled DAGs, from vertices of timed readings or as given."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from pathtraces.functions.columns import whole_label
from pathtraces.operators.clean import clean
from pathtraces.operators.slabs import WIDTH, chained, slab_of
from pathtraces.plans.storage import materialise

STRATEGIES = ("window", "point", "bucket_join", "theta", "grouped")
_PAYLOAD = ("vid", "label", "t_first", "t_last", "value")


def sessions(v: DataFrame, delta: int, width: int = WIDTH) -> DataFrame:
    """``v`` with the number of its tag's session: edges never cross a silence longer than ``delta``."""
    cut = {"session": lambda previous, row: F.coalesce(row["t_first"] - previous["t_last"] > F.lit(delta), F.lit(True))}
    return chained(v, delta, ["t_first", "t_last"], cut, width).select(*v.columns, "session")


def _linked(a: str, b: str, delta: int) -> Column:
    later = (F.col(f"{b}.t_first") > F.col(f"{a}.t_first")) | ((F.col(f"{b}.t_first") == F.col(f"{a}.t_first")) & (F.col(f"{b}.vid") > F.col(f"{a}.vid")))
    return later & (F.col(f"{b}.t_first") - F.col(f"{a}.t_last") <= F.lit(delta)) & (F.col(f"{a}.label") != F.col(f"{b}.label"))


def build_edges(v: DataFrame, delta: int, strategy: str = "window", predicate: Callable[[Callable, Callable], Column] | None = None, width: int = WIDTH) -> DataFrame:
    """``src``, ``dst``: later vertices of the same tag and another label that begin within ``delta`` of the end of the first.

    window: one exchange by tag and time slab; sources stand at their end and targets at their start on one axis, and a range frame
    looks ahead. A target also stands in the slab before if that can see it, so no tag is gathered in one task.
    point: the same by tag alone, for vertices without extent. bucket_join: an equality join on time slots. theta: an equality join on
    the tag with a range condition, quadratic in a tag's vertices. grouped: a forward scan in Arrow by session.
    ``predicate`` gets two accessors, of column names to columns of source and target, for closeness other than in time."""
    if strategy not in STRATEGIES:
        raise ValueError(f"strategy is one of {STRATEGIES}")
    if "value" not in v.columns:
        v = v.withColumn("value", F.lit(None).cast("double"))
    if strategy in ("bucket_join", "theta"):
        a, b = v.alias("a"), v.alias("b")
        same = F.col("a.tag") == F.col("b.tag")
        if strategy == "bucket_join":
            slot = lambda t: F.floor(F.col(t) / F.lit(delta))
            a = v.withColumn("slot", F.explode(F.array(slot("t_last"), slot("t_last") + 1))).alias("a")
            b = v.withColumn("slot", slot("t_first")).alias("b")
            same = same & (F.col("a.slot") == F.col("b.slot"))
        pairs = a.join(b, same & _linked("a", "b", delta))
        if predicate is not None:
            pairs = pairs.where(predicate(lambda c: F.col(f"a.{c}"), lambda c: F.col(f"b.{c}")))
        return pairs.select(F.col("a.vid").alias("src"), F.col("b.vid").alias("dst"))
    if strategy == "grouped":
        if predicate is not None:
            raise ValueError("the forward scan knows time only")
        return sessions(v, delta).select("tag", "session", "vid", "t_first", "t_last", "label").groupBy("tag", "session").applyInArrow(_scan(delta), "src long, dst long")
    payload = F.struct(*_PAYLOAD)
    if strategy == "point":
        ahead = Window.partitionBy("tag").orderBy("t_first").rangeBetween(0, delta)
        framed = v.select(payload.alias("a"), F.collect_list(payload).over(ahead).alias("b"))
    else:
        shape = v.select(payload.alias("p")).schema["p"].dataType
        sources = v.select("tag", slab_of("t_last", delta, width).alias("slab"), F.col("t_last").alias("at"), payload.alias("a"), F.lit(None).cast(shape).alias("b"))
        seen_from = F.explode(F.array_distinct(F.array(slab_of("t_first", delta, width), slab_of(F.col("t_first") - delta, delta, width)))).alias("slab")
        targets = v.select("tag", seen_from, F.col("t_first").alias("at"), F.lit(None).cast(shape).alias("a"), payload.alias("b"))
        ahead = Window.partitionBy("tag", "slab").orderBy("at").rangeBetween(0, delta)
        framed = sources.unionByName(targets).select("a", F.collect_list("b").over(ahead).alias("b")).where("a is not null")

    def fits(b: Column) -> Column:
        later = (b["t_first"] > F.col("a.t_first")) | ((b["t_first"] == F.col("a.t_first")) & (b["vid"] > F.col("a.vid")))
        return later & (b["label"] != F.col("a.label"))

    pairs = framed.select("a", F.explode(F.filter("b", fits)).alias("b"))
    if predicate is not None:
        pairs = pairs.where(predicate(lambda c: F.col(f"a.{c}"), lambda c: F.col(f"b.{c}")))
    return pairs.select(F.col("a.vid").alias("src"), F.col("b.vid").alias("dst"))


def _scan(delta: int):
    def run(group):
        import pyarrow as pa

        from pathtraces.operators.kernels import Piece

        piece = Piece.of(group, delta)
        pairs = [(piece.vid[k], piece.vid[j]) for k, after in enumerate(piece.after) for j in after]
        return pa.table({"src": pa.array([a for a, _ in pairs], pa.int64()), "dst": pa.array([b for _, b in pairs], pa.int64())})

    return run


@dataclass(frozen=True)
class LabeledDag:
    """``vertices`` (vid, label, ...), ``edges`` (src, dst). ``delta`` is set if the graph came from readings: then it falls into
    sessions, and the tag-local methods apply."""

    vertices: DataFrame
    edges: DataFrame
    delta: int | None = None

    @classmethod
    def from_readings(cls, r: DataFrame, delta: int, mode: str = "full", strategy: str = "window", keep: bool = True) -> LabeledDag:
        v = clean(r, delta, mode)
        v = materialise(v, "vertices") if keep else v
        e = build_edges(v, delta, strategy)
        return cls(v, materialise(e, "edges") if keep else e, delta)

    @classmethod
    def from_tables(cls, v: DataFrame, e: DataFrame) -> LabeledDag:
        """A graph as given. Labels must not hold the sign that separates labels in a trace."""
        return cls(v.withColumn("label", whole_label(F.col("label"))), e)

    def labelled_edges(self) -> DataFrame:
        """``src``, ``dst``, ``dst_label``."""
        return self.edges.join(self.vertices.select(F.col("vid").alias("dst"), F.col("label").alias("dst_label")), "dst").select("src", "dst", "dst_label")

    def pieces(self) -> DataFrame:
        if self.delta is None:
            raise ValueError("only graphs from readings fall into sessions")
        return sessions(self.vertices, self.delta).select("tag", "session", "vid", "t_first", "t_last", "label")

    def validate(self) -> DataFrame:
        """``check_name``, ``n_bad``; all zero for a labelled DAG."""
        v, e = self.vertices, self.edges
        ids = v.select("vid")
        checks = {
            "null_label": v.where("vid is null or label is null"),
            "duplicate_vertex": v.groupBy("vid").count().where("count > 1"),
            "duplicate_edge": e.groupBy("src", "dst").count().where("count > 1"),
            "loop": e.where("src = dst"),
            "dangling_src": e.join(ids, e.src == ids.vid, "left_anti"),
            "dangling_dst": e.join(ids, e.dst == ids.vid, "left_anti"),
        }
        rows = [df.agg(F.count(F.lit(1)).alias("n_bad")).select(F.lit(name).alias("check_name"), "n_bad") for name, df in checks.items()]
        cyclic = e.sparkSession.createDataFrame([("on_a_cycle", on_cycles(e))], "check_name string, n_bad long")
        for row in rows:
            cyclic = cyclic.unionByName(row)
        return cyclic


def peeled(e: DataFrame) -> tuple[int, int]:
    """How often vertices without successors can be taken off until no edge is left, and how many edges stay for ever (0 for a DAG). Each round is stored."""
    left, rounds = materialise(e.select("src", "dst").distinct(), "peel"), 0
    n = left.count()
    while n:
        left = materialise(left.join(left.select(F.col("src").alias("dst")).distinct(), "dst", "left_semi"), "peel")
        now = left.count()
        if now == n:
            return rounds, n
        n, rounds = now, rounds + 1
    return rounds, 0


def on_cycles(e: DataFrame) -> int:
    """Edges that no peeling removes; 0 for a DAG."""
    return peeled(e)[1]


def dag_depth(g: LabeledDag) -> int:
    """Vertices on the longest path."""
    rounds, cyclic = peeled(g.edges)
    if cyclic:
        raise ValueError("the graph has a cycle")
    return rounds + (1 if g.vertices.limit(1).count() else 0)


def graph_size(g: LabeledDag) -> DataFrame:
    n = g.vertices.agg(F.count(F.lit(1)).alias("n_vertices"))
    return n.crossJoin(g.edges.agg(F.count(F.lit(1)).alias("n_edges")))
