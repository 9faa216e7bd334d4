"""The methods from SQL: views, a table function, an Arrow function."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F

from pathtraces.functions.columns import SEPARATOR
from pathtraces.operators.counts import count_paths
from pathtraces.operators.dag import LabeledDag
from pathtraces.operators.enumeration import trace_counts


def views(g: LabeledDag, m: int = 3) -> None:
    """``vertices``, ``edges``, ``path_counts``, ``trace_counts``."""
    g.vertices.createOrReplaceTempView("vertices")
    g.edges.createOrReplaceTempView("edges")
    count_paths(g, m).createOrReplaceTempView("path_counts")
    trace_counts(g, m).createOrReplaceTempView("trace_counts")


class MineTraces:
    """Rows of one session to its traces and their counts."""

    def __init__(self):
        self.rows, self.delta, self.m = [], 0, 1

    def eval(self, row, delta: int, m: int):
        self.rows.append((row["t_first"], row["vid"], row["t_last"], row["label"]))
        self.delta, self.m = delta, m

    def terminate(self):
        import pyarrow as pa

        from pathtraces.operators.kernels import Piece

        names = ("t_first", "vid", "t_last", "label")
        group = pa.table({n: [r[k] for r in self.rows] for k, n in enumerate(names)})
        yield from Piece.of(group, self.delta).traces(self.m).items()


def register(spark: SparkSession) -> None:
    """``mine_traces(table(...) partition by (tag, session), delta_us, m)`` returns ``trace``, ``n``."""
    spark.udtf.register("mine_traces", F.udtf(MineTraces, returnType="trace string, n long"))


def trace_hash(codes: dict[str, int]) -> Callable[[str], Column]:
    """Both rolling hashes of a trace's labels. ``codes`` is as small as the alphabet."""

    def run(traces):
        import pandas as pd

        from pathtraces.operators.kernels import hash_of

        found = [hash_of([codes[x] for x in t.split(SEPARATOR)]) for t in traces]
        return pd.DataFrame(found, columns=["h1", "h2"])

    import pandas as pd

    run.__annotations__ = {"traces": pd.Series, "return": pd.DataFrame}
    return F.pandas_udf(run, "h1 long, h2 long")
