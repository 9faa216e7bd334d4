"""Order within a tag without gathering a tag: time is cut into slabs, and (tag, slab) is the unit of work.

What a row needs of the rows before it in other slabs, one value of the last one and one running sum, goes through a table of one row
for each tag and slab. So a tag that holds a third of all rows is as many tasks as it has slabs."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

#: Slab width in time thresholds.
WIDTH = 32


def slab_of(t: Column | str, delta: int, width: int = WIDTH) -> Column:
    return F.floor((F.col(t) if isinstance(t, str) else t) / F.lit(max(1, delta * width)))


def chained(v: DataFrame, delta: int, columns: list[str], marks: dict[str, Callable[[Column, Column], Column]], width: int = WIDTH) -> DataFrame:
    """``v`` with ``slab`` and, for each of ``marks``, how often it was true up to a row of its tag, in (t_first, vid) order. A mark gets two structs of ``columns``: of the
    row before (null for a tag's first) and of the row.

    Rows are met in one window of their slab; the marks of a slab's first row, which hang on another slab's last, are set in the table of slabs, and added to
    all rows of the slab."""
    cut, row = v.withColumn("slab", slab_of("t_first", delta, width)), F.struct(*columns)
    inside = Window.partitionBy("tag", "slab").orderBy("t_first", "vid")
    seen = cut.withColumn("previous", F.lag(row).over(inside))
    for name, mark in marks.items():
        seen = seen.withColumn(name, F.when(F.col("previous").isNull(), 0).otherwise(mark(F.col("previous"), row).cast("int")))
    at = F.struct("t_first", "vid")
    slabs = seen.groupBy("tag", "slab").agg(F.min_by(row, at).alias("head"), F.max_by(row, at).alias("tail"), *[F.sum(name).alias(name) for name in marks])
    slabs = slabs.withColumn("before", F.lag("tail").over(Window.partitionBy("tag").orderBy("slab")))
    upto = Window.partitionBy("tag").orderBy("slab").rowsBetween(Window.unboundedPreceding, 0)
    offsets = [(F.sum(F.col(name) + mark(F.col("before"), F.col("head")).cast("int")).over(upto) - F.col(name)).alias(f"{name}_before") for name, mark in marks.items()]
    joined = seen.drop("previous").join(slabs.select("tag", "slab", *offsets), ["tag", "slab"])
    for name in marks:
        joined = joined.withColumn(name, F.sum(name).over(inside) + F.col(f"{name}_before")).drop(f"{name}_before")
    return joined
