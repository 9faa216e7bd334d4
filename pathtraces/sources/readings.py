"""Readings: who (tag), when (microseconds), in which order among equals, where (label)."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from pathtraces.functions.columns import whole_label

MINUTE, DAY = 60_000_000, 86_400_000_000
SCHEMA = "tag long, t_us long, seq long, label string"


@dataclass(frozen=True)
class SequenceSpec:
    """How a table is read as a set of readings. Columns are SQL expressions; ``order`` must be unique in the table."""

    tag: str
    time: str
    order: str
    label: str
    #: microseconds in a unit of time thresholds
    unit: int = MINUTE

    def delta(self, units: float) -> int:
        return round(units * self.unit)


def place_id(key: str, place: str, room: int) -> str:
    """SQL of an id for each place of a key: ``key * room + place``; places from ``room`` on, which would take ids of the next key, have ids of their own from 2**62
    on, and what fits neither is an error."""
    far = f"{key} between 0 and {(1 << 30) - 1} and {place} between {room} and {(1 << 32) - 1}"
    near = f"{key} is null or {place} is null or {place} between 0 and {room - 1}"
    return f"case when {near} then bigint({key}) * {room} + {place} when {far} then {1 << 62} + bigint({key}) * {1 << 32} + {place} else bigint(raise_error('no id for this place of a key')) end"


EVENTS = SequenceSpec("user_id", "unix_micros(cast(ts as timestamp))", "event_id", "event_type")
FINE_EVENTS = SequenceSpec("user_id", "unix_micros(cast(ts as timestamp))", "event_id", "concat(event_type, '.', cast(floor(cast(get_json_object(props, '$.k') as int) / 10) as string))")
ORDERS = SequenceSpec("o_custkey", "unix_micros(cast(o_orderdate as timestamp))", "o_orderkey", "o_orderpriority", DAY)
CONVERSATIONS = SequenceSpec("conv_id", "turn", place_id("conv_id", "turn", 100_000), "role", 1)


def readings(df: DataFrame, spec: SequenceSpec) -> DataFrame:
    """Rows without tag, time, order or label are no readings; labels must not hold the sign that separates labels in a trace."""
    columns = {"tag": spec.tag, "t_us": spec.time, "seq": spec.order}
    out = df.select(*[F.expr(e).cast("long").alias(n) for n, e in columns.items()], whole_label(F.expr(spec.label)).alias("label"))
    return out.where("tag is not null and t_us is not null and seq is not null and label is not null")


def lineitem_readings(df: DataFrame) -> DataFrame:
    """Parts, ship dates, flag and status. No column is unique, so the order is numbered by part."""
    order = Window.partitionBy("l_partkey").orderBy("l_shipdate", "l_orderkey", "l_linenumber", "l_suppkey", "l_returnflag", "l_linestatus")
    numbered = df.select("*", F.row_number().over(order).alias("place")).withColumn("nr", F.expr(place_id("l_partkey", "place", 1_000_000)))
    return readings(numbered, SequenceSpec("l_partkey", "unix_micros(cast(l_shipdate as timestamp))", "nr", "concat(l_returnflag, l_linestatus)", DAY))


def page_readings(df: DataFrame) -> DataFrame:
    """Browsing by language: the path's language is the tag, the page id the time, the host the label."""
    language = F.regexp_extract("url", r"^https?://[^/]+/([a-z]{2})/", 1)
    host = F.regexp_extract("url", r"^https?://([^/]+)/", 1)
    tag = F.conv(F.hex(language), 16, 10).cast("long")
    return df.where(language != "").select(tag.alias("tag"), F.col("page_id").cast("long").alias("t_us"), F.col("page_id").cast("long").alias("seq"), host.alias("label"))


def words_of(text: str = "text") -> Column:
    """The lower-case words of a text, in order."""
    return F.regexp_extract_all(F.lower(text), F.lit("([a-z]+)"), F.lit(1))


def skipgram_readings(df: DataFrame, keep: Callable[[Column], Column] | None = None) -> DataFrame:
    """Words of documents: the document is the tag, the word's place the time, the lower-case word the label."""
    words = df.select(F.col("doc_id").alias("tag"), F.posexplode(words_of()).alias("t", "label"))
    words = words.where(keep(F.col("label"))) if keep else words
    return words.select("tag", F.col("t").cast("long").alias("t_us"), F.expr(place_id("tag", "t", 100_000)).alias("seq"), "label")


def literal_readings(spark: SparkSession, rows: list[tuple]) -> DataFrame:
    return spark.createDataFrame(rows, SCHEMA)


def band_dag(spark: SparkSession, n: int, steps: tuple[int, ...] = (1, 2, 3)) -> tuple[DataFrame, DataFrame]:
    """Vertices 1 to n, an edge for each step; every vertex has its number as label."""
    vertices = spark.range(1, n + 1).select(F.col("id").alias("vid"), F.col("id").cast("string").alias("label"))
    edges = spark.range(1, n + 1).select(F.col("id").alias("src"), F.explode(F.array(*[F.col("id") + s for s in steps])).alias("dst"))
    return vertices, edges.where(F.col("dst") <= n)


def from_text(spark: SparkSession, path: str, kind: str) -> DataFrame:
    """Readings written as CSV (with header) or JSON lines, read with their schema."""
    reader = spark.read.schema(SCHEMA)
    return reader.csv(path, header=True) if kind == "csv" else reader.json(path)
