"""Mixing sources to target weights by capped water-filling.

Every source gets a share of the wanted size by weight, but at most ``max_epochs`` times its own size; what a capped source
leaves goes to the others by weight, until none is above its cap. With the sources in ascending order of cap over weight, those
below the water level form a prefix, so the level follows from running sums over the source table, one row a source.

A source's target is then taken as whole repetitions of all its rows plus a fraction of one: rows in the order of a seeded
hash, until the words reach the target; the last row gives its first words only, so sums come out exact to the word. The order
is cut in two steps, by hash slot and then within the one slot where the target falls, so no source is sorted in one task.

A null text has no words. A null source is a source of its own, after all others. Sources without words, and
empty tables, give targets of zero. Ties of the hash are broken by id; repeated rows count each. Rows of a null id take part.
Columns beside id, text and source are ignored by ``mixing_plan`` and kept by ``mixed``."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from pathtraces.llm.common import WORD, spill

WEIGHTS, TOTAL, MAX_EPOCHS, SEED, SLOTS = (5, 2, 1), 1.5, 2.0, "mix", 4096


def n_words(text: str = "text") -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("long")


def targets(sizes: DataFrame, weights=WEIGHTS, total: float = TOTAL, max_epochs: float = MAX_EPOCHS) -> DataFrame:
    """``sizes`` (source, source_size) with ``weight`` and ``target``. Weights repeat over the sources in the order of their
    code points, null last. The windows are over one row a source."""
    ranked = sizes.withColumn("k", F.row_number().over(Window.orderBy(F.col("source").cast("binary").asc_nulls_last())) - 1)
    weighed = ranked.withColumn("weight", F.element_at(F.array(*[F.lit(float(w)) for w in weights]), (F.col("k") % len(weights) + 1).cast("int")))
    weighed = weighed.withColumn("cap", F.col("source_size") * F.lit(max_epochs)).withColumn("ratio", F.col("cap") / F.col("weight"))
    rise = Window.orderBy("ratio", "k")
    everything = Window.orderBy("ratio", "k").rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    before = rise.rowsBetween(Window.unboundedPreceding, -1)
    level = weighed.withColumn("wanted", F.sum("source_size").over(everything) * F.lit(total))
    level = level.withColumn("level", (F.col("wanted") - F.coalesce(F.sum("cap").over(before), F.lit(0.0))) / (F.sum("weight").over(everything) - F.coalesce(F.sum("weight").over(before), F.lit(0.0))))
    # the first source whose ratio reaches the level at its place sets the level for it and all after it
    level = level.withColumn("water", F.min(F.when(F.col("ratio") >= F.col("level"), F.struct("ratio", "k", "level"))).over(everything)["level"])
    return level.select("source", "source_size", "weight", F.least("cap", F.coalesce(F.col("water") * F.col("weight"), "cap")).alias("target"))


def mixing_plan(docs: DataFrame, id: str = "doc_id", text: str = "text", source: str = "source", weights=WEIGHTS, total: float = TOTAL, max_epochs: float = MAX_EPOCHS, seed: str = SEED) -> DataFrame:
    """Per row: ``id``, ``source``, ``size``, ``source_size``, ``target``, ``taken``."""
    order = F.md5(F.concat_ws("|", F.lit(seed), F.col(id).cast("string")).cast("binary"))
    sized = docs.select(F.col(id).alias("id"), F.col(source).alias("source"), n_words(text).alias("size"), order.alias("place"))
    sized = spill(sized.withColumn("slot", F.conv(F.substring("place", 1, 3), 16, 10).cast("int")), "sizes")
    slots = sized.groupBy("source", "slot").agg(F.sum("size").alias("slot_size"))
    goal = targets(slots.groupBy("source").agg(F.sum("slot_size").alias("source_size")), weights, total, max_epochs)
    goal = goal.withColumn("whole", F.when(F.col("source_size") > 0, F.floor(F.col("target") / F.col("source_size"))).otherwise(0))
    goal = goal.withColumn("rest", F.floor(F.col("target") - F.col("whole") * F.col("source_size")).cast("long"))
    # one row a source and slot: at most 4096 a source
    run = Window.partitionBy("source").orderBy("slot").rowsBetween(Window.unboundedPreceding, -1)
    slots = slots.withColumn("below", F.coalesce(F.sum("slot_size").over(run), F.lit(0)))
    # exact order is needed in the slot where the rest ends; other slots are taken whole or not at all
    slots = slots.alias("s").join(goal.alias("g"), F.col("s.source").eqNullSafe(F.col("g.source"))).select("s.*", "g.source_size", "g.target", "g.whole", "g.rest")
    rows = sized.alias("d").join(slots.alias("s"), F.col("d.source").eqNullSafe(F.col("s.source")) & (F.col("d.slot") == F.col("s.slot")))
    rows = rows.select("d.*", "s.slot_size", "s.below", "s.source_size", "s.target", "s.whole", "s.rest")
    cut = (F.col("below") < F.col("rest")) & (F.col("rest") < F.col("below") + F.col("slot_size"))
    inside = Window.partitionBy("source", "slot").orderBy("place", "id").rowsBetween(Window.unboundedPreceding, -1)
    edge = rows.where(cut).withColumn("start", F.col("below") + F.coalesce(F.sum("size").over(inside), F.lit(0)))
    part = F.greatest(F.lit(0), F.least("size", F.col("rest") - F.col("start")))
    clear = rows.where(~cut).withColumn("start", F.col("below")).withColumn("part", F.when(F.col("rest") > F.col("below"), F.col("size")).otherwise(0))
    both = clear.unionByName(edge.withColumn("part", part))
    return both.select("id", "source", "size", "source_size", "target", (F.col("whole") * F.col("size") + F.col("part")).cast("long").alias("taken")).withColumnRenamed("id", id)


def mixed(docs: DataFrame, id: str = "doc_id", text: str = "text", source: str = "source", **settings) -> DataFrame:
    """The mix itself: each row as often as it is taken, and cut to its first words where a fraction of it is. Rows without
    words stay once. Needs unique ids (rows that share one are each taken as the one of the fewest words)."""
    plan = mixing_plan(docs, id, text, source, **settings).groupBy(F.col(id).alias("__id")).agg(F.min(F.struct("size", "taken")).alias("__mix")).select("__id", F.col("__mix.size").alias("__size"), F.col("__mix.taken").alias("__taken"))
    rows = docs.join(plan, F.col(id).eqNullSafe(F.col("__id")))
    whole = F.when(F.col("__size") > 0, F.floor(F.col("__taken") / F.col("__size"))).otherwise(1).cast("int")
    part = F.when(F.col("__size") > 0, F.col("__taken") % F.col("__size")).otherwise(0)
    rows = rows.withColumn("__words", F.concat(F.array_repeat(F.col("__size"), whole), F.when(part > 0, F.array(part)).otherwise(F.array().cast("array<long>"))))
    rows = rows.withColumn("__words", F.explode("__words"))
    first = F.array_join(F.slice(F.regexp_extract_all(text, F.lit(f"({WORD})"), F.lit(1)), F.lit(1), F.greatest(F.lit(1), F.col("__words")).cast("int")), " ")
    return rows.withColumn(text, F.when(F.col("__words") < F.col("__size"), first).otherwise(F.col(text))).select(*docs.columns)


def oracle(weights=WEIGHTS, total: float = TOTAL, max_epochs: float = MAX_EPOCHS, seed: str = SEED, docs: str = "documents") -> str:
    """The plan as DuckDB SQL: the order is cut directly, the level found by testing each source as the first uncapped one."""
    listed = ", ".join(f"{float(w)}" for w in weights)
    return f"""
    with sized as (select doc_id, source, coalesce(len(regexp_extract_all(text, '[^\\x20\\x09-\\x0D]+')), 0)::bigint as size, md5('{seed}|' || doc_id::varchar) as place from {docs}),
    s as (select source, sum(size)::bigint as source_size from sized group by source),
    w as (select *, ([{listed}])[(row_number() over (order by source nulls last) - 1) % {len(weights)} + 1] as weight, {max_epochs} * source_size as cap from s),
    levels as (select a.cap / a.weight as ratio, ({total} * (select sum(source_size) from s) - coalesce(sum(b.cap) filter (where b.cap / b.weight < a.cap / a.weight), 0)) / sum(b.weight) filter (where b.cap / b.weight >= a.cap / a.weight) as level from w a cross join w b group by a.source, a.cap, a.weight),
    water as (select arg_min(level, ratio) as level from levels where ratio >= level),
    goal as (select source, source_size, least(cap, coalesce((select level from water) * weight, cap)) as target from w),
    parts as (select *, case when source_size > 0 then floor(target / source_size) else 0 end as whole from goal),
    rest as (select *, floor(target - whole * source_size)::bigint as rest from parts),
    placed as (select doc_id, source, size, coalesce(sum(size) over (partition by source order by place, doc_id rows between unbounded preceding and 1 preceding), 0) as start from sized)
    select p.doc_id, p.size, r.source_size, r.target, (r.whole * p.size + greatest(0, least(p.size, r.rest - p.start)))::bigint as taken
    from placed p join rest r on p.source is not distinct from r.source
    """
