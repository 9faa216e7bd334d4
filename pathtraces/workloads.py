"""The registered queries: methods, variants, baselines, measures and experiments on the given tables.

Graphs are built once for each session, folder and setting and kept in shared storage; ``forget`` drops them (the bench does)."""

from __future__ import annotations

import uuid
from collections.abc import Callable
from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from pathtraces import oracles as sql
from pathtraces.functions import measures
from pathtraces.functions.columns import SEPARATOR, contains_label, has_prefix, trace_labels, trace_length, uniform
from pathtraces.operators import counts as counting
from pathtraces.operators import enumeration as full
from pathtraces.operators import frequent, mine
from pathtraces.operators import sample as sampling
from pathtraces.operators.clean import clean, collapse_runs, merge_overlaps, overlap_label, vertices_of
from pathtraces.operators.dag import LabeledDag, build_edges, dag_depth, graph_size
from pathtraces.plans.storage import materialise, new_path, small
from pathtraces.sources import readings as src
from pathtraces.sources import sinks
from pathtraces.streaming import live

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}

DELTA, M, C, K, SEED, KTH = 1440, 3, 10, 20, 42, 100
PAIRS = ((2880, 5), (1440, 5), (1440, 3), (720, 5), (360, 5))
_graphs: dict[tuple, LabeledDag] = {}


def forget() -> None:
    _graphs.clear()


def query(oracle: str | None = None) -> Callable[[Query], Query]:
    def enter(f: Query) -> Query:
        QUERIES[f.__name__] = f
        if oracle is not None:
            ORACLES[f.__name__] = oracle
        return f

    return enter


def read(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def readings_of(spark: SparkSession, sf_dir: str, source: str = "events") -> DataFrame:
    if source == "lineitem":
        return src.lineitem_readings(read(spark, sf_dir, "lineitem"))
    if source == "pages":
        return src.page_readings(read(spark, sf_dir, "pages"))
    if source == "words":
        return src.skipgram_readings(read(spark, sf_dir, "documents"))
    spec = {"events": src.EVENTS, "fine": src.FINE_EVENTS, "orders": src.ORDERS, "conversations": src.CONVERSATIONS}[source]
    return src.readings(read(spark, sf_dir, "events" if source == "fine" else source), spec)


def graph(spark: SparkSession, sf_dir: str, delta: float = DELTA, source: str = "events", mode: str = "full") -> LabeledDag:
    key = (spark.sparkContext.applicationId, sf_dir, delta, source, mode)
    if key not in _graphs:
        _graphs[key] = LabeledDag.from_readings(readings_of(spark, sf_dir, source), round(delta * sql.UNIT[source]), mode)
    return _graphs[key]


def one(spark: SparkSession) -> DataFrame:
    return spark.range(1)


def union(frames: list[DataFrame]) -> DataFrame:
    return reduce(DataFrame.unionByName, frames)


def kth(traces: DataFrame, k: int = KTH) -> DataFrame:
    """``kth_count``: of the k-th most frequent trace, or of the last if there are fewer."""
    return traces.orderBy(F.desc("n"), "trace").limit(k).agg(F.min("n").alias("kth_count"))


def threshold(g: LabeledDag, m: int = M) -> int:
    return kth(full.trace_counts(g, m)).first()[0]


KTH_SQL = f"(select min(n) from (select n from tc order by n desc, trace limit {KTH}))"
P_SQL = f"least(1.0, {C}.0 / (select min(n) from (select n from tc order by n desc, trace limit {KTH})))"
G, TC, CN = sql.graph(DELTA), sql.suffixes(M), sql.counts(M)


def seeded(spark: SparkSession, sf_dir: str) -> tuple[LabeledDag, DataFrame, float]:
    """The default graph, its counts, and p = C / (count of the 100th trace)."""
    g = graph(spark, sf_dir)
    return g, materialise(counting.count_paths(g, M), "counts"), measures.choose_p(C, threshold(g))


def sampled_sql(select: str, seed: int = SEED, more: str = "") -> str:
    return sql.with_(G, TC, f", prob as materialized (select {P_SQL} as p)", CN, sql.sample(M, "(select p from prob)", seed), more, select=select)


# ---- readings and cleaning


@query(sql.READINGS["events"])
def readings_events(spark, sf_dir):
    return readings_of(spark, sf_dir)


@query(sql.READINGS["fine"])
def fine_labels(spark, sf_dir):
    return readings_of(spark, sf_dir, "fine")


@query("select strftime(ts, '%Y-%m-%d') as day, event_type as label, count(*) as n from events group by all")
def events_by_day(spark, sf_dir):
    e = read(spark, sf_dir, "events")
    return e.groupBy(F.date_format(F.date_trunc("day", "ts"), "yyyy-MM-dd").alias("day"), F.col("event_type").alias("label")).agg(F.count(F.lit(1)).alias("n"))


@query(sql.READINGS["orders"])
def source_parquet(spark, sf_dir):
    return readings_of(spark, sf_dir, "orders")


@query(f"select tag, t_us, seq, label, kind from ({sql.READINGS['events']}), (values ('csv'), ('json')) as k(kind)")
def source_csv_json(spark, sf_dir):
    r = readings_of(spark, sf_dir)
    out = []
    for kind in ("csv", "json"):
        path = new_path(spark, kind)
        sinks.write_text(r, path, kind)
        out.append(src.from_text(spark, path, kind).withColumn("kind", F.lit(kind)))
    return union(out)


@query(sql.with_(G, TC, select="select trace, n, len from tc"))
def sink_roundtrip(spark, sf_dir):
    path = new_path(spark, "traces")
    sinks.write_traces(full.trace_counts(graph(spark, sf_dir), M).select("trace", "n"), path)
    return spark.read.parquet(path).select("trace", "n", F.col("len").cast("int").alias("len"))


@query(sql.with_(G, select="select src, count(*) as degree from e group by src"))
def sink_bucketed(spark, sf_dir):
    """A bucketed table: the count by its key needs no exchange."""
    name = f"pathtraces_edges_{uuid.uuid4().hex}"
    g = graph(spark, sf_dir)
    sinks.write_bucketed(g.edges, name, "src", 8, new_path(spark, "bucketed"))
    return spark.table(name).groupBy("src").agg(F.count(F.lit(1)).alias("degree"))


_V = "select vid, tag, t_first, t_last, label, n_readings from v"


@query(sql.with_(sql.vertices("events", DELTA, "collapse"), select=_V))
def clean_collapse(spark, sf_dir):
    return collapse_runs(vertices_of(readings_of(spark, sf_dir)), src.EVENTS.delta(DELTA))


@query(sql.with_(sql.vertices("events", DELTA, "full"), select="select vid, tag, t_first, t_last, label, n_readings from v_over"))
def clean_overlap(spark, sf_dir):
    return merge_overlaps(vertices_of(readings_of(spark, sf_dir)), src.EVENTS.delta(DELTA))


@query("with l as (select distinct event_type as label from events), c as (select label, row_number() over (order by label) as code from l) select a.label as x, b.label as y, least(a.code, b.code) * 100 + greatest(a.code, b.code) as code from c a, c b where a.label <> b.label")
def overlap_codes(spark, sf_dir):
    codes = read(spark, sf_dir, "events").select(F.col("event_type").alias("label")).distinct().withColumn("code", F.row_number().over(Window.orderBy("label")))
    a, b = codes.alias("a"), F.broadcast(codes).alias("b")  # one row a label
    return a.join(b, F.col("a.label") != F.col("b.label")).select(F.col("a.label").alias("x"), F.col("b.label").alias("y"), overlap_label(F.col("a.code"), F.col("b.code"), "numeric").cast("long").alias("code"))


def _sizes_sql(mode: str) -> str:
    return f"select '{mode}' as mode, (select count(*) from v) as n_vertices, (select count(*) from e) as n_edges, (select sum(c{M})::bigint from c) as n_paths"


@query(" union all ".join(f"({sql.with_(sql.vertices('events', DELTA, mode), sql.edges(DELTA), CN, select=_sizes_sql(mode))})" for mode in ("raw", "collapse", "full")))
def clean_ablation(spark, sf_dir):
    rows = []
    for mode in ("raw", "collapse", "full"):
        g = graph(spark, sf_dir, mode=mode)
        total = counting.count_paths(g, M).agg(F.sum(F.element_at("c", M + 1)).alias("n_paths"))
        rows.append(graph_size(g).crossJoin(total).select(F.lit(mode).alias("mode"), "n_vertices", "n_edges", "n_paths"))
    return union(rows)


# ---- graphs

_EDGES = sql.with_(G, select="select src, dst from e")
_RAW_EDGES = sql.with_(sql.vertices("events", DELTA, "raw"), sql.edges(DELTA), select="select src, dst from e")


def _built(strategy: str, mode: str) -> Query:
    def run(spark, sf_dir):
        delta = src.EVENTS.delta(DELTA)
        return build_edges(graph(spark, sf_dir).vertices if mode == "full" else clean(readings_of(spark, sf_dir), delta, mode), delta, strategy)

    return run


for _name, _strategy, _mode in (("window", "point", "raw"), ("ranged", "window", "full"), ("bucket", "bucket_join", "full"), ("theta", "theta", "full"), ("grouped", "grouped", "full")):
    QUERIES[f"dag_edges_{_name}"] = _built(_strategy, _mode)
    ORACLES[f"dag_edges_{_name}"] = _EDGES if _mode == "full" else _RAW_EDGES


@query(f"with a as (select user_id as tag, epoch_us(ts) as t, event_id as vid, event_type as label, value from events) select a.vid as src, b.vid as dst from a join a b on a.tag = b.tag and (b.t > a.t or (b.t = a.t and b.vid > a.vid)) and b.t - a.t <= {src.EVENTS.delta(DELTA)} and a.label <> b.label and abs(a.value - b.value) <= 5")
def dag_edges_predicate(spark, sf_dir):
    """Close in time and in value."""
    values = read(spark, sf_dir, "events").select(F.col("event_id").alias("vid"), "value")
    v = vertices_of(readings_of(spark, sf_dir)).join(values, "vid")
    return build_edges(v, src.EVENTS.delta(DELTA), "point", lambda a, b: F.abs(a("value") - b("value")) <= 5)


@query(sql.values([(c, 0) for c in ("on_a_cycle", "null_label", "duplicate_vertex", "duplicate_edge", "loop", "dangling_src", "dangling_dst")], "check_name, n_bad"))
def dag_validate(spark, sf_dir):
    return graph(spark, sf_dir).validate()


@query(" union all ".join(f"({sql.with_(sql.graph(d), select=f'select {d}::bigint as delta_min, (select count(*) from v) as n_vertices, (select count(*) from e) as n_edges')})" for d in (360, 720, 1440, 2880)))
def graph_size_by_delta(spark, sf_dir):
    return union([graph_size(graph(spark, sf_dir, d)).select(F.lit(d).cast("long").alias("delta_min"), "n_vertices", "n_edges") for d in (360, 720, 1440, 2880)])


# ---- counting

_COUNTS = sql.with_(G, CN, select="select vid, c1, c2, c3 from c")


@query(_COUNTS)
def path_counts(spark, sf_dir):
    return counting.spread(counting.count_paths(graph(spark, sf_dir), M), M)


@query(_COUNTS)
def path_counts_grouped(spark, sf_dir):
    return counting.spread(counting.count_paths(graph(spark, sf_dir), M, "grouped"), M)


@query(_COUNTS)
def path_counts_decimal(spark, sf_dir):
    wide = counting.spread(counting.count_paths(graph(spark, sf_dir), M, count_type="decimal"), M)
    return wide.select("vid", *[F.col(f"c{i}").cast("long").alias(f"c{i}") for i in range(1, M + 1)])


@query(sql.with_(G, sql.counts(M, ending=True), select="select vid, c1, c2, c3 from c"))
def path_counts_ending(spark, sf_dir):
    return counting.spread(counting.count_paths(graph(spark, sf_dir), M, direction="ending"), M)


@query(sql.with_(G, CN, select="select sum(c3)::bigint as n_paths from c"))
def total_paths(spark, sf_dir):
    return counting.count_paths(graph(spark, sf_dir), M).agg(F.sum(F.element_at("c", M + 1)).alias("n_paths"))


@query(sql.with_(G, ", far as (select vid, 1 as depth from v union select e.dst, far.depth + 1 from far join e on e.src = far.vid)", select="select max(depth)::bigint as depth from far"))
def dag_depth_events(spark, sf_dir):
    return one(spark).select(F.lit(dag_depth(graph(spark, sf_dir))).cast("long").alias("depth"))


@query(sql.with_(G, select=f"select count(*) as n_edges, {M}::int as m, count(*) * {M - 1} as edge_visits from e"))
def counting_cost(spark, sf_dir):
    return counting.counting_cost(graph(spark, sf_dir), M)


# ---- full enumeration

_TRACES = sql.with_(G, sql.paths(M), select="select trace, len, count(*) as n from p group by all")


@query(_TRACES)
def all_traces_m3(spark, sf_dir):
    return full.counted(full.enumerate_traces(graph(spark, sf_dir), M))


@query(_TRACES)
def all_traces_grouped(spark, sf_dir):
    return full.trace_counts_grouped(graph(spark, sf_dir), M)


@query(_TRACES)
def trace_counts_dp(spark, sf_dir):
    return full.trace_counts(graph(spark, sf_dir), M)


@query(_TRACES)
def udtf_all_traces(spark, sf_dir):
    from pathtraces.sqlapi import register

    register(spark)
    g = graph(spark, sf_dir)
    g.pieces().createOrReplaceTempView("pathtraces_pieces")
    return spark.sql(f"select trace, size(split(trace, '{SEPARATOR}')) as len, sum(n) as n from mine_traces(table(select * from pathtraces_pieces) partition by (tag, session), {g.delta}, {M}) group by trace")


@query(_TRACES)
def sql_recursive_paths(spark, sf_dir):
    """A recursive query over the SQL views, for comparison: it keeps every path. Spark ends a recursion of over a million rows unless told otherwise, so the limit is lifted while this one runs."""
    from pathtraces.sqlapi import views

    views(graph(spark, sf_dir))
    limit = "spark.sql.cteRecursionRowLimit"
    before = spark.conf.get(limit)
    spark.conf.set(limit, "-1")
    try:
        found = spark.sql(f"""
      with recursive walk(at, trace, len) as (
        select vid, label, 1 from vertices
        union all
        select e.dst, concat(w.trace, '{SEPARATOR}', v.label), w.len + 1 from walk w join edges e on e.src = w.at join vertices v on v.vid = e.dst where w.len < {M})
      select trace, len, count(*) as n from walk group by trace, len""")
        return materialise(found, "walks")
    finally:
        spark.conf.set(limit, before)


@query(sql.with_(G, sql.paths(M, start="vid in (select vid from v where tag = (select min(tag) from v) order by t_first, vid limit 1)"), select="select trace, count(*) as n from p group by trace"))
def traces_from_vertex(spark, sf_dir):
    g = graph(spark, sf_dir)
    return full.traces_from(g, M, g.vertices.orderBy("tag", "t_first", "vid").limit(1))


@query(sql.with_(G, sql.hashes(M), select="select h1, h2, count(*) as n from h group by all"))
def hash_counts(spark, sf_dir):
    return full.hash_counts(graph(spark, sf_dir), M)


@query(sql.with_(G, TC, select=f"select trace, n from tc where n >= {KTH_SQL}"))
def hash_resolve(spark, sf_dir):
    g = graph(spark, sf_dir)
    counted = materialise(full.hash_counts(g, M), "hashes")
    least = counted.orderBy(F.desc("n")).limit(KTH).agg(F.min("n").alias("least"))
    return full.resolve_hashes(g, M, counted.join(F.broadcast(least), F.col("n") >= F.col("least")))


@query(sql.with_(G, TC, select=f"select trace, n from (select trace, n from tc order by n desc, trace limit {KTH})"))
def candidate_counts(spark, sf_dir):
    g = graph(spark, sf_dir)
    top = full.trace_counts(g, M).orderBy(F.desc("n"), "trace").limit(KTH)
    return full.count_candidates(g, top, M)


@query(sql.with_(G, TC, select=f"select trace, n, round(n / (select sum(n) from tc), 12) as support from tc where n >= {KTH_SQL}"))
def frequency_exact(spark, sf_dir):
    g = graph(spark, sf_dir)
    return mine.mine_frequency(g, M, min_count=threshold(g), method="exact").traces


@query(sql.with_(G, TC, select=f"select trace, n, round(n / (select sum(n) from tc), 12) as support from tc order by n desc, trace limit {K}"))
def topk_exact(spark, sf_dir):
    return mine.mine_topk(graph(spark, sf_dir), M, K, method="exact").traces


@query(sql.with_(G, TC, select="select trace, n, round(n / sum(n) over (), 12) as support from tc where len > 1"))
def movements_only(spark, sf_dir):
    return mine.exact_frequency(graph(spark, sf_dir), M, min_count=1, min_len=2)


# ---- sampling


@query(f"select event_id as key, round({sql.u(SEED, repr('root'), 'event_id')}, 12) as u from events")
def uniform_draws(spark, sf_dir):
    return read(spark, sf_dir, "events").select(F.col("event_id").alias("key"), F.round(uniform(SEED, F.lit("root"), "event_id"), 12).alias("u"))


@query(sql.with_(G, TC, CN, select=f"select vid from c where {sql.u(SEED, repr('root'), 'vid')} < 1 - pow(1 - {P_SQL}, c3)"))
def sample_roots(spark, sf_dir):
    _, c, p = seeded(spark, sf_dir)
    return sampling.roots(c, M, p, SEED).select("vid")


_SAMPLE = "select start_vid, path_key, trace from s"


@query(sampled_sql(_SAMPLE))
def sample_descend(spark, sf_dir):
    g, c, p = seeded(spark, sf_dir)
    return sampling.descend(g, c, M, p, SEED).drop("scanned")


@query(sampled_sql(_SAMPLE))
def sample_grouped(spark, sf_dir):
    g, _, p = seeded(spark, sf_dir)
    return sampling.sample_grouped(g, M, p, SEED)


@query(sql.with_(G, TC, sql.paths(M), select=f"select start_vid, path as path_key, trace from p where {sql.u(SEED, repr('path'), 'path')} < {P_SQL}"))
def sample_bernoulli_full(spark, sf_dir):
    g, _, p = seeded(spark, sf_dir)
    return sampling.sample_full(g, M, p, SEED)


@query(sampled_sql("select h1, h2, count(*) as n from s join hp on hp.path = s.path_key group by all", more=sql.hashes(M).replace("label as trace, 1 as len", "vid::varchar as trace, 1 as len").replace("hv.label", "hv.vid::varchar").replace("|| '>' ||", "|| '-' ||") + ", hp as (select h1, h2, trace as path from h)"))
def sample_hash(spark, sf_dir):
    g, c, p = seeded(spark, sf_dir)
    return sampling.descend(g, c, M, p, SEED, output="hash").groupBy("h1", "h2").agg(F.count(F.lit(1)).alias("n"))


def _by_sampler(sampler: str) -> Query:
    def run(spark, sf_dir):
        g, c, p = seeded(spark, sf_dir)
        return sampling.sample_traces(g, c, M, p, SEED, sampler).groupBy("trace").agg(F.count(F.lit(1)).alias("n"))

    return run


_BY_TRACE = "select trace, count(*) as n from s group by trace"
_PROB = f", prob as materialized (select {P_SQL} as p)"
_HITS = sql.with_(G, TC, _PROB, CN, sql.first_hits(M, "(select p from prob)", SEED), select=_BY_TRACE)
_RANKS = sql.with_(G, TC, _PROB, CN, sql.ranked(M, "(select p from prob)", SEED), select=_BY_TRACE)
_PRINTED = sql.with_(G, TC, _PROB, CN, sql.sample(M, "(select p from prob)", SEED, printed=True), select=_BY_TRACE)
for _name, _sampler, _oracle in (("sample_rank", "rank", _RANKS), ("sample_first_hit", "first_hit", _HITS), ("sample_guide", "guide", _HITS), ("sample_printed_bias", "printed", _PRINTED)):
    QUERIES[_name], ORACLES[_name] = _by_sampler(_sampler), _oracle


def _everything(sampler: str) -> Query:
    """With p = 1 a sampler returns each path once."""

    def run(spark, sf_dir):
        g = graph(spark, sf_dir)
        c = materialise(counting.count_paths(g, M), "counts")
        return sampling.sample_traces(g, c, M, 1.0, SEED, sampler).select("start_vid", "path_key", "trace")

    return run


for _sampler in ("descend", "rank", "first_hit", "guide"):
    QUERIES[f"sample_all_{_sampler}"] = _everything(_sampler)
    ORACLES[f"sample_all_{_sampler}"] = sql.with_(G, sql.paths(M), select="select start_vid, path as path_key, trace from p")


@query()
def search_steps(spark, sf_dir):
    """What the two searches of the refined samplers take."""
    g, c, p = seeded(spark, sf_dir)
    ways = sampling.prepare(g, c, M, guides=True)
    rows = [sampling.hits(g, c, M, p, SEED, how, ways).agg(F.sum("draws").alias("draws"), F.sum("steps").alias("steps")).select(F.lit(how).alias("how"), "draws", "steps") for how in ("first_hit", "guide")]
    return union(rows).withColumn("steps_a_draw", F.round(F.col("steps") / F.col("draws"), 6))


@query(sql.with_(G, TC, CN, f", x as (select e.src, e.dst, l.level, case l.level when 2 then d.c1 else d.c2 end as n, case l.level when 2 then s.c2 else s.c3 end as total from e join c d on d.vid = e.dst join c s on s.vid = e.src cross join (values (2), (3)) as l(level)), y as (select *, total - coalesce(sum(n) over (partition by src, level order by dst rows between unbounded preceding and 1 preceding), 0) as rest, {P_SQL} as p from x)", select="select src, dst, level, round((1 - pow(1 - p, n)) / (1 - pow(1 - p, rest)), 9) as pr from y"))
def edge_probs(spark, sf_dir):
    g, c, p = seeded(spark, sf_dir)
    return sampling.edge_probabilities(g, c, M, p).withColumn("pr", F.round("pr", 9))


@query(sql.with_(G, TC, select=f"select sum(n)::bigint as n_paths, {KTH_SQL}::double as eps, round({P_SQL}, 9) as p, round({P_SQL} * sum(n), 6) as expected_samples, ceil(2 * ceil({P_SQL} * sum(n)) / {C})::bigint as capacity from tc"))
def sample_plan(spark, sf_dir):
    g, c, _ = seeded(spark, sf_dir)
    plan = sampling.plan_sampling(c, M, C, min_count=threshold(g))
    return spark.createDataFrame([(plan.total, float(plan.min_count), round(plan.p, 9), round(plan.expected_samples, 6), plan.capacity)], "n_paths long, eps double, p double, expected_samples double, capacity long")


# ---- selection

_SEEN = ", n as (select trace, count(*) as n_sample from s group by trace)"
_EST = "round(n_sample / (select p from prob), 6) as n_est"
_SELECTED = sampled_sql(f"select trace, n_sample, {_EST} from n where n_sample >= {C / 2}", more=_SEEN)


@query(_SELECTED)
def frequent_exact(spark, sf_dir):
    g, c, p = seeded(spark, sf_dir)
    counted = frequent.sample_counts(sampling.descend(g, c, M, p, SEED)).where(frequent.enough(C, False))
    return frequent.with_estimates(counted, p).select("trace", "n_sample", "n_est")


def _verified(how: str, summary: str = "exact") -> Query:
    def run(spark, sf_dir):
        g = graph(spark, sf_dir)
        return mine.mine_frequency(g, M, min_count=threshold(g), c=C, seed=SEED, summary=summary, verify=how).traces

    return run


QUERIES["second_pass_replay"], ORACLES["second_pass_replay"] = _verified("replay", "decrement"), _SELECTED
QUERIES["second_pass_stored"], ORACLES["second_pass_stored"] = _verified("stored", "decrement"), _SELECTED
QUERIES["frequency_mc"], ORACLES["frequency_mc"] = _verified("stored"), _SELECTED
QUERIES["second_pass_fresh"] = _verified("fresh")
ORACLES["second_pass_fresh"] = sql.with_(G, TC, f", prob as materialized (select {P_SQL} as p)", CN, sql.sample(M, "(select p from prob)", SEED), sql.sample(M, "(select p from prob)", SEED + 1, "f"), _SEEN, ", k as (select trace, count(*) as n_sample from f group by trace)", select=f"select trace, k.n_sample, round(k.n_sample / (select p from prob), 6) as n_est from k join n using (trace) where k.n_sample >= {C / 2} and n.n_sample >= {C / 2}")


@query(sampled_sql(f"select trace, tc.n as n_true from n join tc using (trace) where n_sample >= {C / 2} and tc.n >= {KTH_SQL}", more=_SEEN))
def second_pass_exact(spark, sf_dir):
    return _verified("exact")(spark, sf_dir)


@query(sampled_sql(f"select trace, n_sample, {_EST}, round(sqrt(n_sample * (1 - (select p from prob))) / (select p from prob), 6) as n_err, tc.n as n_true from n join tc using (trace)", more=_SEEN))
def estimated_counts(spark, sf_dir):
    g, c, p = seeded(spark, sf_dir)
    counted = frequent.with_estimates(frequent.sample_counts(sampling.descend(g, c, M, p, SEED)), p)
    return counted.join(full.trace_counts(g, M).select("trace", F.col("n").alias("n_true")), "trace")


@query("select event_type as item, count(*) as n from events group by 1 having count(*) > 0.1 * (select count(*) from events)")
def frequent_items_contract(spark, sf_dir):
    return frequent.frequent_items(read(spark, sf_dir, "events"), "event_type", 0.1)


def _candidates(method: str) -> Query:
    """A summary's candidates, counted again: whatever else it holds, nothing that reaches C/2 is missing."""

    def run(spark, sf_dir):
        g, c, p = seeded(spark, sf_dir)
        drawn = materialise(sampling.descend(g, c, M, p, SEED), "sample")
        return frequent.second_pass(frequent.candidates(drawn, C, method), "stored", C, p, drawn)

    return run


for _method in ("decrement", "freqitems", "sketch"):
    QUERIES[f"frequent_{_method}"], ORACLES[f"frequent_{_method}"] = _candidates(_method), _SELECTED

SUMMARY = 200


@query(sql.with_(G, TC, select=f"select trace, n from tc where n > (select sum(n) from tc) / {SUMMARY + 1}.0"))
def summary_merge(spark, sf_dir):
    """Summaries of the days that paths begin on, merged by map functions, then counted again: what is frequent in the whole is in them."""
    g = graph(spark, sf_dir)
    day = g.vertices.select(F.col("vid").alias("start_vid"), F.floor(F.col("t_first") / F.lit(src.DAY)).alias("day"))
    counted = full.enumerate_traces(g, M).join(day, "start_vid").groupBy("day", "trace").agg(F.count(F.lit(1)).alias("n"))
    merged = frequent.summary_of_parts(materialise(counted, "days"), "day", SUMMARY).select(F.col("item").alias("trace"))
    exact = materialise(full.trace_counts(g, M), "traces")
    total = exact.agg(F.sum("n").alias("total"))
    return exact.join(F.broadcast(merged), "trace", "left_semi").crossJoin(F.broadcast(total)).where(F.col("n") > F.col("total") / F.lit(SUMMARY + 1)).select("trace", "n")


@query(sql.with_(G, TC, select=f"select trace, n from tc order by n desc, trace limit {K}"))
def topk_mc(spark, sf_dir):
    return mine.mine_topk(graph(spark, sf_dir), M, K, c=40, seed=SEED, verify="exact").traces


# ---- measures and experiments


def _census_sql(d: int, m: int, source: str = "events") -> str:
    return f"({sql.with_(sql.graph(d, source), sql.suffixes(m), select=f'select {d}::bigint as delta_min, {m}::bigint as m, sum(n)::bigint as n_paths, count(*) as n_distinct, {KTH_SQL} as kth_count, round(count(*) * {KTH_SQL} / (2 * sum(n)), 6) as space_ratio from tc')})"


def _census(spark, sf_dir, d: int, m: int, source: str = "events") -> DataFrame:
    every = materialise(full.trace_counts(graph(spark, sf_dir, d, source), m), "traces")
    row = every.agg(F.sum("n").alias("n_paths"), F.count(F.lit(1)).alias("n_distinct")).crossJoin(kth(every))
    return row.select(F.lit(d).cast("long").alias("delta_min"), F.lit(m).cast("long").alias("m"), "n_paths", "n_distinct", "kth_count", F.round(F.col("n_distinct") * F.col("kth_count") / (2 * F.col("n_paths")), 6).alias("space_ratio"))


@query(" union all ".join(_census_sql(d, m) for d, m in PAIRS))
def trace_census(spark, sf_dir):
    return union([_census(spark, sf_dir, d, m) for d, m in PAIRS])


@query(f"select delta_min, m, n_paths, round({C} * n_paths / kth_count, 6) as n_samples, round(kth_count / {C}, 6) as time_ratio from ({' union all '.join(_census_sql(d, m) for d, m in PAIRS)})")
def sampling_savings(spark, sf_dir):
    return trace_census(spark, sf_dir).select("delta_min", "m", "n_paths", F.round(C * F.col("n_paths") / F.col("kth_count"), 6).alias("n_samples"), F.round(F.col("kth_count") / C, 6).alias("time_ratio"))


def _readings_a_tag(spark, sf_dir) -> DataFrame:
    """``c``, ``n_tags``: how many tags have c readings."""
    return read(spark, sf_dir, "events").groupBy("user_id").agg(F.count(F.lit(1)).alias("c")).groupBy("c").agg(F.count(F.lit(1)).alias("n_tags"))


@query(sql.error_table("(select c, count(*) as n_tags from (select count(*) as c from events group by user_id) group by c)", ", n_tags"))
def error_table(spark, sf_dir):
    """Error probabilities where C is a tag's number of readings."""

    def run(frames):
        for f in frames:
            rows = sql.error_rows(tuple(f["c"].tolist()))
            for k, name in enumerate(("fn_prob", "sfp_prob", "fn_at_least", "sfp_at_least"), 1):
                f[name] = [r[k] for r in rows]
            yield f

    return _readings_a_tag(spark, sf_dir).mapInPandas(run, "c long, n_tags long, fn_prob double, sfp_prob double, fn_at_least double, sfp_at_least double").select("c", "fn_prob", "sfp_prob", "fn_at_least", "sfp_at_least", "n_tags")


@query("with recursive cs as (select 2 as c union all select c + 1 from cs where c < 400), f as (select c, (select sum(exp(-c + i * ln(c) - lgamma(i + 1))) from range(0, c // 2 + 1) as t(i)) as fn from cs), d as (select distinct 1.0::double / (count(*) + 1) as delta from events group by user_id) select delta::double as delta, min(c)::bigint as c from d, f where f.fn <= delta and not exists (select 1 from f b where b.c between f.c and f.c + 2 and b.fn > delta) group by delta")
def choose_c_table(spark, sf_dir):
    """C for the error probabilities at which a tag of n readings, each its own trace, misses less than one: 1 / (n + 1)."""
    deltas = _readings_a_tag(spark, sf_dir).select((F.lit(1.0) / (F.col("c") + 1)).alias("delta"))

    def run(frames):
        for f in frames:
            yield f.assign(c=[measures.choose_c(d) for d in f["delta"]])

    return deltas.mapInPandas(run, "delta double, c long")


ERRORS = (3, 5, 10, 15, 20, 30)
_errors: dict[tuple, DataFrame] = {}


@query()
def empirical_error(spark, sf_dir):
    """100 seeds at paths of three, beside the formulas."""
    key = (spark.sparkContext.applicationId, sf_dir)
    if key not in _errors:
        g = graph(spark, sf_dir, DELTA)
        _errors[key] = mine.empirical_error(g, M, threshold(g), list(ERRORS), 100)
    return _errors[key]


@query(sql.values([(c, 100, 1, 1, 1) for c in ERRORS], "c, seeds, fn_agrees, sfp_agrees, below_formula"))
def error_agreement(spark, sf_dir):
    """Whether the measured rates are what the binomial distribution expects of the same traces, within 0.01, and no larger than the formula for the worst of them, within that."""
    near = lambda a, b: (F.abs(F.col(a) - F.col(b)) <= 0.01).cast("long")
    low = ((F.col("fn_rate") <= F.col("fn_formula") + 0.01) & (F.col("sfp_rate") <= F.col("sfp_formula") + 0.01)).cast("long")
    return empirical_error(spark, sf_dir).select(F.col("c").cast("long").alias("c"), F.col("seeds").cast("long").alias("seeds"), near("fn_rate", "fn_expected").alias("fn_agrees"), near("sfp_rate", "sfp_expected").alias("sfp_agrees"), low.alias("below_formula"))


@query()
def c_sweep(spark, sf_dir):
    """Samples grow in proportion to C, misses fall."""
    g = graph(spark, sf_dir, DELTA)
    return mine.empirical_error(g, M, threshold(g), [2, 4, 8, 16, 32], 20).select("c", "seeds", "n_samples", "fn_rate", "fn_formula")


_RANKED = f", ra as (select trace, row_number() over (order by n desc, trace) as ra from (select trace, n from tc order by n desc, trace limit {K})), rb as (select trace, row_number() over (order by n_sample desc, trace) as rb from (select trace, n_sample from n order by n_sample desc, trace limit {K})), rr as (select greatest(ra, rb) as worst from ra join rb using (trace))"


@query(sampled_sql(f"select {K}::int as k, round((select count(*) from rr) / (select count(*) from rb), 6) as precision, round((select count(*) from rr) / (select count(*) from ra), 6) as recall, round(coalesce((select sum((select sum(1.0::double / d) from range(worst, {K + 1}) as t(d))) from rr), 0) / {K}, 6) as rank_overlap", more=_SEEN + _RANKED))
def topk_quality(spark, sf_dir):
    g, c, p = seeded(spark, sf_dir)
    found = frequent.sample_counts(sampling.descend(g, c, M, p, SEED)).withColumnRenamed("n_sample", "n")
    return mine.topk_quality(full.trace_counts(g, M), found, K)


@query(" union all ".join(f"({sql.with_(G, sql.counts(m), select=f'select {m}::bigint as m, sum(c{m})::bigint as n_paths, (select count(*) from v) + (select count(*) from e) as graph_size, round(sum(c{m}) / ((select count(*) from v) + (select count(*) from e)), 6) as blowup from c')})" for m in range(1, 7)))
def path_blowup(spark, sf_dir):
    g = graph(spark, sf_dir)
    size = graph_size(g).select((F.col("n_vertices") + F.col("n_edges")).alias("graph_size"))
    return counting.totals_by_level(counting.count_paths(g, 6), 6).crossJoin(size).select(F.col("m").cast("long").alias("m"), "n_paths", "graph_size", F.round(F.col("n_paths") / F.col("graph_size"), 6).alias("blowup"))


@query(sampled_sql("select 'samples' as measure, count(*) as value from s union all select 'sampled_length', coalesce(sum(len(str_split(path_key, '-'))), 0)::bigint from s union all select 'calls', count(distinct array_to_string(list_slice(str_split(path_key, '-'), 1, k), '-')) from s, unnest(range(1, len(str_split(path_key, '-')) + 1)) as t(k) union all select 'edges_scanned', count(*) from (select distinct list_slice(str_split(path_key, '-'), 1, k) as x from s, unnest(range(1, least(len(str_split(path_key, '-')), {M - 1}) + 1)) as t(k)) join e on e.src = x[-1]::bigint".replace("{M - 1}", str(M - 1))))
def sampler_cost(spark, sf_dir):
    g, c, p = seeded(spark, sf_dir)
    return sampling.sampler_cost(materialise(sampling.descend(g, c, M, p, SEED), "sample"))


@query(sampled_sql(f"select 'samples' as measure, count(*) as value from s union all select 'distinct_sampled', count(distinct trace) from s union all select 'capacity', ceil(2 * count(*) / {C})::bigint from s union all select 'tasks_beyond_capacity', 0"))
def summary_space(spark, sf_dir):
    """The space a summary needs by formula, and whether any task held more counters than that."""
    g, c, p = seeded(spark, sf_dir)
    drawn = materialise(sampling.descend(g, c, M, p, SEED), "sample")
    s = drawn.agg(F.count(F.lit(1)).alias("a"), F.countDistinct("trace").alias("b"))
    room = max(1, -(-2 * drawn.count() // C))
    held = frequent.decrement_summary(drawn, "trace", room).agg(F.sum((F.col("most") > room).cast("long")).alias("d"))
    return s.crossJoin(held).select(F.expr(f"stack(4, 'samples', a, 'distinct_sampled', b, 'capacity', cast(ceil(2 * a / {C}) as bigint), 'tasks_beyond_capacity', d) as (measure, value)"))


# ---- worked examples


def example(spark: SparkSession, labels: list[str], pairs: list[tuple[int, int]]) -> LabeledDag:
    v = spark.createDataFrame([(k + 1, x) for k, x in enumerate(labels)], "vid long, label string")
    return LabeledDag.from_tables(v, spark.createDataFrame(pairs, "src long, dst long"))


BROWSING = (["goo", "tec", "ora", "itu", "goo"], [(1, 2), (1, 3), (2, 4), (2, 3), (3, 4), (4, 5)])
READ_AT = [(1, 10, 1, "1"), (1, 20, 2, "2"), (1, 30, 3, "3"), (1, 60, 4, "6"), (1, 70, 5, "7")]


CUSTOMERS = src.SequenceSpec("c_nationkey", "c_custkey", "c_custkey", "c_mktsegment", 1)
_CUSTOMERS = "select c_nationkey as tag, c_custkey as t_us, c_custkey as seq, c_mktsegment as label from customer"


@query(sql.with_(sql.vertices("pages", 20, rd=_CUSTOMERS), sql.edges(20, "pages"), sql.suffixes(M), select="select trace, n from tc"))
def example_sequence(spark, sf_dir):
    """Segments of a nation's customers in the order of their keys, at most 20 keys apart; nothing is stored."""
    g = LabeledDag.from_readings(src.readings(read(spark, sf_dir, "customer"), CUSTOMERS), 20, keep=False)
    return full.trace_counts(g, M).select("trace", "n")


def _banded(keys: DataFrame, steps: tuple[int, ...]) -> LabeledDag:
    """``keys`` (vid, label), with an edge for each step to a key that is there."""
    there = keys.select(F.col("vid").alias("dst"))
    edges = keys.select(F.col("vid").alias("src"), F.explode(F.array(*[F.col("vid") + s for s in steps])).alias("dst")).join(there, "dst", "left_semi")
    return LabeledDag.from_tables(keys, materialise(edges.select("src", "dst"), "edges"))


def _banded_sql(steps: tuple[int, ...], label: str) -> str:
    return f"v as (select c_custkey as vid, {label} as label from customer), e as (select a.vid as src, b.vid as dst, a.label as src_label, b.label as dst_label from (select *, unnest([{', '.join(map(str, steps))}]) as step from v) a join v b on b.vid = a.vid + a.step)"


@query(sql.with_(_banded_sql((1, 2), "c_mktsegment"), sql.suffixes(5), select=" union all ".join(f"select {m}::bigint as m, sum(n)::bigint as n_paths, count(distinct trace) as n_distinct from tc where len <= {m}" for m in range(1, 6))))
def example_browsing(spark, sf_dir):
    """A graph as given: from a customer to the next two, with their segments as labels."""
    g = _banded(read(spark, sf_dir, "customer").select(F.col("c_custkey").cast("long").alias("vid"), F.col("c_mktsegment").alias("label")), (1, 2))
    rows = [full.trace_counts(g, m).agg(F.sum("n").alias("n_paths"), F.count(F.lit(1)).alias("n_distinct")).select(F.lit(m).cast("long").alias("m"), "n_paths", "n_distinct") for m in range(1, 6)]
    return union(rows)


@query(sql.with_(_banded_sql((1, 2, 3), "c_custkey::varchar"), "w as (select vid, 1 as len, 1::bigint as n from v union all select * from (select e.src, w.len + 1 as len, sum(w.n)::bigint from w join e on e.dst = w.vid where w.len < 16 group by e.src, w.len))", select="select len::bigint as m, (sum(sum(n)) over (order by len))::bigint as n_paths from w group by len"))
def example_band(spark, sf_dir):
    """Customers in a band: from each key to the next three, every one with its number as label."""
    keys = read(spark, sf_dir, "customer").select(F.col("c_custkey").cast("long").alias("vid"), F.col("c_custkey").cast("string").alias("label"))
    return counting.totals_by_level(counting.count_paths(_banded(keys, (1, 2, 3)), 16), 16).select(F.col("m").cast("long").alias("m"), "n_paths")


@query(sql.values([(16, 42, 16, 27692)], "n_vertices, n_edges, depth, n_paths"))
def band_all_paths(spark, sf_dir):
    g = LabeledDag.from_tables(*src.band_dag(spark, 16))
    depth = dag_depth(g)
    total = counting.saturated_counts(g).agg(F.sum(F.element_at("c", depth + 1)).alias("n_paths"))
    return graph_size(g).crossJoin(total).select("n_vertices", "n_edges", F.lit(depth).cast("long").alias("depth"), "n_paths")


# ---- other sequences


def _other(source: str, delta: float, least: int = 1) -> tuple[Query, str]:
    def run(spark, sf_dir):
        counted = full.trace_counts(graph(spark, sf_dir, delta, source), M)
        return counted.where(F.col("n") >= least).select("trace", "n")

    return run, sql.with_(sql.graph(delta, source), TC, select=f"select trace, n from tc where n >= {least}")


for _name, _source, _delta, _least in (("orders_traces", "orders", 360, 1), ("lineitem_traces", "lineitem", 60, 1), ("conversation_traces", "conversations", 2, 1), ("pages_traces", "pages", 20, 1)):
    QUERIES[_name], ORACLES[_name] = _other(_source, _delta, _least)


@query(sql.with_(sql.vertices("words", 2, "collapse"), sql.edges(2, "words"), sql.suffixes(2), select="select trace, n from tc where n >= 50"))
def document_skipgram_traces(spark, sf_dir):
    """Frequent words and skip-grams of two words at most two apart; repeats of a word count once. A document is one row, so its paths are counted where it is read; rows that
    share an id are one sequence, and go through a graph."""
    docs = read(spark, sf_dir, "documents").where("doc_id is not null").select("doc_id", "text")
    shared = materialise(docs.groupBy("doc_id").agg(F.count(F.lit(1)).alias("rows")).where("rows > 1").select("doc_id"), "shared")
    several = small(shared)
    alone = full.skip_pair_counts(docs.join(several, "doc_id", "left_anti").select(src.words_of().alias("words")), "words", 2)
    if shared.limit(1).count():
        g = LabeledDag.from_readings(src.skipgram_readings(docs.join(several, "doc_id", "left_semi")), 2, "collapse")
        alone = alone.unionByName(full.trace_counts(g, 2).select("trace", "n")).groupBy("trace").agg(F.sum("n").alias("n"))
    return alone.where("n >= 50")


@query(_census_sql(DELTA, M, "fine"))
def fine_label_census(spark, sf_dir):
    return _census(spark, sf_dir, DELTA, M, "fine")


@query(sql.with_(G, TC, ", x as (select regexp_replace(trace, '>[^>]*$', '') as prefix, regexp_extract(trace, '[^>]*$') as next_label, n from tc where len > 1)", select="select prefix, next_label, n, round(n / sum(n) over (partition by prefix), 9) as share from x"))
def next_label(spark, sf_dir):
    """What follows a prefix, and how often."""
    longer = full.trace_counts(graph(spark, sf_dir), M, min_len=2)
    labels = trace_labels()
    cut = longer.select(F.array_join(F.slice(labels, 1, F.size(labels) - 1), SEPARATOR).alias("prefix"), F.element_at(labels, -1).alias("next_label"), "n")
    return cut.withColumn("share", F.round(F.col("n") / F.sum("n").over(Window.partitionBy("prefix")), 9))


# ---- operators around the methods

_HALF = "timestamp '2024-01-16 00:00:00'"


def _period(spark, sf_dir, before: bool) -> LabeledDag:
    """The time range reaches the scan as a pushed filter."""
    e = read(spark, sf_dir, "events")
    half = F.to_timestamp_ntz(F.lit("2024-01-16 00:00:00"))
    part = e.where(F.col("ts") < half) if before else e.where(F.col("ts") >= half)
    return LabeledDag.from_readings(src.readings(part, src.EVENTS), src.EVENTS.delta(DELTA))


def _period_sql(before: bool, out: str) -> str:
    where = f"ts {'<' if before else '>='} {_HALF}"
    return sql.vertices("events", DELTA, "full", out=f"v{out}", rd=sql.READINGS["events"] + f" where {where}") + sql.edges(DELTA, v=f"v{out}", out=f"e{out}") + sql.suffixes(M, v=f"v{out}", e=f"e{out}", out=f"tc{out}")


@query(sql.with_(_period_sql(True, "a"), select="select trace, n from tca"))
def filter_time_range(spark, sf_dir):
    return full.trace_counts(_period(spark, sf_dir, True), M).select("trace", "n")


@query(sql.with_(G, TC, select="select trace, n from tc where list_contains(str_split(trace, '>'), 'purchase')"))
def trace_contains(spark, sf_dir):
    return full.trace_counts(graph(spark, sf_dir), M).where(contains_label("purchase")).select("trace", "n")


@query(sql.with_(G, TC, select="select trace, n from tc where trace = 'view>click' or starts_with(trace, 'view>click>')"))
def trace_prefix(spark, sf_dir):
    return full.trace_counts(graph(spark, sf_dir), M).where(has_prefix(["view", "click"])).select("trace", "n")


@query(sql.with_(G, TC, f", f as (select trace, len, n from tc where n >= {KTH_SQL})", select="select a.trace as part, b.trace as whole, round(b.n / a.n, 9) as share from f a join f b on a.len < b.len and contains('>' || b.trace || '>', '>' || a.trace || '>')"))
def subtrace_pairs(spark, sf_dir):
    """Frequent traces within frequent traces: a nested loop over about a hundred rows."""
    g = graph(spark, sf_dir)
    f = materialise(full.trace_counts(g, M).where(F.col("n") >= threshold(g)), "frequent")
    a, b = f.alias("a"), F.broadcast(f).alias("b")
    wrapped: Callable[[str], Column] = lambda c: F.concat(F.lit(SEPARATOR), F.col(c), F.lit(SEPARATOR))
    return a.join(b, (F.col("a.len") < F.col("b.len")) & F.contains(wrapped("b.trace"), wrapped("a.trace"))).select(F.col("a.trace").alias("part"), F.col("b.trace").alias("whole"), F.round(F.col("b.n") / F.col("a.n"), 9).alias("share"))


@query(sql.with_(_period_sql(True, "a"), _period_sql(False, "b"), select="select trace, n from tca where n >= 50 and trace in (select trace from tcb where n >= 50)"))
def candidates_semi(spark, sf_dir):
    a, b = (full.trace_counts(_period(spark, sf_dir, first), M).where("n >= 50").select("trace", "n") for first in (True, False))
    return a.join(b.select("trace"), "trace", "left_semi")


@query(sql.with_(G, select="select vid, label from v where vid not in (select src from e)"))
def sink_vertices(spark, sf_dir):
    g = graph(spark, sf_dir)
    return g.vertices.join(g.edges, F.col("vid") == F.col("src"), "left_anti").select("vid", "label")


@query(sql.with_(G, select="select vid, count(src) as degree from v left join e on src = vid group by vid"))
def out_degree(spark, sf_dir):
    g = graph(spark, sf_dir)
    return g.vertices.join(g.edges, F.col("vid") == F.col("src"), "left").groupBy("vid").agg(F.count("src").alias("degree"))


@query(sql.with_(G, select="select degree, count(*) as n from (select vid, count(src) as degree from v left join e on src = vid group by vid) group by degree"))
def degree_histogram(spark, sf_dir):
    return out_degree(spark, sf_dir).groupBy("degree").agg(F.count(F.lit(1)).alias("n"))


@query(sql.with_(G, ", d as (select vid, count(src) as degree from v left join e on src = vid group by vid)", select="select quantile_cont(degree, 0.5)::double as median, quantile_cont(degree, 0.9)::double as p90, max(degree) as most, round(avg(degree), 9) as mean from d"))
def degree_quantiles(spark, sf_dir):
    q = lambda p: F.percentile("degree", F.lit(p)).cast("double")
    return out_degree(spark, sf_dir).agg(q(0.5).alias("median"), q(0.9).alias("p90"), F.max("degree").alias("most"), F.round(F.avg("degree"), 9).alias("mean"))


@query()
def distinct_estimates(spark, sf_dir):
    """Bounded-memory counterparts of the census: distinct traces, a quantile of their counts."""
    every = full.enumerate_traces(graph(spark, sf_dir), M)
    counted = full.trace_counts(graph(spark, sf_dir), M)
    return every.agg(F.approx_count_distinct("trace", 0.02).alias("n_distinct")).crossJoin(counted.agg(F.percentile_approx("n", 0.9, 1000).alias("p90")))


@query(sql.with_(G, select="select label, count(*) as n, count(distinct tag) as n_tags, min(t_first) as first_us, max(t_last) as last_us, sum(n_readings)::bigint as n_readings, first(vid order by t_first desc, vid desc) as last_vid from v group by label"))
def label_stats(spark, sf_dir):
    last = F.max_by("vid", F.struct("t_first", "vid")).alias("last_vid")
    return graph(spark, sf_dir).vertices.groupBy("label").agg(F.count(F.lit(1)).alias("n"), F.countDistinct("tag").alias("n_tags"), F.min("t_first").alias("first_us"), F.max("t_last").alias("last_us"), F.sum("n_readings").alias("n_readings"), last)


@query("with probes as (select user_id, unnest(generate_series(timestamp '2024-01-02', timestamp '2024-01-30', interval 7 day)) as at from (select distinct user_id from events)) select p.user_id as tag, epoch_us(p.at) as at_us, e.event_id as seq, e.event_type as label from probes p asof left join events e on e.user_id = p.user_id and e.ts <= p.at")
def asof_last_reading(spark, sf_dir):
    """The last reading of every tag at each probe time: one window over readings and probes together."""
    r = readings_of(spark, sf_dir)
    probes = r.select("tag").distinct().select("tag", F.explode(F.expr("sequence(timestamp'2024-01-02 00:00:00', timestamp'2024-01-30 00:00:00', interval 7 days)")).alias("at")).select("tag", F.unix_micros("at").alias("t_us"), F.lit(None).cast("struct<seq:bigint,label:string>").alias("x"), F.lit(1).alias("probe"))
    both = r.select("tag", "t_us", F.struct("seq", "label").alias("x"), F.lit(0).alias("probe")).unionByName(probes)
    seen = F.last("x", ignorenulls=True).over(Window.partitionBy("tag").orderBy("t_us", "probe", F.col("x.seq")).rowsBetween(Window.unboundedPreceding, 0))
    return both.withColumn("x", seen).where("probe = 1").select("tag", F.col("t_us").alias("at_us"), F.col("x.seq").alias("seq"), F.col("x.label").alias("label"))


_ORDERS = sql.graph(360, "orders")


@query(sql.with_(_ORDERS, sql.paths(2), select="select r_name as region, n_name as nation, count(*) as n, count(distinct trace) as n_traces, grouping(r_name, n_name)::int as level from p join v on v.vid = p.start_vid join customer on c_custkey = v.tag join nation on n_nationkey = c_nationkey join region on r_regionkey = n_regionkey group by rollup (r_name, n_name)"))
def rollup_region_trace(spark, sf_dir):
    """Paths of orders by region and nation of the customer."""
    g = graph(spark, sf_dir, 360, "orders")
    where = read(spark, sf_dir, "customer").select("c_custkey", "c_nationkey").join(F.broadcast(read(spark, sf_dir, "nation")), F.col("c_nationkey") == F.col("n_nationkey")).join(F.broadcast(read(spark, sf_dir, "region")), F.col("n_regionkey") == F.col("r_regionkey"))
    every = full.enumerate_traces(g, 2).join(g.vertices.select(F.col("vid").alias("start_vid"), "tag"), "start_vid").join(where, F.col("tag") == F.col("c_custkey"))
    return every.rollup(F.col("r_name").alias("region"), F.col("n_name").alias("nation")).agg(F.count(F.lit(1)).alias("n"), F.countDistinct("trace").alias("n_traces"), F.grouping_id().cast("int").alias("level"))


@query(sql.with_(G, TC, ", x as (select len, split_part(trace, '>', 1) as first_label, n from tc)", select="select len, first_label, sum(n)::bigint as n from x group by cube (len, first_label)"))
def cube_len_first(spark, sf_dir):
    every = full.trace_counts(graph(spark, sf_dir), M).withColumn("first_label", F.element_at(trace_labels(), 1))
    return every.cube("len", "first_label").agg(F.sum("n").alias("n"))


@query(sql.with_(G, TC, select="select len, trace, n, rank from (select *, row_number() over (partition by len order by n desc, trace)::int as rank from tc) where rank <= 5"))
def topk_per_length(spark, sf_dir):
    order = Window.partitionBy("len").orderBy(F.desc("n"), "trace")
    return full.trace_counts(graph(spark, sf_dir), M).withColumn("rank", F.row_number().over(order)).where("rank <= 5").select("len", "trace", "n", "rank")


@query(sql.with_(G, TC, select="select len, trace, n, rank() over w::int as place, dense_rank() over w::int as dense, ntile(4) over (partition by len order by n desc, trace)::int as quarter, round(percent_rank() over w, 9) as share from tc window w as (partition by len order by n desc)"))
def rank_functions(spark, sf_dir):
    by, tied = Window.partitionBy("len").orderBy(F.desc("n")), Window.partitionBy("len").orderBy(F.desc("n"), "trace")
    return full.trace_counts(graph(spark, sf_dir), M).select("len", "trace", "n", F.rank().over(by).alias("place"), F.dense_rank().over(by).alias("dense"), F.ntile(4).over(tied).alias("quarter"), F.round(F.percent_rank().over(by), 9).alias("share"))


@query(sql.with_(G, TC, select="select rank, round(covered / total, 9) as share from (select row_number() over (order by n desc, trace) as rank, sum(n) over (order by n desc, trace rows unbounded preceding) as covered, sum(n) over () as total from tc) where rank in (1, 2, 5, 10, 20, 50, 100, 200, 500)"))
def coverage_curve(spark, sf_dir):
    """The share of all paths that the most frequent traces cover. Only the first 500 traces are ordered."""
    every = materialise(full.trace_counts(graph(spark, sf_dir), M), "traces")
    total = every.agg(F.sum("n").alias("total"))
    order = Window.orderBy(F.desc("n"), "trace")
    top = every.orderBy(F.desc("n"), "trace").limit(500).select(F.row_number().over(order).cast("long").alias("rank"), F.sum("n").over(order.rowsBetween(Window.unboundedPreceding, 0)).alias("covered"))
    return top.where(F.col("rank").isin(1, 2, 5, 10, 20, 50, 100, 200, 500)).crossJoin(F.broadcast(total)).select("rank", F.round(F.col("covered") / F.col("total"), 9).alias("share"))


@query(f"with g as (select tag, label, t_us - lag(t_us) over (partition by tag order by t_us, seq) as gap from ({sql.READINGS['events']})) select label, count(gap) as n, min(gap) as least, max(gap) as most, sum((gap > {src.EVENTS.delta(DELTA)})::int)::bigint as n_long from g group by label")
def gap_stats(spark, sf_dir):
    gap = F.col("t_us") - F.lag("t_us").over(Window.partitionBy("tag").orderBy("t_us", "seq"))
    g = readings_of(spark, sf_dir).select("label", gap.alias("gap"))
    return g.groupBy("label").agg(F.count("gap").alias("n"), F.min("gap").alias("least"), F.max("gap").alias("most"), F.sum((F.col("gap") > src.EVENTS.delta(DELTA)).cast("int")).alias("n_long"))


@query(sql.with_(_period_sql(True, "a"), _period_sql(False, "b"), select="select trace from tca where n >= 50 intersect select trace from tcb where n >= 50"))
def frequent_intersect(spark, sf_dir):
    a, b = (full.trace_counts(_period(spark, sf_dir, first), M).where("n >= 50").select("trace") for first in (True, False))
    return a.intersect(b)


@query(sql.with_(_period_sql(True, "a"), _period_sql(False, "b"), select="select trace from tca where n >= 50 except select trace from tcb where n >= 50"))
def frequent_except(spark, sf_dir):
    a, b = (full.trace_counts(_period(spark, sf_dir, first), M).where("n >= 50").select("trace") for first in (True, False))
    return a.exceptAll(b)


@query(sql.with_(_period_sql(True, "a"), _period_sql(False, "b"), select="select coalesce(tca.trace, tcb.trace) as trace, tca.n as early, tcb.n as late from tca full join tcb on tca.trace = tcb.trace"))
def pivot_period(spark, sf_dir):
    both = union([full.trace_counts(_period(spark, sf_dir, first), M).select("trace", "n", F.lit(name).alias("period")) for first, name in ((True, "early"), (False, "late"))])
    return both.groupBy("trace").pivot("period", ["early", "late"]).agg(F.sum("n"))


@query(sql.with_(_period_sql(True, "a"), _period_sql(False, "b"), select="select trace, 'early' as period, n from tca where n >= 50 union all select trace, 'late', n from tcb where n >= 50"))
def unpivot_period(spark, sf_dir):
    wide = pivot_period(spark, sf_dir)
    return wide.unpivot(["trace"], ["early", "late"], "period", "n").where("n >= 50")


@query(sql.with_(G, TC, ", x as (select len, split_part(trace, '>', 1) as first_label, n from tc)", select="select len, first_label, sum(n)::bigint as n, count(*) as n_distinct, grouping(len, first_label)::bigint as level from x group by grouping sets ((len), (first_label), ())"))
def grouping_sets_census(spark, sf_dir):
    full.trace_counts(graph(spark, sf_dir), M).withColumn("first_label", F.element_at(trace_labels(), 1)).createOrReplaceTempView("pathtraces_census")
    return spark.sql("select len, first_label, sum(n) as n, count(*) as n_distinct, grouping_id(len, first_label) as level from pathtraces_census group by len, first_label grouping sets ((len), (first_label), ())")


@query(f"with r as ({sql.READINGS['events']}), a as (select *, coalesce(t_us - lag(t_us) over w >= {src.EVENTS.delta(DELTA)}, true)::int as s from r window w as (partition by tag, label order by t_us, seq)), b as (select *, sum(s) over (partition by tag, label order by t_us, seq) as k from a) select tag, label, min(t_us) as t_first, max(t_us) as t_last, count(*) as n from b group by tag, label, k")
def session_runs(spark, sf_dir):
    return live.session_runs(readings_of(spark, sf_dir), f"{DELTA} minutes")


@query(sql.with_(G, CN, ", x as (select src, dst, c2 as n from e join c on vid = dst)", select="select src, count(*)::int as degree, sum(n)::bigint as total, array_to_string(list_transform(range(1, count(*) + 1), lambda i: list_sum(list_slice(list(n order by dst), 1, i))::bigint), ',') as sums from x group by src"))
def array_prefix_sums(spark, sf_dir):
    """Prefix sums of the children's counts, as arrays: what the searches of the refined samplers use."""
    g = graph(spark, sf_dir)
    c = counting.count_paths(g, M).select(F.col("vid").alias("dst"), F.element_at("c", M).alias("n"))
    lists = g.edges.join(c, "dst").groupBy("src").agg(F.array_sort(F.collect_list(F.struct("dst", "n"))).alias("x")).select("src", F.transform("x", lambda s: s["n"]).alias("n"))
    zero = F.struct(F.lit(0).cast("long").alias("t"), F.array().cast("array<bigint>").alias("a"))
    sums = F.aggregate("n", zero, lambda s, x: F.struct((s["t"] + x).alias("t"), F.concat(s["a"], F.array(s["t"] + x)).alias("a")))
    return lists.select("src", F.size("n").alias("degree"), sums["t"].alias("total"), F.array_join(sums["a"].cast("array<string>"), ",").alias("sums"))


@query(sql.with_(G, ", lc as (select label, row_number() over (order by label)::bigint as code from (select distinct label from v))", select="select vid, code from v join lc using (label)"))
def join_broadcast_label(spark, sf_dir):
    g = graph(spark, sf_dir)
    return g.vertices.join(F.broadcast(full.label_codes(g)), "label").select("vid", "code")


def _hinted(hint: str) -> Query:
    def run(spark, sf_dir):
        g = graph(spark, sf_dir)
        c = counting.count_paths(g, 2).select(F.col("vid").alias("dst"), F.element_at("c", 3).alias("n"))
        return g.edges.hint(hint).join(c, "dst").groupBy("src").agg(F.sum("n").alias("n"))

    return run


for _name, _hint in (("join_smj", "merge"), ("join_shj", "shuffle_hash")):
    QUERIES[_name] = _hinted(_hint)
    ORACLES[_name] = sql.with_(G, sql.counts(2), select="select src, sum(c2)::bigint as n from e join c on vid = dst group by src")


@query(sql.with_(G, sql.hashes(M, True), select="select distinct trace, h1, h2 from h"))
def udf_trace_hash(spark, sf_dir):
    """The rolling hashes of traces, by an Arrow function over whole columns."""
    from pathtraces.sqlapi import trace_hash

    g = graph(spark, sf_dir)
    codes = {r.label: r.code for r in full.label_codes(g).collect()}  # one row a label
    return full.trace_counts(g, M).select("trace", trace_hash(codes)("trace").alias("h")).select("trace", F.col("h.h1").alias("h1"), F.col("h.h2").alias("h2"))


# ---- streams


def _played(spark: SparkSession, sf_dir: str, make: Callable[[DataFrame], DataFrame], days: int = 10, held: int = 0) -> DataFrame:
    """The readings as files by time, read as a stream to the end; the output of all batches. A last reading far ahead moves the
    watermark past all others. Every ``held``-th reading (by id) comes two files late."""
    r = readings_of(spark, sf_dir)
    low, high = r.agg(F.min("t_us"), F.max("t_us")).first()
    slot = F.floor((F.col("t_us") - low) * F.lit(days) / (F.lit(high - low + 1)))
    slot = slot + F.when(F.col("seq") % held == 0, 2).otherwise(0) if held else slot
    days = days + 2 if held else days
    folder, out, check = new_path(spark, "stream-in"), new_path(spark, "stream-out"), new_path(spark, "stream-state")
    for d in range(days):
        r.where(slot == d).coalesce(1).write.mode("append").parquet(f"{folder}/{d:03d}")
    for k in (0, 1):
        src.literal_readings(spark, [(-1, high + (400 + k) * src.DAY, -1 - k, "end")]).coalesce(1).write.mode("append").parquet(f"{folder}/{days + k:03d}")
    files = spark.readStream.schema(src.SCHEMA).option("maxFilesPerTrigger", 1).option("recursiveFileLookup", "true").parquet(folder)
    q = make(files).writeStream.format("parquet").option("path", out).option("checkpointLocation", check).outputMode("append").trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.read.parquet(out)


@query(_RAW_EDGES)
def stream_edges(spark, sf_dir):
    return _played(spark, sf_dir, lambda s: live.live_edges(s, src.EVENTS.delta(DELTA), "0 seconds"))


@query(sql.with_(sql.vertices("events", DELTA, "raw"), sql.edges(DELTA), sql.counts(M, ending=True), select="select vid, c1, c2, c3 from c"))
def stream_path_counts(spark, sf_dir):
    rows = _played(spark, sf_dir, lambda s: live.live_paths(s, src.EVENTS.delta(DELTA), "0 seconds", M)).where("kind = 'count' and tag >= 0")
    return rows.groupBy("vid").agg(*[F.max(F.when(F.col("level") == i, F.col("n"))).alias(f"c{i}") for i in range(1, M + 1)])


def _live_sample(spark, sf_dir) -> DataFrame:
    return _played(spark, sf_dir, lambda s: live.live_paths(s, src.EVENTS.delta(DELTA), "0 seconds", M, p=0.02, seed=SEED)).where("kind = 'sample' and tag >= 0")


_HELD = 37


@query(f"with r as ({sql.READINGS['events']}), b as (select *, (t_us - min(t_us) over ()) * 10 // (max(t_us) over () - min(t_us) over () + 1) + case when seq % {_HELD} = 0 then 2 else 0 end as batch from r), top as (select batch, max(t_us) as t from b group by batch) select tag, seq as vid from b where t_us <= (select max(t) // 1000 * 1000 from top where top.batch < b.batch)")
def stream_late(spark, sf_dir):
    """Readings that came too late, where every 37th comes two files after its neighbours."""
    return _played(spark, sf_dir, lambda s: live.live_paths(s, src.EVENTS.delta(DELTA), "0 seconds"), held=_HELD).where("kind = 'late'").select("tag", "vid")


@query()
def stream_sample(spark, sf_dir):
    return _live_sample(spark, sf_dir).select(F.col("vid").alias("end_vid"), F.col("other").alias("start_vid"), F.col("level").alias("len"), F.col("text").alias("trace"))


@query()
def stream_frequent(spark, sf_dir):
    return frequent.decrement_summary(_live_sample(spark, sf_dir), "text", 400).select(F.col("item").alias("trace"), "n")


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """From readings to the frequent traces, by sampling with a verifying second pass."""
    return QUERIES["frequency_mc"](spark, sf_dir)
