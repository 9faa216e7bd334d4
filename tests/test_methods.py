"""Worked examples, exact baselines, invariants of the samplers, measures."""

import math
from collections import Counter

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pathtraces import workloads as w
from pathtraces.functions import measures
from pathtraces.operators import clean, counts, enumeration, frequent, mine, sample
from pathtraces.operators.dag import LabeledDag, build_edges, dag_depth, on_cycles, sessions
from pathtraces.operators.kernels import Piece, ranks
from pathtraces.sources import readings as src
from pyspark.sql import functions as F

SF = "/root/testdata/sf0.001"
SF2 = "/root/testdata/sf0.01"


def piece(labels, pairs):
    after = [[b - 1 for a, b in pairs if a == k + 1] for k in range(len(labels))]
    return Piece(list(range(1, len(labels) + 1)), list(labels), after)


BROWSING = piece(*w.BROWSING)


def test_browsing_counts():
    assert [sum(c[m] for c in BROWSING.counts(5)) for m in range(1, 6)] == [5, 11, 17, 21, 22]
    assert [c[5] for c in BROWSING.counts(5)] == [10, 6, 3, 2, 1]
    assert [len(BROWSING.traces(m)) for m in range(1, 6)] == [4, 10, 16, 20, 21]
    assert Counter(BROWSING.named(p)[2] for p in BROWSING.paths(5)) == BROWSING.traces(5)


@pytest.mark.parametrize("p", [0.02, 0.1, 0.5])
@pytest.mark.parametrize("how", ["descend", "first_hit", "guide"])
def test_samples_are_independent(how, p):
    """Every path with p, every pair with p**2, the size's variance as of independent draws."""
    runs = 4000
    keys = [BROWSING.named(x)[1] for x in BROWSING.paths(5)]
    at = {k: i for i, k in enumerate(keys)}
    seen = np.zeros((runs, len(keys)), bool)
    for seed in range(runs):
        for _, key, _ in BROWSING.sample(5, p, seed, how):
            assert not seen[seed, at[key]]
            seen[seed, at[key]] = True
    z = (seen.mean(axis=0) - p) / math.sqrt(p * (1 - p) / runs)
    assert np.abs(z).max() < 4.2
    both = (seen.T.astype(float) @ seen) / runs
    pairs = both[np.triu_indices(len(keys), 1)]
    assert np.abs((pairs - p * p) / math.sqrt(p * p * (1 - p * p) / runs)).max() < 4.8
    assert seen.sum(axis=1).var() == pytest.approx(22 * p * (1 - p), rel=0.12)


def test_published_rule_is_biased():
    sizes = [sum(1 for _ in BROWSING.sample(5, 0.1, seed, "printed")) for seed in range(2000)]
    assert np.mean(sizes) < 1.9  # 2.2 would be right


def test_guide_equals_search():
    for seed in range(300):
        assert list(BROWSING.sample(5, 0.3, seed, "guide")) == list(BROWSING.sample(5, 0.3, seed, "first_hit"))


def test_everything_is_drawn_with_p_one():
    for how in ("descend", "first_hit", "guide"):
        assert len(list(BROWSING.sample(5, 1.0, 1, how))) == 22


def test_ranks_are_bernoulli():
    hits = np.zeros(50)
    for v in range(4000):
        hits[ranks(50, 0.1, 3, v)] += 1
    assert np.abs((hits / 4000 - 0.1) / math.sqrt(0.09 / 4000)).max() < 4
    assert list(ranks(5, 1.0, 1, 1)) == [0, 1, 2, 3, 4] and len(ranks(0, 0.5, 1, 1)) == 0


def labels_of(spark, text, gaps=None, mode="full", delta=10):
    rows = [(1, (sum((gaps or [5] * len(text))[: k + 1])), k, x) for k, x in enumerate(text)]
    v = clean.clean(src.literal_readings(spark, rows), delta, mode).orderBy("t_first").collect()
    return [r.label for r in v]


def test_cleaning_fixtures(spark):
    assert labels_of(spark, "xyxy") == ["x*y"]
    assert labels_of(spark, "xyx") == ["x", "y", "x"]
    assert labels_of(spark, "xyxyx") == ["x*y", "x"]
    assert labels_of(spark, "xxyyxy") == ["x*y"]
    assert labels_of(spark, "xyxyzyzy") == ["x*y", "y*z"]
    assert labels_of(spark, "xx", [5, 50]) == ["x", "x"]
    assert labels_of(spark, "xyxy", [5, 5, 50, 5]) == ["x", "y", "x", "y"]
    assert labels_of(spark, "xxyyxy", mode="collapse") == ["x", "y", "x", "y"]


def plain_clean(text):
    """Left to right over runs: the longest even alternation of four or more at each place."""
    runs = [x for k, x in enumerate(text) if not k or text[k - 1] != x]
    out, k = [], 0
    while k < len(runs):
        n = 2 if k + 1 < len(runs) else 1
        while n >= 2 and k + n < len(runs) and runs[k + n] == runs[k + n - 2]:
            n += 1
        if n >= 4:
            out.append("*".join(sorted(runs[k : k + 2])))
            k += n // 2 * 2
        else:
            out.append(runs[k])
            k += 1
    return [x for k, x in enumerate(out) if not k or out[k - 1] != x]


def test_cleaning_random(spark):
    rng = np.random.default_rng(1)
    texts = ["".join(rng.choice(list("xyz"), rng.integers(1, 25))) for _ in range(300)]
    rows = [(t, 5 * k, 1000 * t + k, x) for t, text in enumerate(texts) for k, x in enumerate(text)]
    got = {}
    for r in clean.clean(src.literal_readings(spark, rows), 10).orderBy("tag", "t_first").collect():
        got.setdefault(r.tag, []).append(r.label)
    assert got == {t: plain_clean(text) for t, text in enumerate(texts)}


def test_strategies_agree(spark):
    delta = src.EVENTS.delta(1440)
    g = w.graph(spark, SF)
    base = {tuple(r) for r in g.edges.collect()}
    for strategy in ("bucket_join", "theta", "grouped"):
        assert {tuple(r) for r in build_edges(g.vertices, delta, strategy).collect()} == base
    orders = clean.vertices_of(w.readings_of(spark, SF, "orders"))  # with ties of time
    found = [{tuple(r) for r in build_edges(orders, src.ORDERS.delta(360), s).collect()} for s in ("window", "point", "bucket_join", "theta", "grouped")]
    assert all(f == found[0] for f in found) and found[0]


@pytest.mark.parametrize(("delta", "m", "want"), [(2880, 5, (703, 1973, 66700, 8152, 54)), (1440, 5, (732, 1197, 12778, 2602, 17)), (1440, 3, (732, 1197, 3907, 331, 16)), (720, 5, (823, 686, 3349, 889, 5)), (360, 5, (912, 386, 1591, 218, 1))])
def test_census(spark, delta, m, want):
    g = w.graph(spark, SF, delta)
    traces = enumeration.trace_counts(g, m)
    row = traces.agg(F.sum("n"), F.count(F.lit(1))).first()
    assert (g.vertices.count(), g.edges.count(), row[0], row[1], w.kth(traces).first()[0]) == want


def test_counts_agree(spark):
    g = w.graph(spark, SF)
    a, b = ({r.vid: list(r.c) for r in counts.count_paths(g, 4, s).collect()} for s in ("join", "grouped"))
    assert a == b
    by_start = {r.start_vid: r.n for r in enumeration.enumerate_traces(g, 4).groupBy("start_vid").agg(F.count(F.lit(1)).alias("n")).collect()}
    assert {v: c[4] for v, c in a.items()} == by_start
    assert all(c == sorted(c) for c in a.values())
    assert counts.total_paths(counts.count_paths(g, 4, direction="ending"), 4) == sum(by_start.values())


def test_set_based_equals_tag_local_after_repartitioning(spark):
    g = w.graph(spark, SF)
    c = counts.count_paths(g, 4)
    three = ["start_vid", "path_key", "trace"]
    a = {tuple(r) for r in sample.descend(g, c, 4, 0.1, 5).select(*three).collect()}
    other = LabeledDag(g.vertices.repartition(17), g.edges.repartition(13, "dst"), g.delta)
    assert a == {tuple(r) for r in sample.descend(other, c.repartition(5), 4, 0.1, 5).select(*three).collect()} == {tuple(r) for r in sample.sample_grouped(g, 4, 0.1, 5).collect()}
    assert len(a) > 100
    cost = {r.measure: r.value for r in sample.sampler_cost(sample.descend(g, c, 4, 0.1, 5)).collect()}
    assert cost["calls"] <= cost["sampled_length"]
    out = {r.src: r.n for r in g.edges.groupBy("src").agg(F.count(F.lit(1)).alias("n")).collect()}
    visits = {tuple(key.split("-")[:k]) for _, key, _ in a for k in range(1, min(3, len(key.split("-"))) + 1)}
    assert cost["edges_scanned"] == sum(out.get(int(v[-1]), 0) for v in visits)


def test_searches_on_prepared_sums(spark, monkeypatch):
    """The refined samplers draw the same by either search, joined or tag-local, sent or exchanged, and guides take fewer steps on large degrees."""
    three = ["start_vid", "path_key", "trace"]
    g = w.graph(spark, SF)
    c = counts.count_paths(g, 4).cache()
    ways = sample.prepare(g, c, 4, guides=True)
    drawn = {how: sample.hits(g, c, 4, 0.1, 5, how, ways).cache() for how in ("first_hit", "guide")}
    sets = [{tuple(r) for r in d.select(*three).collect()} for d in drawn.values()]
    assert sets[0] == sets[1] == {tuple(r) for r in sample.sample_grouped(g, 4, 0.1, 5, "guide").collect()} and len(sets[0]) > 100
    monkeypatch.setattr(sample, "BROADCAST_ROWS", 0)
    assert sets[0] == {tuple(r) for r in sample.hits(g, c, 4, 0.1, 5, "guide", ways).select(*three).collect()}
    assert {tuple(r) for r in sample.descend(g, c, 4, 0.1, 5).select(*three).collect()} == {tuple(r) for r in sample.sample_grouped(g, 4, 0.1, 5).collect()}
    n = 400
    v = spark.range(n + 1).selectExpr("id vid", "cast(id as string) label")
    star = LabeledDag.from_tables(v, spark.range(1, n + 1).selectExpr("0L src", "id dst"))
    counted = counts.count_paths(star, 2)
    steps = {how: sample.hits(star, counted, 2, 0.5, 1, how).agg(F.sum("draws"), F.sum("steps")).first() for how in ("first_hit", "guide")}
    assert steps["first_hit"][0] == steps["guide"][0] > 150
    assert steps["first_hit"][1] > 1400 and steps["guide"][1] < 700  # some 200 hits among 400 children


def test_sample_sizes(spark):
    g = w.graph(spark, SF)
    c = counts.count_paths(g, 4).cache()
    total, p = counts.total_paths(c, 4), 0.05
    for sampler in ("descend", "rank", "first_hit", "guide", "bernoulli_full"):
        n = sum(sample.sample_traces(g, c, 4, p, seed, sampler).count() for seed in range(3))
        assert abs(n - 3 * p * total) < 4 * math.sqrt(3 * total * p * (1 - p)), sampler
    every = sample.sample_traces(g, c, 4, 1.0, 1, "rank")
    assert every.exceptAll(enumeration.enumerate_traces(g, 4).select("start_vid", F.col("path").alias("path_key"), "trace")).count() == 0 and every.count() == total


@given(st.lists(st.integers(0, 12), max_size=300), st.integers(1, 8), st.integers(1, 6))
@settings(max_examples=200, deadline=None)
def test_summary_keeps_what_is_frequent(items, capacity, cuts):
    parts = [items[k::cuts] for k in range(cuts)]
    merged = frequent.DecrementSummary(capacity)
    for part in parts:
        one = frequent.DecrementSummary(capacity)
        for item, n in Counter(part).items():
            one.add(item, n)
        assert len(one.counters) <= capacity
        merged.merge(one.counters)
    true = Counter(items)
    assert len(merged.counters) <= capacity
    for item, n in true.items():
        assert n - len(items) / (capacity + 1) <= merged.counters.get(item, 0) <= n


def test_places_beyond_their_room_keep_their_key(spark):
    text = "a b " * 50_001
    ids = src.skipgram_readings(spark.createDataFrame([(1, text), (2, "c d")], "doc_id long, text string")).select("tag", "t_us", "seq")
    assert ids.select("seq").distinct().count() == ids.count() == 100_004
    turns = spark.createDataFrame([(1, 100_000, "user"), (1, 99_999, "user"), (2, 0, "user")], "conv_id long, turn long, role string")
    seqs = [r.seq for r in src.readings(turns, src.CONVERSATIONS).orderBy("tag", "t_us").collect()]
    assert seqs == [199_999, (1 << 62) + (1 << 32) + 100_000, 200_000]
    with pytest.raises(Exception, match="no id"):
        src.readings(spark.createDataFrame([(1, -1, "user")], "conv_id long, turn long, role string"), src.CONVERSATIONS).collect()
    rows = spark.sql("select 2000000L + id key, 1000000L + id place from range(3)").selectExpr(f"{src.place_id('key', 'place', 1_000_000)} id")
    assert [r.id for r in rows.collect()] == [(1 << 62) + (2_000_000 + k << 32) + 1_000_000 + k for k in range(3)]


def test_selection(spark):
    g = w.graph(spark, SF2)
    c = counts.count_paths(g, 3)
    s = sample.descend(g, c, 3, 10 / 186).cache()
    exact = {r.trace for r in frequent.candidates(s, 10).collect()}
    for method in ("decrement", "freqitems", "sketch"):
        assert exact <= {r.trace for r in frequent.candidates(s, 10, method).collect()}, method
    many = s.sparkSession.range(60_000).selectExpr("cast(id % 12000 as string) trace")
    for method in ("freqitems", "sketch"):
        assert frequent.candidates(many, 10, method).select("trace").distinct().count() == 12_000, method
    reported = frequent.second_pass(frequent.candidates(s, 10, "decrement"), "stored", 10, 10 / 186, s).collect()
    assert {r.trace for r in reported} == exact and min(r.n_sample for r in reported) >= 5
    items = frequent.frequent_items(s, "trace", 0.01).collect()
    n = s.count()
    assert {r.item for r in items} == {r.trace for r in frequent.sample_counts(s).where(F.col("n_sample") > 0.01 * n).collect()}
    truth = {r.trace: r.n for r in enumeration.trace_counts(g, 3).collect()}
    assert {r.trace: r.n for r in enumeration.count_candidates(g, s.select("trace").distinct(), 3).collect()} == {t: truth[t] for t in {r.trace for r in s.collect()}}


def test_mining(spark):
    g = w.graph(spark, SF2)
    exact = {r.trace for r in mine.mine_frequency(g, 3, min_count=186, method="exact").traces.collect()}
    found = mine.mine_frequency(g, 3, min_count=186, delta=0.02, verify="exact")
    assert {r.trace for r in found.traces.collect()} <= exact and found.traces.count() >= 0.9 * len(exact)
    assert found.plan.c == measures.choose_c(0.02, False) and found.measures["false_negative"] <= 0.02
    everything = mine.mine_frequency(g, 3, min_count=5, c=10)  # p = 1
    assert {r.trace: r.n_sample for r in everything.traces.collect()} == {r.trace: r.n for r in enumeration.trace_counts(g, 3).where("n >= 3").collect()}
    top = mine.mine_topk(g, 3, 10, c=60)
    quality = mine.topk_quality(enumeration.trace_counts(g, 3), top.traces.withColumnRenamed("n_sample", "n"), 10).first()
    assert quality.precision >= 0.6 and top.traces.count() == 10
    same = mine.topk_quality(enumeration.trace_counts(g, 3), enumeration.trace_counts(g, 3), 10).first()
    assert (same.precision, same.recall, same.rank_overlap) == (1.0, 1.0, 1.0)


def test_errors_follow_the_formula(spark):
    """Many seeds at sf0.001: a trace exactly at the threshold is missed as the binomial tail says."""
    g = w.graph(spark, SF)
    pieces = {}
    for r in g.pieces().collect():
        pieces.setdefault((r.tag, r.session), []).append((r.t_first, r.vid, r.t_last, r.label))
    import pyarrow as pa

    local = [Piece.of(pa.table(dict(zip(("t_first", "vid", "t_last", "label"), zip(*rows, strict=True), strict=True))), g.delta) for rows in pieces.values()]
    truth = sum((x.traces(3) for x in local), Counter())
    eps, c, seeds = 30, 6, 120
    p = c / eps
    near = [t for t, n in truth.items() if n == eps] or [min(truth, key=lambda t: abs(truth[t] - eps))]
    missed = 0
    for seed in range(seeds):
        seen = Counter(t for x in local for _, _, t in x.sample(3, p, seed))
        missed += sum(seen[t] <= c / 2 for t in near)
    want = sum(measures.fn_binomial(c, truth[t], p) for t in near) / len(near)
    n = seeds * len(near)
    assert abs(missed / n - want) < 4 * math.sqrt(want * (1 - want) / n) + 0.02


def test_error_table():
    printed = {3: (0.199, 0.173), 10: (0.0671, 0.0420), 15: (0.0180, 0.0376), 20: (0.0108, None), 30: (0.00195, None)}
    for c, (fn, sfp) in printed.items():
        assert measures.fn_probability(c) == pytest.approx(fn, rel=0.01)
        assert sfp is None or measures.sfp_probability(c) == pytest.approx(sfp, rel=0.01)
    assert measures.sfp_probability(20, False) == pytest.approx(0.0318, rel=0.01)
    assert measures.sfp_probability(30, False) == pytest.approx(0.0103, rel=0.01)
    assert measures.fn_probability(10, False) == pytest.approx(0.02925, rel=0.01)
    assert all(measures.fn_probability(c) <= measures.chernoff_bound(c) for c in (10, 20, 40))
    assert measures.choose_c(0.2) == 5 and measures.fn_binomial(10, 10**6, 1e-5) == pytest.approx(measures.fn_probability(10), rel=1e-3)


def test_savings_formulas():
    rows = [(365_818_472, 4_311_942, 168_000, 990, 21_775, 16_800), (106_678_064, 1_712_646, 52_951, 425, 20_147, 5_295), (6_196_850, 50_085, 9_458, 38.2, 6_552, 946), (66_947_355, 631_300, 42_008, 198, 15_937, 4_200), (23_152_990, 280_454, 15_363, 93, 15_070, 1_536)]
    for total, distinct, eps, space, samples, time in rows:
        assert measures.space_ratio(distinct, total, eps) == pytest.approx(space, rel=0.01)
        assert measures.expected_samples(10, total, eps) == pytest.approx(samples, rel=1e-3)
        assert measures.time_ratio(10, eps) == pytest.approx(time, rel=1e-3)


def test_graph_checks(spark):
    v, e = src.band_dag(spark, 16)
    assert (e.count(), dag_depth(LabeledDag.from_tables(v, e)), on_cycles(e)) == (42, 16, 0)
    bad = LabeledDag.from_tables(spark.createDataFrame([(1, "a"), (2, "b"), (2, "c"), (3, None)], "vid long, label string"), spark.createDataFrame([(1, 2), (2, 1), (1, 2), (3, 3), (9, 1), (1, 8)], "src long, dst long"))
    got = {r.check_name: r.n_bad for r in bad.validate().collect()}
    assert got == {"null_label": 1, "duplicate_vertex": 1, "duplicate_edge": 1, "loop": 1, "dangling_src": 1, "dangling_dst": 1, "on_a_cycle": got["on_a_cycle"]} and got["on_a_cycle"] >= 3
    with pytest.raises(ValueError):
        dag_depth(bad)


def test_slabs_change_nothing(spark):
    """However narrow the slabs, the graph is the same."""
    r, delta = w.readings_of(spark, SF), src.EVENTS.delta(1440)
    want_v, want_e = w.graph(spark, SF).vertices, w.graph(spark, SF).edges
    v = clean.clean(r, delta, width=1).cache()
    e = build_edges(v, delta, "window", width=1)
    assert v.exceptAll(want_v).count() == 0 == want_v.exceptAll(v).count()
    assert e.exceptAll(want_e).count() == 0 == want_e.exceptAll(e).count()
    a, b = sessions(v, delta, 1), sessions(v, delta, 10_000)
    assert a.exceptAll(b.select(*a.columns)).count() == 0


def test_sessions_hold_every_edge(spark):
    g = w.graph(spark, SF)
    s = sessions(g.vertices, g.delta).select("vid", "session", "tag")
    a, b = s.toDF("src", "s1", "t1"), s.toDF("dst", "s2", "t2")
    assert g.edges.join(a, "src").join(b, "dst").where("s1 != s2 or t1 != t2").count() == 0


def test_empty_graph(spark):
    g = LabeledDag.from_readings(src.literal_readings(spark, []), 10)
    assert enumeration.trace_counts(g, 3).count() == enumeration.trace_counts_grouped(g, 3).count() == 0
    c = counts.count_paths(g, 3)
    assert counts.total_paths(c, 3) == 0 and sample.descend(g, c, 3, 0.5).count() == 0 == sample.sample_ranks(g, c, 3, 0.5).count()


def test_readings_with_nulls_are_left_out(spark):
    rows = spark.createDataFrame([(1, 2, 3, "a"), (None, 2, 4, "a"), (1, None, 5, "a"), (1, 2, None, "a"), (1, 2, 6, None)], "a long, b long, c long, d string")
    assert src.readings(rows, src.SequenceSpec("a", "b", "c", "d", 1)).count() == 1


def test_overflow_stops_and_decimal_holds(spark):
    n = 70
    v = spark.range(n).select(F.col("id").alias("vid"), F.lit("x").alias("label"))
    e = spark.range(n).alias("a").join(spark.range(n).alias("b"), F.col("a.id") < F.col("b.id")).select(F.col("a.id").alias("src"), F.col("b.id").alias("dst"))
    g = LabeledDag.from_tables(v, e)
    wide = counts.count_paths(g, n, count_type="decimal").agg(F.sum(F.element_at("c", n + 1))).first()[0]
    assert wide == 2**n - 1
    with pytest.raises(Exception, match="(?i)overflow"):
        counts.count_paths(g, n).collect()


def test_plans(spark):
    """No Cartesian product, filters and columns at the scan, one exchange for the tag-local methods."""
    text = lambda df: df._jdf.queryExecution().executedPlan().toString()
    g = w.graph(spark, SF)
    for df in (counts.count_paths(g, 3), enumeration.trace_counts(g, 3), enumeration.enumerate_traces(g, 3), g.edges):
        assert "Cartesian" not in text(df) and "NestedLoop" not in text(df)
    e = spark.read.parquet(f"{SF}/events.parquet")
    plan = text(src.readings(e.where("ts < timestamp_ntz'2024-01-10 00:00:00'"), src.EVENTS))
    assert "LessThan(ts" in plan and "props" not in plan.split("ReadSchema")[1] and "value" not in plan.split("ReadSchema")[1]
    assert text(build_edges(w.readings_of(spark, SF).transform(clean.vertices_of), 10, "point")).count("Exchange hashpartitioning") == 1


def test_bucketed_counts_need_no_exchange(spark):
    counted = w.sink_bucketed(spark, SF)
    assert "Exchange" not in counted._jdf.queryExecution().executedPlan().toString()
    assert counted.count() > 0


def test_registered_names():
    import __spark_entry__ as entry

    assert set(entry.oracle_sql()) <= set(entry.queries())
    assert len(entry.queries()) >= 118


def test_labels_with_the_separator_are_refused(spark):
    with pytest.raises(Exception, match="a label holds"):
        src.readings(spark.createDataFrame([(1, 1, 1, "a>b")], "t long, u long, s long, l string"), src.SequenceSpec("t", "u", "s", "l")).collect()
    v = spark.createDataFrame([(1, "a"), (2, "b>c")], "vid long, label string")
    with pytest.raises(Exception, match="a label holds"):
        enumeration.trace_counts(LabeledDag.from_tables(v, spark.createDataFrame([(1, 2)], "src long, dst long")), 2).collect()


@pytest.mark.parametrize("tasks", [1, 7])
def test_merged_summaries_keep_what_is_frequent(spark, tasks):
    items = spark.range(30_000).selectExpr("cast(case when id % 3 = 0 then 'hot' when id % 5 = 0 then concat('w', id % 20) else cast(id as string) end as string) x").repartition(tasks)
    got = {r.item: r.n for r in frequent.decrement_summary(items, "x", 9).collect()}
    assert len(got) <= 9 and 10_000 - 3_000 <= got["hot"] <= 10_000
    assert frequent.decrement_summary(items, "x", 9).agg(F.max("most")).first()[0] <= 9
    counted = items.withColumn("day", F.crc32(F.col("x").cast("binary")) % 4).groupBy("day", F.col("x").alias("trace")).agg(F.count(F.lit(1)).alias("n"))
    days = {r.item: r.n for r in frequent.summary_of_parts(counted, "day", 9).collect()}
    assert len(days) <= 9 and 7_000 <= days["hot"] <= 10_000


def test_stored_tables_are_deleted_at_the_end_of_a_block(spark):
    import os

    from pathtraces.plans import storage

    def there(path):
        return os.path.exists(path.removeprefix("file:"))

    before = storage.materialise(spark.range(3), "kept")
    kept = storage._written[-1][-1]
    with storage.released():
        assert storage.materialise(spark.range(5), "gone").count() == 5
        gone = storage._written[-1][-1]
        assert there(gone)
    assert not there(gone) and there(kept) and before.count() == 3


def test_second_collapse_by_session_equals_the_one_by_slabs(spark):
    import random

    draw = random.Random(5)
    rows = [(tag, t, 1000 * tag + k, draw.choice(["x", "y", "x*y"])) for tag in range(6) for k, t in enumerate(sorted(draw.randrange(900) for _ in range(300)))]
    r = src.literal_readings(spark, rows)
    joined = 0
    for delta, width in ((1, 1), (3, 2), (20, 32)):
        units = clean.merge_overlaps(clean.vertices_of(r), delta, width=width)
        slabs = sorted(map(tuple, clean.collapse_runs(units, delta, width).collect()))
        assert sorted(map(tuple, clean.clean(r, delta, width=width).collect())) == slabs
        joined += units.count() - len(slabs)
    assert joined > 0  # a reading's own label beside an equal overlap


def test_recursive_paths_beyond_sparks_limit_of_rows(spark):
    limit = "spark.sql.cteRecursionRowLimit"
    before = spark.conf.get(limit)
    spark.conf.set(limit, "50")
    try:
        found = {tuple(r) for r in w.QUERIES["sql_recursive_paths"](spark, SF).collect()}
        assert spark.conf.get(limit) == "50"
    finally:
        spark.conf.set(limit, before)
    assert found == {(r.trace, r.len, r.n) for r in enumeration.trace_counts(w.graph(spark, SF), w.M).collect()}


def test_skip_pairs_without_a_graph_equal_the_graph(spark):
    import random

    draw = random.Random(3)
    docs = spark.createDataFrame([(k, " ".join(draw.choices("abcd", k=draw.randrange(12)))) for k in range(200)] + [(300, None), (301, "4 5"), (302, "x x x")], "doc_id long, text string")
    for reach in (1, 2, 4):
        g = LabeledDag.from_readings(src.skipgram_readings(docs), reach, "collapse")
        found = enumeration.skip_pair_counts(docs.select(src.words_of().alias("words")), "words", reach)
        assert {tuple(r) for r in found.collect()} == {(r.trace, r.n) for r in enumeration.trace_counts(g, 2).collect()}


def test_skipgrams_of_documents_need_no_stored_graph(spark, tmp_path, monkeypatch):
    stored = []
    monkeypatch.setattr("pathtraces.operators.dag.materialise", lambda df, name: stored.append(name) or df)
    docs = spark.createDataFrame([(k, "a b") for k in range(60)], "doc_id long, text string")
    docs.write.parquet(f"{tmp_path}/documents.parquet")
    assert {tuple(r) for r in w.QUERIES["document_skipgram_traces"](spark, str(tmp_path)).collect()} == {("a", 60), ("b", 60), ("a>b", 60)} and not stored
    docs.unionByName(docs.where("doc_id = 0").withColumn("text", F.lit("c"))).write.mode("overwrite").parquet(f"{tmp_path}/documents.parquet")
    assert {tuple(r) for r in w.QUERIES["document_skipgram_traces"](spark, str(tmp_path)).collect()} >= {("b", 60)} and set(stored) == {"vertices", "edges"}


def test_examples_and_tables_read_what_is_there(spark, tmp_path):
    spark.createDataFrame([(k, 1, "AB"[k % 2]) for k in range(4)], "c_custkey long, c_nationkey long, c_mktsegment string").write.parquet(f"{tmp_path}/customer.parquet")
    spark.createDataFrame([(1,)] * 3 + [(2,)] * 3 + [(3,)] * 5, "user_id long").write.parquet(f"{tmp_path}/events.parquet")
    rows = {q: sorted(map(tuple, w.QUERIES[q](spark, str(tmp_path)).collect())) for q in ("example_sequence", "example_browsing", "example_band", "error_table", "choose_c_table")}
    assert rows["example_sequence"] == [("A*B", 1)]  # alternating labels are an overlap
    assert rows["example_browsing"][:3] == [(1, 4, 2), (2, 9, 6), (3, 13, 10)]
    assert [r[1] for r in rows["example_band"][:3]] == [4, 10, 14] and {r[1] for r in rows["example_band"][3:]} == {15}
    assert [(r[0], r[-1]) for r in rows["error_table"]] == [(3, 2), (5, 1)] and rows["error_table"][1][1] == round(measures.fn_probability(5), 6)
    assert rows["choose_c_table"] == [(1 / 6, measures.choose_c(1 / 6)), (1 / 4, measures.choose_c(1 / 4))]
