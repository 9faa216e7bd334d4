"""Frequent traces and top-k, exactly or by sampling."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pathtraces.functions import measures
from pathtraces.operators.counts import count_paths, total_paths
from pathtraces.operators.dag import LabeledDag, dag_depth
from pathtraces.operators.enumeration import count_candidates, trace_counts
from pathtraces.operators.frequent import candidates, sample_counts, second_pass, with_estimates
from pathtraces.operators.sample import SamplingPlan, plan_sampling, prepare, sample_seeds, sample_traces
from pathtraces.plans.storage import materialise


@dataclass(frozen=True)
class MiningResult:
    traces: DataFrame
    plan: SamplingPlan | None = None
    measures: dict = field(default_factory=dict)


def exact_frequency(g: LabeledDag, m: int, min_count: float | None = None, min_support: float | None = None, min_len: int = 1) -> DataFrame:
    """``trace``, ``n``, ``support``."""
    every = materialise(trace_counts(g, m, min_len), "traces")
    total = every.agg(F.coalesce(F.sum("n"), F.lit(0)).alias("total"))
    floor = F.lit(min_count) if min_count is not None else F.lit(min_support) * F.col("total")
    return every.crossJoin(F.broadcast(total)).where(F.col("n") >= floor).select("trace", "n", F.round(F.col("n") / F.col("total"), 12).alias("support"))


def mine_frequency(g: LabeledDag, m: int | None, min_count: float | None = None, min_support: float | None = None, method: str = "sample", c: float | None = None, delta: float | None = None, seed: int = 42, sampler: str = "descend", strategy: str = "join", summary: str = "exact", verify: str = "stored", strict: bool = False) -> MiningResult:
    """Traces of at least ``min_count`` occurrences, or that share of all. ``c`` or ``delta`` (error probability) sets the sample's size;
    ``m=None`` is any length. By sampling, a trace of exactly the threshold is missed with about the probability that ``measures`` states."""
    m = max(1, dag_depth(g)) if m is None else m
    if method == "exact":
        return MiningResult(exact_frequency(g, m, min_count, min_support))
    c = c if c is not None else measures.choose_c(delta, strict) if delta is not None else 10
    counts = materialise(count_paths(g, m, "grouped" if strategy == "grouped" else "join"), "counts")
    plan = plan_sampling(counts, m, c, min_count, min_support)

    ways = prepare(g, counts, m, sampler == "guide") if strategy == "join" and sampler != "bernoulli_full" else None

    def draw(seed_: int) -> DataFrame:
        return sample_traces(g, counts, m, plan.p, seed_, sampler, strategy, ways, plan.expected_samples)

    sample = materialise(draw(seed), "sample")
    found = materialise(candidates(sample, plan.p * plan.min_count, summary, strict=strict), "found")
    effective = plan.p * plan.min_count  # C, or the threshold itself if everything is taken
    if verify == "none":
        traces = with_estimates(sample_counts(sample).join(found.select("trace"), "trace", "left_semi"), plan.p).select("trace", "n_sample", "n_est")
    else:
        again = {"stored": lambda: sample, "replay": lambda: draw(seed), "fresh": lambda: draw(seed + 1), "exact": lambda: None}[verify]()
        traces = second_pass(found, verify, effective, plan.p, again, g, m, strict)
    return MiningResult(traces, plan, {"false_negative": measures.fn_probability(c, strict), "significant_false_positive": measures.sfp_probability(c, strict)})


def exact_topk(g: LabeledDag, m: int, k: int, min_len: int = 1) -> DataFrame:
    """``trace``, ``n``, ``support``; ties by text."""
    return exact_frequency(g, m, min_count=1, min_len=min_len).orderBy(F.desc("n"), "trace").limit(k)


def mine_topk(g: LabeledDag, m: int, k: int, method: str = "sample", c: float = 10, seed: int = 42, sampler: str = "descend", strategy: str = "join", verify: str = "none") -> MiningResult:
    """The k most frequent traces; ties by text. By sampling: a pilot of about 50 k samples estimates the k-th count, the main round
    takes p from that, lowered by its error. If fewer than k traces pass, the threshold is halved, until everything is drawn: so fewer than k are returned only where
    there are fewer. ``verify="exact"`` counts all that passed in the graph and ranks them by that: then the result is the true one unless a trace of the first k was
    missed, for each of which ``measures`` bounds the probability."""
    if method == "exact":
        return MiningResult(exact_topk(g, m, k))
    counts = materialise(count_paths(g, m, "grouped" if strategy == "grouped" else "join"), "counts")
    total = total_paths(counts, m)
    ways = prepare(g, counts, m, sampler == "guide") if strategy == "join" and sampler != "bernoulli_full" else None

    def drawn(p: float, seed_: int) -> DataFrame:
        return sample_counts(sample_traces(g, counts, m, p, seed_, sampler, strategy, ways, p * total))

    p = min(1.0, 50 * k / max(total, 1))
    pilot = drawn(p, seed + 1).orderBy(F.desc("n_sample"), "trace").limit(k).agg(F.min("n_sample"), F.count(F.lit(1))).first()
    least = pilot[0] or 1
    threshold = max(1.0, (least - least**0.5) / p)
    while True:
        plan = SamplingPlan(total, threshold, c, measures.choose_p(c, threshold))
        passed = materialise(drawn(plan.p, seed).where(F.col("n_sample") >= measures.least_reported(plan.p * threshold, False)), "passed")
        n_passed = passed.limit(k).count()
        if plan.p >= 1 or n_passed >= k:
            break
        threshold = max(1.0, threshold / 2)
    told = {"false_negative": measures.fn_probability(c), "shortfall": k - n_passed}
    if verify == "exact":
        return MiningResult(count_candidates(g, passed, m).orderBy(F.desc("n"), "trace").limit(k), plan, told)
    return MiningResult(with_estimates(passed.orderBy(F.desc("n_sample"), "trace").limit(k), plan.p), plan, told)


def topk_quality(truth: DataFrame, reported: DataFrame, k: int) -> DataFrame:
    """``k``, ``precision``, ``recall``, ``rank_overlap`` (mean share of common traces among the first 1, 2, ..., k)."""
    from pyspark.sql import Window

    order = Window.orderBy(F.desc("n"), "trace")  # k rows
    a = truth.select("trace", "n").orderBy(F.desc("n"), "trace").limit(k).select("trace", F.row_number().over(order).alias("ra"))
    b = reported.select("trace", "n").orderBy(F.desc("n"), "trace").limit(k).select("trace", F.row_number().over(order).alias("rb"))
    both = a.join(b, "trace")
    sizes = a.agg(F.count(F.lit(1)).alias("na")).crossJoin(b.agg(F.count(F.lit(1)).alias("nb")))
    hits = both.agg(F.count(F.lit(1)).alias("hits"), F.sum(F.aggregate(F.sequence(F.greatest("ra", "rb"), F.lit(k)), F.lit(0.0), lambda s, d: s + 1.0 / d)).alias("overlap"))
    return sizes.crossJoin(hits).select(F.lit(k).alias("k"), F.round(F.col("hits") / F.col("nb"), 6).alias("precision"), F.round(F.col("hits") / F.col("na"), 6).alias("recall"), F.round(F.coalesce("overlap", F.lit(0.0)) / k, 6).alias("rank_overlap"))


def empirical_error(g: LabeledDag, m: int, min_count: int, cs: list[float], seeds: int, strict: bool = True) -> DataFrame:
    """``c``, ``seeds``, ``fn_rate`` (over traces at or above the threshold), ``sfp_rate`` (over traces below a quarter of it), ``n_samples`` (mean); beside them
    ``fn_expected`` and ``sfp_expected``, the means over the same traces of what the binomial distribution says of each one's count, and ``fn_formula``, ``sfp_formula``, for traces
    exactly at the threshold and at a quarter of it."""
    spark = g.vertices.sparkSession
    truth = materialise(trace_counts(g, m).select("trace", "n"), "truth")
    high, low = F.col("n") >= min_count, F.col("n") < min_count / 4
    by_count = truth.groupBy("n").agg(F.count(F.lit(1)).alias("times")).where(high | low).collect()  # one row for each distinct count
    # drawn once for the largest C; smaller ones are part of that
    ps = [measures.choose_p(c, min_count) for c in cs]
    drawn = sample_seeds(g, m, max(ps), list(range(1000, 1000 + seeds)))
    counted = drawn.groupBy("seed", "trace").agg(*[F.sum((F.col("u") < p / max(ps)).cast("long")).alias(f"n{k}") for k, p in enumerate(ps)])
    seen = counted.groupBy("trace").agg(*[F.sum((F.col(f"n{k}") >= measures.least_reported(c, strict)).cast("long")).alias(f"times{k}") for k, c in enumerate(cs)], *[F.sum(f"n{k}").alias(f"n{k}") for k in range(len(cs))])
    all_ = truth.join(seen, "trace", "left")
    told = []
    for k in range(len(cs)):
        share = F.coalesce(F.col(f"times{k}"), F.lit(0)) / F.lit(seeds)
        told += [F.avg(F.when(high, 1 - share)).alias(f"fn{k}"), F.avg(F.when(low, share)).alias(f"sfp{k}"), (F.coalesce(F.sum(f"n{k}"), F.lit(0)) / F.lit(seeds)).alias(f"n{k}")]
    r = all_.agg(*told).first()
    rows = []
    for k, (c, p) in enumerate(zip(cs, ps, strict=True)):
        means = []
        for side, missed in ((lambda n: n >= min_count, True), (lambda n: n < min_count / 4, False)):
            tails = [(measures.fn_binomial(c, x.n, p, strict), x.times) for x in by_count if side(x.n)]
            means.append(sum((q if missed else 1 - q) * t for q, t in tails) / max(1, sum(t for _, t in tails)))
        rows.append((float(c), seeds, r[f"fn{k}"], r[f"sfp{k}"], float(r[f"n{k}"]), *means, measures.fn_probability(c, strict), measures.sfp_probability(c, strict)))
    return spark.createDataFrame(rows, "c double, seeds int, fn_rate double, sfp_rate double, n_samples double, fn_expected double, sfp_expected double, fn_formula double, sfp_formula double")
