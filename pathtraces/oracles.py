"""DuckDB SQL for the queries, built from parts: readings, cleaning, edges, counts, paths, seeded samples.

Each part is a list of common table expressions over the ones before. Nothing here is run by Spark."""

from __future__ import annotations

from pathtraces.functions import measures
from pathtraces.functions.columns import BASES, PRIMES
from pathtraces.sources.readings import DAY, MINUTE

READINGS = {
    "events": "select user_id as tag, epoch_us(ts) as t_us, event_id as seq, event_type as label from events",
    "fine": "select user_id as tag, epoch_us(ts) as t_us, event_id as seq, event_type || '.' || floor((props->>'$.k')::int / 10)::int::varchar as label from events",
    "orders": "select o_custkey as tag, epoch_us(o_orderdate) as t_us, o_orderkey as seq, o_orderpriority as label from orders",
    "lineitem": "select l_partkey as tag, epoch_us(l_shipdate) as t_us, l_partkey * 1000000 + row_number() over (partition by l_partkey order by l_shipdate, l_orderkey, l_linenumber, l_suppkey, l_returnflag, l_linestatus) as seq, l_returnflag || l_linestatus as label from lineitem",
    "conversations": "select conv_id as tag, turn as t_us, conv_id * 100000 + turn as seq, role as label from conversations where role is not null",
    "pages": "select ascii(l[1]) * 256 + ascii(l[2]) as tag, page_id as t_us, page_id as seq, host as label from (select page_id, regexp_extract(url, '^https?://[^/]+/([a-z]{2})/', 1) as l, regexp_extract(url, '^https?://([^/]+)/', 1) as host from pages) where l <> ''",
    "words": "select doc_id as tag, i - 1 as t_us, doc_id * 100000 + i - 1 as seq, w[i] as label from (select doc_id, regexp_extract_all(lower(text), '[a-z]+') as w from documents), unnest(range(1, len(w) + 1)) as u(i)",
}
UNIT = {"events": MINUTE, "fine": MINUTE, "orders": DAY, "lineitem": DAY, "conversations": 1, "pages": 1, "words": 1}


def merged(source: str, out: str, delta: int) -> str:
    """Neighbours of one label, at most delta apart, as one row; ``run`` numbers them by tag."""
    return f"""
    {out}_a as (select *, coalesce(lag(label) over w <> label or t_first - lag(t_last) over w > {delta}, true)::int as starts from {source} window w as (partition by tag order by t_first, vid)),
    {out}_b as (select *, sum(starts) over (partition by tag order by t_first, vid) as run from {out}_a),
    {out} as (select first(vid order by t_first, vid) as vid, tag, min(t_first) as t_first, max(t_last) as t_last, first(label) as label, sum(n_readings)::int as n_readings, run from {out}_b group by tag, run)"""


def vertices(source: str = "events", delta: float = 1440, mode: str = "full", where: str = "", out: str = "v", rd: str | None = None) -> str:
    """CTEs that end in ``out``."""
    d = round(delta * UNIT[source])
    raw = f"""
    {out}_rd as ({rd or READINGS[source]}),
    {out}_raw as (select seq as vid, tag, t_us as t_first, t_us as t_last, label, 1 as n_readings from {out}_rd{' where ' + where if where else ''})"""
    columns = "vid, tag, t_first, t_last, label, n_readings"
    if mode == "raw":
        return raw + f", {out} as (select {columns} from {out}_raw)"
    raw += "," + merged(f"{out}_raw", f"{out}_runs", d)
    if mode == "collapse":
        return raw + f", {out} as (select {columns} from {out}_runs)"
    return (
        raw
        + f""",
    {out}_alt as (select tag, run, coalesce(label = lag(label, 2) over w and label <> lag(label, 1) over w and t_first - lag(t_last, 1) over w <= {d} and lag(t_first, 1) over w - lag(t_last, 2) over w <= {d}, false) as alt from {out}_runs window w as (partition by tag order by run)),
    {out}_isl as (select tag, run, run - row_number() over (partition by tag order by run) as island from {out}_alt where alt),
    {out}_str as (select tag, min(run) - 2 as s, max(run) as e, row_number() over (partition by tag order by min(run)) as k from {out}_isl group by tag, island),
    {out}_fold as (
      select tag, k, case when e - s + 1 >= 4 then s end as cs, case when e - s + 1 >= 4 then s + 2 * ((e - s + 1) // 2) - 1 else -1 end as last from {out}_str where k = 1
      union all
      select n.tag, n.k, case when n.e - greatest(n.s, f.last + 1) + 1 >= 4 then greatest(n.s, f.last + 1) end, case when n.e - greatest(n.s, f.last + 1) + 1 >= 4 then greatest(n.s, f.last + 1) + 2 * ((n.e - greatest(n.s, f.last + 1) + 1) // 2) - 1 else f.last end
      from {out}_fold f join {out}_str n on n.tag = f.tag and n.k = f.k + 1),
    {out}_cons as (select tag, cs, last as ce from {out}_fold where cs is not null),
    {out}_unit as (select r.*, c.cs from {out}_runs r left join {out}_cons c on c.tag = r.tag and r.run between c.cs and c.ce),
    {out}_over as (select first(vid order by run) as vid, tag, min(t_first) as t_first, max(t_last) as t_last, case when max(cs) is null then first(label) else min(label) || '*' || max(label) end as label, sum(n_readings)::int as n_readings from {out}_unit group by tag, coalesce(cs, run)),"""
        + merged(f"{out}_over", f"{out}_again", d)
        + f", {out} as (select {columns} from {out}_again)"
    )


def edges(delta: float = 1440, source: str = "events", v: str = "v", out: str = "e", more: str = "") -> str:
    d = round(delta * UNIT[source])
    return f", {out} as (select a.vid as src, b.vid as dst, a.label as src_label, b.label as dst_label from {v} a join {v} b on a.tag = b.tag and (b.t_first > a.t_first or (b.t_first = a.t_first and b.vid > a.vid)) and b.t_first - a.t_last <= {d} and a.label <> b.label{more})"


def counts(m: int, v: str = "v", e: str = "e", out: str = "c", ending: bool = False) -> str:
    """``vid``, c0 ... cm."""
    near, far = ("dst", "src") if ending else ("src", "dst")
    parts = [f", {out}1 as (select vid, 0::bigint as c0, 1::bigint as c1 from {v})"]
    for i in range(2, m + 1):
        before = ", ".join(f"p.c{k}" for k in range(i))
        parts.append(f", {out}{i} as (select p.vid, {before}, (coalesce(s.n, 0) + 1)::bigint as c{i} from {out}{i - 1} p left join (select {near} as vid, sum(q.c{i - 1}) as n from {e} join {out}{i - 1} q on q.vid = {far} group by {near}) s on s.vid = p.vid)")
    return "".join(parts) + f", {out} as (select * from {out}{m})"


def paths(m: int, v: str = "v", e: str = "e", out: str = "p", start: str = "") -> str:
    """Every path: start_vid, end_vid, path, trace, len."""
    return f""", {out} as (
      select vid as start_vid, vid as end_vid, vid::varchar as path, label as trace, 1 as len from {v}{' where ' + start if start else ''}
      union all
      select p.start_vid, x.dst, p.path || '-' || x.dst::varchar, p.trace || '>' || x.dst_label, p.len + 1 from {out} p join {e} x on x.src = p.end_vid where p.len < {m})"""


def suffixes(m: int, v: str = "v", e: str = "e", out: str = "tc") -> str:
    """Counts by trace, by suffixes: trace, n, len."""
    parts = [f", {out}_1 as (select vid, label as trace, 1::bigint as n from {v})"]
    parts += [f", {out}_{i} as (select src as vid, src_label || '>' || s.trace as trace, sum(s.n)::bigint as n from {e} join {out}_{i - 1} s on s.vid = dst group by src, src_label || '>' || s.trace)" for i in range(2, m + 1)]
    union = " union all ".join(f"select trace, n, {i} as len from {out}_{i}" for i in range(1, m + 1))
    return "".join(parts) + f", {out} as (select trace, len, sum(n)::bigint as n from ({union}) group by trace, len)"


def with_(*parts: str, select: str) -> str:
    return "with recursive " + ", ".join(p.strip().removeprefix(",") for p in parts if p.strip()) + " " + select


def graph(delta: float = 1440, source: str = "events", mode: str = "full") -> str:
    return vertices(source, delta, mode) + edges(delta, source)


def u(seed: int, *key: str) -> str:
    text = " || '|' || ".join([f"'{seed}'", *(f"{k}::varchar" if not k.startswith("'") else k for k in key)])
    return f"((('0x' || substr(md5({text}), 1, 13))::bigint + 0.5) / 4503599627370496.0)"


def some(p: str, n: str) -> str:
    """Chance that any of n is drawn. DuckDB has no expm1; the direct form is exact enough for the p used here."""
    return f"(1 - pow(1 - {p}, {n}))"


def sample(m: int, p: str, seed: int = 42, out: str = "s", printed: bool = False) -> str:
    """The seeded descent, level by level: ``out`` (start_vid, path_key, trace). Needs v, e, c. ``printed``: by the published rule."""
    parts = [f", {out}f{m} as (select vid as start_vid, vid as at, vid::varchar as path_key, label as trace, c{m} as total from v join c using (vid) where {u(seed, repr('root'), 'vid')} < {some(p, f'c{m}')})"]
    for i in range(m, 0, -1):
        child = f"c.c{i - 1}"
        parts.append(f""", {out}h{i} as (select f.*, e.dst, e.dst_label, coalesce({child}, 0) as n, f.total - coalesce(sum(coalesce({child}, 0)) over (partition by f.path_key order by e.dst rows between unbounded preceding and 1 preceding), 0) as rest, {u(seed, repr('child'), 'f.path_key', 'e.dst')} as u
          from {out}f{i} f left join e on e.src = f.at left join c on c.vid = e.dst),
        {out}i{i} as (select *, n > 0 and u < {some(p, 'n')} / {some(p, 'rest')} as hit from {out}h{i}),
        {out}j{i} as (select *, coalesce(max(hit::int) over (partition by path_key order by dst rows between unbounded preceding and 1 preceding), 0) = 1 as found from {out}i{i}),
        {out}k{i} as (select *, coalesce({f"n > 0 and u > least(1.0, pow(1 - {p}, n) / {some(p, 'total')})" if printed else f"n > 0 and ((not found and hit) or (found and u < {some(p, 'n')}))"}, false) as taken from {out}j{i}),
        {out}o{i} as (select start_vid, path_key, trace from {out}k{i} group by start_vid, path_key, trace having not bool_or(taken) or {u(seed, repr('self'), 'path_key')} < {p})""")
        if i > 1:
            parts.append(f", {out}f{i - 1} as (select start_vid, dst as at, path_key || '-' || dst::varchar as path_key, trace || '>' || dst_label as trace, n as total from {out}k{i} where taken)")
    union = " union all ".join(f"select * from {out}o{i}" for i in range(1, m + 1))
    return "".join(parts) + f", {out} as ({union})"


def _gap(u: str, p: str) -> str:
    """Elements passed over before the next one drawn."""
    return f"case when {p} >= 1 then 0 else floor(ln(1 - {u}) / ln(1 - least({p}, 0.999999999999)))::bigint end"


def _lines(m: int) -> str:
    """``kid`` (level, src, dst, label, low, high): children on a vertex's line of weight."""
    levels = " union all ".join(f"select {i} as level, src, dst, dst_label, c.c{i - 1} as n from e join c on c.vid = e.dst" for i in range(2, m + 1))
    return f", kid as materialized (select level, src, dst, dst_label, sum(n) over w - n as low, (sum(n) over w)::bigint as high from ({levels}) window w as (partition by level, src order by dst rows unbounded preceding))"


def first_hits(m: int, p: str, seed: int = 42, out: str = "s") -> str:
    """The draws of the refined samplers: a cursor for each visited vertex hops from hit to hit; a hit child is a new cursor. Needs v, c, e."""
    total = "case level " + " ".join(f"when {i} then c.c{i}" for i in range(1, m + 1)) + " end"
    u_ = f"{u(seed, repr('hit'), 'path_key', 'turn')} * case when turn = 0 then {some(p, 'total')} else 1 end"
    return _lines(m) + f""", {out}w as (
      select {m} as level, vid as start_vid, vid as place, vid::varchar as path_key, label as trace, c{m} as total, 0 as turn, 0::bigint as pos, false as own from v join c using (vid) where {u(seed, repr('root'), 'vid')} < {some(p, f'c{m}')}
      union all
      select * from (
        with far as (select *, pos + {_gap(u_, p)} as far from {out}w where not own and pos < total),
        hit as (select far.*, kid.dst, kid.dst_label, kid.high from far left join kid on kid.level = far.level and kid.src = far.place and far.far >= kid.low and far.far < kid.high where far.far < far.total)
        select level, start_vid, place, path_key, trace, total, turn, pos, true from hit where dst is null
        union all
        select level, start_vid, place, path_key, trace, total, turn + 1, high, false from hit where dst is not null
        union all
        select level - 1, start_vid, dst, path_key || '-' || dst::varchar, trace || '>' || dst_label, high - (select low from kid k where k.level = hit.level and k.src = hit.place and k.dst = hit.dst), 0, 0, false from hit where dst is not null)),
    {out} as (select start_vid, path_key, trace from {out}w where own)"""


def ranked(m: int, p: str, seed: int = 42, out: str = "s") -> str:
    """Numbers drawn among the paths of a start vertex, each resolved level by level. Needs v, c, e."""
    u_ = f"{u(seed, repr('rank'), 'vid', 'turn')} * case when turn = 0 then {some(p, 'total')} else 1 end"
    parts = f""", {out}r as (
      select vid, c{m} as total, 0 as turn, {_gap(u_.replace('turn', '0').replace('total', f'c{m}'), p)} as pos from c where {u(seed, repr('root'), 'vid')} < {some(p, f'c{m}')}
      union all
      select vid, total, turn, pos + 1 + {_gap(u_, p)} as pos from (select vid, total, turn + 1 as turn, pos from {out}r) where pos + 1 < total),
    {out}{m} as (select v.vid as start_vid, v.vid as place, v.vid::varchar as path_key, label as trace, pos from {out}r join v on v.vid = {out}r.vid where pos < total)"""
    for i in range(m, 1, -1):
        parts += f", {out}{i - 1} as (select start_vid, coalesce(dst, place) as place, case when dst is null then path_key else path_key || '-' || dst::varchar end as path_key, case when dst is null then trace else trace || '>' || dst_label end as trace, case when dst is null then pos else pos - 1 - low end as pos from {out}{i} left join kid on kid.level = {i} and kid.src = place and pos > 0 and pos - 1 >= low and pos - 1 < high)"
    return _lines(m) + parts + f", {out} as (select start_vid, path_key, trace from {out}1)"


def hashes(m: int, trace: bool = False) -> str:
    """Rolling hashes of every path: h (h1, h2[, trace])."""
    codes = ", lc as (select label, row_number() over (order by label) as code from (select distinct label from v))"
    step = lambda h, k: f"({h} * {BASES[k]} + code) % {PRIMES[k]}"
    return codes + f""", hv as (select vid, label, code from v join lc using (label)), h as (
      select vid as at, {step('0::bigint', 0)} as h1, {step('0::bigint', 1)} as h2, label as trace, 1 as len from hv
      union all
      select e.dst, {step('h.h1', 0)}, {step('h.h2', 1)}, h.trace || '>' || hv.label, h.len + 1 from h join e on e.src = h.at join hv on hv.vid = e.dst where h.len < {m})"""


def values(rows: list[tuple], columns: str) -> str:
    """Constant rows."""

    def text(x) -> str:
        return f"'{x}'" if isinstance(x, str) else f"{x!r}::double" if isinstance(x, float) else f"{x}::bigint"

    return f"select * from (values {', '.join('(' + ', '.join(map(text, r)) + ')' for r in rows)}) as t({columns})"


def error_table(of: str = "(values (3), (5), (10), (15), (20), (30)) as v(c)", more: str = "") -> str:
    """Poisson tails, summed term by term."""
    tail = lambda mean, last: f"(select coalesce(sum(exp(-({mean}) + i * ln({mean}) - lgamma(i + 1))), 0) from range(0, ({last})::bigint + 1) as t(i))"
    strict, loose = "floor(c / 2.0)", "ceil(c / 2.0) - 1"
    return f"select c::bigint as c, round({tail('c', strict)}, 6) as fn_prob, round(1 - {tail('c / 4.0', strict)}, 6) as sfp_prob, round({tail('c', loose)}, 6) as fn_at_least, round(1 - {tail('c / 4.0', loose)}, 6) as sfp_at_least{more} from {of}"


def error_rows(cs: tuple[int, ...] = (3, 5, 10, 15, 20, 30)) -> list[tuple]:
    return [(c, round(measures.fn_probability(c), 6), round(measures.sfp_probability(c), 6), round(measures.fn_probability(c, False), 6), round(measures.sfp_probability(c, False), 6)) for c in cs]
