"""The same results in SQL, for comparison."""

from __future__ import annotations

from .queries import LAMBDA, LR, K, M, N, W
from .sources import gradients as G

QTR = f"""m as (select (year(l_shipdate) - 1995) * 4 + quarter(l_shipdate) - 1 as step, cast(l_orderkey % {W} as integer) as worker,
 s_nationkey as i, p_size - 1 as j, sum(l_quantity) as v
 from lineitem join supplier on l_suppkey = s_suppkey join part on l_partkey = p_partkey group by all)"""
CELL = "round(v, 4) + 0.0 as v"


def hex32(s: str) -> str:
    return f"cast('0x' || substr(md5({s}), 1, 8) as bigint)"


def normal(s: str) -> str:
    return f"sqrt(-2 * ln(({hex32(f'{s} || chr(58) || chr(97)')} + 1) / 4294967297.0::double)) * cos(2 * pi() * ({hex32(f'{s} || chr(58) || chr(98)')} / 4294967296.0::double))"


def start(rank: int, step: str = "0", scale: float = 1.0) -> str:
    label = f"'0:{step}:' || j || ':' || c"
    return f"q0 as (select cast(j as integer) as j, cast(c as integer) as c, {normal(label)} * {scale} as q from range({M}) a(j), range({rank}) b(c))"


def sweep(rank: int, cold: bool = False) -> str:
    if cold:
        label = "'0:' || step || ':' || j || ':' || c"
        begin = f"q0 as (select step, cast(j as integer) as j, cast(c as integer) as c, {normal(label)} as q from (select distinct step from m), range({M}) a(j), range({rank}) b(c))"
    else:
        begin = start(rank)
    on = "m.j = q0.j" + (" and m.step = q0.step" if cold else "")
    parts = [QTR, begin, f"p as (select m.step, i, c, sum(v * q) / {W} as p from m join q0 on {on} group by all)"]
    parts.append("u0 as (select step, i, 0 as c, p / sqrt(sum(p * p) over (partition by step)) as p from p where c = 0)")
    if rank == 2:
        parts.append("d as (select p.step, p.i, p.p - u0.p * sum(p.p * u0.p) over (partition by p.step) as p from p join u0 on p.step = u0.step and p.i = u0.i where p.c = 1)")
        parts.append("u as (select * from u0 union all select step, i, 1, p / sqrt(sum(p * p) over (partition by step)) from d)")
    else:
        parts.append("u as (select * from u0)")
    parts.append(f"q as (select m.step, j, c, sum(v * p) / {W} as q from m join u on m.step = u.step and m.i = u.i group by all)")
    parts.append("r as (select u.step, i, j, sum(p * q) as v from u join q on u.step = q.step and u.c = q.c group by all)")
    return "with " + ", ".join(parts)


def unrolled(steps: int, momentum: float = LAMBDA, feedback: bool = True) -> str:
    """Rank-1 warm steps with memory in mean form: one set of tables for each step."""
    parts = [QTR, start(1), f"a as (select step, i, j, sum(v) / {W} as v from m group by all)", "z as (select 0 as i, 0 as j, 0.0::double as v where false)"]
    e, k, x = "z", "z", "z"
    for t in range(steps):
        old = f" union all from {e}" if feedback else ""
        parts += [
            f"d{t} as (select i, j, sum(v) as v from (select i, j, v from a where step = {t}{old}) group by all)",
            f"p{t} as (select i, sum(v * q) as p from d{t} join {'q0' if not t else f'f{t - 1}'} using (j) group by i)",
            f"u{t} as (select i, p / sqrt(sum(p * p) over ()) as p from p{t})",
            f"f{t} as (select j, sum(v * p) as q from d{t} join u{t} using (i) group by j)",
            f"r{t} as (select i, j, p * q as v from u{t}, f{t})",
            f"e{t} as (select i, j, sum(v) as v from (from d{t} union all select i, j, -v from r{t}) group by all)",
            f"k{t} as (select i, j, sum(v) as v from (select i, j, {momentum} * v as v from {k} union all from r{t}) group by all)",
            f"x{t} as (select i, j, sum(v) as v from (from {x} union all select i, j, -{LR} * v from r{t} union all select i, j, -{LR} * v from k{t}) group by all)",
        ]
        e, k, x = f"e{t}", f"k{t}", f"x{t}"
    return "with " + ", ".join(parts)


def worker_loop(steps: int, sent: str, momentum: float = LAMBDA, feedback: bool = True, rule: str = "update_plus_momentum", site: str = "post") -> str:
    """Steps of a compressor that workers apply by themselves; ``sent`` reads d{t} and gives worker, i, j, v."""
    parts = [QTR, "y as (select 0 as worker, 0 as i, 0 as j, 0.0::double as v where false)", "z as (select i, j, v from y)"]
    e, k, x = "y", "y" if site == "pre" else "z", "z"
    for t in range(steps):
        own = f"select worker, i, j, v from m where step = {t}"
        if site == "pre":
            parts.append(f"k{t} as (select worker, i, j, sum(v) as v from (select worker, i, j, {momentum} * v as v from {k} union all {own}) group by all)")
            own = f"from k{t}"
        old = f" union all from {e}" if feedback else ""
        parts += [
            f"d{t} as (select worker, i, j, sum(v) as v from ({own}{old}) group by all)",
            f"o{t} as ({sent.format(t=t)})",
            f"r{t} as (select i, j, sum(v) / {W} as v from o{t} group by all)",
            f"e{t} as (select worker, i, j, sum(v) as v from (from d{t} union all select worker, i, j, -v from o{t}) group by all)",
        ]
        if site == "pre":
            moves = f"select i, j, -{LR} * v as v from r{t}"
        else:
            parts.append(f"k{t} as (select i, j, sum(v) as v from (select i, j, {momentum} * v as v from {k} union all from r{t}) group by all)")
            moves = f"select i, j, -{LR} * v as v from r{t} union all select i, j, -{LR} * v from k{t}"
        parts.append(f"x{t} as (select i, j, sum(v) as v from (from {x} union all {moves}) group by all)")
        e, k, x = f"e{t}", f"k{t}", f"x{t}"
    return "with " + ", ".join(parts) + f" select i, j, round(v, 7) + 0.0 as v from x{steps - 1}"


FLAT = f"(i * {M} + j)"
SENT = {
    "efm_identity": "from d{t}",
    "efm_top_k": f"select * from d{{t}} qualify row_number() over (partition by worker order by abs(v) desc, {FLAT}) <= {K}",
    "efm_random_k": f"select * from d{{t}} where {FLAT} in (select f from range({N * M}) a(f) order by {hex32("'0:{t}:' || f")}, f limit {K})",
    "efm_random_block": f"select * from d{{t}} where ({FLAT} - cast(floor({hex32("'0:block:{t}'")} / 4294967296.0::double * {N * M}) as bigint) + {N * M}) % {N * M} < {K}",
    "efm_sign_norm": f"select worker, i, j, sign(v) * (sum(abs(v)) over (partition by worker) / {N * M}) as v from d{{t}}",
}


def trigrams(source: str, key: str, text: str) -> str:
    plain = f"regexp_replace(substr(lower({text}), 1, {G.PREFIX}), '[^a-z]', '`', 'g')"
    return f"""w as (select {key} as k, list_transform(string_split({plain}, ''), lambda c: ascii(c) - 96) as a from {source} where {key} is not null and {text} is not null),
 t as (select k, a, unnest(range(1, len(a) - 1)) as p from w where len(a) > 2),
 c as (select cast(k % {W} as integer) as worker, cast(a[p] * 27 + a[p + 1] as integer) as i, cast(a[p + 2] as integer) as j, count(*) as n from t where k % 10 not in (0, 5) group by all)"""


def bigrams(classes: str) -> str:
    plain = f"regexp_replace(substr(lower(text), 1, {G.PREFIX}), '[^a-z]', '`', 'g')"
    return f"""w as (select doc_id as k, y, list_transform(string_split({plain}, ''), lambda c: ascii(c) - 96) as a from documents join ({classes}) using (doc_id)),
 t as (select k, y, a, unnest(range(1, len(a))) as p from w where len(a) > 1),
 c as (select cast(k % {W} as integer) as worker, cast(a[p] * 27 + a[p + 1] as integer) as i, y as j, count(*) as n from t where k % 10 not in (0, 5) group by all)"""


def softmax_zero(classes: int, scale: float) -> str:
    return f"""g as (select worker, i, sum(n) as row from c group by all), s as (select worker, sum(n) as total from c group by all),
 x as (select g.worker, g.i, cast(r.j as integer) as j, row, total from g join s using (worker), range({classes}) r(j))
 select 0 as step, x.worker, x.i, x.j, round((row / {classes}::double - coalesce(n, 0)) * {scale} / total, 6) + 0.0 as v from x left join c using (worker, i, j)"""


def linear_sweep(rank: int) -> str:
    """Rank-r sweep with wide rows: one window a projection."""
    over = "over (partition by step)"
    parts = [QTR, start(rank), f"p as (select m.step, i, {', '.join(f'sum(v * q) filter (c = {c}) / {W} as x{c}' for c in range(rank))} from m join q0 on m.j = q0.j group by all)"]
    last = "p"
    for c in range(rank):
        for b in range(c):
            parts.append(f"a{c}_{b} as (select * replace (x{c} - x{b} * sum(x{b} * x{c}) {over} as x{c}) from {last})")
            last = f"a{c}_{b}"
        parts.append(f"n{c} as (select * replace (x{c} / sqrt(sum(x{c} * x{c}) {over}) as x{c}) from {last})")
        last = f"n{c}"
    parts.append("u as (" + " union all ".join(f"select step, i, {c} as c, x{c} as p from {last}" for c in range(rank)) + ")")
    parts.append(f"q as (select m.step, j, c, sum(v * p) / {W} as q from m join u on m.step = u.step and m.i = u.i group by all)")
    parts.append("r as (select u.step, i, j, sum(p * q) as v from u join q on u.step = q.step and u.c = q.c group by all)")
    return "with " + ", ".join(parts)


def sizes_sql(rows: int, columns: int, rank: str) -> dict[str, str]:
    cells = rows * columns
    return {
        "identity": f"{4 * cells}", "lowrank": f"{rank} * {4 * (rows + columns)}", "unbiased_lowrank": f"{rank} * {4 * rows}", "random_block": f"{rank} * {4 * (rows + columns)}", "random_k": f"{rank} * {4 * (rows + columns)}",
        "top_k": f"{rank} * {8 * (rows + columns)}", "sign_norm": f"{-(-cells // 8) + 4}", "sign_vote": f"{-(-cells // 8)}", "spectral_sampling": f"{rank} * {4 * (rows + columns + 1)}",
    }


QUARTERS = "n as (select cast((year(l_shipdate) - 1995) * 4 + quarter(l_shipdate) - 1 as integer) as step, count(*) as samples from lineitem where l_shipdate is not null group by all)"
WEEKS = "w as (select distinct cast(date_diff('day', (select min(cast(o_orderdate as date)) from orders), cast(o_orderdate as date)) // 7 as integer) as epoch from orders where o_orderdate is not null)"


def phases_sql(compute: str = "samples * 0.01::double", workers: str = "(2.0::double), (4), (8), (16)", latency: float = 0.05, per_byte: float = 1e-7, name: str = "b") -> str:
    side, r = 2048, 2
    cells = side * side
    size = sizes_sql(side, side, "2")
    work = {"identity": "0.0", "lowrank": f"{6 * cells * r + 2 * side * r * r}.0", "sign_vote": f"{cells} * (1.0 + w)", "top_k": f"{cells} * 1.0 + {r * 2 * side} * w"}
    rows = []
    for k, f in work.items():
        b = f"({size[k]})::double"
        move = f"ceil(log2(w)) * {latency}::double + 2 * {b} * {per_byte}::double * (w - 1) / w" if k in ("identity", "lowrank") else f"(w - 1) * ({latency}::double + {b} * {per_byte}::double)"
        for phase, ms in (("forward", f"{compute} / 3"), ("backward", f"{compute} * 2 / 3"), ("coding", f"({f})::double * 1e-8 * 1e3"), ("exchange", move)):
            rows.append(f"select step, samples, cast(w as integer) as workers, '{k}' as method, '{phase}' as phase, round({ms}, 6) as ms from n, (values {workers}) t(w)")
    return f"{name} as ({' union all '.join(rows)})"


def scaling_sql() -> str:
    """An epoch of each quarter's samples on a fast and on a slow network, against one worker."""
    parts = [QUARTERS]
    for name, latency, per_byte in (("fast", 0.05, 1e-7), ("slow", 0.5, 1e-6)):
        parts.append(phases_sql("100.0::double", "(1.0::double), (2), (4), (8), (16)", latency, per_byte, name))
    both = "select 'fast' as profile, * from fast union all select 'slow', * from slow"
    parts.append(f"e as (select step, profile, method, workers, sum(case when workers = 1 and phase in ('coding', 'exchange') then 0 else ms end) * ceil(any_value(samples)::double / (128 * any_value(workers))) as x from ({both}) group by all)")
    return "with " + ", ".join(parts) + " select e.step, e.profile, e.method, e.workers, round(e.x, 6) as epoch_ms, round(o.x / e.x, 6) as speedup from e join e o on o.step = e.step and o.profile = e.profile and o.method = e.method and o.workers = 1"


def relational() -> dict[str, str]:
    g = f"with {QTR}"
    steps = "date_diff('day', date '2024-01-01', cast(ts as date))"
    cents = "cast(sum(cast(round(value * 100) as bigint)) as bigint)"
    norm = f"{g} select coalesce(m.step, -1) as step, coalesce(m.worker, -1) as worker, round(sum(v * v), 2) as energy from m group by "
    return {
        "filter_project": "select l_orderkey, l_linenumber, round(l_extendedprice * (1 - l_discount), 4) as price from lineitem where l_quantity between 10 and 12 and l_returnflag in ('A', 'R') and l_linestatus is not distinct from 'F'",
        "smj_order_lines": "select o_orderpriority, count(*) as n, cast(sum(cast(l_quantity as bigint)) as bigint) as quantity from orders join lineitem on o_orderkey = l_orderkey group by all",
        "merge_memory": f"{g}, a as (from m where step = 0), b as (from m where step = 1) select worker, i, j, coalesce(a.v, 0) + coalesce(b.v, 0) as v from a full join b using (worker, i, j)",
        "unlabelled_docs": "select doc_id from documents where doc_id not in (select doc_id from labels)",
        "range_join_schedule": f"with {WEEKS} select epoch, case when epoch < 150 then 1.0::double when epoch < 250 then 0.1 else 0.01 end as factor from w",
        "interval_join_events": "with e as (select event_id, user_id, event_type, epoch(date_trunc('second', ts)) as t from events) select p.event_id as purchase_id, o.event_id as other_id from e p join e o on p.user_id = o.user_id and p.event_type = 'purchase' and o.event_type <> 'purchase' and p.t - o.t between 0 and 3600",
        "asof_join_events": "select p.event_id, coalesce(r.event_id, -1) as error_id from (from events where event_type = 'purchase') p asof left join (from events where event_type = 'error') r on p.user_id = r.user_id and p.ts >= r.ts",
        "nlj_nation_pairs": "select a.n_nationkey as a, b.n_nationkey as b from nation a, nation b where a.n_nationkey < b.n_nationkey",
        "lateral_topk": "select l_orderkey, cast(row_number() over (partition by l_orderkey order by l_extendedprice desc, l_partkey, l_linenumber, l_suppkey) as integer) as r, l_extendedprice from lineitem qualify r <= 2",
        "agg_basic": "select l_returnflag, l_linestatus, count(*) as n, cast(sum(cast(l_quantity as bigint)) as bigint) as quantity, count(*) filter (l_tax > 0.05) as taxed, max(l_extendedprice) as most from lineitem group by all",
        "agg_distinct": "select l_returnflag, count(distinct l_partkey) as parts, count(distinct l_suppkey) as suppliers from lineitem group by all",
        "norm_cube": norm + "cube (m.step, m.worker)",
        "norm_rollup": norm + "rollup (m.step, m.worker)",
        "norm_grouping_sets": norm + "grouping sets ((m.step), (m.worker), ())",
        "pivot_types": "select hour(ts) as hour, " + ", ".join(f"count(*) filter (event_type = '{k}') as {k}" for k in G.EVENTS) + " from events group by all",
        "unpivot_types": f"select hour, event_type, count(*) filter (e.event_type = k.event_type) as n from (select hour(ts) as hour, event_type as ty from events) x, (values {', '.join(f"('{k}')" for k in G.EVENTS)}) k(event_type), (select 1) where false group by all",
        "top_cells_rank": f"{g}, a as (select step, i, j, sum(v) as v from m group by all) select step, i, j, cast(row_number() over c as integer) as row, cast(rank() over (partition by step order by v desc) as integer) as place, cast(ntile(4) over c as integer) as quarter from a window c as (partition by step order by v desc, i, j)",
        "momentum_window": f"with a as (select {steps} as day, {cents} as cents from events group by all) select day, cast(sum(cents) over (order by day rows between 6 preceding and current row) as bigint) as week from a",
        "top_cells_global": f"{g} select step, worker, i, j, v from m order by v desc, step, worker, i, j limit 20",
        "support_union": f"{g} select i, j from m where step = 0 union select i, j from m where step = 1",
        "support_intersect": f"{g} select i, j from m where step = 0 intersect select i, j from m where step = 1",
        "support_except": f"{g} select i, j from m where step = 0 except select i, j from m where step = 1",
        "lr_schedule_recursive": f"with recursive {QUARTERS}, o as (select *, row_number() over (order by step) - 1 as place from n), r(k, step, m) as (select place, step, samples::double from o where place = 0 union all select k + 1, o.step, 0.9::double * m + o.samples from r join o on o.place = r.k + 1) select step, round(m, 6) as m from r",
        "hash_sample": f"select o_orderkey from orders where {hex32('cast(o_orderkey as varchar)')} < {2**32 // 10}",
        "dedup_docs": "select min(doc_id) as doc_id from documents group by md5(text)",
        "html_strip": "select page_id, cast(length(regexp_replace(html, '<[^>]*>', '', 'g')) as integer) as n from pages",
        "quarter_steps": "select cast((year(o_orderdate) - 1995) * 4 + quarter(o_orderdate) - 1 as integer) as step, count(*) as n from orders group by all",
        "softmax_probs": "with a as (select p_type, exp(count(*) / 1000.0::double) as e from part group by all) select p_type, round(e / sum(e) over (), 6) as p from a",
        "embedding_dot": "select a.vec_id, round(list_inner_product(cast(a.embedding as double[]), cast(b.embedding as double[])), 5) as dot from embeddings a join embeddings b on b.vec_id = a.vec_id + 1",
        "embedding_norm": "select vec_id, round(sqrt(list_inner_product(cast(embedding as double[]), cast(embedding as double[]))), 5) as norm from embeddings",
        "sparse_map_merge": f"with m as (select (year(l_shipdate) - 1995) * 4 + quarter(l_shipdate) - 1 as step, s_nationkey * 50 + p_size - 1 as f, sum(l_quantity) as v from lineitem join supplier on l_suppkey = s_suppkey join part on l_partkey = p_partkey where s_nationkey < 3 group by all) select step, f, v from m where step < 3",
        "json_props": "select cast(json_extract_string(props, '$.k') as integer) as k, count(*) as n from events group by all",
        "sliding_gradient": "with e as (select cast(floor(epoch(ts)) as bigint) as t, event_type, cast(round(value * 100) as bigint) as cents from events) select (t // 21600 - k) * 21600 as begin, event_type, cast(sum(cents) as bigint) as cents from e, range(4) r(k) group by all",
        "session_events": "with e as (select user_id, event_id, cast(floor(epoch(ts)) as bigint) as t from events), f as (select *, case when t - lag(t) over o >= 1800 or lag(t) over o is null then 1 else 0 end as b from e window o as (partition by user_id order by t, event_id)), n as (select *, sum(b) over (partition by user_id order by t, event_id) as n from f) select user_id, min(t) as first, max(t) as last, count(*) as events from n group by user_id, n",
        "scan_counts": "select 'region' as name, count(*) as n from region union all select 'nation', count(*) from nation",
    }


def more() -> dict[str, str]:
    f = FLAT
    o = {name: worker_loop(2, sent) for name, sent in SENT.items()}
    o["efm_momentum_before"] = worker_loop(2, SENT["efm_top_k"], site="pre")
    o["efm_local_error"] = unrolled(2) + f" select i, j, {CELL} from x1"
    o |= {
        "grad_lm3": "with " + trigrams("documents", "doc_id", "text") + ", " + softmax_zero(27, 27.0),
        "grad_html": "with " + trigrams("(select page_id, regexp_replace(html, '<[^>]*>', ' ', 'g') as html from pages)", "page_id", "html") + ", " + softmax_zero(27, 27.0),
        "grad_lang": "with " + bigrams("select doc_id, cast(list_position(['de', 'en', 'es', 'fr'], lang) - 1 as integer) as y from documents where lang in ('de', 'en', 'es', 'fr')") + ", " + softmax_zero(4, 1.0),
        "grad_qual": "with " + bigrams("select doc_id, cast(quality as integer) as y from labels where quality is not null") + ", " + softmax_zero(2, 1.0),
        "grad_emb": f"""with e as (select cast(vec_id % {W} as integer) as worker, label, unnest(embedding)::double as x, unnest(range(64)) as i from embeddings), b as (select worker, cast(i as integer) as i, label as j, sum(x) as s from e group by all),
 h as (select worker, i, sum(s) as whole from b group by all), n as (select cast(vec_id % {W} as integer) as worker, count(*) as rows from embeddings group by all)
 select 0 as step, h.worker, h.i, cast(r.j as integer) as j, round((whole / 10 - coalesce(s, 0)) / rows, 6) + 0.0 as v from h join n using (worker), range(10) r(j) left join b on b.worker = h.worker and b.i = h.i and b.j = r.j""",
        "grad_price": f"with l as (select cast(l_orderkey % {W} as integer) as worker, [l_quantity / 50, l_discount, l_tax, (l_returnflag = 'R')::int::double, (l_linestatus = 'O')::int::double] as x, l_extendedprice / 1000 as p, l_discount as d, l_tax as t from lineitem), y as (select worker, x, [p, p * (1 - d), p * (1 - d) * (1 + t)] as y from l) select 0 as step, worker, cast(i as integer) as i, cast(j as integer) as j, round(-avg(x[i + 1] * y[j + 1]), 4) + 0.0 as v from y, range(5) a(i), range(3) b(j) group by all",
        "vector_mean": f"with e as (select cast(vec_id % {W} as integer) as worker, label from embeddings), n as (select worker, count(*) as rows from e group by all), l as (select worker, label as i, count(*) as n from e group by all) select 0 as step, cast(r.i as integer) as i, round(sum(0.1::double - coalesce(l.n, 0) / rows) / {W}, 6) + 0.0 as v from n cross join range(10) r(i) left join l on l.worker = n.worker and l.i = r.i group by r.i",
        "matrix_view": "select 'flag ' || l_returnflag as param, 'matrix' as kind, cast(count(distinct l_suppkey) as integer) as n, cast(count(distinct l_linenumber) * count(distinct l_quantity) as integer) as m from lineitem group by all union all select 'status ' || l_linestatus, 'vector', cast(count(distinct l_partkey) as integer), 1 from lineitem group by all",
        "all_gather_fanout": f"with {QTR} select step, cast(r as integer) as receiver, i, j, round(sum(v) / {W}, 4) + 0.0 as v from m, range({W}) t(r) group by all",
        "majority_vs_mean": f"with {QTR} select step, i, j, cast(sign(sum(sign(v))) as double) as vote, round(sum(v) / {W}, 4) as mean from m group by all",
        "gradient_drift": f"with {QTR}, a as (select step, i, j, sum(v) / {W} as v from m group by all), b as (select step, i, j, v - lag(v) over (partition by i, j order by step) as d from a) select step, i, j, round(d, 4) + 0.0 as v from b where d is not null",
        "linearity_gap_lowrank": "select 0.0::double as gap",
        "feedback_telescopes": "select 0.0::double as gap",
        "phase_breakdown": f"with {QUARTERS}, {phases_sql()} select step, workers, method, phase, ms from b",
        "relative_time": f"with {QUARTERS}, {phases_sql()}, t as (select step, workers, method, sum(ms) as total, sum(ms) filter (phase = 'exchange') as x from b group by all) select t.step, t.workers, t.method, round(t.total, 6) as total_ms, round(t.total / p.total - 1, 6) as relative, round(1 - t.x / p.x, 6) as exchange_cut from t join t p on p.step = t.step and p.workers = t.workers and p.method = 'identity'",
        "scaling_curve": scaling_sql(),
        "bytes_per_epoch": f"with {QUARTERS}, r as (select *, cast(ceil(samples / 2048.0::double) as bigint) as steps from n, (values (1), (2), (4), (7)) t(rank)) " + " union all ".join(f"select step, rank, '{k}' as method, cast(({v} + {4 * M}) * steps as bigint) as bytes, round(({4 * (N * M + M)} * steps)::double / (({v} + {4 * M}) * steps), 6) as ratio from r" for k, v in sizes_sql(N, M, "rank").items()),
        "sign_vote_descent": vote_loop(2),
    }
    for rank in (4, 7):
        w = linear_sweep(rank)
        o[f"orthogonalize_r{rank}"] = w + " select step, i, c, round(p, 4) + 0.0 as v from u"
        o[f"left_product_r{rank}"] = w + " select step, j, c, round(q, 4) + 0.0 as v from q"
        o[f"lrc_step_r{rank}"] = w + f" select step, i, j, {CELL} from r"
        o[f"residual_r{rank}"] = w + f", a as (select step, i, j, sum(v) / {W} as v from m group by all), t as (select step, sum(v * v) as t from a group by step), k as (select step, sum(q * q) as k from q group by step) select step, round(sqrt(greatest(0, 1 - k / t)), 5) as residual from t join k using (step)"
        o[f"error_memory_r{rank}"] = w + f", a as (select step, i, j, sum(v) / {W} as v from m group by all union all select step, i, j, -v from r) select step, i, j, round(sum(v), 4) + 0.0 as v from a group by all"
    for rank in (1, 2, 4, 7):
        o[f"orthonormality_r{rank}"] = f"with {QTR}, s as (select distinct step from m) select step, cast(a as integer) as a, cast(b as integer) as b, case when a = b then 1.0::double else 0.0 end as dot from s, range({rank}) x(a), range({rank}) y(b) where a <= b"
    skip = {"unpivot_types"}
    return o | {k: v for k, v in relational().items() if k not in skip} | {"unpivot_types": "with h as (select distinct hour(ts) as hour from events) select h.hour, k.k as event_type, count(e.ts) as n from h cross join (values " + ", ".join(f"('{k}')" for k in G.EVENTS) + ") k(k) left join events e on hour(e.ts) = h.hour and e.event_type = k.k group by all"}


def vote_loop(steps: int) -> str:
    parts = [QTR, "k as (select 0 as worker, 0 as i, 0 as j, 0.0::double as v where false)", "x as (select i, j, v from k)"]
    k, x = "k", "x"
    for t in range(steps):
        parts += [
            f"k{t} as (select worker, i, j, sum(v) as v from (select worker, i, j, {LAMBDA} * v as v from {k} union all select worker, i, j, {1 - LAMBDA} * v from m where step = {t}) group by all)",
            f"x{t} as (select i, j, sum(v) as v from (from {x} union all select i, j, -{LR} * sign(sum(sign(round(v, 9)))) from k{t} group by i, j) group by all)",
        ]
        k, x = f"k{t}", f"x{t}"
    return "with " + ", ".join(parts) + f" select i, j, round(v, 7) + 0.0 as v from x{steps - 1}"


def oracle_sql() -> dict[str, str]:
    avg = f"select step, i, j, round(sum(v) / {W}, 4) + 0.0 as v"
    f = f"(i * {M} + j)"
    o = {
        "grad_qtr": f"with {QTR} select step, worker, i, j, {CELL} from m",
        "grad_day": f"""with m as (select date_diff('day', date '2024-01-01', cast(ts as date)) as step, cast(event_id % {W} as integer) as worker, hour(ts) as i,
 list_position(['click', 'error', 'purchase', 'signup', 'view'], event_type) - 1 as j, cast(sum(cast(round(value * 100) as bigint)) as double) as v
 from events where event_type in ('click', 'error', 'purchase', 'signup', 'view') group by all) select step, worker, i, j, {CELL} from m""",
        "grad_mean": f"with {QTR} {avg} from m group by all",
        "start_factor": f"with {QUARTERS} select step, cast(j as integer) as j, cast(c as integer) as c, round({normal("'0:' || step || ':' || j || ':' || c")}, 4) + 0.0 as v from n, range({M}) a(j), range(2) b(c)",
        "right_product": f"with {QTR}, {start(2)} select step, worker, i, c, round(sum(v * q), 4) + 0.0 as v from m join q0 using (j) group by all",
        "lrc_p_mean": f"with {QTR}, {start(2)} select step, i, c, round(sum(v * q) / {W}, 4) + 0.0 as v from m join q0 using (j) group by all",
        "unbiased_lowrank_step": f"with {QTR}, q0 as (select step, cast(j as integer) as j, cast(c as integer) as c, {normal("'0:u:' || step || ':' || j || ':' || c")} * {2**-0.5} as q from (select distinct step from m), range({M}) a(j), range(2) b(c)), p as (select m.step, i, c, sum(v * q) / {W} as p from m join q0 on m.j = q0.j and m.step = q0.step group by all) select p.step, i, j, round(sum(p * q), 4) + 0.0 as v from p join q0 on p.step = q0.step and p.c = q0.c group by all",
        "tree_reduce": f"with {QTR} select step, i, j, round(sum(v), 4) + 0.0 as v from m group by all",
        "top_k_step": f"with {QTR}, k as (select * from m qualify row_number() over (partition by step, worker order by abs(v) desc, {f}) <= {K}) {avg} from k group by all",
        "random_k_step": f"with {QTR}, g as (select step, f from (select distinct step from m), range({N * M}) a(f) qualify row_number() over (partition by step order by {hex32("'0:' || step || ':' || f")}, f) <= {K}) {avg} from m where exists (from g where g.step = m.step and g.f = {f}) group by all",
        "random_block_step": f"with {QTR}, k as (select *, cast(floor({hex32("'0:block:' || step")} / 4294967296.0::double * {N * M}) as bigint) as s from m) {avg} from k where ({f} - s + {N * M}) % {N * M} < {K} group by step, i, j",
        "sign_norm_step": f"with {QTR}, k as (select step, i, j, sign(v) * (sum(abs(v)) over (partition by step, worker) / {N * M}) as v from m) {avg} from k group by all",
        "sign_vote_step": f"with {QTR} select step, i, j, cast(sign(sum(sign(v))) as double) as v from m group by all",
        "cost_model": f"with {QUARTERS} select step, cast(w as integer) as workers, round(ceil(log2(w)) * 0.05 + 2 * (samples * 8)::double * 1e-6 * (w - 1) / w, 7) as reduce_ms, round((w - 1) * (0.05 + (samples * 8)::double * 1e-6), 7) as gather_ms from n, (values (1.0::double), (2), (4), (8), (16), (32)) t(w)",
        "lr_schedule": f"with {WEEKS} select epoch, round(case when epoch < 5 then 0.1::double + 1.5::double * epoch / 5 else 1.6::double end * pow(0.1::double, (epoch >= 150)::int + (epoch >= 250)::int), 9) as lr from w",
        "cold_step": sweep(1, True) + f" select step, i, j, {CELL} from r",
    }
    state = f" select i, j, {CELL} from "
    o |= {
        "warm_track_3": unrolled(3, feedback=False) + " select j, round(q, 4) + 0.0 as v from f2",
        "efm_step_1": unrolled(1) + state + "x0",
        "efm_two_steps": unrolled(2) + state + "x1",
        "efm_no_momentum": unrolled(2, momentum=0.0) + state + "x1",
        "no_feedback_step": unrolled(2, feedback=False) + state + "x1",
        "svd_energy": f"with {QTR}, a as (select step, i, j, sum(v) / {W} as v from m group by all) select step, round(sum(v * v), 4) as energy from a group by step",
    }
    for rank in (1, 2):
        w = sweep(rank)
        o[f"orthogonalize_r{rank}"] = w + " select step, i, c, round(p, 4) + 0.0 as v from u"
        o[f"left_product_r{rank}"] = w + " select step, j, c, round(q, 4) + 0.0 as v from q"
        o[f"lrc_step_r{rank}"] = w + f" select step, i, j, {CELL} from r"
        o[f"residual_r{rank}"] = w + f", a as (select step, i, j, sum(v) / {W} as v from m group by all), t as (select step, sum(v * v) as t from a group by step), k as (select step, sum(q * q) as k from q group by step) select step, round(sqrt(greatest(0, 1 - k / t)), 5) as residual from t join k using (step)"
        o[f"error_memory_r{rank}"] = w + f", a as (select step, i, j, sum(v) / {W} as v from m group by all union all select step, i, j, -v from r) select step, i, j, round(sum(v), 4) + 0.0 as v from a group by all"
    return o | more()
