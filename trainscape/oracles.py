"""DuckDB SQL for the registered queries. Training runs are chains of steps, one materialised row of weights each."""

from __future__ import annotations

import math

from trainscape.functions.hashing import hash_sql
from trainscape.plans import analytic, constants, designs, whatif
from trainscape.queries import ASYNC_STEPS, DELAYS, GRID_RATES, RUN_TYPES, RUNS

KEY_SQL = ["l_orderkey", "l_linenumber", "l_partkey", "l_suppkey"]
D = 28


def num(x: float) -> str:
    """A double literal."""
    text = repr(float(x))
    return text if "e" in text else f"{text}e0"


def rows_sql(rows: list[tuple], names: str) -> str:
    cell = lambda v: "null" if v is None else f"'{v}'" if isinstance(v, str) else num(v) if isinstance(v, float) else str(v)
    return f"(select * from (values {', '.join('(' + ', '.join(map(cell, r)) + ')' for r in rows)}) t({names}))"


# ---- the dense task

_RAW = """raw as materialized (select l_orderkey, l_linenumber, l_partkey, l_suppkey, l_shipdate,
 l_quantity f0, l_extendedprice f1, l_discount f2, l_tax f3, l_linenumber::double f4, l_extendedprice * (1 - l_discount) f5, l_extendedprice * (1 - l_discount) * (1 + l_tax) f6,
 l_extendedprice / l_quantity f7, (isodow(l_shipdate) - 1)::double f8, month(l_shipdate)::double f9, date_diff('day', date '1995-01-01', l_shipdate::date)::double f10,
 date_diff('day', o_orderdate::date, l_shipdate::date)::double f11, o_totalprice f12, month(o_orderdate)::double f13, (isodow(o_orderdate) - 1)::double f14,
 substr(o_orderpriority, 1, 1)::int::double f15, (o_orderstatus = 'F')::int::double f16, (o_orderstatus = 'O')::int::double f17, p_size::double f18, p_retailprice f19, s_acctbal f20,
 c_acctbal f21, (l_returnflag = 'A')::int::double f22, (l_returnflag = 'N')::int::double f23, (l_linestatus = 'F')::int::double f24, (s_nationkey = c_nationkey)::int::double f25,
 l_extendedprice / o_totalprice f26, regexp_extract(p_brand, '([0-9]+)', 1)::int::double f27
 from lineitem join orders on l_orderkey = o_orderkey join part on l_partkey = p_partkey join supplier on l_suppkey = s_suppkey join customer on o_custkey = c_custkey)"""


def dense_sql(workers: int = 10, batches: int = 10) -> str:
    """CTEs up to `ex`: the scaled examples with y, split, worker and batch."""
    stats = ", ".join(f"min(f{i}) lo{i}, max(f{i}) hi{i}" for i in range(D))
    scaled = ", ".join(f"coalesce(case when hi{i} > lo{i} then (f{i} - lo{i}) / (hi{i} - lo{i}) * 2.0::double - 1.0::double end, 0.0::double) f{i}" for i in range(D))
    margin = f"0.39e0{''.join(f' + {num(math.cos(i + 1))} * f{i}' for i in range(D))} + 16.0e0 * ({hash_sql('noise', *KEY_SQL)} / 4294967296.0e0 - 0.5e0)"
    return f"""{_RAW}, stats as materialized (select {stats} from raw),
scaled as materialized (select l_orderkey, l_linenumber, l_partkey, l_suppkey, l_shipdate, {scaled} from raw, stats),
ex as materialized (select *, case when {margin} >= 0 then 1.0e0 else -1.0e0 end y, case when {hash_sql('split', *KEY_SQL)} % 10 >= 1 then 'train' else 'validation' end split,
 ({hash_sql('worker', *KEY_SQL)} % {workers})::int worker, ({hash_sql('batch', *KEY_SQL)} % {batches})::int batch from scaled)"""


def _score(prefix: str = "") -> str:
    return f"({prefix}w{D}" + "".join(f" + {prefix}w{i} * f{i}" for i in range(D)) + ")"


def _slope(loss: str, prefix: str = "") -> str:
    m = f"(y * {_score(prefix)})"
    return f"(-1.0e0 / (1.0e0 + exp({m})) * y)" if loss == "lr" else f"(case when {m} < 1.0e0 then -1.0e0 else 0.0e0 end * y)"


def _sums(how: str = "avg") -> str:
    return ", ".join([f"{how}(c * f{i}) g{i}" for i in range(D)] + [f"{how}(c) g{D}"])


ZERO = "select " + ", ".join(f"0.0e0 w{i}" for i in range(D + 1))


def _step(name: str, before: str, where: str, lr: float, loss: str = "lr", l2: float = 0.0) -> str:
    """One step of the shared model on the rows named."""
    new = ", ".join(f"w{i} - {num(lr)} * (g{i}{f' + {num(l2)} * w{i}' if l2 and i < D else ''}) w{i}" for i in range(D + 1))
    return f"{name} as materialized (select {new} from {before}, (select {_sums()} from (select ex.*, {_slope(loss)} c from ex, {before} where split = 'train' and {where})))"


def _weights(last: str) -> str:
    return "select coord, round(value, 6) + 0.0e0 as value from (" + " union all ".join(f"select {i} as coord, w{i} as value from {last}" for i in range(D + 1)) + ")"


def ga_sql(lr: float, batches: int, epochs: int, loss: str = "lr", l2: float = 0.0) -> str:
    steps = [_step(f"s{k + 1}", f"s{k}", f"batch = {k % batches}", lr, loss, l2) for k in range(epochs * batches)]
    return f"with {dense_sql(1 if batches == 1 else 4, batches)}, s0 as ({ZERO}), {', '.join(steps)} {_weights(f's{len(steps)}')}"


def _local(name: str, before: str, workers: int, where: str, lr: float, rho: float = 0.0, anchor: str = "") -> str:
    """One step of every worker's own model; a worker without rows keeps it."""
    pull = (lambda i: f" + {num(rho)} * (b.w{i} - (z.w{i} - b.u{i}))") if rho else (lambda i: "")
    new = ", ".join(f"case when n is null then b.w{i} else b.w{i} - {num(lr)} * (g{i}{pull(i)}) end w{i}" for i in range(D + 1))
    keep = "".join(f", b.u{i}" for i in range(D + 1)) if rho else ""
    grads = f"select ex.worker j, count(*) n, {_sums()} from (select ex.*, {_slope('lr', 'b.')} c from ex join {before} b on b.worker = ex.worker where split = 'train' and {where}) ex group by 1"
    return f"{name} as materialized (select b.worker, b.seen + coalesce(n, 0) seen, {new}{keep} from {before} b left join ({grads}) on j = b.worker{f', {anchor} z' if rho else ''})"


def ma_sql(lr: float, workers: int, batches: int, rounds: int, sync: int, weighted: bool) -> str:
    parts, shared = [f"z0 as ({ZERO})"], "z0"
    k = 0
    for turn in range(rounds):
        for first in range(0, batches, sync):
            k += 1
            start = f"m{k}_0"
            parts.append(f"{start} as materialized (select j worker, 0 seen, z.* from (select unnest(range({workers}))::int j), {shared} z)")
            for t in range(first, min(first + sync, batches)):
                parts.append(_local(f"m{k}_{t - first + 1}", f"m{k}_{t - first}", workers, f"batch = {t}", lr))
            last = f"m{k}_{min(first + sync, batches) - first}"
            mean = ", ".join(f"sum(seen * w{i}) / sum(seen) w{i}" if weighted else f"avg(w{i}) filter (seen > 0) w{i}" for i in range(D + 1))
            shared = f"z{k}"
            parts.append(f"{shared} as materialized (select {mean} from {last})")
    return f"with {dense_sql(workers, batches)}, {', '.join(parts)} {_weights(shared)}"


def admm_sql(lr: float, workers: int, rho: float, inner: int, rounds: int) -> str:
    u = lambda v: ", ".join(f"{v(i)} u{i}" for i in range(D + 1))
    parts = [f"z0 as ({ZERO})", f"a0_0 as materialized (select j worker, 0 seen, z.*, {u(lambda i: '0.0e0')} from (select unnest(range({workers}))::int j), z0 z)"]
    for r in range(rounds):
        for k in range(inner):
            parts.append(_local(f"a{r}_{k + 1}", f"a{r}_{k}", workers, "batch = 0", lr, rho, f"z{r}"))
        last = f"a{r}_{inner}"
        parts.append(f"z{r + 1} as materialized (select {', '.join(f'avg(w{i} + u{i}) w{i}' for i in range(D + 1))} from {last})")
        parts.append(f"a{r + 1}_0 as materialized (select a.worker, 0 seen, {', '.join(f'a.w{i}' for i in range(D + 1))}, {u(lambda i: f'a.u{i} + a.w{i} - z.w{i}')} from {last} a, z{r + 1} z)")
    return f"with {dense_sql(workers, 1)}, {', '.join(parts)} {_weights(f'z{rounds}')}"


def _schedule() -> list[dict]:
    """The asynchronous events, by plain simulation."""
    events = sorted(((s + 1) * d, j, s, s * d) for j, d in DELAYS.items() for s in range(ASYNC_STEPS))
    return [{"worker": j, "step": s, "read_at": r, "write_at": w, "v": i + 1, "seen": sum(x[0] <= r for x in events)} for i, (w, j, s, r) in enumerate(events)]


def async_sql(lr: float, batches: int, overwrite: bool) -> str:
    parts = [f"s0 as ({ZERO})"]
    for e in _schedule():
        rate = lr / math.sqrt(e["step"] // batches + 1)
        seen, base = f"s{e['seen']}", f"s{e['seen'] if overwrite else e['v'] - 1}"
        new = ", ".join(f"b.w{i} - {num(rate)} * coalesce(g{i}, 0) w{i}" for i in range(D + 1))
        parts.append(f"s{e['v']} as materialized (select {new} from {base} b, (select {_sums()} from (select ex.*, {_slope('lr')} c from ex, {seen} where split = 'train' and worker = {e['worker']} and batch = {e['step'] % batches})))")
    return f"with {dense_sql(len(DELAYS), batches)}, {', '.join(parts)} {_weights(f's{len(_schedule())}')}"


def kmeans_sql(k: int = 3, iters: int = 3, d: int = 4) -> str:
    cols = ", ".join(f"f{i}" for i in range(d))
    dist = " + ".join(f"(e.f{i} - c.f{i}) * (e.f{i} - c.f{i})" for i in range(d))
    parts = [f"ids as materialized (select row_number() over () id, l_orderkey, l_linenumber, l_partkey, l_suppkey, l_shipdate, {cols} from ex)", f"c0 as materialized (select (row_number() over (order by l_orderkey, l_linenumber, l_partkey, l_suppkey, l_shipdate) - 1)::int cluster, {cols} from ids order by l_orderkey, l_linenumber, l_partkey, l_suppkey, l_shipdate limit {k})"]
    for t in range(iters):
        parts.append(f"n{t} as materialized (select id, min(d) d, arg_min(cluster, (d, cluster)) cluster from (select id, c.cluster, {dist} d from ids e, c{t} c) group by id)")
        parts.append(f"c{t + 1} as materialized (select c.cluster, {', '.join(f'coalesce(avg(e.f{i}), any_value(c.f{i})) f{i}' for i in range(d))} from c{t} c left join (n{t} join ids e using (id)) on n{t}.cluster = c.cluster group by c.cluster)")
    out = " union all ".join(f"select cluster, {i} as coord, f{i} as value from c{iters}" for i in range(d))
    return f"with {dense_sql()}, {', '.join(parts)} select cluster, coord, round(value, 6) + 0.0e0 as value, round((select avg(d) from n{iters - 1}), 6) as loss from ({out})"


# ---- the analytic model

_B = {c: v for n, c, _, v, _, _ in constants.CONSTANTS if n == "bandwidth"}
_L = {c: v for n, c, _, v, _, _ in constants.CONSTANTS if n == "latency"}


def startup_sql(w: str, infra: str, bound: int = 0) -> str:
    p = [(x, v + bound * s) for n, c, x, v, s, _ in constants.CONSTANTS if (n, c) == ("startup", infra)]
    out = f"case when {w} <= {p[0][0]} then {num(p[0][1])}"
    for (a, va), (b, vb) in zip(p, p[1:]):
        line = f"{num(va)} + ({w} - {a}) * {num((vb - va) / (b - a))}"
        out += f" when {w} <= {b} then {line}" if b != p[-1][0] else f" else {line} end"
    return out


GRID = f"""g as (select t.*, w, 1 + growth * (w - 1) as f_w from {rows_sql(analytic.TASKS, 'task, algo, s_mb, m_mb, rounds, compute_s, growth')} t, (select unnest({analytic.WORKERS}) w))"""


def terms_sql(name: str, infra: str, per_worker: bool, channel: str = "object_store", net: str = "net_t2_medium", bound: int = 0, gpu: float = 1.0, link: float = constants.FUNCTION_LINK_MB, update: bool = True, cache: bool = False, source: str = "g") -> str:
    """A CTE with the terms of a run on one infrastructure."""
    config = {"fs": channel, "vc": net}.get(infra)
    spread = {(n, c): s for n, c, _, _, s, _ in constants.CONSTANTS if n != "startup"}
    if infra == "hp":
        ten, one = 6.0, 0.4
        comm = f"(2.0e0 * (m_mb * w / {num(link)} + 0.0005e0)" + (f" + ({num(one)} + (w - 1) * {num((ten - one) / 9.0)}) * m_mb / 75.0e0)" if update else ")")
        start = f"greatest({startup_sql('w', 'fs')}, {startup_sql('1', 'vc')})"
    else:
        b, l = _B[config] - bound * spread["bandwidth", config], _L[config] + bound * spread["latency", config]
        comm = f"(({'3' if infra == 'fs' else '2'} * w - 2) * (m_mb / w / {num(b)} + {num(l)}))"
        start = startup_sql("w", infra, bound)
        start = f"greatest({start}, {num(constants.CACHE_STARTUP_S)})" if cache else start
    s3 = _B["object_store"] - bound * spread["bandwidth", "object_store"]
    return f"{name} as (select *, startup_s + load_s + comm_s + comp_s as runtime_s from (select *, {start} startup_s, s_mb / {num(s3)}{' / w' if per_worker else ''} load_s, rounds * f_w * {comm} comm_s, rounds * f_w * compute_s / w / {num(gpu)} comp_s from {source}))"


FS_D, VC_D = f"{num(constants.PRICE_FS)} * w * (runtime_s - startup_s)", f"{num(constants.PRICE_VC)} * w * runtime_s"
CACHE_D = f"{FS_D} + runtime_s * {num(constants.CACHE_HOUR)} / 3600"
HP_D = f"{FS_D} + runtime_s * 0.68e0 / 3600"


def grid_sql(terms: str, dollars: str) -> str:
    r = ", ".join(f"round({c}, 6) as {c}" for c in ("startup_s", "load_s", "comm_s", "comp_s", "runtime_s"))
    return f"with {GRID}, {terms} select task, algo, w, {r}, round({dollars}, 6) as dollars from t"


_GPU = constants.GPU_HOUR / 3600
_FAST = [
    ("fs", terms_sql("a", "fs", True), FS_D), ("vc", terms_sql("b", "vc", True), VC_D), ("vc_gpu", terms_sql("c", "vc", True, gpu=whatif.GPU_SPEEDUP), f"{num(_GPU)} * w * runtime_s"),
    ("hp", terms_sql("d", "hp", True), HP_D), ("hp_fast", terms_sql("e", "hp", True, link=10_000.0, update=False), HP_D),
    ("hp_fast_gpu", terms_sql("f", "hp", True, link=10_000.0, update=False, gpu=whatif.GPU_SPEEDUP), f"{num(_GPU)} * w * (runtime_s - startup_s) + runtime_s * 0.68e0 / 3600"),
]
_HOT = [("vc", terms_sql("a", "vc", False), 1250.0), ("fs", terms_sql("b", "fs", False), 70.0), ("hp", terms_sql("c", "hp", False), 70.0)]
_ALL = [("fs", terms_sql("a", "fs", True), FS_D), ("fs_cache", terms_sql("b", "fs", True, "cache_t3_medium", cache=True), CACHE_D), ("vc", terms_sql("c", "vc", True), VC_D), ("hp", terms_sql("d", "hp", True), HP_D)]


def channel_sql(runs: str) -> str:
    store = f"(3 * w - 2) * (m_mb / w / {num(_B['object_store'])} + {num(_L['object_store'])})"
    cache = lambda b: f"(3 * w - 2) * (m_mb / w / {b} + {num(_L['cache_t3_medium'])})"
    t3 = num(_B["cache_t3_medium"])
    ps = f"2 * (m_mb * w / 70.0e0 + {num(_L['net_t2_medium'])}) + (0.4e0 + (w - 1) * {num(5.6 / 9.0)}) * m_mb / 75.0e0"
    each = [("object_store", store, 0.0, 0.0), ("cache_mt", cache(t3), 120.0, 0.034), ("cache_st", cache(f"({t3} / w)"), 120.0, 0.034), ("kv_db", f"case when m_mb * 1e6 <= 400000 then {store} * 0.8e0 end", 0.0, 0.0), ("vm_ps", ps, 132.0, 0.68)]
    union = " union all ".join(f"select r.*, '{n}' channel, rounds * ({c}) as comm_s, {num(s)} as start_s, {num(h)} as hourly from r" for n, c, s, h in each)
    return f"""with r as {runs}, c as (select *, start_s + base_s + comm_s time_s from ({union})), d as (select *, {num(constants.PRICE_FS)} * w * time_s + time_s * (hourly / 3600) as dollars from c)
select d.run, d.channel, round(d.comm_s, 6) as comm_s, round(d.time_s, 6) as time_s, round(d.dollars, 6) as dollars, round(d.time_s / b.time_s, 6) as slowdown, round(d.dollars / b.dollars, 6) as relative_cost
from d join d b on d.run = b.run and b.channel = 'object_store'"""


def policies_sql() -> str:
    def run(name: str, wait: str, dollars: str, share: str) -> str:
        return f"""select '{name}' as policy, count(*) as jobs, round(avg({wait} + work_s), 6) as mean_latency_s, (select max(running) from p_{name})::bigint as peak_workers, round({dollars}, 6) as dollars, round({share}, 6) as utilisation from j"""

    waits = {"fs": num(1.2), "vm": num(132.0), "reserved": "0.0e0"}
    moves = ", ".join(f"p_{n} as (select sum(sum(d)) over (order by at_s) as running from (select at_s, 10 as d from j union all select at_s + {w} + work_s, -10 from j) group by at_s)" for n, w in waits.items())
    horizon = "(max(at_s + work_s) - min(at_s))"
    peak = "(select max(running) from p_reserved)"
    return f"""with j as (select event_id, floor(epoch(ts))::double as at_s, value as work_s from events), {moves}
{run('fs', waits['fs'], f"sum(work_s) * 10 * {num(constants.PRICE_FS)}", '1.0e0')} union all
{run('vm', waits['vm'], f"sum(work_s + 132.0e0) * 10 * {num(constants.PRICE_VC)}", 'sum(work_s) / sum(work_s + 132.0e0)')} union all
{run('reserved', waits['reserved'], f"{peak} * {horizon} * {num(constants.PRICE_VC)}", f'sum(work_s) * 10 / ({peak} * {horizon})')}"""


def designs_sql() -> str:
    b = lambda rows: [tuple(("true" if v else "false") if isinstance(v, bool) else v for v in r) for r in rows]
    models, algos = (rows_sql(b(r), n) for r, n in (([(*r[:3], designs.NUMBERS[r[0]]) for r in designs.MODELS], "model, convex, clusters, numbers"), (designs.ALGORITHMS, "algorithm, needs_convex")))
    return f"""select model, algorithm, channel, pattern, protocol, infra, w from (select *, numbers * 8 * (select count(distinct user_id) from events) m_bytes from {models}) m, {algos} a, (select unnest({designs.CHANNELS}) channel), (select unnest(['all_reduce', 'scatter_reduce']) pattern),
(select unnest(['bsp', 'async']) protocol), (select unnest(['fs', 'vc', 'hp']) infra), (select unnest([10, 50]) w)
where (needs_convex = 'false' or convex = 'true') and (clusters = 'true') = (algorithm = 'em') and (channel <> 'kv_db' or m_bytes <= 400000)
and (infra = 'vc') = (channel = 'direct') and (infra = 'hp') = (channel = 'vm_ps') and (protocol = 'bsp' or (algorithm = 'ga' and pattern = 'all_reduce'))"""


_STATS = f"st as (select ({hash_sql('worker', 'vec_id')} % 8)::int worker, unnest(range(64))::int coord, unnest(embedding)::double value from embeddings)"
_MEAN = f"with {_STATS} select coord, round(avg(value), 6) + 0.0e0 as value from st group by coord"
_LEDGER = [("all_reduce", "object_store", 10, 1), ("scatter_reduce", "object_store", 22, 8), ("scatter_reduce", "direct", 14, 8), ("all_reduce", "vm_ps", 2, 1)]
_EVENT_F = "case when event_type = 'click' then 1.0e0 else -1.0e0 end y, least(value, 500.0e0) / 250.0e0 - 1 f0, hour(ts) / 11.5e0 - 1 f1, (props->>'k')::int / 49.5e0 - 1 f2"


def _small_step(before: str) -> str:
    c = "(-1.0e0 / (1.0e0 + exp(y * (w3 + w0 * f0 + w1 * f1 + w2 * f2))) * y)"
    return f"(select any_value(w0) - 0.1e0 * avg(c * f0) w0, any_value(w1) - 0.1e0 * avg(c * f1) w1, any_value(w2) - 0.1e0 * avg(c * f2) w2, any_value(w3) - 0.1e0 * avg(c) w3 from (select *, {c} c from e, {before}))"


def _timeline() -> str:
    once = "case when phase in ('startup', 'load') then case when round = 0 then s else 0 end else s / 3 end"
    grid = f"g as (select 8000.0e0 s_mb, 0.000224e0 m_mb, 3.0e0 rounds, 90.0e0 compute_s, 10 w, 1.0e0 f_w)"
    phases = " union all ".join(f"select '{i}' infra, '{p}' phase, {c} s from {i}_" for i in ("fs", "vc") for p, c in (("startup", "startup_s"), ("load", "load_s"), ("communicate", "comm_s")))
    return f"""with {grid}, {terms_sql('fs_', 'fs', True)}, {terms_sql('vc_', 'vc', True)}, p as ({phases}), r as (select infra, phase, {once} s from p, (select unnest(range(3)) round) union all
select infra, 'compute', max(s) from (select day(ts) % 3 k, user_id % 10 j, sum(value) / 1000.0e0 s from events group by all), (select unnest(['fs', 'vc']) infra) group by infra, k)
select infra, coalesce(phase, 'total') as phase, round(sum(s), 6) as seconds from r group by rollup (infra, phase) having infra is not null"""


_TEXT = """d as (select doc_id, text from documents where doc_id in (select doc_id from labels where quality is not null)),
 w as (select doc_id, unnest(list_filter(regexp_split_to_array(lower(text), '[^\\p{L}\\p{N}]+'), lambda t: t <> '')) term from d),
 tf as (select doc_id, (""" + hash_sql("term", "term") + """ % 47236)::int coord, count(*) tf from w group by 1, 2),
 v as (select doc_id, coord, tf * (ln((1.0e0 + (select count(*) from d)) / (1.0e0 + count(*) over (partition by coord))) + 1.0e0) v from tf),
 x as materialized (select doc_id, coord, v / sqrt(sum(v * v) over (partition by doc_id)) as value from v)"""

_CTR = """e as (select *, (props->>'k')::int as k, hour(ts) as hh, isodow(ts) - 1 as wd from events), x as materialized (select event_id doc_id, coord, 1.0e0 as value from (""" + " union all ".join(f"select event_id, ({hash_sql(n, *c)} % 1048576)::int coord from e" for n, c in {"user": ["user_id"], "k": ["k"], "hour": ["hh"], "day_hour": ["wd", "hh"], "user_k": ["user_id", "k"], "user_hour": ["user_id", "hh"]}.items()) + "))"


def two_sparse_steps(source: str, labels: str, first: float, slope: str) -> str:
    """Two steps from nothing; `first` is the slope at margin 0."""
    return f"with {source}, y as ({labels}), n as (select count(*) n from y), m1 as materialized (select coord, -sum({num(first)} * y * value) / any_value(n) w from x join y using (doc_id), n group by coord), s as (select doc_id, sum(value * w) s from x join m1 using (coord) group by doc_id), m2 as (select coord, sum({slope} * y * value) / any_value(n) g from x join y using (doc_id) join s using (doc_id), n group by coord) select coord, round(w - g, 6) + 0.0e0 as value from m1 join m2 using (coord)"


_QUALITY = "select doc_id, case when quality = 1 then 1.0e0 else -1.0e0 end y from labels where quality is not null"
_LOGISTIC, _HINGE = "(-1.0e0 / (1.0e0 + exp(y * s)))", "(case when y * s < 1.0e0 then -1.0e0 else 0.0e0 end)"
_WIDE = f"v as materialized (select vec_id, unnest(range(64)) i, unnest(embedding)::double v from embeddings), l as (select vec_id, case when label = 0 then 1.0e0 else -1.0e0 end y from embeddings where {hash_sql('split', 'vec_id')} % 10 >= 1), x as materialized (select a.vec_id, a.i * 64 + b.i coord, a.v * b.v as value from v a join v b using (vec_id))"
_STORE_L, _STORE_B = num(_L["object_store"]), num(_B["object_store"])
_KINDS = [("fs", terms_sql("a", "fs", False, source="h"), FS_D), ("vc", terms_sql("b", "vc", False, source="h"), VC_D), ("vc_c5", terms_sql("c", "vc", False, net="net_c5_large", source="h"), f"{num(2 * constants.PRICE_VC)} * w * runtime_s"), ("gpu", terms_sql("d", "vc", False, net="net_c5_large", gpu=8.0, source="h"), f"{num(_GPU)} * w * runtime_s")]

#: Event types as workloads, as in tasks.event_work.
WORK = "(select event_type as task, count(*) n, count(distinct user_id) users, round(avg(value), 6) mean_s from events where event_type is not null group by 1)"

EVENT_GRID = f"g as (select t.*, w, 1 + growth * (w - 1) as f_w from (select task, 'ga' as algo, n * 64.0e0 / 1e6 s_mb, users * 8.0e0 / 1e6 m_mb, 10.0e0 rounds, n * mean_s / 1000.0e0 compute_s, 0.01e0 growth from {WORK}) t, (select unnest({analytic.WORKERS}) w))"

ORACLES: dict[str, str] = {
    "sparse_svm_step": two_sparse_steps(_TEXT, _QUALITY, -1.0, _HINGE),
    "ctr_lr_step": two_sparse_steps(_CTR, "select event_id doc_id, case when event_type = 'click' then 1.0e0 else -1.0e0 end y from events", -0.5, _LOGISTIC),
    "sparse_kmeans": f"with {_TEXT}, f as (select doc_id, row_number() over (order by doc_id) - 1 as cluster from (select distinct doc_id from x order by doc_id limit 3)), c as materialized (select cluster, coord, value c from x join f using (doc_id)), xx as (select doc_id, sum(value * value) xx from x group by doc_id), cc as (select cluster, sum(c * c) cc from c group by cluster), xc as (select doc_id, cluster, sum(value * c) xc from x join c using (coord) group by all), far as (select doc_id, cluster, round(xx - 2 * coalesce(xc, 0) + cc, 9) as dist from xx cross join cc left join xc using (doc_id, cluster)), b as (select doc_id, min(dist) d, arg_min(cluster, (dist, cluster))::int cluster from far group by doc_id) select cluster, count(*) as n, round(sum(d), 6) + 0.0e0 as loss from b group by cluster",
    "wide_lr_steps": f"with {_WIDE}, n as (select count(*) n from l), m1 as materialized (select coord, -sum(-0.5e0 * y * value) / any_value(n) w from x join l using (vec_id), n group by coord), s as (select vec_id, sum(value * w) s from x join m1 using (coord) group by vec_id), m2 as (select coord, sum({_LOGISTIC} * y * value) / any_value(n) g from x join l using (vec_id) join s using (vec_id), n group by coord) select coord::int as coord, round(w - g, 6) + 0.0e0 as value from m1 join m2 using (coord)",
    "pattern_table": f"select task as model, 10::int as w, users * 8.0e0 / 1e6 as m_mb, round(12 * (users * 8.0e0 / 1e6 / {_STORE_B} + {_STORE_L}), 6) as all_reduce_s, round(28 * (users * 8.0e0 / 1e6 / 10 / {_STORE_B} + {_STORE_L}), 6) as scatter_reduce_s from {WORK}",
    "_patterns": f"select model, w, m_mb, round((w + 2) * (m_mb / {_STORE_B} + {_STORE_L}), 6) as all_reduce_s, round((3 * w - 2) * (m_mb / w / {_STORE_B} + {_STORE_L}), 6) as scatter_reduce_s from {rows_sql([('lr', 50, 0.000224), ('conv', 10, 12.0), ('residual', 10, 89.0)], 'model, w, m_mb')}",
    "cache_threads": f"select task, m_mb, w, round((m_mb / w / ({num(_B['cache_t3_medium'])} / w) + {num(_L['cache_t3_medium'])}) / (m_mb / w / {num(_B['cache_t3_medium'])} + {num(_L['cache_t3_medium'])}), 6) as ratio from (select task, users * 8.0e0 / 1e6 m_mb from {WORK}), (select unnest([2, 10, 50]) w)",
    "rpc_servers": "select servers, round(3.7e0 - 0.6e0 + 0.6e0 / servers + 27.0e0, 6) as seconds from (select unnest([1, 2, 3, 4, 5]) servers)",
    "memory_failures": "select infra, batch, (350000000 + 4 * 89000000 + batch::bigint * 400 * (select coalesce(max(length(text)), 0) from documents)) / 1e9 <= gb as fits from (values ('fs', 3), ('vc', 64)) t(infra, gb), (select unnest([32, 64]) batch)",
    "workers_sweep": f"with {GRID}, {', '.join(t for _, t, _ in _ALL)} " + " union all ".join(f"select task, algo, '{n}' as infra, w, round(runtime_s, 6) as runtime_s, round({c}, 6) as dollars from {v}" for (n, _, c), v in zip(_ALL, "abcd")),
    "instance_scatter": f"with {EVENT_GRID}, h as (select * from g where w = 10), {', '.join(t for _, t, _ in _KINDS)}, r as (select unnest([0.01e0, 0.05e0, 0.1e0]) lr) " + " union all ".join(f"select task, '{n}' as infra, lr, w, round(startup_s + load_s + (comm_s + comp_s) * (0.1e0 / lr), 6) as runtime_s, round(({c}) * (startup_s + load_s + (comm_s + comp_s) * (0.1e0 / lr)) / runtime_s, 6) as dollars from {v}, r" for (n, _, c), v in zip(_KINDS, "abcd")),
    "payload_reduce": "select l_partkey // 1000 as block, round(sum(v), 6) as value, count(*) as n from (select l_partkey, avg(l_quantity) v from lineitem group by 1) group by 1",
    "dense28_features": f"with {dense_sql()} select l_orderkey, l_linenumber, l_partkey, l_suppkey, {', '.join(f'f{i}' for i in range(D))}, y, split, worker, batch from ex",
    "split_balance": f"with {dense_sql()} select split, worker, count(*) as n, count(*) filter (y > 0) as positive from ex group by all",
    "exact_partition": f"""with h as (select event_id, row_number() over (order by {hash_sql('worker', 'event_id')}, event_id) - 1 k, count(*) over () t from events) select floor(k * 7 / t)::int as worker, count(*) as n, sum(event_id)::bigint as ids from h group by 1""",
    "minmax_scale": "select l_orderkey, l_linenumber, l_partkey, l_suppkey, " + ", ".join(f"round(({c} - min({c}) over ()) / (max({c}) over () - min({c}) over ()) * 2.0::double - 1.0::double, 6) + 0.0e0 as {c}" for c in ("l_quantity", "l_extendedprice", "l_discount", "l_tax")) + " from lineitem",
    "tfidf_text": f"with {_TEXT} select doc_id, coord, round(value, 6) + 0.0e0 as value from x",
    "ctr_crosses": "with e as (select *, (props->>'k')::int as k, hour(ts) as hh, isodow(ts) - 1 as wd from events) select coord, count(*) as n from (" + " union all ".join(f"select ({hash_sql(n, *c)} % 1048576)::int coord from e" for n, c in {"user": ["user_id"], "k": ["k"], "hour": ["hh"], "day_hour": ["wd", "hh"], "user_k": ["user_id", "k"], "user_hour": ["user_id", "hh"]}.items()) + ") group by coord",
    "wide_outer_stats": "with a as (select vec_id, unnest(range(64)) i, unnest(embedding)::double v from embeddings) select (64 * a.i + b.i)::int as coord, round(avg(a.v * b.v), 6) + 0.0e0 as mean, count(*) as n from a join a b using (vec_id) group by 1",
    "grid_classes": f"""with a as (select vec_id, unnest(range(64)) i, unnest(embedding)::double v from embeddings), s as (select vec_id, c, sum(v * cos((c + 1)::double * (i + 1))) s from a, (select unnest(range(10)) c) group by all),
 y as (select vec_id, arg_max(c, (s, -c))::int y, case when {hash_sql('split', 'vec_id')} % 10 >= 1 then 'train' else 'validation' end split from s group by vec_id) select y, split, count(*) as n from y group by all""",
    "lr_gd": ga_sql(0.5, 1, 4),
    "lr_ga_sgd": ga_sql(0.3, 4, 1),
    "svm_ga_sgd": ga_sql(0.2, 4, 1, "svm", 0.01),
    "lr_ma_sgd": ma_sql(0.3, 4, 3, 2, 3, True),
    "lr_ma_sync2": ma_sql(0.3, 4, 4, 1, 2, False),
    "lr_admm": admm_sql(0.3, 3, 0.1, 2, 2),
    "kmeans_em": kmeans_sql(),
    "allreduce_mean": _MEAN,
    "scatter_reduce_mean": _MEAN,
    "tree_reduce_mean": _MEAN,
    "two_phase_missing": """with l as (select distinct day(ts)::int epoch, hour(ts)::int iteration, user_id % 8 worker from events where event_type = 'error'), r as (select distinct epoch, iteration from l)
select r.epoch, r.iteration, w.worker from r cross join (select unnest(range(8)) worker) w anti join l on l.epoch = r.epoch and l.iteration = r.iteration and l.worker = w.worker""",
    "grid_search_lr": f"with {dense_sql(1, 2)}, s0 as ({ZERO}), " + ", ".join(f"{_step(f'c{i}_1', 's0', 'batch = 0', r)}, {_step(f'c{i}_2', f'c{i}_1', 'batch = 1', r)}" for i, r in enumerate(GRID_RATES)) + " " + " union all ".join(f"select {num(r)} as lr, round(avg(greatest(-m, 0.0e0) + ln(1 + exp(-abs(m)))), 6) as loss from (select y * {_score()} m from ex, c{i}_2 where split = 'validation')" for i, r in enumerate(GRID_RATES)),
    "pipeline_end_to_end": f"with {dense_sql(10, 2)}, s0 as ({ZERO}), " + ", ".join(f"{_step(f'c{i}_1', 's0', 'batch = 0', r)}, {_step(f'c{i}_2', f'c{i}_1', 'batch = 1', r)}" for i, r in enumerate(GRID_RATES)) + ", p as (" + " union all ".join(f"select {num(r)} lr, y, {_score()} s from ex, c{i}_2 where split = 'validation'" for i, r in enumerate(GRID_RATES)) + "), l as (select lr, avg(greatest(-y * s, 0.0e0) + ln(1 + exp(-abs(y * s)))) loss from p group by lr) select count(*) as n, round(avg((y = case when s >= 0 then 1 else -1 end)::int), 6) as accuracy from p where lr = (select arg_min(lr, (loss, lr)) from l)",
    "tag_imbalance": " union all ".join(f"select '{t}' as tag, ({t_} )::int as label, count(*) as n, round(count(*) / sum(count(*)) over (), 6) as share from documents group by 2" for t, t_ in (("de", "coalesce(lang = 'de' or source = 'de', false)"), ("src0", "coalesce(lang = 'src0' or source = 'src0', false)"), ("fr", "coalesce(lang = 'fr' or source = 'fr', false)"))),
    "auc_toxic": "with d as (select toxic, n_chars::double s from documents join labels using (doc_id)), c as (select s, count(*) filter (toxic = 1) p, count(*) filter (toxic <> 1) q from d group by s), b as (select *, coalesce(sum(q) over (order by s rows between unbounded preceding and 1 preceding), 0) b from c) select sum(p)::bigint as n_pos, sum(q)::bigint as n_neg, round(sum(p * (b + q / 2.0e0)) / (sum(p) * sum(q)), 6) as auc from b",
    "class_metrics": f"with {dense_sql()}, p as (select y, case when 0.39e0{''.join(f' + {num(math.cos(i + 1))} * f{i}' for i in range(D))} >= 0 then 1.0e0 else -1.0e0 end h from ex where split = 'validation'), c as (select count(*) n, avg((y = h)::int) a, count(*) filter (y = 1 and h = 1) tp, count(*) filter (y <> 1 and h = 1) fp, count(*) filter (y = 1 and h <> 1) fn from p) select n, round(a, 6) as accuracy, round(tp / (tp + fp), 6) as precision, round(tp / (tp + fn), 6) as recall, round(2.0e0 * tp / (2 * tp + fp + fn), 6) as f1 from c",
    "stability_lag": "with d as (select event_type, day(ts) r, avg(value) v from events group by all), c as (select event_type, v - lag(v) over (partition by event_type order by r) ch from d) select event_type, count(*) filter (ch > 0)::bigint as rises, round(avg(ch), 6) + 0.0e0 as mean_change, round(var_pop(ch), 6) as variance from c group by event_type",
    "table_constants": f"select symbol, config, workers::int as workers, value, spread, unit from {rows_sql(constants.CONSTANTS, 'symbol, config, workers, value, spread, unit')}",
    "rpc_table": f"with t as {rows_sql(constants.RPC_TRIALS, 'workers, gb, server, t1, u1, t2, u2')} select workers, gb, server, 1 as framework, t1 as transfer_s, u1 as update_s, round(u1 / (u1 + t1), 6) as update_share from t union all select workers, gb, server, 2, t2, u2, round(u2 / (u2 + t2), 6) from t",
    "startup_curve": " union all ".join(f"select w, '{i}' as infra, round({startup_sql('w', i)}, 6) as seconds, w < 10 or w > 200 as extrapolated from (select unnest([1, 10, 30, 50, 75, 100, 150, 200, 300]) w)" for i in ("fs", "vc")),
    "runtime_fs_grid": grid_sql(terms_sql("t", "fs", False), FS_D),
    "runtime_vc_grid": grid_sql(terms_sql("t", "vc", True), VC_D),
    "runtime_hp_grid": grid_sql(terms_sql("t", "hp", False), HP_D),
    "runtime_bounds": f"with {GRID}, {terms_sql('a', 'fs', False, bound=-1)}, {terms_sql('b', 'fs', False)}, {terms_sql('c', 'fs', False, bound=1)} select b.task, b.algo, b.w, round(a.runtime_s, 6) as low_s, round(b.runtime_s, 6) as runtime_s, round(c.runtime_s, 6) as high_s from a join b using (task, algo, w) join c using (task, algo, w)",
    "cost_grid_pareto": f"with {EVENT_GRID}, {', '.join(t for _, t, _ in _ALL)}, every as materialized ({' union all '.join(f'select task, algo, {chr(39)}{n}{chr(39)} as infra, w, round(runtime_s, 6) as runtime_s, round({c}, 6) as dollars from {v}' for (n, _, c), v in zip(_ALL, 'abcd'))}) select * from every e where not exists (select 1 from every o where o.task = e.task and o.runtime_s <= e.runtime_s and o.dollars <= e.dollars and (o.runtime_s < e.runtime_s or o.dollars < e.dollars))",
    "regime_crossover": f"with {GRID}, {terms_sql('a', 'fs', True)}, {terms_sql('b', 'vc', True)}, x as (select a.task, a.algo, a.w, a.runtime_s f, b.runtime_s v, a.comm_s / a.runtime_s s, {FS_D.replace('w *', 'a.w *').replace('runtime_s', 'a.runtime_s').replace('startup_s', 'a.startup_s')} fd, {VC_D.replace('w *', 'b.w *').replace('runtime_s', 'b.runtime_s')} vd from a join b using (task, algo, w)), y as (select *, case when f <= v then 'fs' else 'vc' end winner, case when fd <= vd then 'fs' else 'vc' end cheaper from x) select task, algo, w, round(f, 6) as fs_s, round(v, 6) as vc_s, winner, cheaper, coalesce(lag(winner) over (partition by task, algo order by w) <> winner, false) as crossover, round(s, 6) as comm_share from y",
    "whatif_fast_link": f"with {GRID}, {', '.join(t for _, t, _ in _FAST)} " + " union all ".join(f"select task, algo, w, '{n}' as design, round(runtime_s, 6) as runtime_s, round({c}, 6) as dollars from {v}" for (n, _, c), v in zip(_FAST, "abcdef")),
    "whatif_hot_data": f"with {GRID}, {', '.join(t for _, t, _ in _HOT)} " + " union all ".join(f"select task, algo, w, '{n}' as design, round(s_mb / {num(b)}, 6) as load_s, round(startup_s + s_mb / {num(b)} + comm_s + comp_s, 6) as runtime_s from {v}" for (n, _, b), v in zip(_HOT, "abc")),
    "multitenant_peaks": "with h as (select event_type kind, date_trunc('hour', ts) h, count(*) n from events group by all) select kind, count(*) as hours, round(avg(n), 6) as mean_jobs, max(n) as max_jobs, round(max(n) / avg(n), 6) as peakiness from h group by kind",
    "multitenant_policies": policies_sql(),
    "design_space": designs_sql(),
    "breakdown_phases": _timeline(),
    "speedup_sanity": f"with {GRID}, {terms_sql('fs', 'fs', True)}, {terms_sql('vc', 'vc', True)}, t as ({' union all '.join(f'select task model, {chr(39)}{i}{chr(39)} infra, w, runtime_s - startup_s as seconds from {i} where algo = {chr(39)}admm{chr(39)} and w in (1, 10)' for i in ('fs', 'vc'))}) select t.model, t.infra, t.w, round(t.seconds, 6) as seconds, round(o.seconds / t.seconds, 6) as speedup from t join t o on o.model = t.model and o.infra = t.infra and o.w = 1",
    "channel_relative": channel_sql(f"(select task || '_w' || w as run, w, users * 8.0e0 / 1e6 m_mb, 10.0e0 rounds, mean_s base_s from {WORK}, (select unnest([10, 50]) w))"),
    "pattern_ledger": f"with {_STATS}, o as (select worker, count(distinct coord) * 8 m from st group by worker) " + " union all ".join(f"select '{p}' as pattern, '{c}' as channel, worker, {n}::bigint as n_msgs, ceil(m / {k} * {n})::bigint as n_bytes from o" for p, c, n, k in _LEDGER),
    "async_schedule": f"with d as (select ((user_id % 4 + 4) % 4)::int worker, round(avg(value), 6) delay from events where user_id is not null and value is not null group by 1), e as (select worker, step::int step, step * delay read_at, (step + 1) * delay write_at from d, (select unnest(range({ASYNC_STEPS})) step)), v as (select *, (select count(*) from e o where (o.write_at, o.worker) <= (e.write_at, e.worker)) version_written, (select count(*) from e o where o.write_at <= e.read_at) version_read from e) select worker, step, read_at, write_at, version_read::int as version_read, version_written::int as version_written, (version_written - version_read - 1)::int as staleness from v",
    "lr_async": async_sql(0.5, 2, True),
    "lr_async_add": async_sql(0.5, 2, False),
    "lifetime_restarts": "with s as (select o_custkey worker, o_orderkey step, o_totalprice / 1000.0e0 as seconds, sum(o_totalprice / 1000.0e0) over (partition by o_custkey order by o_orderkey) as u from orders), i as (select *, greatest(ceil(u / 840.0e0) - 1, 0)::int i from s) select worker, step, round(seconds, 6) as seconds, round(u, 6) as until_s, i as incarnation, i > coalesce(lag(i) over (partition by worker order by step), 0) as restart from i",
    "sparse_lr_step": f"with {_TEXT}, y as (select doc_id, case when quality = 1 then 1.0e0 else -1.0e0 end y from labels where quality is not null), n as (select count(*) n from y), m1 as materialized (select coord, -sum(-0.5e0 * y * value) / any_value(n) w from x join y using (doc_id), n group by coord), s as (select doc_id, sum(value * w) s from x join m1 using (coord) group by doc_id), m2 as (select coord, sum(-1.0e0 / (1.0e0 + exp(y * s)) * y * value) / any_value(n) g from x join y using (doc_id) join s using (doc_id), n group by coord) select coord, round(w - g, 6) + 0.0e0 as value from m1 join m2 using (coord)",
    "retrain_stream": f"with e as materialized (select {_EVENT_F} from events), s0 as (select 0.0e0 w0, 0.0e0 w1, 0.0e0 w2, 0.0e0 w3), s1 as materialized {_small_step('s0')}, s2 as materialized {_small_step('s1')} select (select count(*) from e) as n, coord, round(value, 6) + 0.0e0 as value from (" + " union all ".join(f"select {i} as coord, w{i} as value from s2" for i in range(4)) + ")",
    "session_arrivals": "with g as (select *, coalesce(ts - lag(ts) over (partition by user_id order by ts) > interval 6 hours, true) starts from events), s as (select *, sum(starts::int) over (partition by user_id order by ts, event_id rows unbounded preceding) k from g) select user_id, epoch_us(min(ts)) as start_us, epoch_us(max(ts) + interval 6 hours) as end_us, count(*) as n, round(sum(value), 4) as value from s group by user_id, k",
    "price_as_of": "select p.event_id, p.user_id, v.value as last_view from (select * from events where event_type = 'purchase') p asof left join (select * from events where event_type = 'view') v on p.user_id = v.user_id and p.ts >= v.ts",
    "job_overlaps": "with j as (select event_id, epoch_us(ts) / 1e6 a, epoch_us(ts) / 1e6 + value * 60 b from events where event_type = 'signup') select l.event_id, count(*) as n from j l join j r on l.a < r.b and r.a < l.b and l.event_id <> r.event_id group by 1",
    "estimate_sample": f"select o_orderkey from orders where {hash_sql('sample', 'o_orderkey')} < {int(0.1 * 2**32)}",
    "hash_buckets": f"select {hash_sql('worker', 'o_orderkey')} % 16 as bucket, count(*) as n from orders group by 1",
}

# ---- views over events, vectors and published values

_VW = f"with {_WIDE}, n as (select count(*)::double n from l)"
_SCORES = "select vec_id, sum(value * w) s from x join {m} using (coord) group by vec_id"
_HINGE_LOSS = "select {k}::int as step, round(avg(greatest(0, 1 - y * s)), 6) + 0.0e0 as loss from l join {s} using (vec_id)"
_KM = "with v as materialized (select vec_id, unnest(range(64)) i, unnest(embedding)::double v from embeddings), x as materialized (select a.vec_id, a.i * 64 + b.i coord, a.v * b.v as value from v a join v b using (vec_id)), first as (select vec_id, row_number() over (order by vec_id) - 1 as cluster from (select vec_id from embeddings order by vec_id limit 10)), c0 as materialized (select cluster, coord, value c from x join first using (vec_id))"


def _km_step(k: int) -> str:
    nearest = f"d{k} as materialized (select vec_id, cluster, sum((value - c) * (value - c)) d from x join c{k} using (coord) group by all), a{k} as materialized (select vec_id, min(d) d, arg_min(cluster, (round(d, 9), cluster)) cluster from d{k} group by vec_id)"
    return f"{nearest}, c{k + 1} as materialized (select cluster, coord, avg(value) c from x join a{k} using (vec_id) group by all union all select cluster, coord, c from c{k} where cluster not in (select cluster from a{k}))"


def _published_channels() -> str:
    theirs = rows_sql(constants.PUBLISHED_CHANNELS, "run, channel, published_slowdown, published_cost")
    named = rows_sql([(*r[:4], RUN_TYPES[r[0].split("_")[0]]) for r in RUNS], "run, w, m_mb, rounds, task")
    ours = channel_sql(f"(select run, w, m_mb, rounds, rounds * mean_s / w as base_s from {named} join {WORK} using (task))")
    return f"with ours as ({ours}), theirs as (select run, channel, published_slowdown::double as published_slowdown, published_cost::double as published_cost from {theirs}) select run, channel, slowdown, published_slowdown, round(slowdown / published_slowdown - 1, 6) + 0.0e0 as slowdown_error, relative_cost, published_cost, round(relative_cost / published_cost - 1, 6) + 0.0e0 as cost_error from theirs join ours using (run, channel)"


_TYPES = ["click", "error", "purchase", "signup", "view"]
ORACLES |= {
    "wide_svm_steps": f"{_VW}, m1 as materialized (select coord, sum(y * value) / any_value(n) w from x join l using (vec_id), n group by coord), s1 as materialized ({_SCORES.format(m='m1')}), g1 as (select coord, sum(y * value) / any_value(n) g from x join l using (vec_id) join s1 using (vec_id), n where y * s < 1 group by coord), m2 as materialized (select coord, w + coalesce(g, 0) w from m1 left join g1 using (coord)), s2 as materialized ({_SCORES.format(m='m2')}) select 0::int as step, 1.0e0 as loss union all {_HINGE_LOSS.format(k=1, s='s1')} union all {_HINGE_LOSS.format(k=2, s='s2')}",
    "wide_kmeans": f"{_KM}, {_km_step(0)}, {_km_step(1)} select 0::int as step, round(avg(d), 6) + 0.0e0 as loss from a0 union all select 1::int, round(avg(d), 6) + 0.0e0 from a1",
    "published_channels": _published_channels(),
    "published_patterns": f"with p as ({ORACLES.pop('_patterns')}), t as {rows_sql(constants.PUBLISHED_PATTERNS, 'model, a, s')}, q as (select model, (w + 2) * (m_mb / {_STORE_B} + {_STORE_L}) a0, (3 * w - 2) * (m_mb / w / {_STORE_B} + {_STORE_L}) s0 from p) select model, round(a0 / s0, 6) as ratio, round(a::double / s::double, 6) as published_ratio, round(a0 / a::double - 1, 6) as all_reduce_error, round(s0 / s::double - 1, 6) as scatter_reduce_error from q join t using (model)",
    "published_pipelines": f"with t as {rows_sql(constants.PUBLISHED_PIPELINES, 'infra, model, seconds, accuracy, published')}, d as (select infra, model, seconds::double * 100.0e0 * case when infra = 'fs' then {num(constants.PRICE_FS)} else {num(constants.PRICE_VC)} end as d, published::double as published_dollars from t) select infra, model, round(d, 6) as dollars, published_dollars, round(d / published_dollars - 1, 6) as error from d",
    "time_to_loss": "with d as (select dayofyear(ts)::int as round, avg(value) l, sum(value) s from events group by 1), r as (select min(d.round) as round from d where l <= (select avg(l) from d)) select d.round, round(s, 4) as seconds, d.round as rounds from d join r on d.round = r.round",
    "event_ranks": "select event_id, row_number() over w as row_no, rank() over w as rank, dense_rank() over w as dense, ntile(4) over w as tile, round(percent_rank() over w, 6) + 0.0e0 as percent, round(cume_dist() over w, 6) + 0.0e0 as cume from events where event_type = 'purchase' window w as (partition by event_type order by value desc, event_id)",
    "event_cube": "select event_type, hour(ts)::int as hour, grouping_id(event_type, hour(ts))::int as level, count(*) as n, round(sum(value), 2) + 0.0e0 as total from events group by cube (event_type, hour(ts))",
    "event_sets": "select 'event_type' as kind, event_type as key, count(*) as n from events group by event_type union all select 'hour', hour(ts)::varchar, count(*) from events group by hour(ts)",
    "daily_types": f"select d.day::int as day, t.event_type, (select count(*) from events e where day(e.ts) = d.day and e.event_type = t.event_type) as n from (select distinct day(ts) as day from events) d, (select unnest({_TYPES}) as event_type) t",
    "user_sets": "with b as (select distinct user_id from events where event_type = 'purchase'), c as (select distinct user_id from events where event_type = 'click') select 'both' as kind, count(*) as n from (from b intersect from c) union all select 'only_click', count(*) from (from c except from b) union all select 'either', count(*) from (from b union from c)",
    "user_balance": "select user_id, count(*) filter (event_type = 'click') as click, count(*) filter (event_type = 'purchase') as purchase from events where event_type in ('click', 'purchase') group by user_id",
    "dearest_purchases": "select user_id, event_id, value from events where event_type = 'purchase' qualify row_number() over (partition by user_id order by value desc, event_id) <= 2",
    "value_change": "select event_type, count(*) filter (day(ts) % 2 = 0) as n_before, count(*) filter (day(ts) % 2 = 1) as n_after, round(avg(value) filter (day(ts) % 2 = 1) - avg(value) filter (day(ts) % 2 = 0), 6) + 0.0e0 as change from events group by event_type",
    "sketch_errors": "select event_type, count(distinct user_id) as users, true as distinct_ok, true as median_ok, true as bars_ok from events group by event_type",
    "join_ways": "select way, n from (select count(*) as n from orders join customer on o_custkey = c_custkey), (select unnest(['broadcast', 'merge', 'shuffle_hash']) as way)",
    "vector_products": "select vec_id, round(list_inner_product(embedding::double[], embedding::double[]), 5) + 0.0e0 as dot, round(3 * list_sum(embedding::double[]), 5) + 0.0e0 as total from embeddings",
    "label_means": "select label, i::int as coord, round(avg(v), 5) + 0.0e0 as value from (select label, unnest(range(64)) i, unnest(embedding)::double v from embeddings) group by label, i",
    "rate_stream": "select residue, count(*) as n from (select unnest(range(100)) % 7 as residue) group by 1",
    "invocation_plan": "select 0::int as worker, 'events.parquet' as name, 0::int as attempt",
}
