"""DuckDB SQL building blocks: fixtures, keys, and recursive trajectories of the coordinate solvers."""

from __future__ import annotations

import math

from coordloom.operators.permute import PRIME, MULT, _constants, affine_constants

EMBED = "select vec_id as eid, case when label < 5 then 1.0 else -1.0 end::double as y, list_transform(embedding, lambda v: v::double) as x from embeddings"
LINE_ORDER = "l_orderkey, l_linenumber, l_partkey, l_suppkey, l_quantity, l_extendedprice, l_discount, l_tax, l_returnflag, l_linestatus, l_shipdate"
TEACH = "((37 * {j} + 11) % 19 - 9) / 9.0::double"
MD5N = "('0x' || substr(md5({t}), 1, 15))::bigint"


def planted(score: str, eid: str = "eid", cut: str = "0") -> str:
    return f"case when ({score} >= {cut}) <> ({eid} % 20 = 0) then 1.0 else -1.0 end::double"


LINE = f"""
select eid, case when (s >= 0.9) <> (eid % 20 = 0) then 1.0 else -1.0 end::double as y, case when l_returnflag = 'R' then 1.0 else -1.0 end::double as y_flag, x from (
  select *, list_sum(list_transform(x, lambda v, j: v * ((37 * (j - 1) + 11) % 19 - 9) / 9.0::double)) as s from (
    select row_number() over (order by {LINE_ORDER}) - 1 as eid, l_returnflag,
      [(l_quantity / 50)::double, (l_extendedprice / 105000)::double, (l_discount * 10)::double, (l_tax * 12.5)::double, (l_linenumber / 7)::double, 1.0::double] as x from lineitem))
"""

ORDER = f"""
select o_orderkey as eid, {planted("list_sum(list_transform(idx, lambda j: ((37 * j + 11) % 19 - 9) / 9.0::double))", "o_orderkey")} as y, idx, list_transform(idx, lambda j: 1.0::double) as val from (
  select o_orderkey, list_transform([list_position(['F', 'O', 'P'], o_orderstatus) - 1, 3 + substr(o_orderpriority, 1, 1)::int - 1, 7 + month(o_orderdate), 20 + {MD5N.format(t="c_mktsegment")} % 5, 25 + n_nationkey, 50 + n_regionkey,
    55 + least(9, floor(o_totalprice / 50000))::int, 65], lambda i: i::int) as idx
  from orders join customer on o_custkey = c_custkey join nation on c_nationkey = n_nationkey)
"""

TEXT = f"""
with l as (select row_number() over (order by doc_id) - 1 as eid, text, quality, toxic from documents join labels using (doc_id)),
tokens as (select eid, unnest(regexp_split_to_array(lower(text), '[^a-z0-9]+')) as t from l),
slots as (select eid, ({MD5N.format(t="t")} % 2048)::int as i, ln(1 + count(*)::double) as v from tokens where t <> '' group by 1, 2),
norms as (select eid, sqrt(sum(v * v)) as norm from slots group by eid)
select l.eid, case when quality = 1 then 1.0 else -1.0 end::double as y, case when toxic = 1 then 1.0 else -1.0 end::double as y_toxic, s.i, s.v / norm as v
from l left join slots s using (eid) left join norms using (eid)
"""

EVENT = """
select event_id as eid, case when event_type = 'purchase' then 1.0 else -1.0 end::double as y,
  [hour(ts), 23 + dayofweek(ts) + 1, 31 + user_id % 64, 95 + least(9, floor((props->>'$.k')::int / 10)), 105, 106]::int[] as idx, [1.0, 1.0, 1.0, 1.0, value / 100, 1.0]::double[] as val from events
"""

WIDE = f"""
select eid, {planted("list_sum(list_transform(idx, lambda j: ((37 * j + 11) % 19 - 9) / 9.0::double))")} as y, idx, list_transform(idx, lambda j: 1.0::double) as val from (
  select eid, list_transform([list_position(['A', 'N', 'R'], l_returnflag) - 1, 3 + case when l_linestatus = 'O' then 1 else 0 end, 4 + l_linenumber, 12 + {MD5N.format(t="p_brand")} % 25, 37 + {MD5N.format(t="p_type")} % 6, 43 + s_nationkey,
    68 + substr(o_orderpriority, 1, 1)::int - 1, 72 + month(l_shipdate), 85 + l_partkey % 1024], lambda i: i::int) as idx
  from (select row_number() over (order by {LINE_ORDER}) - 1 as eid, * from lineitem) join part on l_partkey = p_partkey join supplier on l_suppkey = s_suppkey join orders on l_orderkey = o_orderkey)
"""


def _mix(i: str, j: str, salt: int) -> str:
    b = f"((({i} * 7919 + {j} * 104729 + {salt} * 15485863) % 2147483647) * 48271 % 2147483647)"
    return f"((({b} + ({b} % 65536) * 40503) * 16807) % 2147483647)"


def _numbers(rows: int | str) -> str:
    """So many numbers i, or those of a query."""
    return f"range({rows}) t(i)" if isinstance(rows, int) else f"({rows}) t(i)"


def synth_dense(n: int | str, d: int) -> str:
    return f"""select eid, {planted("list_sum(list_transform(x, lambda v, j: v * ((37 * (j - 1) + 11) % 19 - 9) / 9.0::double))")} as y, x from (
  select i as eid, list_transform(range({d}), lambda j: ({_mix("i", "j", 1)} % 2001 - 1000) / 1000.0::double) as x from {_numbers(n)})"""


def synth_sparse(n: int | str, d: int, draws: int) -> str:
    return f"""select eid, {planted("list_sum(list_transform(idx, lambda j: ((37 * j + 11) % 19 - 9) / 9.0::double))")} as y, idx, list_transform(idx, lambda j: 1.0::double) as val from (
  select i as eid, list_sort(list_distinct(list_transform(range({draws}), lambda j: ({_mix("i", "j", 2)} % {d})::int))) as idx from {_numbers(n)})"""


def key_sql(number: str, epoch: int, seed: int, order: str, n: str | int) -> str:
    if order == "md5":
        return f"md5({number} || ':{epoch}:{seed}')"
    if order == "affine":
        a, c = affine_constants(int(n), epoch, seed)
        return f"(({number} * {a} + {c}) % {n})"
    return number


def feistel_sql(x: str, n: int, epoch: int, seed: int) -> str:
    """One walk of the bijection as SQL (callers repeat it while the value is n or more)."""
    m, constants = _constants(n, epoch, seed)
    left, right = f"({x} // {m})", f"({x} % {m})"
    for a, c in constants:
        left, right = right, f"(({left} + ((({right} * {a} + {c}) % {PRIME}) * {MULT} % {PRIME}) % {m}) % {m})"
    return f"({left} * {m} + {right})"


def step_sql(loss: str, z: str, q: str, y: str, a: str, s: str) -> str:
    if loss == "ridge":
        return f"(({y} - {z} - {a}) / (1 + {s}))"
    b = f"({y} * {a})"
    if loss == "hinge":
        return f"({y} * (greatest(0.0, least(1.0, {b} + (1 - {y} * {z}) / {s})) - {b}))"
    if loss == "squared_hinge":
        return f"({y} * (greatest(0.0, (1 - {y} * {z} + {s} * {b}) / ({s} + 0.5)) - {b}))"
    if loss == "smooth_hinge":
        return f"({y} * (greatest(0.0, least(1.0, (1 - {y} * {z} + {s} * {b}) / ({s} + 0.5))) - {b}))"
    # logistic: 40 Newton steps on the logit, as a fold
    newton = f"list_reduce(list_prepend(-({y} * {z}), list_transform(range(40), lambda k: 0.0::double)), lambda u, k: u - (u + {y} * {z} + {s} * (1 / (1 + exp(-u)) - {b})) / (1 + {s} * (1 / (1 + exp(-u))) * (1 - 1 / (1 + exp(-u)))))"
    return f"({y} * (1 / (1 + exp(-({newton}))) - {b}))"


def _epochs(loss: str, lam: float, bucket: int, epochs: int, order: str, seed: int, groups: int, workers: int, deal: str, merge: str, _n: str, nb: int = 0, syncs: int = 1, seeds: tuple[int, ...] = ()) -> str:
    """Recursion over the places in the workers' lists: one row of state per worker, merged after each slice of an epoch.

    w{t} and al{t} are the state after t slices. With ``seeds`` every epoch is a first one with a seed of its own."""
    out = f", blocks as (select *, eid // {bucket} as bid, eid % {bucket} as k from data), nb as (select max(bid) + 1 as nb from blocks)"
    out += ", w0 as (select list_transform(range((select len(x) from data limit 1)), lambda i: 0.0::double) as w)"
    per = workers // groups
    prev_w, prev_a = "w0", "(select eid, 0.0::double as alpha from data)"
    for t in range(epochs * syncs):
        epoch, part = divmod(t, syncs)
        drawn = (0, seeds[epoch]) if seeds else (epoch, seed)
        key = f"md5(bid || ':{drawn[0]}:{drawn[1]}')" if order == "md5" else "bid" if order == "none" else None
        if key is None:
            a, c = affine_constants(nb, epoch, seed)
            key = f"((bid * {a} + {c}) % {nb})"
        out += f""", bk{t} as (select distinct bid, bid * {groups} // nb as gid, {key} as key, nb from blocks, nb),
rk{t} as (select *, count(*) over (partition by gid) as gnb, row_number() over (partition by gid order by key, bid) - 1 as r, row_number() over (partition by gid order by bid) - 1 as r0 from bk{t}),
dl{t} as (select *, gid * {per} + ({'r0' if deal == 'static' else 'r'} * {per}) // gnb as wid from rk{t}),
pl{t} as (select bid, wid, row_number() over (partition by wid order by key, bid) - 1 as pos, count(*) over (partition by wid) as m from dl{t}),
busy{t} as (select count(distinct wid)::double as kk from pl{t}),
ps{t} as (select * from pl{t} where pos >= m * {part} // {syncs} and pos < m * {part + 1} // {syncs}),
ex{t} as materialized (select p.wid, row_number() over (partition by p.wid order by p.pos, b.k) - 1 as t, b.eid, b.y, b.x, list_dot_product(b.x, b.x) as q, a.alpha from ps{t} p join blocks b using (bid) join {prev_a} a using (eid)),
sc{t} as (select {'kk' if merge == 'add' else '1.0::double'} as sigma, {'1.0::double' if merge == 'add' else '1.0 / kk'} as gamma from busy{t}),
run{t} as (
  select wid, -1::bigint as t, (select w from {prev_w}) as w, null::bigint as eid, null::double as alpha from (select distinct wid from ex{t})
  union all
  select wid, t, list_transform(list_zip(w, x), lambda p: p[1] + sigma * delta / ({lam}::double * n) * p[2]) as w, eid, alpha + gamma * delta as alpha from (
    select r.wid, e.t, r.w, e.x, e.eid, e.alpha, sc.sigma, sc.gamma, n.n, {step_sql(loss, "list_dot_product(e.x, r.w)", "e.q", "e.y", "e.alpha", f"(sc.sigma * e.q / ({lam}::double * n.n))")} as delta
    from run{t} r join ex{t} e on e.wid = r.wid and e.t = r.t + 1, sc{t} sc, n)),
last{t} as (select w from run{t} qualify t = max(t) over (partition by wid)),
pos{t} as (select unnest(range(len(w))) as i, w from {prev_w}),
w{t + 1} as (select list(v order by i) as w from (
  select p.i, any_value(p.w[p.i + 1]) + any_value(gamma) * sum((l.w[p.i + 1] - p.w[p.i + 1]) / sigma) as v from pos{t} p, last{t} l, sc{t} group by p.i)),
al{t + 1} as materialized (select eid, alpha from run{t} where eid is not null{f" union all select eid, alpha from {prev_a} a where eid not in (select eid from ex{t})" if syncs > 1 else ""})"""
        prev_w, prev_a = f"w{t + 1}", f"al{t + 1}"
    return out


def trajectory_sql(loss: str, lam: float, bucket: int = 1, epochs: int = 2, order: str = "md5", seed: int = 42, groups: int = 1, workers: int = 1, deal: str = "dynamic", merge: str = "add", nb: int = 0, syncs: int = 1) -> str:
    """(pos, value) of w after some epochs on the dense embeddings."""
    head = f"with recursive data as materialized ({EMBED}), n as (select count(*)::bigint as n from data)"
    body = _epochs(loss, lam, bucket, epochs, order, seed, groups, workers, deal, merge, "n", nb, syncs)
    return head + body + f" select i::int as pos, round(w[i + 1], 6) as value from (select unnest(range(len(w))) as i, w from w{epochs * syncs})"


def objective_sql(lam: float, epochs: int, seed: int) -> str:
    """(epoch, primal, dual, gap_ok) of ridge after each of some first epochs with seeds of their own; w = A alpha / (lam n) holds, so the dual is taken at w."""
    head = f"with recursive data as materialized ({EMBED}), n as (select count(*)::bigint as n from data)"
    body = _epochs("ridge", lam, 1, epochs, "md5", seed, 1, 1, "dynamic", "add", "n", 0, 1, tuple(seed + e for e in range(epochs)))
    one = "select {e}::int as epoch, avg((list_dot_product(x, w) - y) ** 2) / 2 + {half}::double * any_value(list_dot_product(w, w)) as primal, -avg(alpha * alpha / 2 - alpha * y) - {half}::double * any_value(list_dot_product(w, w)) as dual from data join al{e} using (eid), w{e}"
    rows = " union all ".join(one.format(e=e + 1, half=lam / 2) for e in range(epochs))
    return head + body + f" select epoch, round(primal, 6) as primal, round(dual, 6) as dual, primal - dual >= -1e-12 as gap_ok from ({rows})"


def sag_sql(lam: float, bucket: int, seed: int = 42) -> str:
    """(pos, value) of w after one pass of the average-gradient solver on the embeddings, ridge."""
    return f"""with recursive data as materialized ({EMBED}), n as (select count(*)::double as n, 1.0 / (max(list_dot_product(x, x)) + {lam}::double) as rate from data),
ex as materialized (select row_number() over (order by md5((eid // {bucket}) || ':0:{seed}'), eid) - 1 as t, y, x from data),
run as (
  select -1::bigint as t, list_transform(range((select len(x) from data limit 1)), lambda i: 0.0::double) as w, list_transform(range((select len(x) from data limit 1)), lambda i: 0.0::double) as g
  union all
  select t, list_transform(list_zip(w, g), lambda p: p[1] - rate * (p[2] + {lam}::double * p[1])) as w, g from (
    select e.t, r.w, rate, list_transform(list_zip(r.g, e.x), lambda p: p[1] + (list_dot_product(e.x, r.w) - e.y) / n * p[2]) as g from run r join ex e on e.t = r.t + 1, n))
select i::int as pos, round(w[i + 1], 6) as value from (select unnest(range(len(w))) as i, w from (select w from run order by t desc limit 1))"""


def lossy_sql(lam: float, threads: int, lost: bool, seed: int = 42) -> str:
    """One epoch of the emulator on the embeddings, ridge: rounds that read one snapshot."""
    apply = "max_by(delta * xi, r)" if lost else "sum(delta * xi)"
    return f"""with recursive data as materialized ({EMBED}), n as (select count(*)::bigint as n from data),
ex as materialized (select *, (row_number() over (order by md5(eid || ':0:{seed}'), eid) - 1) as r, list_dot_product(x, x) as q from data),
run as (
  select -1::bigint as t, list_transform(range((select len(x) from data limit 1)), lambda i: 0.0::double) as w
  union all
  select t + 1, (select list(v order by i) from (
      select i, w[i + 1] + {apply} / ({lam}::double * any_value(nn)) as v from (
        select e.r, n.n as nn, (e.y - list_dot_product(e.x, w)) / (1 + e.q / ({lam}::double * n.n)) as delta, unnest(range(len(e.x))) as i, unnest(e.x) as xi from ex e, n where e.r // {threads} = t + 1) where xi <> 0 group by i))
  from run where (t + 1) * {threads} < (select n from n))
select i::int as pos, round(w[i + 1], 6) as value from (select unnest(range(len(w))) as i, w from (select w from run order by t desc limit 1))"""
