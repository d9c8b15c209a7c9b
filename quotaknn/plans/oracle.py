"""DuckDB SQL that answers the same questions by other means: exact truth by a program over cells in a recursive query."""

from __future__ import annotations

from quotaknn.functions.lsh import BASE, Family
from quotaknn.sources.catalog import ATTRS, RELATION_SQL

DISTANCE = {"l2": "list_distance({a}, {b})", "cosine": "(1 - list_cosine_similarity({a}, {b}))"}


def base(relation: str, attrs: list[str], n: int, k: int, seed: int = 1) -> str:
    """CTEs v, drawn, q (query_id, qvec, src), quotas (query_id, attr, value, need)."""
    known = " and ".join(f"{a} is not null" for a in attrs) or "true"
    parts = " union all ".join(f"select query_id, '{a}' as attr, {a} as value from drawn where rn <= {k}" for a in attrs)
    return f"""v as ({RELATION_SQL[relation]}),
drawn as (select * from (select query_id, v.*, row_number() over (partition by query_id order by ((rec_id % 1000003) * 2654435761 + query_id * 40503017 + {seed}) % 4294967291, rec_id) as rn
  from v, (select unnest(range({n})) as query_id) where {known}) where rn <= {k + 1}),
q as (select query_id, vec as qvec, rec_id as src from drawn where rn = {k + 1}),
quotas as (select query_id, attr, value, cast(count(*) as integer) as need from ({parts}) group by all)"""


def pool(attrs: list[str], metric: str = "l2") -> str:
    """CTEs nd, rel, ranked, pool: the k_cell nearest of each coarse cell of every query."""
    joins = " ".join(f"join nd n{i} on n{i}.query_id = q.query_id and n{i}.attr = '{a}' and n{i}.value = v.{a}" for i, a in enumerate(attrs))
    ps = ", ".join(f"n{i}.pos as p{i}" for i in range(len(attrs)))
    p = ", ".join(f"p{i}" for i in range(len(attrs)))
    kc = "least(" + ", ".join(f"n{i}.need" for i in range(len(attrs))) + ")"
    return f"""nd as (select *, row_number() over (partition by query_id order by attr, value) - 1 as pos from quotas where need > 0),
rel as (select q.query_id, v.rec_id, {DISTANCE[metric].format(a='v.vec', b='q.qvec')} as dist, {ps}, {kc} as kc from q join v on v.rec_id <> q.src {joins}),
ranked as (select *, row_number() over (partition by query_id, {p} order by dist, rec_id) as rk from rel),
pool as (select *, dense_rank() over (partition by query_id order by {p}) as cell from ranked where rk <= kc)"""


def solve(attrs: list[str], source: str = "pool") -> str:
    """CTEs opts, dp, best over the rows of `source` (cell, rk by distance, p0...)."""
    m = range(len(attrs))
    p = ", ".join(f"p{i}" for i in m)
    fits = " and ".join(f"((d.state >> cast(4 * o.p{i} as integer)) & 15) >= o.take" for i in m)
    weight = " + ".join(f"(1::bigint << cast(4 * o.p{i} as integer))" for i in m)
    return f"""opts as (select query_id, cell, {p}, rk as take, sum(dist) over w as cost, list(rec_id) over w as ids from {source}
    window w as (partition by query_id, cell order by rk rows between unbounded preceding and current row)
  union all select distinct query_id, cell, {p}, 0, 0.0::double, []::bigint[] from {source}),
dp(query_id, step, state, cost, ids) as (
  select query_id, 0::bigint, cast(sum(need::bigint << cast(4 * pos as integer)) as bigint), 0.0::double, []::bigint[] from nd group by query_id
  union all
  select d.query_id, d.step + 1, d.state - o.take * ({weight}), min(d.cost + o.cost), arg_min(list_concat(d.ids, o.ids), d.cost + o.cost)
  from dp d join opts o on o.query_id = d.query_id and o.cell = d.step + 1 and {fits} group by 1, 2, 3),
best as (select d.query_id, d.cost, d.ids from dp d join (select query_id, max(cell) as last from {source} group by 1) c on c.query_id = d.query_id and c.last = d.step where d.state = 0)"""


ANSWERS = """select q.query_id, case when best.query_id is null then 'infeasible' else 'ok' end as status, round(best.cost, 6) as total_dist,
array_to_string(list_sort(best.ids), ',') as ids from q left join best using (query_id)"""


def truth(relation: str, m: int, n: int, k: int, metric: str = "l2", tail: str = ANSWERS) -> str:
    attrs = ATTRS[relation][:m]
    return f"with recursive {base(relation, attrs, n, k)},\n{pool(attrs, metric)},\n{solve(attrs)}\n{tail}"


def projections(family: Family) -> str:
    """The family's numbers as rows (table_no, hash_no, a, b)."""
    a, b = family.projections()
    rows = [f"({t}, {h}, [{', '.join(repr(float(x)) for x in a[t, h])}], {float(b[t, h])!r})" for t in range(family.tables) for h in range(family.hashes)]
    return f"proj(table_no, hash_no, a, b) as (values {', '.join(rows)})"


def keys(family: Family, rows: str, key: str, vec: str, name: str = "keys") -> str:
    """CTE `name` (key, table_no, bucket) for the vectors of a CTE."""
    one = "case when list_dot_product(x.{v}, p.a::double[]) >= 0 then 1 else 0 end" if family.kind == "sign" else "cast(floor((list_dot_product(x.{v}, p.a::double[]) + p.b) / {w!r}) as bigint)"
    one = one.format(v=vec, w=family.width)
    power = " ".join(f"when {h} then {BASE ** (family.hashes - 1 - h)}" for h in range(family.hashes))
    return f"""{name} as (select {key}, table_no, cast(sum(h * case hash_no {power} end) as bigint) as bucket
  from (select x.{key}, p.table_no, p.hash_no, {one} as h from {rows} x, proj p) group by {key}, table_no)"""


def codes(attrs: list[str]) -> str:
    """CTEs dict (attr_no, attr, value, code, width), fields (attr, width, shift, mask), coded (v with cell_code)."""
    parts = " union all ".join(f"select {i} as attr_no, '{a}' as attr, {a} as value from v where {a} is not null" for i, a in enumerate(attrs))
    joins = " ".join(f"left join fields d{i} on d{i}.attr = '{a}' and d{i}.value = v.{a}" for i, a in enumerate(attrs))
    total = " + ".join(f"coalesce(d{i}.code * (1::bigint << cast(d{i}.shift as integer)), 0)" for i in range(len(attrs)))
    return f"""dict as (select attr_no, attr, value, dense_rank() over (partition by attr order by value) as code from (select distinct * from ({parts}))),
widths as (select attr_no, attr, cast(ceil(log2(count(*) + 1)) as bigint) as width from dict group by all),
shifts as (select *, coalesce(sum(width) over (order by attr_no desc rows between unbounded preceding and 1 preceding), 0) as shift from widths),
fields as (select d.attr_no, d.attr, d.value, d.code, s.width, cast(s.shift as bigint) as shift, ((1::bigint << cast(s.width as integer)) - 1) * (1::bigint << cast(s.shift as integer)) as mask from dict d join shifts s using (attr_no, attr)),
coded as (select v.*, cast({total} as bigint) as cell_code from v {joins})"""


def query_codes(attrs: list[str]) -> str:
    """CTE asked (query_id, mask, qcode, k_cell); needs quotas and fields."""
    p = [f"select x.query_id, f.mask, f.code * (1::bigint << cast(f.shift as integer)) as at, x.need from quotas x join fields f using (attr, value) where x.attr = '{a}' and x.need > 0" for a in attrs]
    froms = " join ".join(f"({s}) a{i}" + ("" if i == 0 else " using (query_id)") for i, s in enumerate(p))
    m = range(len(attrs))
    return f"""asked as (select query_id, cast({' + '.join(f'a{i}.mask' for i in m)} as bigint) as mask, cast({' + '.join(f'a{i}.at' for i in m)} as bigint) as qcode,
  least({', '.join(f'a{i}.need' for i in m)}) as k_cell from {froms})"""
