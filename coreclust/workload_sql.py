"""SQL counterparts of the workloads, for an engine whose recursive queries may use window aggregates.

Statements are put together from instances (id, part, w, v) and distance expressions; all
figures are whole numbers.
"""

from __future__ import annotations

from .plans.resolve import ROWS

L1 = "abs({a}.x - {b}.x)"
L1_2D = "(abs({a}.x - {b}.x) + abs({a}.y - {b}.y))"
SQUARE = "({a}.x - {b}.x) * ({a}.x - {b}.x)"
SQUARE_2D = "(({a}.x - {b}.x) * ({a}.x - {b}.x) + ({a}.y - {b}.y) * ({a}.y - {b}.y))"
HAMMING = "(({a}.x <> {b}.x)::bigint + ({a}.y <> {b}.y)::bigint + ({a}.z <> {b}.z)::bigint)"
EDIT = "levenshtein({a}.x, {b}.x)"


def parts(key: str, table: str, least: int = 4) -> str:
    return f"({key} % greatest({least}, (select ceil(count(*) / {ROWS}.0)::bigint from {table})))::int"


CENTS = "cast(round({} * 100) as bigint)"
CUSTOMER = f"select c_custkey::bigint as id, {parts('c_custkey', 'customer')} as part, 1::bigint as w, {{'x': {CENTS.format('c_acctbal')}}} as v from customer"
SUPPLIER = f"select s_suppkey::bigint as id, {parts('s_suppkey', 'supplier', 2)} as part, 1::bigint as w, {{'x': {CENTS.format('s_acctbal')}}} as v from supplier"
PART_V = "{'x': (p_size * 10)::bigint, 'y': cast(round(p_retailprice * 10) as bigint)}"
PART = f"select p_partkey::bigint as id, {parts('p_partkey', 'part')} as part, 1::bigint as w, {PART_V} as v from part"
PART_CATEGORIES = f"select p_partkey::bigint as id, {parts('p_partkey', 'part')} as part, 1::bigint as w, {{'x': p_brand, 'y': p_type, 'z': p_size::varchar}} as v from part"
PART_WEIGHTED = f"select p_partkey::bigint as id, {parts('p_partkey', 'part')} as part, greatest(1, coalesce(l.n, 0))::bigint as w, {PART_V} as v from part left join (select l_partkey, count(*) as n from lineitem group by l_partkey) l on l_partkey = p_partkey"
ORDERS = f"select o_orderkey::bigint as id, {parts('o_orderkey', 'orders', 11)} as part, 1::bigint as w, {{'x': cast(round(o_totalprice / 100) as bigint), 'y': (date_diff('day', date '1995-01-01', o_orderdate::date) * 10)::bigint}} as v from orders"
EVENTS = f"select event_id::bigint as id, date_diff('day', date '1970-01-01', ts::date)::int as part, 1::bigint as w, {{'x': {CENTS.format('value')}, 'y': ((date_part('hour', ts) * 3600 + date_part('minute', ts) * 60 + floor(date_part('second', ts)))::bigint // 36)}} as v from events"
#: Every character of the texts as a byte of its own, so that byte and character edits are the same; for up to 127 different ones.
_ALPHABET = "(select list(distinct c order by c) from (select unnest(string_split(coalesce(text, ''), '')) as c from benchmark))"
BENCHMARK = f"select item_id::bigint as id, {parts('item_id', 'benchmark', 2)} as part, 1::bigint as w, {{'x': coalesce(array_to_string(list_transform(list_filter(string_split(coalesce(text, ''), ''), lambda c: c <> ''), lambda c: chr(list_position(abc, c)::int)), ''), '')}} as v from benchmark cross join (select {_ALPHABET} as abc)"


def _d(dist: str, a: str, b: str) -> str:
    return dist.format(a=a, b=b)


def seeded(src: str, dist: str, m: int, number: str = "hugeint") -> str:
    """pts, ff (one row a point and step), dt (cost to the seeds), tol (weight and cost by part)."""
    return f"""
pts as materialized ({src}),
ff as (
  select 1 as step, id, part, w, v, pid, {_d(dist, 'v', 'pv')} as d
  from (select *, min(id) over (partition by part) as pid, arg_min(v, id) over (partition by part) as pv from pts)
  union all
  select step + 1, id, part, w, v, npid, least(d, {_d(dist, 'v', 'npv')})
  from (select *, arg_max(id, (d, -id)) over (partition by part) as npid, arg_max(v, (d, -id)) over (partition by part) as npv, max(d) over (partition by part) as md from ff where step < {m})
  where md > 0),
dt as materialized (select id, part, w, v, min(d) as d from ff group by id, part, w, v),
tol as materialized (select part, sum(w)::{number} as n, sum(w * d)::{number} as r from dt group by part)"""


def covered(name: str, source: str, dist: str, p: int = 1, order: str = "id", floor: bool = True, num: int = 1, den: int = 2, number: str = "hugeint") -> str:
    """Greedy cover of `source` (id, part, w, v, d, n, r) as tables {name} (steps) and {name}_tau; in whole numbers, or in floats by the engine's own order of operations."""
    first = ("min(id)", "arg_min(v, id)") if order == "id" else ("arg_max(id, (d, -id))", "arg_max(v, (d, -id))")
    pick = f"{first[0]} over (partition by part) as pid, {first[1]} over (partition by part) as pv"
    reach = "greatest(r, n * d)" if floor else "n * d"
    near = f"{_d(dist, 'v', 'pv')}::hugeint * {2 * den**p} * n <= {num**p} * {reach}" if number == "hugeint" else f"{_d(dist, 'v', 'pv')} <= {num**p / (2 * den**p)} * greatest(r / n, d)"
    return f"""
{name} as (
  select 1 as step, id, part, w, v, d, n, r, {pick} from ({source})
  union all
  select step + 1, id, part, w, v, d, n, r, {pick} from {name} where not ({near})),
{name}_tau as materialized (select id, part, w, arg_max(pid, step) as tau_id, arg_max({_d(dist, 'v', 'pv')}, step) as d, any_value(d) as d_t from {name} group by id, part, w)"""


FIRST = "select dt.*, tol.n, tol.r from dt join tol using (part)"


def second(dist: str, **options) -> str:
    """Round 2: distances to the union of the first cover, the global tolerance, and the cover against them."""
    source = "select * from d2"
    return f"""
c1 as materialized (select distinct pts.id, pts.v from cov_tau join pts on pts.id = cov_tau.tau_id),
every as materialized (select sum(n)::hugeint as n, sum(r)::hugeint as r from tol),
d2 as materialized (select p.id, p.part, p.w, p.v, min({_d(dist, 'p.v', 'c.v')}) as d, any_value(every.n) as n, any_value(every.r) as r from pts p cross join c1 c cross join every group by p.id, p.part, p.w, p.v),
{covered('cov2', source, dist, **options)}"""


def core(tables: str, name: str = "cov_tau", label: str = "part") -> str:
    return f"with recursive {tables} select part as {label}, tau_id as id, sum(w)::bigint as w from {name} group by part, tau_id"


def one_round(src: str, dist: str, m: int, number: str = "hugeint", **options) -> str:
    return f"{seeded(src, dist, m, number)}, {covered('cov', FIRST, dist, number=number, **options)}"


def given(src: str, dist: str, k: int, **options) -> str:
    """Covers of the parts against the k smallest ids as targets of all, each part with its own tolerance."""
    return f"""{centers_of(src, k)}, dt as materialized (select p.id, p.part, p.w, p.v, min({_d(dist, 'p.v', 'c.v')}) as d from pts p cross join cen c group by p.id, p.part, p.w, p.v),
tol as materialized (select part, sum(w)::hugeint as n, sum(w * d)::hugeint as r from dt group by part), {covered('cov', FIRST, dist, **options)}"""


def two_round(src: str, dist: str, m: int, p: int = 1) -> str:
    return f"{one_round(src, dist, m, p=p)}, {second(dist, p=p)}"


def centers_of(src: str, k: int) -> str:
    """The k smallest ids of an instance serve as stated centers."""
    return f"pts as materialized ({src}), cen as materialized (select id as center_id, v from pts order by id limit {k})"


def nearest(src: str, dist: str, k: int) -> str:
    return f"with {centers_of(src, k)}, near as (select p.id, p.w, arg_min(c.center_id, ({_d(dist, 'p.v', 'c.v')}, c.center_id)) as center_id, min({_d(dist, 'p.v', 'c.v')})::bigint as d from pts p cross join cen c group by p.id, p.w)"
