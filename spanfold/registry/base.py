"""Registration, and SQL shared by the reference forms."""

from __future__ import annotations

REGISTRY: dict = {}


def query(sql: str | None = None):
    def keep(f):
        REGISTRY[f.__name__] = (f, sql)
        return f

    return keep


# lineitem with its dense position, features and target as scaled integers
LINES = """
lines as (
  select *, row_number() over (order by l_orderkey, l_linenumber, l_partkey, l_suppkey, l_extendedprice, l_shipdate) - 1 as pid,
    (l_orderkey * 7919 + l_partkey * 104729 + l_suppkey * 1299709 + l_linenumber * 15485863) % 1000 as h
  from lineitem),
pts as (
  select pid, l_returnflag, l_linestatus, l_orderkey, l_partkey, l_suppkey, l_shipdate, h,
    cast(cast(l_quantity as decimal(18,2)) * 100 as bigint) as v1, cast(cast(l_extendedprice as decimal(18,2)) * 100 as bigint) as v2,
    cast(cast(l_discount as decimal(18,2)) * 100 as bigint) as v3, cast(cast(l_tax as decimal(18,2)) * 100 as bigint) as v4,
    cast(l_linenumber as bigint) as v5, l_partkey % 10 as v6, l_suppkey % 7 as v7, cast(month(l_shipdate) as bigint) as v8,
    cast(day(l_shipdate) as bigint) as v9, case when l_returnflag = 'R' then 1 else 0 end as v10
  from lines),
full_pts as (
  select *, 3 * v1 - 20 * v3 + v5 * 100 + 2 * h - 1000 as y,
    56 * v1 + 21000 * v3 - 17500 * v4 + v2 / 100.0 + 140 * h - 297500 as z,
    case when 5600 * v1 + 2100000 * v3 - 1750000 * v4 + v2 + 14000 * h - 29750000 > 0 then 1 else 0 end as c2,
    case when 5600 * v1 + 2100000 * v3 - 1750000 * v4 + v2 + 14000 * h - 29750000 <= -6000000 then 'low'
         when 5600 * v1 + 2100000 * v3 - 1750000 * v4 + v2 + 14000 * h - 29750000 > 6000000 then 'high' else 'middle' end as c3
  from pts),
size as (select count(*) as n from lineitem)
"""

#: Logistic features of the design: a constant and ten scaled columns.
SCALED = """
sc as (
  select pid, c2, [1.0, v1 / 100.0 / 50.0, v2 / 100.0 / 105000.0, v3 / 100.0 / 0.1, v4 / 100.0 / 0.08, v5 / 7.0, v6 / 10.0, v7 / 7.0, v8 / 12.0, v9 / 31.0, v10 / 1.0]::double[] as x
  from full_pts)
"""

UNITS = "[1, 100, 100, 100, 100, 1, 1, 1, 1, 1, 1, 100]"


def linreg_sql(where: str, by: str = "") -> str:
    """Packed second moments of (1, ten features, target) over some points, long form."""
    cols = f"{by}, " if by else ""
    return f"""
with {LINES},
p as (select {cols} [1, v1, v2, v3, v4, v5, v6, v7, v8, v9, v10, y]::hugeint[] as x from full_pts, size where {where}),
idx as (select i, j from (select unnest(range(12)) as i) a, (select unnest(range(12)) as j) b where i <= j)
select {cols} cast(i as int) as i, cast(j as int) as j, cast(sum(x[i + 1] * x[j + 1]) as double) / ({UNITS}[i + 1] * {UNITS}[j + 1]) as v
from p, idx group by {cols} i, j"""


def events_sql(where: str, extra: str = "") -> str:
    """Per class and feature: count, sum and sum of squares over some events."""
    cols = f"{extra}, " if extra else ""
    return f"""
with size as (select count(*) as n from events),
e as (select {cols} event_type as class, unnest([
    {{'name': 'value', 'v': cast(cast(value as decimal(18,2)) * 100 as hugeint), 'u': 100}},
    {{'name': 'k', 'v': cast(cast(props->>'$.k' as int) as hugeint), 'u': 1}},
    {{'name': 'hour', 'v': cast(hour(ts) as hugeint), 'u': 1}},
    {{'name': 'user10', 'v': cast(user_id % 10 as hugeint), 'u': 1}}]) as f
  from events, size where {where})
select {cols} class, f.name as feature, count(*) as n, cast(sum(f.v) as double) / max(f.u) as s, cast(sum(f.v * f.v) as double) / (max(f.u) * max(f.u)) as q
from e group by {cols} class, f.name"""


#: Ends of the running example, as parts of the number of events: a b c d e f.
ENDS = {"a": (1, 10), "b": (2, 10), "c": (35, 100), "d": (6, 10), "e": (85, 100), "f": (9, 10)}


def ends_of(n: int) -> dict:
    return {k: n * p // q for k, (p, q) in ENDS.items()}


ENDS_SQL = "ends as (select " + ", ".join(f"n * {p} // {q} as {k}" for k, (p, q) in ENDS.items()) + " from (select count(*) as n from events))"

#: 25 descriptors spread over the events' keys, in ten-thousandths of their number, and a request.
PLACES = [(f"m{i:02d}", (i * 7919) % 9300, (i * 7919) % 9300 + 50 + (i * 104729) % 450) for i in range(25)]
MODELS_SQL = """n_events as (select count(*) as n from events),
models as (select 'm' || lpad(cast(i as varchar), 2, '0') as model_id, (i * 7919) % 9300 * n // 10000 as lo, ((i * 7919) % 9300 + 50 + (i * 104729) % 450) * n // 10000 as hi
  from (select unnest(range(25)) as i), n_events),
ask as (select n * 2 // 10 as a, n * 52 // 100 as b, n from n_events)"""


def models_of(n: int) -> list:
    return [(m, lo * n // 10000, hi * n // 10000) for m, lo, hi in PLACES]


def request_of(n: int) -> tuple[int, int]:
    return n * 2 // 10, n * 52 // 100


GROUPS_SQL = """
swept as (select *, case when max(hi) over w is null or lo >= max(hi) over w then 1 else 0 end as opens from models
  window w as (order by lo, hi, model_id rows between unbounded preceding and 1 preceding)),
islands as (select *, sum(opens) over (order by lo, hi, model_id rows between unbounded preceding and current row) as island from swept),
grouped as (select island, min(lo) as glo, max(hi) as ghi, count(*) as n_models, string_agg(model_id, ',' order by model_id) as model_ids from islands group by island)
"""
