"""SQL for DuckDB that answers zonal queries by brute force: every pixel against every edge.

It never forms runs: a pixel lies inside a zone if the number of edges whose crossing is at
or left of its centre, compared by cross-multiplication, is odd.
"""

from __future__ import annotations

#: raster: (meta source, pixel select); the select sees w and h.
RASTERS = {
    "RO": ("select count(*) as n from orders", "select o_orderkey % w as x, o_orderkey // w as y, cast(round(o_totalprice * 100) as bigint) as v from orders, m"),
    "RT": ("select count(*) as n from orders", "select o_orderkey % w as x, o_orderkey // w as y, case when o_orderkey % 11 <> 0 then round(o_totalprice * 100) / cast(64 as double) end as v from orders, m"),
    "RC": ("select count(*) as n from orders", "select o_orderkey % w as x, o_orderkey // w as y, cast(substr(o_orderpriority, 1, 1) as bigint) as v from orders, m"),
    "RE": ("select count(*) as n from events", "select event_id % w as x, event_id // w as y, cast(round(value * 100) as bigint) as v from events, m"),
    "RD": ("select count(*) as n from documents", "select doc_id % w as x, doc_id // w as y, n_chars as v from documents, m"),
    "RL": ("select count(*) as n from documents", "select doc_id % w as x, doc_id // w as y, cast(quality as bigint) as v from labels, m"),
    "RM": (None, "select i as x, vec_id as y, cast(round(cast(e as double) * 1000000) as bigint) as v from (select vec_id, unnest(embedding) as e, unnest(range(len(embedding))) as i from embeddings)"),
    "RP": (None, "select l_partkey as x, l_suppkey as y, cast(sum(cast(l_quantity as bigint)) as bigint) as v from lineitem group by all"),
}
SHAPES = {
    "RM": "select max(len(embedding)) as w, max(vec_id) + 1 as h from embeddings",
    "RP": "select max(l_partkey) + 1 as w, max(l_suppkey) + 1 as h from lineitem",
}
_OUT = "(0,-2,-5),(1,2,-5),(2,5,-2),(3,5,2),(4,2,5),(5,-2,5),(6,-5,2),(7,-5,-2)"
_IN = "(0,0,-2),(1,2,0),(2,0,2),(3,-2,0)"


def _scattered(tab: str, key: str, scale: str, fx: int, fy: int, dx: int, dy: int, rings: list[str]) -> str:
    parts = [
        f"select cast({key} as bigint) as zone_id, {n} as ring, i, ({fx} * cast({key} as bigint) % w) * 16 + {dx} + ({scale}) * dx as gx, "
        f"({fy} * cast({key} as bigint) % h) * 16 + {dy} + ({scale}) * dy as gy from {tab}, m, (values {r}) as t(i, dx, dy)"
        for n, r in enumerate(rings)
    ]
    return " union all ".join(parts)


_NATION = """
select {zone} as zone_id, n_nationkey as ring, c as i,
  (16 * w * ci) // 5 + case when ci in (0, 5) then 0 else 11 * ((7 * ci + 13 * cj) % 5 - 2) end as gx,
  (16 * h * cj) // 5 + case when cj in (0, 5) then 0 else 9 * ((11 * ci + 5 * cj) % 5 - 2) end as gy
from (select *, cast(n_nationkey % 5 as bigint) + a as ci, cast(n_nationkey // 5 as bigint) + b as cj
      from nation, (values (0,0,0),(1,1,0),(2,1,1),(3,0,1)) as t(c, a, b)), m"""

ZONES = {
    "ZN": ("select cast(n_nationkey as bigint) as zone_id from nation", _NATION.format(zone="cast(n_nationkey as bigint)")),
    "ZR": ("select distinct cast(n_regionkey as bigint) as zone_id from nation", _NATION.format(zone="cast(n_regionkey as bigint)")),
    "ZS": ("select s_suppkey as zone_id from supplier", _scattered("supplier", "s_suppkey", "10 + s_suppkey % 20", 37, 61, 3, 5, [_OUT, _IN])),
    "ZC": ("select c_custkey as zone_id from customer", _scattered("customer", "c_custkey", "3 + c_custkey % 9", 7919, 104729, 3, 5, [_OUT])),
    "ZP": ("select p_partkey as zone_id from part", _scattered("part", "p_partkey", "2 + p_size % 13", 613, 769, 1, 1, [_IN])),
    "ZB": (
        "select cast(r_regionkey as bigint) as zone_id from region",
        """
select cast(r_regionkey as bigint) as zone_id, 0 as ring, t as i,
  case when t <= 80 then 7 + (16 * w - 14) * t // 80 when t = 81 then 7 + 16 * w - 14 else 7 end as gx,
  case when t <= 80 then 16 * h * r_regionkey // 5 + 3 + case when t % 2 = 1 then 3 * (16 * h // 5 - 6) // 4 else 0 end
       else 16 * h * (r_regionkey + 1) // 5 - 3 end as gy
from region, m, (select unnest(range(83)) as t)""",
    ),
}


def base(zone: str, raster: str, where: str = "true") -> str:
    """CTEs m(w, h), px(x, y, v), zone(zone_id), edge(zone_id, xa, ya, xb, yb)."""
    n, pixels = RASTERS[raster]
    shape = SHAPES.get(raster) or f"select w, (n + w - 1) // w as h from (select n, cast(ceil(sqrt(n)) as bigint) as w from ({n}))"
    ids, vertices = ZONES[zone]
    return f"""
m as ({shape}),
px as ({pixels}),
zone as (select zone_id from ({ids}) where {where}),
vertex as (select * from ({vertices}) where zone_id in (select zone_id from zone)),
side as (
  select zone_id, gx, gy,
    coalesce(lead(gx) over s, first_value(gx) over s) as hx, coalesce(lead(gy) over s, first_value(gy) over s) as hy
  from vertex window s as (partition by zone_id, ring order by i rows between unbounded preceding and unbounded following)),
edge as (
  select zone_id, case when gy < hy then gx else hx end as xa, least(gy, hy) as ya,
         case when gy < hy then hx else gx end as xb, greatest(gy, hy) as yb
  from side where gy <> hy)"""


def pairs(zone: str, raster: str, where: str = "true", pixels: str = "px") -> str:
    """As ``base``, and pair(zone_id, x, y, v)."""
    return base(zone, raster, where) + f""",
pair as (
  select zone_id, x, y, v from {pixels}, edge
  where 16 * y + 8 >= ya and 16 * y + 8 < yb and xa * (yb - ya) + (16 * y + 8 - ya) * (xb - xa) <= (16 * x + 8) * (yb - ya)
  group by zone_id, x, y, v having count(*) % 2 = 1)"""


AGGS = "count(*) as cnt, cast(sum(v) as bigint) as sum_v, min(v) as min_v, max(v) as max_v"


def zonal(zone: str, raster: str, where: str = "true", avg: bool = False) -> str:
    more = ", avg_v" if avg else ""
    return f"""with {pairs(zone, raster, where)},
got as (select zone_id, {AGGS}{', cast(sum(v) as double) / count(*) as avg_v' if avg else ''} from pair group by zone_id)
select zone.zone_id, coalesce(cnt, 0) as cnt, sum_v, min_v, max_v{more} from zone left join got on got.zone_id = zone.zone_id"""


def zonal_real(zone: str, raster: str = "RT", avg: bool = False) -> str:
    """Doubles and missing values: sums stay doubles, counts skip nodata."""
    more = ", avg_v" if avg else ""
    return f"""with {pairs(zone, raster)},
got as (select zone_id, count(v) as cnt, sum(v) as sum_v, min(v) as min_v, max(v) as max_v{', sum(v) / count(v) as avg_v' if avg else ''} from pair group by zone_id)
select zone.zone_id, coalesce(cnt, 0) as cnt, sum_v, min_v, max_v{more} from zone left join got on got.zone_id = zone.zone_id"""


def ceil_div(a: str, b: str) -> str:
    """Ceiling of whole numbers, whatever way the engine rounds negatives."""
    return f"((({a}) + ((({b}) - ({a}) % ({b})) % ({b}))) // ({b}))"


CROSSINGS = f"""
crossing as (
  select zone_id, y, {ceil_div('n - 8 * d', '16 * d')} as x
  from (select *, yb - ya as d, xa * (yb - ya) + (16 * y + 8 - ya) * (xb - xa) as n
        from (select *, unnest(range(greatest({ceil_div('ya - 8', '16')}, 0), least({ceil_div('yb - 8', '16')}, h))) as y from edge, m)))"""

RUNS = CROSSINGS + """,
run as (
  select zone_id, y, greatest(x, 0) as x0, least(nx, w) as x1
  from (select zone_id, y, x, lead(x) over s as nx, row_number() over s as k from crossing window s as (partition by zone_id, y order by x)), m
  where k % 2 = 1 and greatest(x, 0) < least(nx, w))"""


def cut_runs(tile_w: int | str, tile_h: int) -> str:
    return RUNS + f""",
piece as (
  select zone_id, y, greatest(x0, c * {tile_w}) as x0, least(x1, (c + 1) * {tile_w}) as x1,
         (y // {tile_h}) * ((w + {tile_w} - 1) // {tile_w}) + c as tile_id
  from (select *, unnest(range(x0 // {tile_w}, (x1 - 1) // {tile_w} + 1)) as c from run), m)"""
