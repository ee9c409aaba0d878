"""SQL over the given tables that gives the rows of our queries.

Written against the tables directly, and with other means than the engine
where there are any: common areas come from rectangle parts in each block's
own frame, groups from a recursive walk.
"""

from __future__ import annotations

from functools import cache

from cityweave import workload
from cityweave.plans import ontology as onto
from cityweave.functions import crs
from cityweave.sources import city as C

_TURN = C.TURNED
STREETS = workload.STREET


def _values(rows) -> str:
    return ", ".join("(" + ", ".join(f"{x!r}::double" if isinstance(x, float) else repr(x) for x in r) + ")" for r in rows)


def _points(rings: dict) -> str:
    return _values((v, s, i, float(x), float(y)) for (v, s), ring in sorted(rings.items()) for i, (x, y) in enumerate(ring))


def _parts(common: dict, variants: dict) -> str:
    rows = []
    for v, own in variants.items():
        for slot, shape in sorted((common | own).items()):
            turned = int(v == _TURN and slot in own)
            boxes = [(0, 0, 12, 4), (0, 4, 4, 12)] if shape == "L" else [shape]
            rows += [(v, slot, turned, *map(float, b)) for b in boxes]
    return _values(rows)


def _text(points: str, z: str = "") -> str:
    """Comma-joined points of a ring, closed, in order i."""
    one = "printf('%.3f %.3f', x, y)" if not z else f"printf('%.3f %.3f %.3f', x, y, {z})"
    return f"string_agg({one}, ', ' order by i) || ', ' || max(case when i = 0 then {one} end)"


@cache
def base() -> str:
    """Common table expressions; a query uses what it names."""
    number = "regexp_extract(p_brand, '([0-9]+)', 1)::int % 5"
    codes = " ".join(f"when {k} then {c}" for k, (c, _) in C.ROOF_CODES.items())
    labels = " ".join(f"when {k} then '{n}'" for k, (_, n) in C.ROOF_CODES.items())
    roads = " ".join(f"when {k} then '{n}'" for k, n in enumerate(C.ROAD_CLASSES))
    homes = ", ".join(f"'{c}'" for c in C.RESIDENTIAL)
    return f"""with recursive
building as (
  select p_partkey::bigint as building_id, p_size::double as height_m, case {number} {codes} end as roof_code, case {number} {labels} end as roof_label,
         p_type as usage, p_partkey // 8 as b, (p_partkey // 8) % 5 as v, p_partkey % 8 as slot
  from part
),
crowd as (
  select c_custkey::bigint as area_id, case when c_acctbal >= 0 then c_name end as label, c_custkey // 6 as b, (c_custkey // 6) % 5 as v, c_custkey % 6 as slot,
         case c_mktsegment when 'HOUSEHOLD' then 'HousingBlock' || substr('ABC', (c_custkey % 3 + 1)::int, 1) when 'BUILDING' then 'DetachedHome' || substr('AB', (c_custkey % 2 + 1)::int, 1)
              when 'FURNITURE' then 'Hotel' when 'MACHINERY' then 'Workshop' else 'Garage' end as class
  from customer
),
city_layout(v, slot, i, px, py) as (values {_points(C.CITY_LAYOUT)}),
crowd_layout(v, slot, i, px, py) as (values {_points(C.CROWD_LAYOUT)}),
city_boxes(v, slot, turned, x0, y0, x1, y1) as (values {_parts(C.COMMON_CITY, C.VARIANT_CITY)}),
crowd_boxes(v, slot, turned, x0, y0, x1, y1) as (values {_parts(C.COMMON_CROWD, C.VARIANT_CROWD)}),
city_pts as (select building_id as surface_id, i, px + b % 50 * 64 as x, py + b // 50 * 64 as y from building join city_layout using (v, slot)),
crowd_pts as (select area_id, i, px + b % 50 * 64 as x, py + b // 50 * 64 as y from crowd join crowd_layout using (v, slot)),
city_part as (select building_id as surface_id, b, turned, x0, y0, x1, y1 from building join city_boxes using (v, slot)),
crowd_part as (select area_id, b, turned, x0, y0, x1, y1 from crowd join crowd_boxes using (v, slot)),
city_area as (select surface_id, sum((x1 - x0) * (y1 - y0)) as area_m2 from city_part group by 1),
crowd_area as (select area_id, sum((x1 - x0) * (y1 - y0)) as area_m2 from crowd_part group by 1),
city_box as (select surface_id, min(x) as xmin, min(y) as ymin, max(x) as xmax, max(y) as ymax from city_pts group by 1),
crowd_box as (select area_id, min(x) as xmin, min(y) as ymin, max(x) as xmax, max(y) as ymax from crowd_pts group by 1),
commons as (
  select surface_id, area_id, sum(greatest(least(c.x1, w.x1) - greatest(c.x0, w.x0), 0) * greatest(least(c.y1, w.y1) - greatest(c.y0, w.y0), 0)) as common
  from city_part c join crowd_part w using (b, turned) group by 1, 2
),
overlap as (
  select surface_id, area_id, common, common / least(c.area_m2, w.area_m2) as ratio
  from commons join city_area c using (surface_id) join crowd_area w using (area_id) where common > 1e-9
),
edges as (select surface_id, area_id, ratio from overlap where ratio >= 0.5 - 1e-9),
nodes as (select surface_id * 2 as n, area_id * 2 + 1 as m from edges union select area_id * 2 + 1, surface_id * 2 from edges),
walk(n, m) as (select n, n from nodes union select walk.n, nodes.m from walk join nodes on walk.m = nodes.n),
groups as (select n, min(case when m % 2 = 0 then m // 2 end) as group_id, count(*) filter (m % 2 = 0) as surfaces, count(*) filter (m % 2 = 1) as areas from walk group by 1),
related as (
  select surface_id, area_id, ratio, group_id, case when surfaces = 1 and areas = 1 then '1:1' when areas = 1 then '1:n' when surfaces = 1 then 'm:1' else 'm:n' end as relation
  from edges join groups on n = surface_id * 2
),
classes as (
  select 'crowd' as layer, crowd.area_id as id, coalesce(max(relation), '1:0') as relation from crowd left join related using (area_id) group by 2
  union all select 'city', building_id, '0:1' from building where building_id not in (select surface_id from edges)
),
touching as (
  select a.surface_id, n.surface_id as neighbour_id,
         sum(case when a.x1 = n.x0 or n.x1 = a.x0 then greatest(least(a.y1, n.y1) - greatest(a.y0, n.y0), 0) else 0 end
           + case when a.y1 = n.y0 or n.y1 = a.y0 then greatest(least(a.x1, n.x1) - greatest(a.x0, n.x0), 0) else 0 end) as shared_m,
         min(sqrt(power(greatest(greatest(a.x0, n.x0) - least(a.x1, n.x1), 0), 2) + power(greatest(greatest(a.y0, n.y0) - least(a.y1, n.y1), 0), 2))) as gap
  from city_part a join city_part n using (b, turned) where a.surface_id <> n.surface_id group by 1, 2
),
matched as (select distinct surface_id from edges),
beside as (
  select t.surface_id, e.area_id, t.neighbour_id, t.shared_m, t.gap from touching t join edges e on e.surface_id = t.neighbour_id
  where t.surface_id not in (select surface_id from matched)
),
adjacent as (select surface_id, area_id, max(shared_m) as shared_m from beside where shared_m > 1e-6 group by 1, 2),
poi as (
  select o_orderkey::bigint as poi_id, o_custkey::bigint as host, o_orderpriority as class, xmin + (7 * o_orderkey) % 16 - 1.75 as x, ymin + (11 * o_orderkey) % 16 - 1.75 as y, o_custkey // 6 as b
  from orders join crowd_box on area_id = o_custkey
),
poi_local as (
  select poi_id, host, b, 0 as turned, x - b % 50 * 64 as lx, y - b // 50 * 64 as ly from poi
  union all select poi_id, host, b, 1, 0.8 * (x - b % 50 * 64 - 20) + 0.6 * (y - b // 50 * 64 - 20), -0.6 * (x - b % 50 * 64 - 20) + 0.8 * (y - b // 50 * 64 - 20) from poi
),
poi_area as (select distinct poi_id, area_id from poi_local join crowd_part using (b, turned) where lx > x0 and lx < x1 and ly > y0 and ly < y1),
links as (
  select surface_id, area_id, 'match' as kind, ratio, cast(null as double) as shared_m, relation from related
  union all select surface_id, area_id, 'adjacent', null, shared_m, null from adjacent
),
poi_links as (select distinct poi_id, surface_id, area_id from poi_area join links using (area_id)),
road as (
  select s_suppkey::bigint as road_id, s_name as label, case s_nationkey % 6 {roads} end as class, (s_suppkey % 20 * 160)::double as x, (s_suppkey // 20 * 64 - 8)::double as y from supplier
),
road_pts as (select road_id, 0 as i, x, y from road union all select road_id, 1, x + 80, y - 4 from road union all select road_id, 2, x + 160, y from road),
road_seg as (select a.road_id, a.i, a.x as x1, a.y as y1, n.x as x2, n.y as y2 from road_pts a join road_pts n on a.road_id = n.road_id and n.i = a.i + 1),
city_seg as (select a.surface_id, a.i, a.x as x1, a.y as y1, n.x as x2, n.y as y2 from city_pts a join (select surface_id, max(i) as top from city_pts group by 1) using (surface_id) join city_pts n on n.surface_id = a.surface_id and n.i = case when a.i = top then 0 else a.i + 1 end),
ends as (
  select road_id, surface_id, r.x1 as ux, r.y1 as uy, r.x2 as wx, r.y2 as wy, c.x1 as px, c.y1 as py from road_seg r join city_seg c on abs(c.y1 - r.y1) < 100 and c.x1 between r.x1 - 100 and r.x2 + 100
  union all select road_id, surface_id, c.x1, c.y1, c.x2, c.y2, r.x1, r.y1 from road_seg r join city_seg c on abs(c.y1 - r.y1) < 100 and c.x1 between r.x1 - 100 and r.x2 + 100
  union all select road_id, surface_id, c.x1, c.y1, c.x2, c.y2, r.x2, r.y2 from road_seg r join city_seg c on abs(c.y1 - r.y1) < 100 and c.x1 between r.x1 - 100 and r.x2 + 100
),
feet as (select *, greatest(0, least(1, ((px - ux) * (wx - ux) + (py - uy) * (wy - uy)) / (power(wx - ux, 2) + power(wy - uy, 2)))) as u from ends),
road_near as (select road_id, surface_id, min(sqrt(power(px - ux - u * (wx - ux), 2) + power(py - uy - u * (wy - uy), 2))) as d from feet group by 1, 2 having d <= 20),
ground_text as (select surface_id, 'POLYGON ((' || {_text("city_pts")} || '))' as shape from city_pts group by 1),
roof_text as (select surface_id as building_id, 'POLYGON Z ((' || {_text("city_pts", "height_m")} || '))' as shape from city_pts join building on building_id = surface_id group by 1),
area_text as (select area_id, 'POLYGON ((' || {_text("crowd_pts")} || '))' as shape from crowd_pts group by 1),
road_text as (select road_id, 'LINESTRING (' || string_agg(printf('%.3f %.3f', x, y), ', ' order by i) || ')' as shape from road_pts group by 1),
solid_floor as (
  select surface_id, string_agg(printf('%.3f %.3f %.3f', x, y, 0.0), ', ' order by i desc) || ', ' || max(case when i = top then printf('%.3f %.3f %.3f', x, y, 0.0) end) as t
  from city_pts join (select surface_id, max(i) as top from city_pts group by 1) using (surface_id) group by 1
),
solid_walls as (
  select surface_id, string_agg(printf('((%.3f %.3f 0.000, %.3f %.3f 0.000, %.3f %.3f %.3f, %.3f %.3f %.3f, %.3f %.3f 0.000))', x1, y1, x2, y2, x2, y2, height_m, x1, y1, height_m, x1, y1), ', ' order by i) as t
  from city_seg join building on building_id = surface_id group by 1
),
solid_text as (
  select f.surface_id as building_id, 'POLYHEDRALSURFACE Z (((' || f.t || ')), ' || w.t || ', ' || replace(r.shape, 'POLYGON Z ', '') || ')' as shape
  from solid_floor f join solid_walls w using (surface_id) join roof_text r on r.building_id = f.surface_id
),
address as (select s_suppkey::bigint as address_id, s_name as street, n_name as city, r_name as country, s_name || ', ' || n_name || ', ' || r_name as label from supplier join nation on n_nationkey = s_nationkey join region on r_regionkey = n_regionkey),
bridge as (select distinct l_partkey::bigint as building_id, l_suppkey::bigint as address_id from lineitem where l_linenumber = 1),
face as (select l_orderkey::bigint as ord, l_linenumber::bigint as line, l_partkey::bigint as building_id, l_suppkey::bigint as supp, case l_returnflag when 'R' then 'roof' when 'A' then 'wall' else 'closure' end as kind from lineitem),
roof as (select *, 'cw:f/' || ord || '/' || line || '/' || building_id || '/' || supp as iri from face where kind = 'roof'),
linked as (select surface_id, area_id, class, label, height_m, roof_label, class in ({homes}) as home from edges join crowd using (area_id) join building on building_id = surface_id)
"""


def q(select: str) -> str:
    return base() + select


_pair = "'cw:crowd/way/' || area_id as area, 'cw:g/' || surface_id as ground"
_q6 = f"select {_pair}, a.shape as \"areaShape\", g.shape as \"groundShape\" from linked join area_text a using (area_id) join ground_text g using (surface_id)"
_roads = ", ".join(f"'{c}'" for c in C.ROADS_OF_INTEREST)
_impact = f"from road_near join road using (road_id) join ground_text using (surface_id) join city_area using (surface_id) where class in ({_roads}) and contains(label, '{workload.ROAD_NAME}')"


def workload_sql() -> dict[str, str]:
    """By query; the same for every engine that answers it."""
    return {
        "q1_tall_addresses": q("select 'cw:b/' || building_id as building, label from building join bridge using (building_id) join address using (address_id) where height_m > 30"),
        "q2_address_contains": q(f"select 'cw:b/' || building_id as building, label from bridge join address using (address_id) where contains(label, '{STREETS}')"),
        "q2_address_exact": q(f"select 'cw:b/' || building_id as building, label from bridge join address using (address_id) where street = '{STREETS}'"),
        "q3_most_roofs": q("select 'cw:b/' || building_id as building, count(*) as roofs from roof group by 1 order by 2 desc, 1 limit 10"),
        "q4_tall_roofs": q("select iri as roof, shape from roof join building using (building_id) join roof_text using (building_id) where height_m > 30"),
        "q5_tall_solids": q("select 'cw:b/' || building_id as building, shape from building join solid_text using (building_id) where height_m > 30"),
        "q6_ground_pairs_listing": q(_q6 + " where height_m > 30"),
        "q6_ground_pairs_prose": q(_q6 + " where home"),
        "q6_ground_pairs_table": q(_q6 + " where home and height_m > 30"),
        "q7_tall_hotels": q("select 'cw:b/' || building_id as building, height_m::double as h, 'cw:crowd/way/' || area_id as area, label as name, shape from linked join solid_text on building_id = surface_id where class = 'Hotel' and height_m > 30"),
        "q8_tall_residential": q(f"select 'cw:b/' || surface_id as building, {_pair}, shape as \"groundShape\" from linked join ground_text using (surface_id) where home and height_m > 30"),
        "q8_entailed": q(f"select 'cw:b/' || surface_id as building, {_pair}, shape as \"groundShape\" from linked join ground_text using (surface_id) where home and height_m > 30"),
        "q9_pitched_residential": q(f"select 'cw:crowd/way/' || area_id as area, iri as roof, roof_label as \"roofType\", shape from linked join roof on building_id = surface_id join roof_text using (building_id) where home and roof_label <> '{workload.FLAT}'"),
        "q10_road_impact_rows": q(f"select 'cw:crowd/road/' || road_id as road, 'cw:g/' || surface_id as ground, shape, round(area_m2, 4) as area {_impact}"),
        "q10_road_impact_total": q(f"select count(*) as surfaces, round(sum(area_m2), 4) as total from (select distinct surface_id, area_m2 {_impact})"),
    }


def linker_sql() -> dict[str, str]:
    shares = "select stage, relation, count(*) as n, round(count(*) * 100.0::double / sum(count(*)) over (partition by stage), 4) as share"
    return {
        "fx_city_surface": q("select surface_id, building_id, height_m, roof_code, round(area_m2, 6) as area_m2, shape from city_area join building on building_id = surface_id join ground_text using (surface_id)"),
        "fx_crowd_area": q("select area_id, label, class, round(area_m2, 6) as area_m2, shape from crowd_area join crowd using (area_id) join area_text using (area_id)"),
        "fx_truth_edges": q("select surface_id, area_id, round(ratio, 6) as ratio from edges"),
        "link_edges": q("select surface_id, area_id, round(ratio, 6) as ratio, relation from related"),
        "link_classes_group": q("select layer, id, relation from classes"),
        "link_classes_degree": q("""select 'crowd' as layer, area_id as id, coalesce(case max(rank) when 3 then 'm:n' when 2 then '1:n' when 1 then 'm:1' when 0 then '1:1' end, '1:0') as relation
            from crowd left join (select area_id, case when ns > 1 and na > 1 then 3 when ns > 1 then 2 when na > 1 then 1 else 0 end as rank
              from (select area_id, count(*) over (partition by area_id) as ns, count(*) over (partition by surface_id) as na from edges)) using (area_id) group by 2
            union all select layer, id, relation from classes where layer = 'city'"""),
        "link_groups": q("select surface_id, area_id, group_id from related"),
        "link_adjacent_edge": q("select surface_id, area_id, round(shared_m, 6) as shared_m, 1 as hop from adjacent"),
        "link_adjacent_touch": q("select surface_id, area_id, round(max(shared_m), 6) as shared_m, 1 as hop from beside where gap <= 1e-6 group by 1, 2"),
        "link_adjacent_gap": q("select surface_id, area_id, round(max(shared_m), 6) as shared_m, 1 as hop from beside where gap <= 2.0 group by 1, 2"),
        "link_adjacent_transitive": q("""select surface_id, area_id, round(shared_m, 6) as shared_m, 1 as hop from adjacent
            union all select t.surface_id, a.area_id, round(max(t.shared_m), 6), 2 from touching t join adjacent a on a.surface_id = t.neighbour_id
            where t.shared_m > 1e-6 and t.surface_id not in (select surface_id from matched) and t.surface_id not in (select surface_id from adjacent) group by 1, 2"""),
        "link_adjacent_longest": q("""select b.surface_id, area_id, round(shared_m, 6) as shared_m, 1 as hop from beside b
            join (select surface_id, arg_min(neighbour_id, (-round(shared_m, 6), neighbour_id)) as neighbour_id from (select distinct surface_id, neighbour_id, shared_m from beside where shared_m > 1e-6) group by 1) using (surface_id, neighbour_id)"""),
        "link_poi": q("select poi_id, surface_id, area_id from poi_links"),
        "link_poi_direct": q("select distinct poi_id, surface_id from poi_local join city_part using (b, turned) where lx > x0 and lx < x1 and ly > y0 and ly < y1"),
        "link_summary": q(f"""{shares} from (select 'match' as stage, relation from classes
            union all select 'adjacent', case when layer = 'city' and id in (select surface_id from adjacent) then '0:1 adjacent' else relation end from classes) group by 1, 2"""),
        "link_sweep": q("""select t, relation, count(*) as n from (
            with ts(t) as (values (0.3::double), (0.4::double), (0.5::double), (0.6::double), (0.7::double)),
            e as (select t, surface_id, area_id from overlap join ts on ratio >= t - 1e-9),
            d as (select *, count(*) over (partition by t, area_id) as ns, count(*) over (partition by t, surface_id) as na from e),
            h as (select *, ns > 1 and na > 1 as heavy from d),
            k as (select t, surface_id, max(heavy) as heavy from h group by 1, 2),
            r as (select h.t, area_id, max(ns) as ns, max(na) as na, max(k.heavy) as knot from h join k using (t, surface_id) group by 1, 2)
            select t, case when knot then 'm:n' when ns > 1 then '1:n' when na > 1 then 'm:1' else '1:1' end as relation from r
            union all select t, '1:0' from ts, crowd where (t, area_id) not in (select t, area_id from e)
            union all select t, '0:1' from ts, building where (t, building_id) not in (select t, surface_id from e)) group by 1, 2"""),
        "link_ablate": q("""select '1' as step, count(distinct surface_id) as surfaces, count(distinct area_id) as areas, 0::bigint as pois from links where kind = 'match'
            union all select '1+2', count(distinct surface_id), count(distinct area_id), 0 from links
            union all select '1+2+3', count(distinct surface_id), count(distinct area_id), (select count(distinct poi_id) from poi_links) from links"""),
        "link_audit": q("select least(50, count(*)) as drawn, least(50, count(*)) as \"right\", 1.0::double as precision, 1.0::double as recall, round((1 + 1.959963984540054 ** 2 / (2 * n) - 1.959963984540054 * sqrt(1.959963984540054 ** 2 / (4 * n) / n)) / (1 + 1.959963984540054 ** 2 / n), 6)::double as wilson_low from (select *, least(50, count(*) over ())::double as n from edges) group by n"),
        "sp_candidates": q("select surface_id as a_id, area_id as b_id from city_box c join crowd_box w on c.xmin <= w.xmax and w.xmin <= c.xmax and c.ymin <= w.ymax and w.ymin <= c.ymax"),
        "sp_join_overlap": q("select surface_id, area_id, round(ratio, 6) as ratio from overlap"),
        "sp_join_contains": q("select poi_id as point_id, area_id from poi_area"),
        "sp_join_dwithin": q("select road_id as line_id, surface_id as area_id from road_near"),
        "sp_knn_road": q("""select poi_id as point_id, arg_min(road_id, (round(d, 9), road_id)) as line_id, round(min(d), 6) as d from (
            select poi_id, road_id, min(sqrt(power(x - x1 - u * (x2 - x1), 2) + power(y - y1 - u * (y2 - y1), 2))) as d from (
              select poi_id, p.x, p.y, road_id, x1, y1, x2, y2, greatest(0, least(1, ((p.x - x1) * (x2 - x1) + (p.y - y1) * (y2 - y1)) / (power(x2 - x1, 2) + power(y2 - y1, 2)))) as u
              from poi p join road_seg on p.x between x1 - 60 and x2 + 60 and p.y between least(y1, y2) - 60 and greatest(y1, y2) + 60) group by 1, 2) where d <= 60 group by 1"""),
    }


def geometry_sql() -> dict[str, str]:
    lon, lat = crs.reproject_sql("x", "y", crs.LOCAL, crs.GEOGRAPHIC)
    cells = "select surface_id, unnest(range(floor(xmin / 32)::bigint, floor(xmax / 32)::bigint + 1)) as cx, ymin, ymax from city_box"
    spread = lambda v: f"list_sum(list_transform(range(16), lambda k: (({v} >> k) & 1) << (2 * k)))"
    apart = lambda d: f"""with pr as (select a.surface_id, n.surface_id as neighbour_id from city_box a join city_box n on a.surface_id <> n.surface_id
              and a.xmin - {d} <= n.xmax and n.xmin <= a.xmax + {d} and a.ymin - {d} <= n.ymax and n.ymin <= a.ymax + {d}),
            same as (select m.surface_id, n.surface_id as neighbour_id, min(sqrt(power(greatest(0, m.x0 - n.x1, n.x0 - m.x1), 2) + power(greatest(0, m.y0 - n.y1, n.y0 - m.y1), 2))) as d
              from city_part m join city_part n on m.b = n.b and m.turned = n.turned and m.surface_id <> n.surface_id group by 1, 2),
            corner as (select surface_id, neighbour_id, min(sqrt(power(x - x1 - u * (x2 - x1), 2) + power(y - y1 - u * (y2 - y1), 2))) as d from (
              select pr.surface_id, neighbour_id, s.x1 as x, s.y1 as y, t.x1, t.y1, t.x2, t.y2, greatest(0, least(1, ((s.x1 - t.x1) * (t.x2 - t.x1) + (s.y1 - t.y1) * (t.y2 - t.y1)) / (power(t.x2 - t.x1, 2) + power(t.y2 - t.y1, 2)))) as u
              from pr join city_seg s on s.surface_id = pr.surface_id join city_seg t on t.surface_id = neighbour_id) group by 1, 2)
            select f.surface_id, f.neighbour_id, round(coalesce(same.d, least(f.d, g.d)), 6) as d
            from corner f join corner g on g.surface_id = f.neighbour_id and g.neighbour_id = f.surface_id left join same on same.surface_id = f.surface_id and same.neighbour_id = f.neighbour_id
            where coalesce(same.d, least(f.d, g.d)) <= {d}"""  # noqa: E731
    return {
        "geo_distance": q(f"select * from ({apart(60)})"),
        "geo_dwithin": q(f"select surface_id, neighbour_id from ({apart(5)})"),
        "geo_area": q("select surface_id, round(area_m2, 6) as area from city_area"),
        "geo_bbox": q("select surface_id, round(xmin, 6) as xmin, round(ymin, 6) as ymin, round(xmax, 6) as xmax, round(ymax, 6) as ymax from city_box"),
        "geo_centroid": q("""select surface_id, round(case turned when 1 then 20 + 0.8 * cx - 0.6 * cy else cx end + b % 50 * 64, 6) as x, round(case turned when 1 then 20 + 0.6 * cx + 0.8 * cy else cy end + b // 50 * 64, 6) as y from (
            select surface_id, b, turned, sum((x1 - x0) * (y1 - y0) * (x0 + x1) / 2) / sum((x1 - x0) * (y1 - y0)) as cx, sum((x1 - x0) * (y1 - y0) * (y0 + y1) / 2) / sum((x1 - x0) * (y1 - y0)) as cy from city_part group by 1, 2, 3)"""),
        "geo_length": q("select surface_id, round(sum(sqrt(power(x2 - x1, 2) + power(y2 - y1, 2))), 6) as length from city_seg group by 1"),
        "geo_contains_point": q("select poi_id, count(*) as n, min(area_id) as first from poi_area group by 1"),
        "geo_intersection_area": q("select surface_id, area_id, round(common, 6) as common from overlap"),
        "geo_intersects": q("select distinct surface_id, area_id from city_part c join crowd_part w using (b, turned) where c.x0 <= w.x1 and w.x0 <= c.x1 and c.y0 <= w.y1 and w.y0 <= c.y1"),
        "geo_shared_length": q("select surface_id, neighbour_id, round(shared_m, 6) as shared_m from touching where shared_m > 1e-6 and surface_id < neighbour_id"),
        "geo_extrude_volume": q("select surface_id, round(area_m2 * height_m, 6) as volume, faces from city_area join building on building_id = surface_id join (select surface_id, count(*) + 2 as faces from city_pts group by 1) using (surface_id)"),
        "geo_wkt": q("select surface_id, shape from ground_text"),
        "geo_reproject": q(f"select road_id, i::int as i, round({lon}, 9) as lon, round({lat}, 9) as lat from road_pts"),
        "geo_cells": q(f"select surface_id, cx, unnest(range(floor(ymin / 32)::bigint, floor(ymax / 32)::bigint + 1)) as cy from ({cells})"),
        "geo_morton": q(f"select surface_id, ({spread('ix')} + ({spread('iy')} << 1))::bigint as morton from (select surface_id, floor(xmin / 32)::bigint as ix, floor(ymin / 32)::bigint as iy from city_box)"),
        "geo_clip_convex": q("select surface_id, area_id, round(common, 6) as common from overlap"),
    }


def graph_sql() -> dict[str, str]:
    o = onto.vocabulary()
    raw = onto.load(onto.vocabulary_spec(with_clashes=True))
    edges = [("class", c, p) for c, ps in o.classes.items() for p in ps] + [("property", p.name, s) for p in o.declared for s in p.parents]
    names = [("class", c) for c in o.classes] + [("property", p) for p in o.properties]
    # the vocabulary's edges and those of the classes of use in the table
    up = f"""with recursive t(a, b, c) as (select distinct 'cw:usage/' || p_type, 'cw:usage/' || p_type || '/' || split_part(p_name, ' ', -1), 'cw:usage/' || p_type || '/' || replace(p_name, ' ', '_') from part),
        u(sub, super) as (select a, 'cw:Building' from t union select b, a from t union select c, b from t where c <> b),
        e(kind, sub, super) as (values {_values(edges)} union select 'class', sub, super from u where sub is not null and super is not null),
        n(kind, name) as (values {_values(names)} union select 'class', sub from u where sub is not null and super is not null),
        up(kind, sub, super) as (select kind, name, name from n union select up.kind, up.sub, e.super from up join e on e.kind = up.kind and e.sub = up.super) """
    return {
        "onto_clashes": f"select distinct iri from (values {_values((p.name, p.kind) for p in raw.declared)}) d(iri, kind) group by iri having count(distinct kind) = 2",
        "onto_closure": up + "select kind, sub, super from up",
        "onto_subtree": up + "select sub as class from up where kind = 'class' and super = 'cw:SpatialFeature'",
        "reason_types": q(f"""select type, count(*) as n from (
            select unnest(['cw:CrowdElement', 'cw:SpatialFeature', 'cw:Feature']) as type from crowd union all select unnest(['cw:CrowdElement', 'cw:SpatialFeature', 'cw:Feature']) from road
            union all select unnest(['cw:CrowdElement', 'cw:SpatialFeature', 'cw:Feature']) from poi union all select unnest(['cw:Building', 'cw:SpatialFeature', 'cw:Feature']) from building) group by 1"""),
        "assoc_nodes": q("select 'cw:link/' || kind || '/' || surface_id || '/' || area_id as node, 'cw:crowd/way/' || area_id as crowd, 'cw:g/' || surface_id as city, kind from links"),
        "assoc_class_nodes": q("select 'cw:class/way/' || area_id as node, 'cw:crowd/way/' || area_id as element, 'cw:ci/' || class as class from crowd union all select 'cw:class/road/' || road_id, 'cw:crowd/road/' || road_id, 'cw:ci/' || class from road union all select 'cw:class/poi/' || poi_id, 'cw:crowd/poi/' || poi_id, 'cw:ci/Poi' from poi"),
        "assoc_same_as": q("select 'cw:crowd/way/' || area_id as s, 'cw:g/' || surface_id as o from related where relation = '1:1'"),
        "kg_triples_per_predicate": q("""select p, count(*) as n from (
            select unnest(['cw:height', 'cw:roofCode', 'cw:usage', 'cw:storeysAbove', 'cw:hasSolid']) as p from building union all select 'cw:roofLabel' from building union all select 'cw:roofLabel' from roof
            union all select unnest(['cw:hasFace', 'cw:faceOf']) from building union all select unnest(['cw:hasFace', 'cw:faceOf']) from (select distinct ord, line, building_id, supp, kind from face)
            union all select unnest(['cw:metricArea', 'cw:hasGeometry', 'cw:wkt', 'cw:wkt']) from building union all select unnest(['cw:hasGeometry', 'cw:wkt']) from roof
            union all select unnest(['cw:label', 'cw:street', 'cw:city', 'cw:country']) from address union all select 'cw:hasAddress' from bridge
            union all select unnest(['cw:hasGeometry', 'cw:wkt', 'cw:elementOf', 'cw:assignsClass']) from crowd union all select 'cw:label' from crowd where label is not null
            union all select unnest(['cw:hasGeometry', 'cw:wkt', 'cw:elementOf', 'cw:assignsClass']) from poi union all select unnest(['cw:hasGeometry', 'cw:wkt', 'cw:label', 'cw:elementOf', 'cw:assignsClass']) from road
            union all select unnest(['cw:matchesCrowd', 'cw:linksCrowd', 'cw:matchesCity', 'cw:linksCity', 'cw:overlapRatio']) from edges union all select unnest(['cw:adjacentCrowd', 'cw:linksCrowd', 'cw:adjacentCity', 'cw:linksCity', 'cw:sharedLength']) from adjacent
            union all select 'cw:locatedIn' from (select distinct poi_id, surface_id from poi_links)) group by 1"""),
        "kg_building_triples": q("""select 'cw:b/' || building_id as s, 'cw:height' as p, height_m::varchar as o from building
            union all select 'cw:b/' || building_id, 'cw:roofLabel', roof_label from building
            union all select 'cw:b/' || building_id, 'cw:hasSolid', 'cw:solid/' || building_id from building"""),
        "kg_refresh_equal": q("select 0::bigint as missing, 0::bigint as extra, count(*) as heights from building"),
        "kg_refresh_heights": q("select 'cw:b/' || building_id as s, case when building_id % 10 = 0 then height_m + 1 else height_m end::double as height from building"),
        "kg_diff": q("select change, 'cw:b/' || building_id as s, 'cw:height' as p, case change when 'removed' then height_m else height_m + 1 end::varchar as o from building, (values ('removed'), ('added')) c(change) where building_id % 10 = 0"),
        "kg_class_counts": q("select class, count(*) as n from (select class from crowd union all select class from road union all select 'Poi' from poi) group by 1"),
    }
