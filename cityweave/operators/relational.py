"""Relational operators, sources and functions around the methods, one query each with its SQL.

Each takes the shared context; the tables stand for the city as in
sources.city, or are read as they are.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from typing import TYPE_CHECKING

import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from cityweave import oracles
from cityweave.functions import geom, wkt
from cityweave.operators import spatial
from cityweave.plans import mappings
from cityweave.sources import triples_io

if TYPE_CHECKING:
    from cityweave.context import Context

QUERIES: dict[str, Callable[[Context], DataFrame]] = {}
ORACLE: dict[str, str] = {}


def query(sql: str | None) -> Callable:
    def register(fn: Callable) -> Callable:
        QUERIES[fn.__name__] = fn
        if sql is not None:
            ORACLE[fn.__name__] = sql
        return fn

    return register


# Range joins and as-of joins, for use with any tables.
def range_join(points: DataFrame, bands: DataFrame, value: str, low: str, high: str, width: float) -> DataFrame:
    """Rows of points in half-open bands [low, high): by buckets of `width`, then exactly.

    A band goes to each bucket it touches; a point has one bucket, so no pair
    comes twice.
    """
    dealt = bands.withColumn("_bucket", F.explode(F.sequence(F.floor(F.col(low) / width), F.floor(F.col(high) / width))))
    return points.withColumn("_bucket", F.floor(F.col(value) / width)).join(dealt, "_bucket").where((F.col(value) >= F.col(low)) & (F.col(value) < F.col(high))).drop("_bucket")


def asof_join(left: DataFrame, right: DataFrame, by: str, on: str, take: str, alias: str) -> DataFrame:
    """left with the latest value of `take` from right at or before `on`, per `by`: one sort, no pairs.

    Both sides are stacked and the last seen right row is carried along; at equal
    times right rows come first.
    """
    stacked = left.select("*", F.lit(1).alias("_side"), F.lit(None).cast(right.schema[take].dataType).alias("_value")).unionByName(
        right.select(by, on, F.lit(0).alias("_side"), F.col(take).alias("_value")), allowMissingColumns=True
    )
    order = Window.partitionBy(by).orderBy(on, "_side").rowsBetween(Window.unboundedPreceding, 0)
    return stacked.withColumn(alias, F.last("_value", ignorenulls=True).over(order)).where("_side = 1").drop("_side", "_value")


# Scans.
@query("select count(*) as parts, sum(p_size)::bigint as sizes, (select count(*) from lineitem) as faces, (select round(sum(l_quantity), 2) from lineitem) as quantity from part")
def src_parquet(c: Context) -> DataFrame:
    parts = c.city.table("part").agg(F.count("*").alias("parts"), F.sum("p_size").cast("bigint").alias("sizes"))
    return parts.join(c.city.table("lineitem").agg(F.count("*").alias("faces"), F.round(F.sum("l_quantity"), 2).alias("quantity")))


_NATION = "select n_nationkey::bigint as n_nationkey, n_name, n_regionkey::bigint as n_regionkey from nation"


def _nation(c: Context) -> DataFrame:
    return c.city.table("nation").select(F.col("n_nationkey").cast("long").alias("n_nationkey"), "n_name", F.col("n_regionkey").cast("long").alias("n_regionkey"))


@query(_NATION)
def src_csv(c: Context) -> DataFrame:
    path = f"{c.scratch.base}/nation-csv"
    df = _nation(c)
    df.write.mode("overwrite").option("header", True).csv(path)
    return c.spark.read.schema(df.schema).option("header", True).csv(path)


@query(_NATION)
def src_json(c: Context) -> DataFrame:
    path = f"{c.scratch.base}/nation-json"
    df = _nation(c)
    df.write.mode("overwrite").json(path)
    return c.spark.read.schema(df.schema).json(path)


@query("select s_suppkey::bigint as address_id, s_name as street, n_name as city, r_name as country from supplier join nation on n_nationkey = s_nationkey join region on r_regionkey = n_regionkey")
def src_xml(c: Context) -> DataFrame:
    path = f"{c.scratch.base}/address-xml"
    c.city.addresses.select("address_id", "street", "city", "country").write.mode("overwrite").format("xml").option("rowTag", "address").option("rootTag", "addresses").save(path)
    schema = T.StructType.fromDDL("address_id long, street string, city string, country string")
    return c.spark.read.format("xml").schema(schema).option("rowTag", "address").load(path)


@query("""select 'cw:b/' || p_partkey as s, 'cw:height' as p, p_size::double::varchar as o from part
  union all select 'cw:b/' || p_partkey, 'cw:usage', p_type from part union all select 'cw:b/' || p_partkey, 'rdf:type', 'cw:Building' from part""")
def src_ntriples(c: Context) -> DataFrame:
    path = f"{c.scratch.base}/building.nt"
    wanted = c.triples.where("(p in ('cw:height', 'cw:usage') or (p = 'rdf:type' and o = 'cw:Building')) and s like 'cw:b/%'")
    triples_io.write_ntriples(wanted, path)
    return triples_io.read_ntriples(c.spark, path).select("s", "p", "o")


# Filters.
@query("select p_partkey::bigint as id, p_size::double as height_m from part where p_size > 30")
def op_filter_numeric(c: Context) -> DataFrame:
    return c.city.buildings.where("height_m > 30").select(F.col("building_id").alias("id"), "height_m")


@query("select s_suppkey::bigint as id, s_name as name from supplier where contains(s_name, '00001') and starts_with(s_name, 'Supplier') and regexp_matches(s_name, '[0-9]+$')")
def op_filter_string(c: Context) -> DataFrame:
    name = F.col("s_name")
    return c.city.table("supplier").where(name.contains("00001") & name.startswith("Supplier") & name.rlike("[0-9]+$")).select(F.col("s_suppkey").cast("long").alias("id"), name.alias("name"))


@query("select c_custkey::bigint as id from customer where c_mktsegment in ('HOUSEHOLD', 'BUILDING')")
def op_filter_in(c: Context) -> DataFrame:
    return c.city.table("customer").where(F.col("c_mktsegment").isin("HOUSEHOLD", "BUILDING")).select(F.col("c_custkey").cast("long").alias("id"))


@query("select c_custkey::bigint as id, case when c_acctbal >= 0 then c_name else 'unnamed' end as label, c_acctbal < 0 as unnamed from customer")
def op_filter_null(c: Context) -> DataFrame:
    return c.city.crowd.select(F.col("area_id").alias("id"), F.coalesce("label", F.lit("unnamed")).alias("label"), F.col("label").isNull().alias("unnamed"))


# Joins.
_ROOFS = "(select l_partkey::bigint as building_id, count(*) as roofs from lineitem where l_returnflag = 'R' group by 1)"


def _roofs(c: Context) -> DataFrame:
    return c.city.faces.where("kind = 'roof'").groupBy("building_id").agg(F.count("*").alias("roofs"))


@query(f"select p_partkey::bigint as building_id, p_size::double as height_m, roofs from part join {_ROOFS} on building_id = p_partkey")
def op_join_inner(c: Context) -> DataFrame:
    return c.city.buildings.join(_roofs(c), "building_id").select("building_id", "height_m", "roofs")


_q = oracles.q


def _areas(c: Context) -> DataFrame:
    return c.city.crowd.select(F.col("area_id").alias("id"))


def _edges(c: Context) -> DataFrame:
    return c.links.edges.select("area_id", "surface_id")


@query(_q("select crowd.area_id as id, surface_id from crowd left join edges using (area_id)"))
def op_join_left(c: Context) -> DataFrame:
    return _areas(c).join(_edges(c), F.col("id") == F.col("area_id"), "left").select("id", "surface_id")


@query(_q("select building_id as id, area_id from edges right join building on building_id = surface_id"))
def op_join_right(c: Context) -> DataFrame:
    return _edges(c).join(c.city.buildings, F.col("building_id") == F.col("surface_id"), "right").select(F.col("building_id").alias("id"), "area_id")


@query(_q("select w.area_id, b.building_id from crowd w left join edges e using (area_id) full join building b on b.building_id = e.surface_id"))
def op_join_full(c: Context) -> DataFrame:
    left = _areas(c).join(_edges(c), F.col("id") == F.col("area_id"), "left").select(F.col("id").alias("area_id"), "surface_id")
    return left.join(c.city.buildings.select("building_id"), F.col("building_id") == F.col("surface_id"), "full").select("area_id", "building_id")


@query(_q("select building_id from building where building_id in (select surface_id from edges)"))
def op_join_semi(c: Context) -> DataFrame:
    return c.city.buildings.join(_edges(c), F.col("building_id") == F.col("surface_id"), "left_semi").select("building_id")


@query(_q("select building_id from building where building_id not in (select surface_id from edges)"))
def op_join_anti(c: Context) -> DataFrame:
    return c.city.buildings.join(_edges(c), F.col("building_id") == F.col("surface_id"), "left_anti").select("building_id")


_SUPPLIERS = "select s_suppkey::bigint as id, n_name as nation from supplier join nation on n_nationkey = s_nationkey"


def _hinted(c: Context, how: str) -> DataFrame:
    n = c.city.table("nation")
    return c.city.table("supplier").join(n.hint(how), F.col("s_nationkey") == F.col("n_nationkey")).select(F.col("s_suppkey").cast("long").alias("id"), F.col("n_name").alias("nation"))


@query(_SUPPLIERS)
def op_join_broadcast(c: Context) -> DataFrame:
    return _hinted(c, "broadcast")


@query(_SUPPLIERS)
def op_join_merge(c: Context) -> DataFrame:
    return _hinted(c, "merge")


@query(_SUPPLIERS)
def op_join_shuffle_hash(c: Context) -> DataFrame:
    return _hinted(c, "shuffle_hash")


# Height bands in metres.
BANDS = ((0.0, 10.0), (10.0, 20.0), (20.0, 30.0), (30.0, 45.0), (45.0, 60.0))
_BANDS = ", ".join(f"({lo}::double, {hi}::double)" for lo, hi in BANDS)


def _bands(c: Context) -> DataFrame:
    return c.spark.createDataFrame(list(BANDS), "low double, high double")


@query(f"select n_name as nation, low from nation, (values {_BANDS}) b(low, high) where n_nationkey * 2 < high")
def op_join_theta(c: Context) -> DataFrame:
    return c.city.table("nation").join(F.broadcast(_bands(c)), F.col("n_nationkey") * 2 < F.col("high")).select(F.col("n_name").alias("nation"), "low")


@query(f"select p_partkey::bigint as building_id, low from part join (values {_BANDS}) b(low, high) on p_size >= low and p_size < high")
def op_range_join(c: Context) -> DataFrame:
    return range_join(c.city.buildings, _bands(c), "height_m", "low", "high", 10.0).select("building_id", "low")


@query("""select p.event_id::bigint as event_id, strftime(c.ts, '%Y-%m-%d %H:%M:%S.%f') as clicked from (select * from events where event_type = 'purchase') p
  asof left join (select * from events where event_type = 'click') c on p.user_id = c.user_id and p.ts >= c.ts""")
def op_asof(c: Context) -> DataFrame:
    e = c.city.table("events").select(F.col("event_id").cast("long").alias("event_id"), "user_id", "ts", "event_type")
    clicks = e.where("event_type = 'click'").select("user_id", "ts", F.col("ts").alias("at"))
    return asof_join(e.where("event_type = 'purchase'"), clicks, "user_id", "ts", "at", "clicked").select("event_id", F.date_format("clicked", "yyyy-MM-dd HH:mm:ss.SSSSSS").alias("clicked"))


@query("""select p.event_id::bigint as purchase, s.event_id::bigint as signup from events p join events s on p.user_id = s.user_id
  and s.ts between p.ts - interval 1 hour and p.ts where p.event_type = 'purchase' and s.event_type = 'signup'""")
def op_interval_join(c: Context) -> DataFrame:
    e = c.city.table("events").select(F.col("event_id").cast("long").alias("event_id"), "user_id", "ts", "event_type")
    s = e.where("event_type = 'signup'").select("user_id", F.col("ts").alias("s_ts"), F.col("event_id").alias("signup"))
    both = e.where("event_type = 'purchase'").join(s, "user_id")
    return both.where((F.col("s_ts") <= F.col("ts")) & (F.col("s_ts") >= F.col("ts") - F.expr("interval 1 hour"))).select(F.col("event_id").alias("purchase"), "signup")


# Aggregates and grouping.
@query(_q("select class, count(*) as n, round(sum(area_m2), 4) as area, round(avg(area_m2), 6) as mean_area from crowd join crowd_area using (area_id) group by 1"))
def op_agg_basic(c: Context) -> DataFrame:
    return c.city.crowd.groupBy("class").agg(F.count("*").alias("n"), F.round(F.sum("area_m2"), 4).alias("area"), F.round(F.avg("area_m2"), 6).alias("mean_area"))


@query("select l_suppkey::bigint as supp, count(distinct l_partkey) as buildings from lineitem group by 1")
def op_agg_distinct(c: Context) -> DataFrame:
    return c.city.faces.groupBy("supp").agg(F.count_distinct("building_id").alias("buildings"))


@query(None)
def op_agg_approx_distinct(c: Context) -> DataFrame:
    return c.city.faces.groupBy("supp").agg(F.approx_count_distinct("building_id", 0.02).alias("buildings"))


@query("select p_type as usage, median(p_size)::double as height, quantile_cont(p_size, 0.9)::double as tall from part group by 1")
def op_agg_percentile(c: Context) -> DataFrame:
    return c.city.buildings.groupBy("usage").agg(F.percentile("height_m", F.lit(0.5)).alias("height"), F.percentile("height_m", F.lit(0.9)).alias("tall"))


@query(None)
def op_agg_percentile_approx(c: Context) -> DataFrame:
    return c.city.buildings.groupBy("usage").agg(F.percentile_approx("height_m", 0.5, 1000).alias("height"))


def _people(c: Context) -> DataFrame:
    cust = c.city.table("customer").join(F.broadcast(c.city.table("nation")), F.col("c_nationkey") == F.col("n_nationkey")).join(F.broadcast(c.city.table("region")), F.col("n_regionkey") == F.col("r_regionkey"))
    return cust.join(c.city.crowd.select("area_id", "area_m2"), F.col("area_id") == F.col("c_custkey")).select(F.col("r_name").alias("region"), F.col("n_name").alias("nation"), F.col("c_mktsegment").alias("segment"), "area_m2")


_PEOPLE = "from customer join nation on n_nationkey = c_nationkey join region on r_regionkey = n_regionkey join crowd_area on area_id = c_custkey"


def _sums() -> list:
    return [F.count("*").alias("n"), F.round(F.sum("area_m2"), 4).alias("area")]


@query(_q(f"select r_name as region, n_name as nation, count(*) as n, round(sum(area_m2), 4) as area {_PEOPLE} group by rollup (r_name, n_name)"))
def op_rollup(c: Context) -> DataFrame:
    return _people(c).rollup("region", "nation").agg(*_sums())


@query(_q(f"select r_name as region, c_mktsegment as segment, count(*) as n, round(sum(area_m2), 4) as area {_PEOPLE} group by cube (r_name, c_mktsegment)"))
def op_cube(c: Context) -> DataFrame:
    return _people(c).cube("region", "segment").agg(*_sums())


@query(_q(f"select r_name as region, c_mktsegment as segment, grouping_id(r_name, c_mktsegment)::bigint as level, count(*) as n, round(sum(area_m2), 4) as area {_PEOPLE} group by grouping sets ((r_name), (c_mktsegment), ())"))
def op_grouping_sets(c: Context) -> DataFrame:
    sets = [[F.col("region")], [F.col("segment")], []]
    return _people(c).groupingSets(sets, "region", "segment").agg(F.grouping_id().alias("level"), *_sums())


# Windows.
_BY_BRAND = "over (partition by p_brand order by roofs desc, building_id)"


@query(f"""select building_id, p_brand as brand, (rank() over w)::bigint as "rank", (dense_rank() over w)::bigint as dense, (row_number() {_BY_BRAND})::bigint as row, (ntile(4) {_BY_BRAND})::bigint as quarter
  from {_ROOFS} join part on p_partkey = building_id window w as (partition by p_brand order by roofs desc)""")
def op_window_rank(c: Context) -> DataFrame:
    df = _roofs(c).join(c.city.table("part").select(F.col("p_partkey").cast("long").alias("building_id"), F.col("p_brand").alias("brand")), "building_id")
    w, full = Window.partitionBy("brand").orderBy(F.desc("roofs")), Window.partitionBy("brand").orderBy(F.desc("roofs"), "building_id")
    ranks = {"rank": F.rank().over(w), "dense": F.dense_rank().over(w), "row": F.row_number().over(full), "quarter": F.ntile(4).over(full)}
    return df.select("building_id", "brand", *[r.cast("long").alias(n) for n, r in ranks.items()])


@query("""select l_orderkey::bigint as ord, l_linenumber::bigint as line, l_partkey::bigint as part, l_suppkey::bigint as supp,
  round(sum(l_quantity) over (partition by l_partkey order by l_orderkey, l_linenumber, l_suppkey rows unbounded preceding), 4) as running,
  round(avg(l_quantity) over (partition by l_partkey order by l_orderkey, l_linenumber, l_suppkey rows between 1 preceding and 1 following), 6) as centred,
  count(*) over (partition by l_partkey order by l_orderkey range between 1000 preceding and current row) as near from lineitem""")
def op_window_frame(c: Context) -> DataFrame:
    keys = {"l_orderkey": "ord", "l_linenumber": "line", "l_partkey": "part", "l_suppkey": "supp"}
    df = c.city.table("lineitem").select(*[F.col(k).cast("long").alias(v) for k, v in keys.items()], "l_quantity")
    rows, near = Window.partitionBy("part").orderBy("ord", "line", "supp"), Window.partitionBy("part").orderBy("ord").rangeBetween(-1000, 0)
    return df.select("ord", "line", "part", "supp", F.round(F.sum("l_quantity").over(rows.rowsBetween(Window.unboundedPreceding, 0)), 4).alias("running"), F.round(F.avg("l_quantity").over(rows.rowsBetween(-1, 1)), 6).alias("centred"), F.count("*").over(near).alias("near"))


@query("""select event_id::bigint as event_id, date_diff('second', lag(ts) over w, ts)::bigint as since, lead(event_type) over w as next, first_value(event_type) over w as first,
  nth_value(event_type, 2) over (partition by user_id order by event_id rows between unbounded preceding and unbounded following) as second from events window w as (partition by user_id order by event_id)""")
def op_window_lag(c: Context) -> DataFrame:
    w = Window.partitionBy("user_id").orderBy("event_id")
    whole = w.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    e = c.city.table("events").withColumn("at", F.unix_timestamp(F.col("ts").cast("timestamp")))
    return e.select(F.col("event_id").cast("long").alias("event_id"), (F.col("at") - F.lag("at").over(w)).alias("since"), F.lead("event_type").over(w).alias("next"), F.first("event_type").over(w).alias("first"), F.nth_value("event_type", 2).over(whole).alias("second"))


# Sorting and sets.
@query(f"select building_id, roofs, row_number() over (order by roofs desc, building_id) as place from {_ROOFS}")
def op_sort(c: Context) -> DataFrame:
    """Places in a global order without one task for all rows: ranges are sorted apart, and counted before.

    The rows of a range get their place from the sizes of the ranges above.
    """
    ranges = c.scratch.keep(_roofs(c).repartitionByRange(F.desc("roofs"), "building_id").withColumn("part", F.spark_partition_id()))
    sizes = ranges.groupBy("part").agg(F.count("*").alias("n"))
    before = sizes.join(sizes.withColumnsRenamed({"part": "p", "n": "m"}), F.col("p") < F.col("part"), "left").groupBy("part").agg(F.coalesce(F.sum("m"), F.lit(0)).alias("before"))
    own = Window.partitionBy("part").orderBy(F.desc("roofs"), "building_id")
    return ranges.withColumn("row", F.row_number().over(own)).join(before, "part").select("building_id", "roofs", (F.col("row") + F.col("before")).alias("place"))


@query(f"select building_id, roofs from {_ROOFS} order by roofs desc, building_id limit 25")
def op_topk(c: Context) -> DataFrame:
    return _roofs(c).orderBy(F.desc("roofs"), "building_id").limit(25)


_HALVES = ("(select c_nationkey::bigint as k from customer)", "(select s_nationkey::bigint as k from supplier)")


def _halves(c: Context) -> tuple[DataFrame, DataFrame]:
    return c.city.table("customer").select(F.col("c_nationkey").cast("long").alias("k")), c.city.table("supplier").select(F.col("s_nationkey").cast("long").alias("k"))


@query(f"select * from {_HALVES[0]} union all select * from {_HALVES[1]}")
def op_set_union(c: Context) -> DataFrame:
    a, b = _halves(c)
    return a.unionByName(b)


@query(f"select * from {_HALVES[0]} intersect select * from {_HALVES[1]}")
def op_set_intersect(c: Context) -> DataFrame:
    a, b = _halves(c)
    return a.intersect(b)


@query(f"select * from {_HALVES[0]} except all select * from {_HALVES[1]}")
def op_set_except(c: Context) -> DataFrame:
    a, b = _halves(c)
    return a.exceptAll(b)


# Reshaping.
@query("select p_type as usage, count(*) filter (p_size <= 10) as low, count(*) filter (p_size > 10 and p_size <= 30) as middle, count(*) filter (p_size > 30) as tall from part group by 1")
def op_pivot(c: Context) -> DataFrame:
    band = F.when(F.col("height_m") <= 10, "low").when(F.col("height_m") <= 30, "middle").otherwise("tall")
    return c.city.buildings.withColumn("band", band).groupBy("usage").pivot("band", ["low", "middle", "tall"]).count().na.fill(0)


@query(_q("select 'cw:b/' || building_id as s, p, o from (select building_id, unnest(['height', 'usage', 'roofLabel']) as p, unnest([height_m::varchar, usage, roof_label]) as o from building)"))
def op_unpivot(c: Context) -> DataFrame:
    b = c.city.buildings.select(F.concat(F.lit("cw:b/"), F.col("building_id").cast("string")).alias("s"), F.col("height_m").cast("string").alias("height"), "usage", F.col("roof_label").alias("roofLabel"))
    return b.unpivot(["s"], ["height", "usage", "roofLabel"], "p", "o")


# Functions.
@query("select s_suppkey::bigint as id, upper(substr(s_name, 1, 4)) as head, length(s_name)::int as size, concat_ws('|', s_name, s_nationkey::varchar) as joined, regexp_extract(s_name, '([0-9]+)', 1) as digits, lpad(s_nationkey::varchar, 4, '0') as padded from supplier")
def fn_string(c: Context) -> DataFrame:
    name, nation = F.col("s_name"), F.col("s_nationkey").cast("string")
    return c.city.table("supplier").select(F.col("s_suppkey").cast("long").alias("id"), F.upper(F.substring(name, 1, 4)).alias("head"), F.length(name).alias("size"), F.concat_ws("|", name, nation).alias("joined"), F.regexp_extract(name, "([0-9]+)", 1).alias("digits"), F.lpad(nation, 4, "0").alias("padded"))


@query("select p_partkey::bigint as id, 'cw:name/' || replace(replace(p_name, ' ', '%20'), '#', '%23') as iri from part")
def fn_iri_encode(c: Context) -> DataFrame:
    return c.city.table("part").select(F.col("p_partkey").cast("long").alias("id"), mappings.fill("cw:name/{}", [F.col("p_name")]).alias("iri"))


@query("select l_orderkey::bigint as ord, l_linenumber::bigint as line, l_partkey::bigint as building_id, l_suppkey::bigint as supp from lineitem where l_returnflag = 'R'")
def fn_iri_decode(c: Context) -> DataFrame:
    iri = mappings.fill("cw:f/{}/{}/{}/{}", [F.col(k) for k in ("ord", "line", "building_id", "supp")])
    back = lambda k: F.regexp_extract("iri", "^cw:f/([^/]+)/([^/]+)/([^/]+)/([^/]+)$", k).cast("long")
    return c.city.faces.where("kind = 'roof'").select(iri.alias("iri")).select(back(1).alias("ord"), back(2).alias("line"), back(3).alias("building_id"), back(4).alias("supp"))


@query("select o_orderkey::bigint as id, year(o_orderdate)::int as year, quarter(o_orderdate)::int as quarter, date_trunc('month', o_orderdate)::date as month, date_diff('day', o_orderdate, timestamp '2000-01-01')::int as age from orders")
def fn_date(c: Context) -> DataFrame:
    d = F.col("o_orderdate")
    return c.city.table("orders").select(F.col("o_orderkey").cast("long").alias("id"), F.year(d).alias("year"), F.quarter(d).alias("quarter"), F.trunc(d.cast("date"), "month").alias("month"), F.date_diff(F.lit("2000-01-01").cast("date"), d.cast("date")).alias("age"))


@query("select p_partkey::bigint as id, round(sin(p_size), 9) as s, round(cos(p_size), 9) as c, round(sqrt(p_size * p_size + 9.0::double), 9) as h, round(ln(p_size), 9) as l, (p_size % 7)::int as m from part")
def fn_math(c: Context) -> DataFrame:
    x = F.col("p_size").cast("double")
    return c.city.table("part").select(F.col("p_partkey").cast("long").alias("id"), F.round(F.sin(x), 9).alias("s"), F.round(F.cos(x), 9).alias("c"), F.round(F.hypot(x, F.lit(3.0)), 9).alias("h"), F.round(F.log(x), 9).alias("l"), (F.col("p_size") % 7).cast("int").alias("m"))


@query(_q("select surface_id, count(*)::int as corners, round(max(x) filter (i = 0), 6) as first_x, round(sum(y), 6) as sum_y, round(max(y) filter (i = top), 6) as last_y from city_pts join (select surface_id, max(i) as top from city_pts group by 1) using (surface_id) group by 1"))
def fn_array(c: Context) -> DataFrame:
    ring = F.element_at("rings", 1)
    ys = F.transform(ring, lambda p: p["y"])
    return c.city.ground.select("surface_id", F.size(ring).alias("corners"), F.round(F.element_at(ring, 1)["x"], 6).alias("first_x"), F.round(F.aggregate(ys, F.lit(0.0), lambda a, v: a + v), 6).alias("sum_y"), F.round(F.element_at(F.reverse(ys), 1), 6).alias("last_y"))


@query("select c_custkey::bigint as id, c_mktsegment as segment, (case when c_acctbal >= 0 then 3 else 2 end)::int as tags from customer")
def fn_map(c: Context) -> DataFrame:
    bag = F.create_map(F.lit("segment"), F.col("c_mktsegment"), F.lit("nation"), F.col("c_nationkey").cast("string"), F.lit("name"), F.when(F.col("c_acctbal") >= 0, F.col("c_name")))
    tags = F.map_filter(bag, lambda k, v: v.isNotNull())
    return c.city.table("customer").select(F.col("c_custkey").cast("long").alias("id"), F.element_at(tags, "segment").alias("segment"), F.size(F.map_keys(tags)).alias("tags"))


@query("select event_id::bigint as event_id, json_extract_string(props, '$.k') as k from events")
def fn_json(c: Context) -> DataFrame:
    return c.city.table("events").select(F.col("event_id").cast("long").alias("event_id"), F.get_json_object("props", "$.k").alias("k"))


@query(_q("select surface_id, round(area_m2, 4) as area from city_area"))
def udf_wkt(c: Context) -> DataFrame:
    """Area of WKT text through the Arrow function."""
    return c.city.ground.select("surface_id", F.round(wkt.wkt_area(wkt.polygon_wkt(F.col("rings"))), 4).alias("area"))


@query(_q("select (surface_id // 8)::bigint as block, round(min(x), 6) as xmin, round(min(y), 6) as ymin, round(max(x), 6) as xmax, round(max(y), 6) as ymax from city_pts group by 1"))
def udaf_extent(c: Context) -> DataFrame:
    box = c.city.ground.groupBy(F.floor(F.col("surface_id") / 8).alias("block"))
    return box.agg(*[F.round(f(f"bbox.{k}"), 6).alias(k) for f, k in ((F.min, "xmin"), (F.min, "ymin"), (F.max, "xmax"), (F.max, "ymax"))])


@F.pandas_udf(T.DoubleType())
def _spread(values: pd.Series) -> float:
    return float(values.max() - values.min()) if len(values) else 0.0


@query("select p_type as usage, (max(p_size) - min(p_size))::double as spread from part group by 1")
def udaf_spread(c: Context) -> DataFrame:
    """A grouped aggregate in pandas; groups here are few and their columns narrow."""
    return c.city.buildings.groupBy("usage").agg(_spread("height_m").alias("spread"))


@F.udtf(returnType=T.StructType().add("i", "integer").add("x1", "double").add("y1", "double").add("x2", "double").add("y2", "double"))
class RingEdges:
    """Rows for the edges of a ring given as arrays of x and y."""

    def eval(self, xs: list, ys: list) -> Iterator[tuple]:
        for i in range(len(xs)):
            j = (i + 1) % len(xs)
            yield i, xs[i], ys[i], xs[j], ys[j]


def _ring_edges(c: Context, ground: DataFrame) -> DataFrame:
    ring = F.element_at("rings", 1)
    rows = ground.select("surface_id", F.transform(ring, lambda p: p["x"]).alias("xs"), F.transform(ring, lambda p: p["y"]).alias("ys"))
    c.spark.udtf.register("ring_edges", RingEdges)
    rows.createOrReplaceTempView("_cw_rings")
    return c.spark.sql("select surface_id, i, round(x1, 6) as x1, round(y1, 6) as y1, round(x2, 6) as x2, round(y2, 6) as y2 from _cw_rings, lateral ring_edges(xs, ys)")


@query(_q("select surface_id, i::int as i, round(x1, 6) as x1, round(y1, 6) as y1, round(x2, 6) as x2, round(y2, 6) as y2 from city_seg"))
def udtf_edges(c: Context) -> DataFrame:
    return _ring_edges(c, c.city.ground)


@query(_q("select surface_id, area_id, round(common, 6) as common from overlap"))
def geo_intersection_edges(c: Context) -> DataFrame:
    """The kernel with its pairs of edges as rows: wholly compiled, for shapes with many corners."""
    strip = lambda df, key, n: df.select(F.col(key), F.explode(geom.strips(F.col("rings"))).alias(n))
    found = spatial.candidates(c.city.ground.select(F.col("surface_id").alias("id"), "bbox"), c.city.crowd.select(F.col("area_id").alias("id"), "bbox"), strict=True)
    edges = found.select(F.col("a_id").alias("surface_id"), F.col("b_id").alias("area_id"), F.least("a_box.ymin", "b_box.ymin").alias("base")).join(strip(c.city.ground, "surface_id", "e"), "surface_id").join(strip(c.city.crowd, "area_id", "f"), "area_id")
    low, high = F.greatest("e.x1", "f.x1"), F.least("e.x2", "f.x2")
    height = lambda g, x: F.col(f"{g}.y1") - F.col("base") + (x - F.col(f"{g}.x1")) * (F.col(f"{g}.y2") - F.col(f"{g}.y1")) / (F.col(f"{g}.x2") - F.col(f"{g}.x1"))
    at = edges.where(low < high).select("surface_id", "area_id", (F.col("e.s") * F.col("f.s")).alias("sign"), (high - low).alias("w"), height("e", low).alias("el"), height("e", high).alias("eh"), height("f", low).alias("fl"), height("f", high).alias("fh"))
    left, right = F.col("el") - F.col("fl"), F.col("eh") - F.col("fh")
    t = left / F.when(left != right, left - right)
    cross = F.col("el") + t * (F.col("eh") - F.col("el"))
    below = F.when((left <= 0) & (right <= 0), (F.col("el") + F.col("eh")) / 2).when((left >= 0) & (right >= 0), (F.col("fl") + F.col("fh")) / 2).otherwise((t * (F.least("el", "fl") + cross) + (1 - t) * (cross + F.least("eh", "fh"))) / 2)
    return at.groupBy("surface_id", "area_id").agg(F.round(F.sum(F.col("sign") * F.col("w") * below), 6).alias("common")).where("common > 0")
