"""Getting data ready: city markup, semi-structured columns, keys, coverage, harmonised layers."""

from __future__ import annotations

from collections.abc import Callable
from typing import TYPE_CHECKING

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from cityweave.functions import geom
from cityweave.plans.mappings import Mapping, Store
from cityweave.sources.city import City

if TYPE_CHECKING:
    from cityweave.context import Context

MARKUP = """id long, height double, roofCode int, address struct<country string, city string, street string, number string>,
  surface array<struct<kind string, posList string>>"""


def read_city_markup(spark: SparkSession, path: str, row_tag: str = "building") -> dict[str, DataFrame]:
    """Buildings, surfaces and addresses of city files: one row a building, surfaces unrolled.

    posList has x y pairs, the first repeated at the end.
    """
    rows = spark.read.format("xml").schema(_ddl(MARKUP)).option("rowTag", row_tag).load(path)
    numbers = F.transform(F.split(F.trim("s.posList"), r"\s+"), lambda v: v.cast("double"))
    ring = F.transform(F.sequence(F.lit(0), F.greatest(F.size(numbers) / 2 - 2, F.lit(0)).cast("int")), lambda k: geom.point(F.get(numbers, 2 * k), F.get(numbers, 2 * k + 1)))
    surfaces = rows.select("id", F.explode("surface").alias("s")).select(F.col("id").alias("building_id"), F.col("s.kind").alias("kind"), F.array(ring).alias("rings"))
    return {
        "building": rows.select(F.col("id").alias("building_id"), F.col("height").alias("height_m"), F.col("roofCode").alias("roof_code")),
        "surface": surfaces,
        "address": rows.select(F.col("id").alias("building_id"), "address.*"),
    }


def _ddl(text: str):
    from pyspark.sql.types import StructType

    return StructType.fromDDL(text.replace("struct<country string, city string, street string, number string>", "struct<country:string,city:string,street:string,number:string>").replace("struct<kind string, posList string>", "struct<kind:string,posList:string>"))


def append_city(store: DataFrame, more: DataFrame, key: list[str]) -> DataFrame:
    """Rows of further files whose keys aren't there yet, added; within them the first of each key counts."""
    return store.unionByName(more.dropDuplicates(key).join(store.select(*key), key, "left_anti"))


def split_xml(df: DataFrame, col: str, schema: str) -> DataFrame:
    """An XML text column's parts as columns."""
    return df.withColumn("_parts", F.from_xml(F.col(col), schema)).select("*", "_parts.*").drop("_parts")


def split_json(df: DataFrame, col: str, schema: str) -> DataFrame:
    return df.withColumn("_parts", F.from_json(F.col(col), schema)).select("*", "_parts.*").drop("_parts")


def address_xml(city: City) -> DataFrame:
    """Addresses as the text of one XML element, as city files have them."""
    tag = lambda name, value: F.concat(F.lit(f"<{name}>"), value, F.lit(f"</{name}>"))
    inner = F.concat(tag("country", F.col("country")), tag("city", F.col("city")), tag("street", F.col("street")), tag("number", F.col("address_id").cast("string")))
    return city.addresses.select("address_id", tag("address", inner).alias("raw_xml"))


def duplicate_keys(df: DataFrame, key: list[str]) -> DataFrame:
    return df.groupBy(*key).count().where("count > 1")


def check_keys(tables: dict[str, DataFrame], primary: dict[str, list[str]], foreign: list[tuple[str, str, str, str]]) -> DataFrame:
    """(rule, violations): keys that aren't unique, and references that lead nowhere."""
    out = None
    for name, key in primary.items():
        part = duplicate_keys(tables[name], key).agg(F.count("*").alias("violations")).select(F.lit(f"{name} key {', '.join(key)}").alias("rule"), "violations")
        out = part if out is None else out.unionByName(part)
    for name, col, other, key in foreign:
        lost = tables[name].select(F.col(col).alias("_k")).where("_k is not null").join(tables[other].select(F.col(key).alias("_k")), "_k", "left_anti")
        part = lost.agg(F.count("*").alias("violations")).select(F.lit(f"{name}.{col} refers to {other}").alias("rule"), "violations")
        out = part if out is None else out.unionByName(part)
    return out


def coverage(store: Store, mappings: list[Mapping]) -> DataFrame:
    """(source, n_rows, triple_patterns) for each source: what is mapped, and how much of it there is."""
    out = None
    for name, source in store.sources.items():
        n = sum(len(m.targets) for m in mappings if m.source == name)
        part = source.frame().agg(F.count("*").alias("n_rows")).select(F.lit(name).alias("source"), "n_rows", F.lit(n).alias("triple_patterns"))
        out = part if out is None else out.unionByName(part)
    return out


def unify_elements(*layers: DataFrame) -> DataFrame:
    """Nodes, ways and relations in one schema; columns that a layer lacks are null."""
    out = layers[0]
    for more in layers[1:]:
        out = out.unionByName(more, allowMissingColumns=True)
    return out


def clip(df: DataFrame, box: tuple[float, float, float, float], margin: float = 0.0) -> DataFrame:
    """Rows whose boxes touch the study area grown by a margin; the stored box decides, so files can be skipped."""
    x0, y0, x1, y1 = box
    return df.where((F.col("bbox.xmin") <= x1 + margin) & (F.col("bbox.xmax") >= x0 - margin) & (F.col("bbox.ymin") <= y1 + margin) & (F.col("bbox.ymax") >= y0 - margin))


_specs: dict[str, dict[str, Column]] = {}


def register_source(name: str, df: DataFrame, spec: dict[str, Column]) -> DataFrame:
    """Any table as a crowd layer: spec gives area_id, label, class, elem_kind and rings."""
    missing = {"area_id", "label", "class", "elem_kind", "rings"} - spec.keys()
    if missing:
        raise ValueError(f"{name} lacks {sorted(missing)}")
    _specs[name] = spec
    out = df.select(*[c.alias(k) for k, c in spec.items()])
    return out.withColumns({"bbox": geom.bbox(F.col("rings")), "area_m2": geom.area(F.col("rings"))})


def _elements(c: Context) -> DataFrame:
    ways = c.city.crowd.select("elem_kind", F.col("area_id").alias("elem_id"), "label", F.col("bbox.xmin").alias("x"), F.col("bbox.ymin").alias("y"))
    nodes = c.city.pois.select(F.lit("poi").alias("elem_kind"), F.col("poi_id").alias("elem_id"), "x", "y")
    roads = c.city.roads.select(F.lit("road").alias("elem_kind"), F.col("road_id").alias("elem_id"), "label")
    found = unify_elements(ways, nodes, roads)
    return found.groupBy("elem_kind").agg(F.count("*").alias("n"), F.count("label").alias("labelled"), F.round(F.sum("x"), 4).alias("sum_x"))


def _key_violations(c: Context) -> DataFrame:
    tables = {"building": c.city.buildings, "crowd": c.city.crowd.select("area_id"), "face": c.city.faces, "address": c.city.addresses.select("address_id"), "bridge": c.city.building_address}
    primary = {"building": ["building_id"], "crowd": ["area_id"], "face": ["ord", "line", "building_id", "supp"], "address": ["address_id"]}
    return check_keys(tables, primary, [("face", "building_id", "building", "building_id"), ("bridge", "address_id", "address", "address_id")])


def _title(c: Context) -> DataFrame:
    """Titles of pages: markup that isn't well-formed XML is read by pattern."""
    title = F.trim(F.regexp_extract("html", r"(?is)<title[^>]*>(.*?)</title>", 1))
    return c.city.table("pages").select(F.col("page_id").cast("long").alias("page_id"), title.alias("title"))


QUERIES: dict[str, Callable[[Context], DataFrame]] = {
    "init_xml_address": lambda c: split_xml(address_xml(c.city), "raw_xml", "country string, city string, street string, number string").drop("raw_xml"),
    "init_json_props": lambda c: split_json(c.city.table("events").select(F.col("event_id").cast("long").alias("event_id"), "props"), "props", "k long").select("event_id", "k"),
    "init_key_violations": _key_violations,
    "init_coverage": lambda c: coverage(c.store, c.virtual.mappings).where("source in ('building', 'ground', 'roof', 'address', 'crowd', 'road', 'poi')").select("source", "n_rows"),
    "init_unify_elements": _elements,
    "init_clip": lambda c: clip(c.city.ground, (64.0, 0.0, 320.0, 64.0), 4.0).select("surface_id"),
    "init_page_title": _title,
}

_PARTS = "s_suppkey::bigint as address_id, r_name as country, n_name as city, s_name as street, s_suppkey::varchar as number from supplier join nation on n_nationkey = s_nationkey join region on r_regionkey = n_regionkey"


def _oracle() -> dict[str, str]:
    from cityweave import oracles

    dup = lambda table, key: f"(select count(*) from (select 1 from {table} group by {key} having count(*) > 1))"
    return {
        "init_xml_address": f"select {_PARTS}",
        "init_json_props": "select event_id::bigint as event_id, json_extract(props, '$.k')::bigint as k from events",
        "init_key_violations": oracles.q(f"""select 'building key building_id' as rule, {dup("building", "building_id")} as violations union all select 'crowd key area_id', {dup("crowd", "area_id")}
            union all select 'face key ord, line, building_id, supp', {dup("face", "ord, line, building_id, supp")} union all select 'address key address_id', {dup("address", "address_id")}
            union all select 'face.building_id refers to building', (select count(*) from face where building_id not in (select building_id from building))
            union all select 'bridge.address_id refers to address', (select count(*) from bridge where address_id not in (select address_id from address))"""),
        "init_coverage": oracles.q("select 'building' as source, count(*) as n_rows from building union all select 'ground', count(*) from building union all select 'roof', count(*) from roof union all select 'address', count(*) from address union all select 'crowd', count(*) from crowd union all select 'road', count(*) from road union all select 'poi', count(*) from poi"),
        "init_unify_elements": oracles.q("select 'way' as elem_kind, count(*) as n, count(label) as labelled, round(sum(xmin), 4) as sum_x from crowd join crowd_box using (area_id) union all select 'poi', count(*), 0, round(sum(x), 4) from poi union all select 'road', count(*), count(*), null from road"),
        "init_clip": oracles.q("select surface_id from city_box where xmin <= 324 and xmax >= 60 and ymin <= 68 and ymax >= -4"),
        "init_page_title": "select page_id::bigint as page_id, trim(regexp_extract(html, '(?is)<title[^>]*>(.*?)</title>', 1)) as title from pages",
    }


ORACLE = _oracle()
