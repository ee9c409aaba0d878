"""Mappings from relations to triples: an id, a source, and target patterns.

A target's subject and object are IRI templates over the source's columns,
columns taken as literals, or constants. Templates are injective: keys are
joined by slashes and percent-encoded where they are text.
"""

from __future__ import annotations

import json
import re
from collections.abc import Callable
from dataclasses import dataclass, field, replace
from functools import cache, cached_property, lru_cache

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from cityweave.functions import geom, wkt
from cityweave.operators.linker import LinkResult
from cityweave.plans.ontology import TYPE, Ontology, crowd_closure_rows
from cityweave.sources.city import RESIDENTIAL, ROAD_CLASSES, City


@dataclass(frozen=True)
class Template:
    """`cw:b/{}` and the columns that fill it."""

    pattern: str
    columns: tuple[str, ...]

    def invert(self, iri: str) -> tuple[str, ...] | None:
        return invert(self.pattern, iri)


@lru_cache(maxsize=4096)
def _matcher(pattern: str) -> re.Pattern:
    return re.compile("([^/]+)".join(map(re.escape, pattern.split("{}"))))


def invert(pattern: str, iri: str) -> tuple[str, ...] | None:
    """The keys that fill a template to an IRI, or None if it can't be."""
    from urllib.parse import unquote

    m = _matcher(pattern).fullmatch(iri)
    return tuple(unquote(g) for g in m.groups()) if m else None


def compatible(a: str, b: str) -> bool:
    """Whether two templates can give one IRI. Ours can only if they are the same."""
    return a == b


def fill(pattern: str, keys: list[Column], whole: list[bool] | None = None) -> Column:
    """IRI text from keys. whole: which keys are whole numbers, whose text needs no encoding."""
    parts = pattern.split("{}")
    out: list[Column] = [F.lit(parts[0])]
    for key, tail, plain in zip(keys, parts[1:], whole or [False] * len(keys), strict=True):
        out += [key.cast("string") if plain else iri_encode(key.cast("string")), F.lit(tail)]
    return F.concat(*out)


def iri_encode(text: Column) -> Column:
    """Percent-encoding; spaces become %20. Plain keys skip the work."""
    return F.when(text.rlike(r"^[A-Za-z0-9._~-]*$"), text).otherwise(F.replace(F.url_encode(text), F.lit("+"), F.lit("%20")))


@dataclass(frozen=True)
class Field:
    """A column as a literal; null gives no triple.

    A literal that is the text of a geometry can name its form and the columns
    it is made of; queries then carry those, and make the text at the end.
    """

    column: str
    dtype: str
    nullable: bool = False
    form: str = ""
    raw: tuple[str, ...] = ()


@dataclass(frozen=True)
class Const:
    iri: str


@dataclass(frozen=True)
class Target:
    subject: Template
    predicate: str
    object: Template | Field | Const


@dataclass(frozen=True)
class Mapping:
    id: str
    source: str
    targets: tuple[Target, ...]


@dataclass(frozen=True)
class Source:
    """A relation that mappings read: its frame, its key, and columns that refer to other sources' keys.

    Sources with one `part_of` are parts of a whole and share no key. `unique`:
    other columns that are unique as well. `joins`: its rows are those of the
    first source named, each with at most one row of each other, if those keep
    their keys. `derived`: made of rows of the sources it refers to, so that all
    keys it refers to are there. `keys`: the keys alone as the table has them, of
    the whole that it is part of, so that looking them up plans no geometry. `few`: so few rows that triples are
    made distinct at once, and keys aren't looked up for them.
    """

    frame: Callable[[], DataFrame]
    key: tuple[str, ...]
    refers: dict[tuple[str, ...], str] = field(default_factory=dict)
    part_of: str = ""
    unique: tuple[tuple[str, ...], ...] = ()
    joins: tuple[str, ...] = ()
    derived: bool = False
    distinct: bool = False
    keys: Callable[[], DataFrame] | None = None
    few: bool = False

    def tells_rows_apart(self, columns) -> bool:
        return any(set(key) <= set(columns) for key in (self.key, *self.unique))


@dataclass
class Store:
    """All sources over one city and its links; links may be what makes them, when a source of theirs is read first."""

    city: City
    links: LinkResult | Callable[[], LinkResult]
    ontology: Ontology
    extra: dict[str, Source] = field(default_factory=dict)

    @cached_property
    def sources(self) -> dict[str, Source]:
        city = self.city
        links = lambda: self.links() if callable(self.links) else self.links
        spark = city.spark
        text = lambda form, *cols: FORMS[form](*map(F.col, cols))

        def ground() -> DataFrame:
            return city.ground.select("surface_id", "building_id", "area_m2", "rings", "height_m", text("polygon", "rings").alias("wkt"), text("solid", "rings", "height_m").alias("solid_wkt"))

        def roof_shape() -> DataFrame:
            shapes = city.ground.select("building_id", "rings", "height_m", text("lifted", "rings", "height_m").alias("wkt"))
            return city.faces.where("kind = 'roof'").drop("kind").join(shapes, "building_id").select("ord", "line", "building_id", "supp", "rings", "height_m", "wkt")

        def roof() -> DataFrame:
            return city.faces.where("kind = 'roof'").drop("kind")

        leaves = dict.fromkeys(crowd_closure_rows(self.ontology, (*RESIDENTIAL, "Hotel", "Workshop", "Garage", "Poi", *ROAD_CLASSES)))
        face_key = ("ord", "line", "building_id", "supp")
        key = lambda table, **columns: lambda: city.table(table).select(*[F.col(c).cast("long").alias(a) for a, c in columns.items()])
        face_keys = key("lineitem", ord="l_orderkey", line="l_linenumber", building_id="l_partkey", supp="l_suppkey")
        to_building = {("building_id",): "building"}
        out = {
            "building": Source(lambda: city.buildings, ("building_id",), keys=key("part", building_id="p_partkey")),
            "ground": Source(ground, ("surface_id",), to_building, unique=(("building_id",),), keys=key("part", surface_id="p_partkey")),
            "roof": Source(roof, face_key, to_building, "face", keys=face_keys),
            "roof_shape": Source(roof_shape, face_key, to_building | {face_key: "roof"}, joins=("roof", "ground")),
            "roof_label": Source(lambda: roof().join(city.buildings.select("building_id", "roof_label"), "building_id"), face_key, to_building | {face_key: "roof"}, joins=("roof", "building")),
            "wall": Source(lambda: city.faces.where("kind = 'wall'").drop("kind"), face_key, to_building, "face", keys=face_keys),
            "closure": Source(lambda: city.faces.where("kind = 'closure'").drop("kind"), face_key, to_building, "face", keys=face_keys),
            "address": Source(lambda: city.addresses, ("address_id",), few=True),
            "building_address": Source(lambda: city.building_address, ("building_id", "address_id"), {("building_id",): "building", ("address_id",): "address"}, distinct=True),
            "crowd": Source(lambda: city.crowd.select("area_id", "label", "class", "rings", wkt.polygon_wkt(F.col("rings")).alias("wkt")), ("area_id",), keys=key("customer", area_id="c_custkey")),
            "poi": Source(lambda: city.pois.select("poi_id", F.lit("Poi").alias("class"), wkt.point_wkt(F.col("x"), F.col("y")).alias("wkt")), ("poi_id",), keys=key("orders", poi_id="o_orderkey")),
            "road": Source(lambda: city.roads.select("road_id", "label", "class", "pts", wkt.line_wkt(F.col("pts")).alias("wkt")), ("road_id",), keys=key("supplier", road_id="s_suppkey")),
            "class_closure": Source(lambda: spark.createDataFrame([*leaves], "class string, super string"), ("class", "super"), distinct=True),
            "link_match": Source(lambda: links().edges.select("surface_id", "area_id", F.round("ratio", 6).alias("ratio")), ("surface_id", "area_id"), {("surface_id",): "ground", ("area_id",): "crowd"}, derived=True),
            "link_adjacent": Source(lambda: links().adjacent.select("surface_id", "area_id", F.round("shared_m", 6).alias("shared_m")), ("surface_id", "area_id"), {("surface_id",): "ground", ("area_id",): "crowd"}, derived=True),
            "poi_link": Source(lambda: links().poi_links.select("poi_id", F.col("surface_id").alias("building_id")).distinct(), ("poi_id", "building_id"), to_building | {("poi_id",): "poi"}, derived=True),
        }
        # a frame is planned once, whatever number of triples is made of it
        return {name: replace(source, frame=cache(source.frame)) for name, source in out.items()} | self.extra


B, G, SOLID, ADDR = (Template(f"cw:{n}/{{}}", (c,)) for n, c in (("b", "building_id"), ("g", "surface_id"), ("solid", "building_id"), ("addr", "address_id")))
_FACE = ("ord", "line", "building_id", "supp")
FACE, FACE_GEO = Template("cw:f/{}/{}/{}/{}", _FACE), Template("cw:geo/f/{}/{}/{}/{}", _FACE)
GROUND_GEO = Template("cw:geo/g/{}", ("surface_id",))
INDIVIDUAL = Template("cw:ci/{}", ("class",))


def crowd_element(kind: str, key: str) -> Template:
    """One template for each kind of element: what can't be joined is seen from the templates alone."""
    return Template(f"cw:crowd/{kind}/{{}}", (key,))


def crowd_geometry(kind: str, key: str) -> Template:
    return Template(f"cw:geo/crowd/{kind}/{{}}", (key,))


def class_assignment(name: str, source: str, kind: str, key: str) -> Mapping:
    """The node between an element of the crowd layer and its class, and the class as an individual."""
    node = Template(f"cw:class/{kind}/{{}}", (key,))
    return Mapping(name, source, (_type(node, "ClassAssignment"), Target(node, "cw:elementOf", crowd_element(kind, key)), Target(node, "cw:assignsClass", INDIVIDUAL)))


def _type(subject: Template, name: str) -> Target:
    return Target(subject, TYPE, Const(f"cw:{name}"))


def _data(subject: Template, **fields: tuple) -> tuple[Target, ...]:
    return tuple(Target(subject, f"cw:{p}", Field(*spec)) for p, spec in fields.items())


#: Text of geometry from raw columns, by form.
FORMS: dict[str, Callable[..., Column]] = {
    "polygon": wkt.polygon_wkt,
    "line": wkt.line_wkt,
    "solid": wkt.solid_wkt,
    "lifted": lambda rings, height: F.concat(F.lit("POLYGON Z ("), wkt._ring(F.element_at(rings, 1), lambda p: F.concat_ws(" ", wkt.number(p["x"]), wkt.number(p["y"]), wkt.number(height))), F.lit(")")),
}


def _shape(subject: Template, node: Template, kind: str, form: str = "", raw: tuple[str, ...] = (), **more: tuple) -> tuple[Target, ...]:
    return (Target(subject, "cw:hasGeometry", node), _type(node, kind), *_data(node, wkt=("wkt", "wkt", False, form, raw), **more))


def building() -> Mapping:
    return Mapping("MP01", "building", (_type(B, "Building"), *_data(B, height=("height_m", "double"), roofCode=("roof_code", "int"), roofLabel=("roof_label", "string"), usage=("usage", "string"), storeysAbove=("storeys", "int"))))


def building_solid() -> Mapping:
    return Mapping("MP02", "building", (Target(B, "cw:hasSolid", SOLID),))


def solid_geometry() -> Mapping:
    solid = Template("cw:solid/{}", ("building_id",))
    return Mapping("MP03", "ground", (_type(solid, "PolyhedralSurface"), *_data(solid, wkt=("solid_wkt", "wkt", False, "solid", ("rings", "height_m")))))


def catalogue() -> list[Mapping]:
    """All mappings of the city, the crowd layer and the links."""
    face = lambda name, kind, source: Mapping(name, source, (Target(B, "cw:hasFace", FACE), Target(FACE, "cw:faceOf", B), _type(FACE, kind)))
    area, poi, road = crowd_element("way", "area_id"), crowd_element("poi", "poi_id"), crowd_element("road", "road_id")
    link = {k: Template(f"cw:link/{k}/{{}}/{{}}", ("surface_id", "area_id")) for k in ("match", "adjacent")}
    return [
        building(),
        building_solid(),
        solid_geometry(),
        Mapping("MP04", "ground", (Target(B, "cw:hasFace", G), Target(G, "cw:faceOf", B), _type(G, "GroundSurface"), *_shape(G, GROUND_GEO, "Polygon", "polygon", ("rings",), metricArea=("area_m2", "double")))),
        face("MP05", "RoofSurface", "roof"),
        Mapping("MP05b", "roof_label", _data(FACE, roofLabel=("roof_label", "string"))),
        Mapping("MP05c", "roof_shape", _shape(FACE, FACE_GEO, "Polygon")),
        face("MP06a", "WallSurface", "wall"),
        face("MP06b", "ClosureSurface", "closure"),
        Mapping("MP07", "address", (_type(ADDR, "Address"), *_data(ADDR, label=("label", "string"), street=("street", "string"), city=("city", "string"), country=("country", "string")))),
        Mapping("MP08", "building_address", (Target(B, "cw:hasAddress", ADDR),)),
        Mapping("MP09", "crowd", (_type(area, "CrowdElement"), *_data(area, label=("label", "string", True)), *_shape(area, crowd_geometry("way", "area_id"), "Polygon", "polygon", ("rings",)))),
        Mapping("MP10", "poi", (_type(poi, "CrowdElement"), *_shape(poi, crowd_geometry("poi", "poi_id"), "Point"))),
        Mapping("MP11", "road", (_type(road, "CrowdElement"), *_data(road, label=("label", "string", True)), *_shape(road, crowd_geometry("road", "road_id"), "Line", "line", ("pts",)))),
        class_assignment("MP12", "crowd", "way", "area_id"),
        class_assignment("MP13", "poi", "poi", "poi_id"),
        class_assignment("MP14", "road", "road", "road_id"),
        Mapping("MP14b", "class_closure", (Target(INDIVIDUAL, TYPE, Template("cw:{}", ("super",))),)),
        Mapping("MP15", "link_match", (_type(link["match"], "Association"), Target(link["match"], "cw:matchesCrowd", area), Target(link["match"], "cw:matchesCity", G), *_data(link["match"], overlapRatio=("ratio", "double")))),
        Mapping("MP16", "link_adjacent", (_type(link["adjacent"], "Association"), Target(link["adjacent"], "cw:adjacentCrowd", area), Target(link["adjacent"], "cw:adjacentCity", G), *_data(link["adjacent"], sharedLength=("shared_m", "double")))),
        Mapping("MP17", "poi_link", (Target(poi, "cw:locatedIn", B),)),
    ]


def saturate(mappings: list[Mapping], o: Ontology) -> list[Mapping]:
    """Mappings with everything that the hierarchies entail: super-classes, super-properties, inverses, domains, ranges."""
    props = o.properties
    out = []
    for m in mappings:
        seen: dict[Target, None] = {}
        todo = list(m.targets)
        while todo:
            t = todo.pop(0)
            if t in seen:
                continue
            seen[t] = None
            if t.predicate == TYPE:
                if isinstance(t.object, Const):
                    todo += [Target(t.subject, TYPE, Const(c)) for c in sorted(o.ancestors(t.object.iri))]
                continue
            p = props.get(t.predicate)
            todo += [Target(t.subject, s, t.object) for s in sorted(o.super_properties(t.predicate))]
            if p is None:
                continue
            if p.inverse and isinstance(t.object, Template):
                todo.append(Target(t.object, p.inverse, t.subject))
            if p.domain:
                todo.append(Target(t.subject, TYPE, Const(p.domain)))
            if p.kind == "object" and p.range and isinstance(t.object, Template):
                todo.append(Target(t.object, TYPE, Const(p.range)))
        out.append(Mapping(m.id, m.source, tuple(seen)))
    return out


def validate(mappings: list[Mapping], o: Ontology, store: Store) -> list[str]:
    """What is wrong with a set of mappings; empty if nothing is."""
    wrong, ids = [], [m.id for m in mappings]
    wrong += [f"id {i} is used {ids.count(i)} times" for i in sorted(set(ids)) if ids.count(i) > 1]
    for m in mappings:
        if m.source not in store.sources:
            wrong.append(f"{m.id}: no source {m.source}")
            continue
        columns = set(store.sources[m.source].frame().columns)
        for t in m.targets:
            used = [*t.subject.columns, *(t.object.columns if isinstance(t.object, Template) else [t.object.column] if isinstance(t.object, Field) else [])]
            wrong += [f"{m.id}: {m.source} has no column {c}" for c in used if c not in columns]
            for x in (t.subject, t.object):
                if isinstance(x, Template) and x.pattern.count("{}") != len(x.columns):
                    wrong.append(f"{m.id}: {x.pattern} doesn't take {len(x.columns)} keys")
                if isinstance(x, Template) and "}{" in x.pattern:
                    wrong.append(f"{m.id}: keys of {x.pattern} run into each other")
            if t.predicate == TYPE:
                if isinstance(t.object, Const) and t.object.iri not in o.classes:
                    wrong.append(f"{m.id}: no class {t.object.iri}")
            elif t.predicate not in o.properties:
                wrong.append(f"{m.id}: no property {t.predicate}")
            elif (o.properties[t.predicate].kind == "data") != isinstance(t.object, Field):
                wrong.append(f"{m.id}: {t.predicate} is declared as {o.properties[t.predicate].kind} property")
    return wrong


def to_document(mappings: list[Mapping]) -> str:
    """Mappings as text: an id line, a source line, and a line for each target."""
    lines = []
    for m in mappings:
        lines += [f"mappingId\t{m.id}", f"source\t\t{m.source}"]
        for t in m.targets:
            if isinstance(t.object, Template):
                shown = json.dumps([t.object.pattern, *t.object.columns])
            elif isinstance(t.object, Field):
                shown = json.dumps({"column": t.object.column, "type": t.object.dtype, "nullable": t.object.nullable, "form": t.object.form, "raw": t.object.raw})
            else:
                shown = t.object.iri
            lines.append(f"target\t\t{json.dumps([t.subject.pattern, *t.subject.columns])}\t{t.predicate}\t{shown}")
        lines.append("")
    return "\n".join(lines)


def from_document(text: str) -> list[Mapping]:
    out = []
    for block in filter(str.strip, text.split("\n\n")):
        rows = [line.split("\t") for line in block.strip().split("\n")]
        targets = []
        for row in rows:
            if row[0] == "target":
                first, predicate, shown = row[-3:]
                s = json.loads(first)
                if shown[0] == "[":
                    o = json.loads(shown)
                    obj: Template | Field | Const = Template(o[0], tuple(o[1:]))
                elif shown[0] == "{":
                    o = json.loads(shown)
                    obj = Field(o["column"], o["type"], o["nullable"], o["form"], tuple(o["raw"]))
                else:
                    obj = Const(shown)
                targets.append(Target(Template(s[0], tuple(s[1:])), predicate, obj))
        out.append(Mapping(rows[0][-1], rows[1][-1], tuple(targets)))
    return out
