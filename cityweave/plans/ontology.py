"""The vocabulary: classes and properties, their hierarchies, and repairs."""

from __future__ import annotations

from collections.abc import Iterable
from dataclasses import dataclass, field, replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from cityweave.scratch import Scratch

PREFIXES = {
    "cw": "https://example.org/cityweave/",
    "rdf": "http://www.w3.org/1999/02/22-rdf-syntax-ns#",
    "rdfs": "http://www.w3.org/2000/01/rdf-schema#",
    "xsd": "http://www.w3.org/2001/XMLSchema#",
    "geo": "http://www.opengis.net/ont/geosparql#",
}
TYPE = "rdf:type"


@dataclass(frozen=True)
class Property:
    """A declaration: kind `object` or `data`; datatype for data properties."""

    name: str
    kind: str
    domain: str | None = None
    range: str | None = None
    parents: tuple[str, ...] = ()
    inverse: str | None = None


@dataclass(frozen=True)
class Ontology:
    """Declared classes with their parents, and all property declarations, clashing ones included."""

    classes: dict[str, tuple[str, ...]] = field(default_factory=dict)
    declared: tuple[Property, ...] = ()

    @property
    def properties(self) -> dict[str, Property]:
        """One declaration for each name; clashes must be resolved before."""
        return {p.name: p for p in self.declared}

    def ancestors(self, name: str) -> set[str]:
        """A class with all it falls under."""
        return _reach(name, self.classes)

    def descendants(self, name: str) -> set[str]:
        return {c for c in self.classes if name in self.ancestors(c)} | {name}

    def super_properties(self, name: str) -> set[str]:
        return _reach(name, {p.name: p.parents for p in self.declared})

    def sub_properties(self, name: str) -> set[str]:
        return {p.name for p in self.declared if name in self.super_properties(p.name)} | {name}


def _reach(name: str, up: dict[str, tuple[str, ...]]) -> set[str]:
    seen, todo = {name}, [name]
    while todo:
        for parent in up.get(todo.pop(), ()):
            if parent not in seen:
                seen.add(parent)
                todo.append(parent)
    return seen


def load(spec: dict) -> Ontology:
    """From a plain description: {"classes": {name: [parents]}, "properties": [keyword dicts]}."""
    classes = {name: tuple(parents) for name, parents in spec["classes"].items()}
    return Ontology(classes, tuple(Property(**{k: tuple(v) if isinstance(v, list) else v for k, v in p.items()}) for p in spec["properties"]))


def merge(a: Ontology, b: Ontology) -> Ontology:
    """Both vocabularies; classes named in both get both lists of parents."""
    classes = dict(a.classes)
    for name, parents in b.classes.items():
        classes[name] = tuple(dict.fromkeys((*classes.get(name, ()), *parents)))
    return Ontology(classes, tuple(dict.fromkeys((*a.declared, *b.declared))))


def extend(o: Ontology, *more: Property) -> Ontology:
    return replace(o, declared=(*o.declared, *more))


def resolve(o: Ontology, choices: dict[str, str]) -> Ontology:
    """Of a property declared in both kinds only the chosen kind stays."""
    return replace(o, declared=tuple(p for p in o.declared if choices.get(p.name, p.kind) == p.kind))


def declarations(spark: SparkSession, o: Ontology) -> DataFrame:
    return spark.createDataFrame([(p.name, p.kind) for p in o.declared], "iri string, kind string")


def clashes(spark: SparkSession, o: Ontology) -> DataFrame:
    """(iri) declared both as object and as data property."""
    d = declarations(spark, o).distinct()
    return d.where("kind = 'object'").select("iri").join(d.where("kind = 'data'").select("iri"), "iri")


def closure(spark: SparkSession, o: Ontology) -> DataFrame:
    """(kind, sub, super): reflexive and transitive, of classes and properties."""
    rows = [("class", c, s) for c in o.classes for s in o.ancestors(c)]
    rows += [("property", p, s) for p in o.properties for s in o.super_properties(p)]
    return spark.createDataFrame(sorted(rows), "kind string, sub string, super string")


def closure_recursive(spark: SparkSession, o: Ontology) -> DataFrame:
    """The same by a recursive query over the direct edges."""
    edges = [("class", c, p) for c, ps in o.classes.items() for p in ps] + [("property", p.name, s) for p in o.declared for s in p.parents]
    names = [("class", c) for c in o.classes] + [("property", p) for p in o.properties]
    spark.createDataFrame(edges, "kind string, sub string, super string").createOrReplaceTempView("_cw_edges")
    spark.createDataFrame(names, "kind string, name string").createOrReplaceTempView("_cw_names")
    return spark.sql("""
        with recursive up(kind, sub, super) as (
          select kind, name, name from _cw_names
          union all
          select up.kind, up.sub, e.super from up join _cw_edges e on e.kind = up.kind and e.sub = up.super
        ) select distinct kind, sub, super from up""")


def subtree(spark: SparkSession, o: Ontology, name: str) -> DataFrame:
    """(class) at or under a class."""
    return closure(spark, o).where((F.col("kind") == "class") & (F.col("super") == name)).select(F.col("sub").alias("class"))


def usage_edges(parts: DataFrame) -> DataFrame:
    """(sub, super) of the classes of use that buildings have by their table: a type of use, a kind within it, a kind's variant."""
    steps = [F.concat(F.lit("cw:usage/"), F.col("p_type"))]
    steps.append(F.concat(steps[0], F.lit("/"), F.split_part("p_name", F.lit(" "), F.lit(-1))))
    steps.append(F.concat(steps[0], F.lit("/"), F.replace("p_name", F.lit(" "), F.lit("_"))))
    pairs = [F.struct(steps[0].alias("sub"), F.lit("cw:Building").alias("super")), *[F.struct(x.alias("sub"), y.alias("super")) for x, y in zip(steps[1:], steps, strict=False)]]
    each = parts.select("p_type", "p_name").distinct().select(F.explode(F.array(*pairs)).alias("e")).select("e.*")
    return each.where("sub is not null and super is not null and sub <> super").distinct()


def closure_with(spark: SparkSession, o: Ontology, more: DataFrame, scratch: Scratch) -> DataFrame:
    """(kind, sub, super) as closure, over the vocabulary and further classes (sub, super): each round goes up one step, until nothing is new."""
    direct = [("class", c, p) for c, ps in o.classes.items() for p in ps] + [("property", p.name, s) for p in o.declared for s in p.parents]
    names = [("class", c) for c in o.classes] + [("property", p) for p in o.properties]
    edges = spark.createDataFrame(direct, "kind string, sub string, super string").unionByName(more.select(F.lit("class").alias("kind"), "sub", "super"))
    edges = scratch.keep(edges.distinct())
    own = spark.createDataFrame(names, "kind string, sub string").unionByName(edges.select("kind", "sub")).unionByName(edges.select("kind", F.col("super").alias("sub")))
    front = found = scratch.keep(own.distinct().withColumn("super", F.col("sub")))
    up = edges.select("kind", F.col("sub").alias("super"), F.col("super").alias("next"))
    while True:
        longer = front.join(up, ["kind", "super"]).select("kind", "sub", F.col("next").alias("super")).distinct()
        front = scratch.keep(longer.join(found, ["kind", "sub", "super"], "left_anti"))
        if front.isEmpty():
            return found
        found = scratch.keep(found.unionByName(front))


def subtree_with(spark: SparkSession, o: Ontology, more: DataFrame, scratch: Scratch, name: str) -> DataFrame:
    """(class) at or under a class, further classes included."""
    return closure_with(spark, o, more, scratch).where((F.col("kind") == "class") & (F.col("super") == name)).select(F.col("sub").alias("class"))


# Our vocabulary.
_CLASSES: dict[str, list[str]] = {
    "Feature": [],
    "SpatialFeature": ["Feature"],
    "Building": ["SpatialFeature"],
    "BoundarySurface": ["SpatialFeature"],
    **{c: ["BoundarySurface"] for c in ("RoofSurface", "GroundSurface", "WallSurface", "ClosureSurface")},
    "Geometry": ["Feature"],
    "Solid": ["Geometry"],
    "PolyhedralSurface": ["Solid"],
    **{c: ["Geometry"] for c in ("Polygon", "Line", "Point")},
    "Address": ["Feature"],
    "CrowdElement": ["SpatialFeature"],
    "Residential": ["CrowdElement"],
    **{c: ["Residential"] for c in ("HousingBlockA", "HousingBlockB", "HousingBlockC", "DetachedHomeA", "DetachedHomeB")},
    **{c: ["CrowdElement"] for c in ("Hotel", "Workshop", "Garage", "Road", "Poi")},
    **{c: ["Road"] for c in ("Secondary", "Tertiary", "Service", "Unclassified", "Primary", "Footway")},
    "Association": ["Feature"],
    "ClassAssignment": ["Feature"],
}
_OBJECT = [
    dict(name="hasAddress", domain="Building", range="Address"),
    dict(name="hasFace", domain="Building", range="BoundarySurface", inverse="faceOf"),
    dict(name="faceOf", domain="BoundarySurface", range="Building", inverse="hasFace"),
    dict(name="hasSolid", domain="Building", range="Solid"),
    dict(name="hasGeometry", range="Geometry"),
    dict(name="linksCity", domain="Association", range="BoundarySurface"),
    dict(name="matchesCity", parents=["linksCity"]),
    dict(name="adjacentCity", parents=["linksCity"]),
    dict(name="linksCrowd", domain="Association", range="CrowdElement"),
    dict(name="matchesCrowd", parents=["linksCrowd"]),
    dict(name="adjacentCrowd", parents=["linksCrowd"]),
    dict(name="elementOf", domain="ClassAssignment", range="CrowdElement"),
    dict(name="assignsClass", domain="ClassAssignment"),
    dict(name="locatedIn", domain="Poi", range="Building"),
    dict(name="sameAs"),
]
_DATA = [
    dict(name="height", domain="Building", range="double"),
    dict(name="roofCode", domain="Building", range="int"),
    dict(name="roofLabel", range="string"),
    dict(name="usage", domain="Building", range="string"),
    dict(name="storeysAbove", domain="Building", range="int"),
    dict(name="storeysBelow", domain="Building", range="int"),
    dict(name="builtYear", domain="Building", range="int"),
    dict(name="label", range="string"),
    dict(name="wkt", domain="Geometry", range="wkt"),
    dict(name="metricArea", domain="Geometry", range="double"),
    dict(name="overlapRatio", domain="Association", range="double"),
    dict(name="sharedLength", domain="Association", range="double"),
    *[dict(name=n, domain="Address", range="string") for n in ("street", "city", "country")],
]


def _named(name: str) -> str:
    return f"cw:{name}"


def vocabulary_spec(with_clashes: bool = False) -> dict:
    """Our vocabulary; with_clashes adds declarations of data properties as object properties, to be repaired."""
    props = []
    for kind, items in (("object", _OBJECT), ("data", _DATA)):
        for item in items:
            p = dict(item, kind=kind, name=_named(item["name"]))
            for k in ("domain", "inverse"):
                if k in p:
                    p[k] = _named(p[k])
            if kind == "object" and "range" in p:
                p["range"] = _named(p["range"])
            p["parents"] = [_named(x) for x in item.get("parents", ())]
            props.append(p)
    if with_clashes:
        props += [dict(name=_named(n), kind="object") for n in ("roofCode", "usage", "street", "city")]
    return {"classes": {_named(c): [_named(p) for p in ps] for c, ps in _CLASSES.items()}, "properties": props}


def vocabulary() -> Ontology:
    return load(vocabulary_spec())


LEAF_CLASSES: tuple[str, ...] = tuple(c for c in _CLASSES if c not in {p for ps in _CLASSES.values() for p in ps})


def crowd_closure_rows(o: Ontology, names: Iterable[str]) -> list[tuple[str, str]]:
    """(leaf, class above or itself), local names, for the classes of crowd elements."""
    return sorted((n, s.removeprefix("cw:")) for n in names for s in o.ancestors(_named(n)))
