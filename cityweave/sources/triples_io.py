"""Triples and layers as files: N-Triples, Turtle, folders by predicate, WKT tables, GeoJSON."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from cityweave.functions import wkt
from cityweave.plans.ontology import PREFIXES

_XSD = {"double": "xsd:double", "int": "xsd:integer", "wkt": "geo:wktLiteral", "boolean": "xsd:boolean"}


def expand(iri: Column) -> Column:
    """prefix:local to a full IRI."""
    out = iri
    for prefix, namespace in PREFIXES.items():
        out = F.when(F.startswith(iri, F.lit(f"{prefix}:")), F.concat(F.lit(namespace), F.substring(iri, len(prefix) + 2, 1 << 20))).otherwise(out)
    return out


def shorten(iri: Column) -> Column:
    out = iri
    for prefix, namespace in PREFIXES.items():
        out = F.when(F.startswith(iri, F.lit(namespace)), F.concat(F.lit(f"{prefix}:"), F.substring(iri, len(namespace) + 1, 1 << 20))).otherwise(out)
    return out


# Characters that a literal escapes. The backslash comes first.
ESCAPES = (("\\", "\\\\"), ('"', '\\"'), ("\n", "\\n"), ("\r", "\\r"), ("\t", "\\t"))


def escape(text: Column) -> Column:
    for raw, written in ESCAPES:
        text = F.replace(text, F.lit(raw), F.lit(written))
    return text


def unescape(text: Column) -> Column:
    """The inverse: cut at escaped backslashes first, so that they can't join what follows."""

    def plain(part: Column) -> Column:
        for raw, written in ESCAPES[1:]:
            part = F.replace(part, F.lit(written), F.lit(raw))
        return part

    return F.array_join(F.transform(F.split(text, r"\\\\", -1), plain), "\\")


def _typed(dtype: Column, form: Callable[[str], str]) -> Column:
    out = F.lit("")
    for name, xsd in _XSD.items():
        out = F.when(dtype == name, F.lit(f"^^{form(xsd)}")).otherwise(out)
    return out


def _full(short: str) -> str:
    prefix, _, local = short.partition(":")
    return f"<{PREFIXES[prefix]}{local}>"


def ntriples(triples: DataFrame) -> DataFrame:
    """(value): a line for each triple."""
    iri = lambda c: F.concat(F.lit("<"), expand(F.col(c)), F.lit(">"))
    literal = F.concat(F.lit('"'), escape(F.col("o")), F.lit('"'), F.coalesce(F.concat(F.lit("@"), F.col("lang")), _typed(F.col("dtype"), _full)))
    return triples.select(F.concat_ws(" ", iri("s"), iri("p"), F.when(F.col("o_kind") == 0, iri("o")).otherwise(literal), F.lit(".")).alias("value"))


def write_ntriples(triples: DataFrame, path: str) -> None:
    ntriples(triples).write.mode("overwrite").text(path)


def read_ntriples(spark: SparkSession, path: str) -> DataFrame:
    """Triples of N-Triples files; lines that aren't triples are left out."""
    line = r'^<([^>]*)>\s+<([^>]*)>\s+(?:<([^>]*)>|"((?:[^"\\]++|\\.)*+)"(?:@([A-Za-z-]+)|\^\^<([^>]*)>)?)\s*\.\s*$'
    part = lambda k: F.regexp_extract("value", line, k)
    rows = spark.read.text(path).where(F.col("value").rlike(line)).select(*[part(k).alias(f"g{k}") for k in range(1, 7)])
    literal = F.col("g3") == ""
    dtype = F.lit("string")
    for name, short in _XSD.items():
        dtype = F.when(F.col("g6") == _full(short)[1:-1], name).otherwise(dtype)
    return rows.select(
        shorten(F.col("g1")).alias("s"),
        shorten(F.col("g2")).alias("p"),
        F.when(literal, unescape(F.col("g4"))).otherwise(shorten(F.col("g3"))).alias("o"),
        F.when(literal, 1).otherwise(0).cast("tinyint").alias("o_kind"),
        F.when(literal, dtype).alias("dtype"),
        F.when(F.col("g5") != "", F.col("g5")).alias("lang"),
        F.when(literal & F.col("g6").isin(*[_full(_XSD[k])[1:-1] for k in ("double", "int")]), F.col("g4").try_cast("double")).alias("o_num"),
    )


def write_turtle(triples: DataFrame, path: str) -> None:
    """A block for each subject, its predicates in order. Each file starts with the prefixes."""
    literal = F.concat(F.lit('"'), escape(F.col("o")), F.lit('"'), F.coalesce(F.concat(F.lit("@"), F.col("lang")), _typed(F.col("dtype"), lambda x: x)))
    name = lambda c: F.when(F.col(c).rlike(r"^\w+:[\w-]+$"), F.col(c)).otherwise(F.concat(F.lit("<"), expand(F.col(c)), F.lit(">")))
    rows = triples.select("s", F.concat_ws(" ", name("p"), F.when(F.col("o_kind") == 0, name("o")).otherwise(literal)).alias("po"), name("s").alias("subject"))
    blocks = rows.groupBy("s", "subject").agg(F.array_sort(F.collect_list("po")).alias("all"))
    body = blocks.select(F.concat(F.col("subject"), F.lit(" "), F.array_join("all", " ;\n  "), F.lit(" .")).alias("value"))
    head = "\n".join(f"@prefix {p}: <{ns}> ." for p, ns in PREFIXES.items())
    first = body.select("value", F.spark_partition_id().alias("part"), F.monotonically_increasing_id().alias("row"))
    opened = first.select(F.when(F.col("row") == F.shiftleft(F.col("part").cast("long"), 33), F.concat(F.lit(head + "\n"), F.col("value"))).otherwise(F.col("value")).alias("value"))
    opened.write.mode("overwrite").text(path)


def write_predicate_layout(triples: DataFrame, path: str) -> None:
    """A folder for each predicate."""
    triples.withColumn("p_id", F.regexp_replace("p", "[^A-Za-z]", "_")).write.mode("overwrite").partitionBy("p_id").parquet(path)


def write_wkt_csv(layer: DataFrame, path: str) -> None:
    """Attributes and WKT of a layer with `rings`."""
    plain = [c for c, t in layer.dtypes if not t.startswith(("array", "struct"))]
    layer.select(*plain, wkt.polygon_wkt(F.col("rings")).alias("wkt")).write.mode("overwrite").option("header", True).csv(path)


def geojson(layer: DataFrame) -> DataFrame:
    """(value): a GeoJSON feature a line, of a layer with `rings`."""
    plain = [c for c, t in layer.dtypes if not t.startswith(("array", "struct"))]
    ring = lambda r: F.transform(F.concat(r, F.slice(r, 1, 1)), lambda p: F.array(p["x"], p["y"]))
    shape = F.struct(F.lit("Polygon").alias("type"), F.transform("rings", ring).alias("coordinates"))
    return layer.select(F.to_json(F.struct(F.lit("Feature").alias("type"), shape.alias("geometry"), F.struct(*plain).alias("properties"))).alias("value"))


def write_geojson(layer: DataFrame, path: str) -> None:
    geojson(layer).write.mode("overwrite").text(path)
