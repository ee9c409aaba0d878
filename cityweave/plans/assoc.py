"""Links as nodes of the graph, so that they can say more than that two things are one."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def nodes(links: DataFrame) -> DataFrame:
    """(node, crowd, city, kind): one association for each link, with both ends."""
    iri = lambda prefix, *keys: F.concat_ws("/", F.lit(prefix), *keys)
    return links.select(iri("cw:link", "kind", F.col("surface_id").cast("string"), F.col("area_id").cast("string")).alias("node"), iri("cw:crowd/way", F.col("area_id").cast("string")).alias("crowd"), iri("cw:g", F.col("surface_id").cast("string")).alias("city"), "kind")


def build(links: DataFrame) -> DataFrame:
    """(s, p, o) of associations: type and both ends, with the sub-properties of their kind."""
    n = nodes(links)
    ends = F.explode(
        F.array(
            F.struct(F.lit("rdf:type").alias("p"), F.lit("cw:Association").alias("o")),
            F.struct(F.when(F.col("kind") == "match", "cw:matchesCrowd").otherwise("cw:adjacentCrowd").alias("p"), F.col("crowd").alias("o")),
            F.struct(F.when(F.col("kind") == "match", "cw:matchesCity").otherwise("cw:adjacentCity").alias("p"), F.col("city").alias("o")),
        )
    ).alias("t")
    return n.select(F.col("node").alias("s"), ends).select("s", "t.p", "t.o")


def class_nodes(crowd_classes: DataFrame) -> DataFrame:
    """(node, element, class): which class an element of the crowd layer was given."""
    key = F.concat_ws("/", "elem_kind", F.col("elem_id").cast("string"))
    return crowd_classes.select(F.concat(F.lit("cw:class/"), key).alias("node"), F.concat(F.lit("cw:crowd/"), key).alias("element"), F.concat(F.lit("cw:ci/"), F.col("class")).alias("class"))


def same_as(links: DataFrame) -> DataFrame:
    """(s, o) of the plain alternative: identity, which only 1:1 links bear."""
    one = links.where("kind = 'match' and relation = '1:1'")
    return one.select(F.concat(F.lit("cw:crowd/way/"), F.col("area_id").cast("string")).alias("s"), F.concat(F.lit("cw:g/"), F.col("surface_id").cast("string")).alias("o"))
