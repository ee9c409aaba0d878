"""All queries of the library by key, and the SQL that gives the same rows."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import replace
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from cityweave import measures, oracles, workload
from cityweave.context import Context, context
from cityweave.functions import crs, geom, wkt
from cityweave.operators import linker, relational, spatial
from cityweave.plans import assoc, graph, mappings, ontology
from cityweave.scratch import free_shuffles
from cityweave.sources import init
from cityweave.streaming import feeds

Query = Callable[[SparkSession, str], DataFrame]


def _rounded(df: DataFrame, *names: str, digits: int = 6) -> DataFrame:
    return df.withColumns({n: F.round(n, digits) for n in names})


def _layer(df: DataFrame, key: str) -> DataFrame:
    return df.select(F.col(key).alias("id"), "bbox")


def _ground(c: Context) -> DataFrame:
    return c.city.ground


def _pairs(c: Context, strict: bool = True) -> DataFrame:
    """Candidate pairs of both layers with their shapes."""
    city, crowd = c.city.ground, c.city.crowd
    found = spatial.candidates(_layer(city, "surface_id"), _layer(crowd, "area_id"), strict=strict)
    a = city.select(F.col("surface_id").alias("a_id"), F.col("rings").alias("a"))
    b = crowd.select(F.col("area_id").alias("b_id"), F.col("rings").alias("b"))
    return found.join(a, "a_id").join(b, "b_id").withColumnsRenamed({"a_id": "surface_id", "b_id": "area_id"})


def _neighbours(c: Context, pad: float, less: bool = False) -> DataFrame:
    """Pairs of ground surfaces whose boxes are within pad, with their edges."""
    g = c.city.ground
    found = spatial.candidates(_layer(g, "surface_id"), _layer(g, "surface_id"), pad=pad).where("a_id < b_id" if less else "a_id <> b_id")
    side = lambda n: g.select(F.col("surface_id").alias(f"{n}_id"), geom.segments(F.col("rings")).alias(n))
    return found.join(side("a"), "a_id").join(side("b"), "b_id").withColumnsRenamed({"a_id": "surface_id", "b_id": "neighbour_id"})


_FAR = 60.0


def _gaps(c: Context) -> DataFrame:
    """Distances up to _FAR of all ground surfaces, of any shape and across blocks; each pair both ways.

    A distance is worked out once for both ways and the test of its length, so it isn't a column that filters could repeat; only pairs
    whose boxes touch can have a point in common.
    """
    half = _neighbours(c, _FAR, less=True)
    apart = geom.box_gap(F.col("a_box"), F.col("b_box"))
    d = F.when(apart > 0, geom.gap(F.col("a"), F.col("b"))).otherwise(geom.distance(F.col("a"), F.col("b")))
    pair = lambda x, y, d: F.struct(F.col(x).alias("surface_id"), F.col(y).alias("neighbour_id"), d.alias("d"))
    both = geom.let(d, lambda d: F.when(d <= _FAR, F.array(pair("surface_id", "neighbour_id", d), pair("neighbour_id", "surface_id", d))))
    return half.where(apart <= _FAR + 1e-6).select(F.explode_outer(both).alias("p")).where("p is not null").select("p.*")


def _near(c: Context, d: float) -> DataFrame:
    half = _neighbours(c, d, less=True).where(geom.dwithin(F.col("a"), F.col("b"), d)).select("surface_id", "neighbour_id")
    return half.unionByName(half.select(F.col("neighbour_id").alias("surface_id"), F.col("surface_id").alias("neighbour_id")))


def _clipped(subject, clip):
    """Common area by clipping; the clip is taken as a fan of triangles with signs, so it may have any simple shape."""
    fan = F.transform(F.sequence(F.lit(2), F.size(clip) - 1), lambda k: F.array(F.element_at(clip, 1), F.element_at(clip, k), F.element_at(clip, k + 1)))
    signed = lambda t: F.signum(geom.ring_area(t)) * F.abs(geom.ring_area(geom.clip_convex(subject, F.element_at(geom.ccw(F.array(t)), 1))))
    return F.abs(geom.total(fan, signed))

LINKER: dict[str, Callable[[Context], DataFrame]] = {
    "fx_city_surface": lambda c: _rounded(c.city.ground.join(c.city.buildings.select("building_id", "roof_code"), "building_id").select("surface_id", "building_id", "height_m", "roof_code", "area_m2", wkt.polygon_wkt(F.col("rings")).alias("shape")), "area_m2"),
    "fx_crowd_area": lambda c: _rounded(c.city.crowd.select("area_id", "label", "class", "area_m2", wkt.polygon_wkt(F.col("rings")).alias("shape")), "area_m2"),
    "fx_truth_edges": lambda c: _rounded(c.city.truth, "ratio"),
    "link_edges": lambda c: _rounded(linker.relations(linker.direct_match(c.city.ground, c.city.crowd)).select("surface_id", "area_id", "ratio", "relation"), "ratio"),
    "link_classes_group": lambda c: linker.classify(c.links.edges, c.city.ground, c.city.crowd),
    "link_classes_degree": lambda c: linker.classify(c.links.edges, c.city.ground, c.city.crowd, "degree"),
    "link_groups": lambda c: linker.groups(c.links.edges, c.scratch),
    "link_adjacent_edge": lambda c: _rounded(linker.adjacent(c.city.ground, c.links.edges), "shared_m"),
    "link_adjacent_touch": lambda c: _rounded(linker.adjacent(c.city.ground, c.links.edges, rule="touch"), "shared_m"),
    "link_adjacent_gap": lambda c: _rounded(linker.adjacent(c.city.ground, c.links.edges, rule="gap"), "shared_m"),
    "link_adjacent_transitive": lambda c: _rounded(linker.adjacent(c.city.ground, c.links.edges, hops=None, scratch=c.scratch), "shared_m"),
    "link_adjacent_longest": lambda c: _rounded(linker.adjacent(c.city.ground, c.links.edges, pick="longest"), "shared_m"),
    "link_poi": lambda c: c.links.poi_links,
    "link_poi_direct": lambda c: linker.poi_match_direct(c.city.pois, c.city.ground),
    "link_summary": lambda c: linker.summary(c.links),
    "link_sweep": lambda c: linker.sweep(c.city.ground, c.city.crowd),
    "link_ablate": lambda c: linker.ablate_steps(c.links),
    "link_audit": lambda c: linker.audit(c.links.edges, c.city.truth),
    "sp_candidates": lambda c: spatial.candidates(_layer(c.city.ground, "surface_id"), _layer(c.city.crowd, "area_id")).select("a_id", "b_id"),
    "sp_candidates_brute": lambda c: spatial.candidates_brute(_layer(c.city.ground, "surface_id"), _layer(c.city.crowd, "area_id")).select("a_id", "b_id"),
    "sp_candidates_adaptive": lambda c: spatial.candidates_adaptive(_layer(c.city.ground, "surface_id"), _layer(c.city.crowd, "area_id"), max_per_cell=3).select("a_id", "b_id"),
    "sp_candidates_broadcast": lambda c: spatial.candidates_broadcast(_layer(c.city.ground, "surface_id"), _layer(c.city.crowd, "area_id")).select("a_id", "b_id"),
    "sp_join_overlap": lambda c: _rounded(linker.overlaps(c.city.ground, c.city.crowd), "ratio"),
    "sp_join_contains": lambda c: spatial.points_in_polygons(c.city.pois.select(F.col("poi_id").alias("point_id"), "x", "y"), c.city.crowd),
    "sp_join_dwithin": lambda c: spatial.lines_near_polygons(c.city.roads.select(F.col("road_id").alias("line_id"), "pts", "bbox"), c.city.ground.select(F.col("surface_id").alias("area_id"), "rings", "bbox"), 20.0),
    "sp_knn_road": lambda c: _rounded(spatial.nearest_lines(c.city.pois.select(F.col("poi_id").alias("point_id"), "x", "y"), c.city.roads.select(F.col("road_id").alias("line_id"), "pts", "bbox"), 60.0), "d"),
}

_SAME = {"reason_types_chained": "reason_types", "reason_types_rewritten": "reason_types", "sp_candidates_brute": "sp_candidates", "sp_candidates_adaptive": "sp_candidates", "sp_candidates_broadcast": "sp_candidates"}

GEOMETRY: dict[str, Callable[[Context], DataFrame]] = {
    "geo_area": lambda c: c.city.ground.select("surface_id", F.round(geom.area(F.col("rings")), 6).alias("area")),
    "geo_bbox": lambda c: c.city.ground.select("surface_id", *[F.round(f"bbox.{k}", 6).alias(k) for k in ("xmin", "ymin", "xmax", "ymax")]),
    "geo_centroid": lambda c: c.city.ground.select("surface_id", geom.centroid(F.col("rings")).alias("m")).select("surface_id", F.round("m.x", 6).alias("x"), F.round("m.y", 6).alias("y")),
    "geo_length": lambda c: c.city.ground.select("surface_id", F.round(geom.length(geom.segments(F.col("rings"))), 6).alias("length")),
    "geo_contains_point": lambda c: spatial.points_in_polygons(c.city.pois.select(F.col("poi_id").alias("point_id"), "x", "y"), c.city.crowd).groupBy(F.col("point_id").alias("poi_id")).agg(F.count("*").alias("n"), F.min("area_id").alias("first")),
    "geo_intersection_area": lambda c: _pairs(c).select("surface_id", "area_id", F.round(geom.intersection_area(geom.strips(F.col("a")), geom.strips(F.col("b")), F.least("a_box.ymin", "b_box.ymin")), 6).alias("common")).where("common > 0"),
    "geo_intersects": lambda c: _pairs(c, strict=False).where(geom.intersects(geom.segments(F.col("a")), geom.segments(F.col("b")))).select("surface_id", "area_id"),
    "geo_shared_length": lambda c: _neighbours(c, 1e-6, less=True).select("surface_id", "neighbour_id", F.round(geom.shared_length(F.col("a"), F.col("b")), 6).alias("shared_m")).where("shared_m > 0"),
    "geo_distance": lambda c: _rounded(_gaps(c), "d"),
    "geo_dwithin": lambda c: _near(c, 5.0),
    "geo_buffer_area": lambda c: c.city.roads.select("road_id", geom.buffer(geom.line_segments(F.col("pts")), 20.0).alias("zone")).select("road_id", F.round(geom.total(F.col("zone"), lambda p: geom.area(p)) - geom.intersection_area(geom.strips(F.get("zone", F.lit(0))), geom.strips(F.get("zone", F.lit(1))), geom.bbox(F.get("zone", F.lit(0)))["ymin"] - 10), 4).alias("area")),
    "geo_extrude_volume": lambda c: c.city.ground.select("surface_id", F.round(geom.volume(F.col("area_m2"), F.col("height_m")), 6).alias("volume"), geom.face_count(F.col("rings")).alias("faces")),
    "geo_wkt": lambda c: c.city.ground.select("surface_id", wkt.polygon_wkt(F.col("rings")).alias("shape")),
    "geo_reproject": lambda c: c.city.roads.select("road_id", F.posexplode(crs.reproject("pts", crs.LOCAL, crs.GEOGRAPHIC)).alias("i", "p")).select("road_id", "i", F.round("p.x", 9).alias("lon"), F.round("p.y", 9).alias("lat")),
    "geo_cells": lambda c: c.city.ground.select("surface_id", F.explode(geom.cells(F.col("bbox"), 32.0)).alias("c")).select("surface_id", "c.cx", "c.cy"),
    "geo_morton": lambda c: c.city.ground.select("surface_id", geom.morton(F.floor(F.col("bbox.xmin") / 32), F.floor(F.col("bbox.ymin") / 32)).alias("morton")),
    "geo_clip_convex": lambda c: _pairs(c).select("surface_id", "area_id", F.round(_clipped(F.element_at("a", 1), F.element_at("b", 1)), 6).alias("common")).where("common > 0"),
}


_TYPES = ("cw:CrowdElement", "cw:SpatialFeature", "cw:Feature", "cw:Building")


def _subjects(df: DataFrame) -> DataFrame:
    """Buildings and elements of the crowd layer among the subjects of (s, type) of a few classes, counted by class."""
    own = df.where(F.col("type").isin(*_TYPES) & (F.col("s").startswith("cw:b/") | F.col("s").startswith("cw:crowd/")))
    return own.select("s", "type").distinct().groupBy("type").agg(F.count("*").alias("n"))


def _bare(c: Context) -> DataFrame:
    """The triples that mappings state, without what they entail."""
    if "bare" not in c.kept:
        c.kept["bare"] = c.scratch.keep(graph.VirtualGraph(c.ontology, mappings.catalogue(), c.store).stated())
    return c.kept["bare"]


def _types_saturated(c: Context) -> DataFrame:
    """By saturated mappings: the types are among the triples as they are made."""
    return _subjects(c.triples.where("p = 'rdf:type'").select("s", F.col("o").alias("type")))


def _types_chained(c: Context) -> DataFrame:
    """By forward chaining over the triples that mappings state."""
    return _subjects(graph.forward_chain(_bare(c), c.ontology).where("p = 'rdf:type'").select("s", F.col("o").alias("type")))


def _types_rewritten(c: Context) -> DataFrame:
    """By rewriting: each query for a class is widened by the hierarchies and asked of a graph that holds no entailed triples."""
    if "bare graph" not in c.kept:
        c.kept["bare graph"] = graph.MaterializedGraph.write(_bare(c), c.ontology, "predicate", f"{c.scratch.base}/graph-bare")
    asked = [c.kept["bare graph"].query(graph.rewritten(f"SELECT DISTINCT ?s {{ ?s rdf:type {t} }}", c.ontology)).select("s", F.lit(t).alias("type")) for t in _TYPES]
    return _subjects(reduce(DataFrame.unionByName, asked))


def _grown(c: Context) -> mappings.Store:
    """The relations after every tenth building has grown by a metre."""
    higher = lambda df, key: df.withColumn("height_m", F.when(F.col(key) % 10 == 0, F.col("height_m") + 1).otherwise(F.col("height_m")))
    store = mappings.Store(c.city, c.links, c.ontology)
    changed = {n: replace(s, frame=lambda s=s: higher(s.frame(), "building_id")) for n, s in store.sources.items() if n == "building"}
    return replace(store, extra=changed)


def _refresh(c: Context) -> graph.MaterializedGraph:
    """A written graph, brought up to date by the triples of changed buildings alone; it is the only one written, unless another query has had all triples written."""
    own = graph.MaterializedGraph.write(c.all_triples(), c.ontology, "predicate", f"{c.scratch.base}/graph-refresh-{c.scratch.count}")
    c.scratch.count += 1
    after = graph.VirtualGraph(c.ontology, mappings.catalogue(), _grown(c)).materialize_sources({"building"})
    before = c.virtual.materialize_sources({"building"})
    keys = ["s", "p", "o"]
    gone = c.scratch.keep(before.join(after.select(keys), keys, "left_anti"))
    come = c.scratch.keep(after.join(before.select(keys), keys, "left_anti"))
    free_shuffles(c.spark)
    graph.refresh_written(own, gone, come, c.scratch)
    for kept in (gone, come):
        c.scratch.remove(kept)
    return own


def _refresh_heights(c: Context) -> DataFrame:
    """Heights in the refreshed graph."""
    return _refresh(c).table.where("p = 'cw:height'").select("s", F.col("o_num").alias("height"))


def _refresh_equal(c: Context) -> DataFrame:
    """Triples that a refresh lacks, has beyond what writing all anew gives, and shares with it; the graphs are compared in slices, and the shuffle of one goes before the next."""
    own = _refresh(c)
    total = [0, 0, 0]
    for each in graph.compared(own, graph.VirtualGraph(c.ontology, mappings.catalogue(), _grown(c))):
        found = each.agg(F.sum(F.greatest(F.col("w") - F.col("r"), F.lit(0))).alias("missing"), F.sum(F.greatest(F.col("r") - F.col("w"), F.lit(0))).alias("extra"), F.count_if((F.col("p") == "cw:height") & (F.col("r") == 1) & (F.col("w") == 1)).alias("heights")).first()
        total = [n + (x or 0) for n, x in zip(total, found, strict=True)]
        del each, found
        free_shuffles(c.spark)
    c.scratch.remove(own.path)
    return c.spark.createDataFrame([tuple(total)], "missing long, extra long, heights long")


def _diff(c: Context) -> DataFrame:
    """What changes in the graph when every tenth building grows by a metre."""
    heights = c.triples.where("p = 'cw:height'").select("s", "p", "o")
    tenth = F.col("s").rlike("^cw:b/[0-9]*0$")
    grown = heights.withColumn("o", F.when(tenth, (F.col("o").cast("double") + 1).cast("string")).otherwise(F.col("o")))
    return graph.difference(heights, grown)


GRAPH: dict[str, Callable[[Context], DataFrame]] = {
    "onto_clashes": lambda c: ontology.clashes(c.spark, ontology.load(ontology.vocabulary_spec(with_clashes=True))),
    "onto_closure": lambda c: ontology.closure_with(c.spark, c.ontology, ontology.usage_edges(c.city.table("part")), c.scratch),
    "onto_subtree": lambda c: ontology.subtree_with(c.spark, c.ontology, ontology.usage_edges(c.city.table("part")), c.scratch, "cw:SpatialFeature"),
    "reason_types": _types_saturated,
    "reason_types_chained": _types_chained,
    "reason_types_rewritten": _types_rewritten,
    "assoc_nodes": lambda c: assoc.nodes(c.links.links),
    "assoc_class_nodes": lambda c: assoc.class_nodes(c.city.crowd_classes),
    "assoc_same_as": lambda c: assoc.same_as(c.links.links),
    "kg_triples_per_predicate": lambda c: c.triples.where("p <> 'rdf:type'").groupBy("p").agg(F.count("*").alias("n")),
    "kg_triples_per_predicate_all": lambda c: c.triples.groupBy("p").agg(F.count("*").alias("n")),
    "kg_building_triples": lambda c: c.triples.where("p in ('cw:height', 'cw:roofLabel', 'cw:hasSolid') and s like 'cw:b/%'").select("s", "p", "o"),
    "kg_triples_all": lambda c: c.triples.select("s", "p", "o"),
    "kg_refresh_equal": _refresh_equal,
    "kg_refresh_heights": _refresh_heights,
    "kg_diff": _diff,
    "kg_class_counts": lambda c: c.virtual.query("SELECT ?named (COUNT(?x) AS ?n) { ?x cw:assignsClass ?named ; cw:elementOf ?e } GROUP BY ?named").select(F.replace("named", F.lit("cw:ci/"), F.lit("")).alias("class"), "n"),
}


def _workload() -> dict[str, Callable[[Context], DataFrame]]:
    out: dict[str, Callable[[Context], DataFrame]] = {}
    for key, text in workload.QUERIES.items():
        out[key] = lambda c, k=key, t=text: workload.finished(k, c.virtual.query(t))
        out[f"{key}_naive"] = lambda c, k=key, t=text: workload.finished(k, c.naive.query(t))
        out[f"{key}_sql"] = lambda c, k=key: c.by_hand.query(k)
        for layout in graph.LAYOUTS:
            out[f"{key}_mkg_{layout}"] = lambda c, k=key, t=text, how=layout: workload.finished(k, c.asked(how).query(t))
    out["q10_sql_published"] = lambda c: c.by_hand.published_sql()
    return out


def _over_context(fn: Callable[[Context], DataFrame]) -> Query:
    return lambda spark, sf_dir: fn(context(spark, sf_dir))


def queries() -> dict[str, Query]:
    by_context = LINKER | GEOMETRY | GRAPH | _workload() | init.QUERIES | relational.QUERIES | feeds.QUERIES | measures.QUERIES
    return {k: _over_context(fn) for k, fn in by_context.items()}


def oracle_sql() -> dict[str, str]:
    out = oracles.linker_sql() | oracles.geometry_sql() | oracles.graph_sql() | init.ORACLE | relational.ORACLE | feeds.oracle()
    out |= {k: out[same] for k, same in _SAME.items()}
    for key, sql in oracles.workload_sql().items():
        for suffix in ("", "_naive", "_sql", *(f"_mkg_{x}" for x in graph.LAYOUTS)):
            out[key + suffix] = sql
    out["q10_sql_published"] = oracles.q("select distinct road_id as line_id, surface_id as area_id, r.shape as line, g.shape as shape from road_near join road using (road_id) join road_text r using (road_id) join ground_text g using (surface_id) where class = 'Secondary'")
    return out
