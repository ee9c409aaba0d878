"""What runs at size depends on: plans and writes that don't grow with what they needn't hold."""

from dataclasses import replace
from functools import reduce

import pytest
from conftest import SMALL
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cityweave import measures, registry, workload
from cityweave.context import Context, context
from cityweave.functions import geom, wkt
from cityweave.operators import spatial
from cityweave.plans import graph, mappings, ontology
from cityweave.plans.graph import VirtualGraph
from cityweave.sources import city as layers
from cityweave.streaming import feeds


def _below_dealing(df):
    """Parts of a plan that are worked out by the tasks that read a dealt table's file."""
    return [x.split("RelationV2")[0].split("Relation [")[0] for x in df._jdf.queryExecution().optimizedPlan().toString().split("RepartitionByExpression")[1:]]


@pytest.mark.parametrize("key", ["q10_sql_published", "q10_road_impact_total_sql"])
def test_layers_are_dealt_by_rows(spark, city, monkeypatch, key):
    """A layer in one small file is many tasks' work, the filters of its geometry too; the rows stay the same."""
    run = lambda c: {"q10_sql_published": lambda: c.by_hand.published_sql()}.get(key, lambda: c.by_hand.query(key.removesuffix("_sql")))()
    want = sorted(map(repr, run(Context(spark, city.sf_dir)).collect()))
    monkeypatch.setattr(layers, "TASK_ROWS", 64, raising=False)
    own = Context(spark, city.sf_dir)
    assert own.city.ground.rdd.getNumPartitions() == 4
    rows = run(own)
    below = _below_dealing(rows)
    assert below and not any("transform(" in x or "array_min" in x for x in below)
    assert want and sorted(map(repr, rows.collect())) == want


@pytest.mark.parametrize("key", ["q10_road_impact_rows_sql", "q10_sql_published", "q10_road_impact_total_sql"])
def test_road_queries_by_hand_link_nothing(spark, city, key):
    own = Context(spark, city.sf_dir)
    fn = {"q10_sql_published": lambda c: c.by_hand.published_sql()}.get(key, lambda c: c.by_hand.query(key.removesuffix("_sql")))
    rows = fn(own)
    assert "links" not in vars(own)
    assert "Broadcast" not in rows._jdf.queryExecution().sparkPlan().toString()


def test_geometry_is_not_broadcast_by_estimate(spark, city):
    """A layer's file is small, its geometry isn't: only measured sizes count."""
    c = context(spark, city.sf_dir)
    ids = lambda df, k: df.select(df[k].alias("id"), "bbox")
    plan = spatial.candidates(ids(c.city.ground, "surface_id"), ids(c.city.crowd, "area_id"))._jdf.queryExecution().sparkPlan().toString()
    assert "SortMergeJoin" in plan and "Broadcast" not in plan
    assert spark.conf.get("spark.sql.adaptive.autoBroadcastJoinThreshold") not in (None, "-1")


def test_late_count_over_several_files(spark, tmp_path, monkeypatch):
    """The table's own events are never late, in whatever files and order they lie."""
    monkeypatch.setattr(feeds, "STRETCH_ROWS", 300, raising=False)
    spark.read.parquet(f"{SMALL}/events.parquet").repartition(4, "event_id").write.parquet(f"{tmp_path}/events.parquet")
    assert [tuple(r) for r in feeds._late(Context(spark, str(tmp_path))).collect()] == [(50,)]


@pytest.mark.parametrize("key", ["onto_closure", "onto_subtree"])
def test_vocabulary_has_the_tables_classes(spark, city, key):
    """Classes of use come from the table of buildings."""
    df = registry.queries()[key](spark, city.sf_dir)
    named = {r[0] for r in df.select("class" if key == "onto_subtree" else "sub").distinct().collect()}
    assert {f"cw:usage/{r[0]}" for r in city.city.table("part").select("p_type").distinct().collect()} <= named
    assert len({n for n in named if n.count("/") == 2}) > 10 and "cw:HousingBlockA" in named


def test_subtree_follows_new_rows(spark, tmp_path):
    """A part of an unknown type brings its class, at any depth; null and one-word names bring what they can."""
    rows = spark.createDataFrame([(1, "old hut", "LONELY"), (2, "hut", "LONELY"), (3, None, "BARE"), (4, "old hut", None)], "p_partkey long, p_name string, p_type string")
    edges = {tuple(r) for r in ontology.usage_edges(rows).collect()}
    assert edges == {("cw:usage/LONELY", "cw:Building"), ("cw:usage/LONELY/hut", "cw:usage/LONELY"), ("cw:usage/LONELY/old_hut", "cw:usage/LONELY/hut"), ("cw:usage/BARE", "cw:Building")}


def test_triples_made_once_and_unknown_keys_kept(spark, city):
    """Types that a face entails come from the buildings themselves; a face of a building that isn't there still makes it one, once."""
    plain = city.virtual
    walls = spark.createDataFrame([(1, 1, 999999, 1), (1, 2, 999999, 1)], "ord long, line long, building_id long, supp long")
    store = replace(city.store, extra={"wall": replace(city.store.sources["wall"], frame=lambda: walls)})
    store.__dict__.pop("sources", None)
    made = VirtualGraph(plain.ontology, plain.mappings, store).materialize_sources({"wall", "building"})
    assert "LeftAnti" in made._jdf.queryExecution().optimizedPlan().toString()
    found = made.where("s = 'cw:b/999999'").groupBy("p", "o").count().collect()
    assert all(r["count"] == 1 for r in found)
    assert {r["o"] for r in found if r["p"] == "rdf:type"} == {"cw:Building", "cw:SpatialFeature", "cw:Feature"} and sum(r["p"] == "cw:hasFace" for r in found) == 2


#: Queries over written graphs, with the number of parts or kinds of subject that they ask for.
ASKED = {
    "q2_address_exact_mkg_predicate": 3,
    "q2_address_exact_mkg_wide": 2,
    "q3_most_roofs_mkg_wide": 2,
    "q1_tall_addresses_mkg_triples": 3,
    "q2_address_contains_mkg_predicate": 2,
    "q2_address_contains_mkg_triples": 2,
    "q4_tall_roofs_mkg_predicate": 5,
    "q4_tall_roofs_mkg_wide": 3,
    "q10_road_impact_rows_mkg_triples": 15,
    "q5_tall_solids_mkg_wide": 2,
}


@pytest.mark.parametrize("key", ASKED)
def test_graph_is_written_as_asked(spark, city, key):
    """A query has the parts of the graph written that it may match, and links are made only if one of these needs them."""
    own, (name, layout) = Context(spark, city.sf_dir), key.split("_mkg_")
    rows = lambda c, g: sorted(map(repr, workload.finished(name, g.query(workload.QUERIES[name])).collect()))
    got = rows(own, own.asked(layout))
    assert "links" not in vars(own)
    assert len(own.asked(layout).written) == ASKED[key]
    assert got and got == rows(city, city.virtual)


def test_parts_are_the_graph(city):
    """All parts together are all triples, each once."""
    v, keys = city.virtual, ["s", "p", "o", "o_num"]
    assert all(len({(a.target.predicate, a.target.subject.pattern) for a in part}) == 1 for part in v.parts)
    made = [v.part(k).select(*keys, F.lit(k).alias("k")) for k in range(len(v.parts))]
    parts = reduce(DataFrame.unionByName, made).localCheckpoint()
    whole = city.triples.select(keys)
    assert parts.count() == whole.count()
    assert parts.select(keys).exceptAll(whole).isEmpty()


def test_wide_rows_are_made_either_way(spark, city):
    """Rows of subjects straight from a source are those that gathering the triples gives; a key that comes twice is gathered."""
    v = city.virtual
    number = {(a.target.predicate, a.target.subject.pattern, getattr(a.target.object, "iri", None)): k for k, part in enumerate(v.parts) for a in part}
    parts = frozenset({number["cw:label", "cw:crowd/way/{}", None], number["cw:hasGeometry", "cw:crowd/way/{}", None]})
    straight = v.subject_rows("cw:crowd/way/{}", parts)
    gathered = graph._gathered(reduce(DataFrame.unionByName, [v.part(k) for k in parts]), ["cw:hasGeometry", "cw:label"])
    assert straight.columns == gathered.columns and straight.where("size(cw_label) = 0").count() > 0
    assert straight.exceptAll(gathered).isEmpty() and gathered.exceptAll(straight).isEmpty()
    crowd = city.store.sources["crowd"]
    store = replace(city.store, extra={"crowd": replace(crowd, frame=lambda: crowd.frame().unionAll(crowd.frame().where("area_id = 1")))})
    store.__dict__.pop("sources", None)
    twice = VirtualGraph(v.ontology, v.mappings, store)
    assert twice.subject_rows("cw:crowd/way/{}", parts) is None


def test_links_of_given_buildings_keep_their_own(spark, city):
    """A link's building is among the city's; where buildings come from elsewhere, those that only links know stay buildings."""
    store = replace(city.store, extra={"building": replace(city.store.sources["building"], frame=lambda: city.city.buildings.where("building_id < 0"))})
    store.__dict__.pop("sources", None)
    v = VirtualGraph(city.virtual.ontology, city.virtual.mappings, store)
    made = v.materialize_sources({"poi_link", "building"}).where("p = 'rdf:type' and o = 'cw:Building'")
    assert made.count() == city.links.poi_links.select("surface_id").distinct().count() > 0


def test_distances_are_worked_out_once(spark, city):
    """No filter or join repeats the distance of a pair; shapes that don't touch are as far apart as their nearest edges."""
    plan = registry.queries()["geo_distance"](spark, city.sf_dir)._jdf.queryExecution().optimizedPlan().toString()
    assert not [x for x in plan.splitlines() if x.lstrip(" :+-").startswith(("Filter", "Join")) and "exists(" in x]
    shapes = ["POLYGON ((0 0, 4 0, 4 2, 0 2, 0 0))", "POLYGON ((10 5, 12 9, 6 9, 10 5))", "POLYGON ((7 -6, 9 -3, 7 0, 5 -3, 7 -6))"]
    rows = spark.createDataFrame([(s, t) for s in shapes for t in shapes if s != t], "s string, t string")
    a, b = (geom.segments(wkt.from_polygon_wkt(F.col(c))) for c in "st")
    edges = F.array_min(F.flatten(F.transform(a, lambda e: F.transform(b, lambda f: geom.segment_distance(e, f)))))
    assert all(abs(r[0] - r[1]) < 1e-12 and r[0] > 0.5 for r in rows.select(geom.gap(a, b), edges).collect())
    line = geom.line_segments(F.array(geom.point(0, 10), geom.point(0, 6)))
    assert spark.range(1).select(geom.gap(line, geom.segments(F.array(geom.box_ring(*map(F.lit, (0.0, 0.0, 4.0, 2.0))))), a_closed=False)).first()[0] == 4.0


def test_support_writes_what_is_asked(spark, city):
    """The ten queries on all systems need no graph written as a whole, and run to the same rows."""
    own = Context(spark, city.sf_dir)
    done = measures.support(own, simple_features_only=False)
    assert not own._written
    assert len(done) == 40 and {o for _, _, o, _ in done} == {"ok"}
    assert len({(q, n) for _, q, _, n in done}) == 10


def test_solids_are_written_corner_by_corner(spark):
    """The text of a solid is that of its faces, for any ring; a corner's numbers aren't written again for each face."""
    point = "struct<x:double,y:double>"
    ring = lambda *p: [[dict(x=x, y=y) for x, y in p]]
    shapes = [ring((0.0, 0.0), (4.0, -0.0001), (4.0, 2.5)), ring((0.0, 0.0), (12.0, 0.0), (12.0, 4.0), (4.0, 4.0), (4.0, 12.0), (-0.5, 12.0)), ring((1.0, 1.0)), ring((None, 1.0), (2.0, 3.0)), None]
    rows = spark.createDataFrame([(s, h) for s in shapes for h in (31.0, 0.0, None)], f"rings array<array<{point}>>, h double")
    rings, h = F.col("rings"), F.col("h")
    both = rows.select(mappings.FORMS["solid"](rings, h), wkt.polyhedral_wkt(geom.faces(rings, h))).collect()
    assert len({r[0] for r in both}) == 13 and all(r[0] == r[1] for r in both)
    plan = rows.select(mappings.FORMS["solid"](rings, h).alias("t"))._jdf.queryExecution().analyzed().toString()
    assert "format_string" not in plan.split("POLYHEDRALSURFACE")[1]


@pytest.mark.parametrize("key", ["q2_address_contains_mkg_predicate", "q1_tall_addresses_mkg_triples", "q2_address_exact_mkg_wide", "q2_address_contains_mkg_triples"])
def test_what_is_made_distinct_is_not_looked_up(spark, city, key):
    """The pairs of building and address are distinct as they are made: they are read to be written, and not for their keys as well."""
    own, (name, layout), reads = Context(spark, city.sf_dir), key.split("_mkg_"), []
    source = own.store.sources["building_address"]
    own.store.sources["building_address"] = replace(source, frame=lambda: reads.append(1) or source.frame())
    got = own.asked(layout).query(workload.QUERIES[name])
    assert len(reads) == 1
    assert sorted(map(repr, got.collect())) == sorted(map(repr, city.virtual.query(workload.QUERIES[name]).collect()))


@pytest.mark.parametrize("key", ["q10_road_impact_rows_mkg_triples", "q4_tall_roofs_mkg_predicate"])
def test_parts_asked_are_written_in_one_pass(spark, city, key):
    """Parts that share a source are written together, and read back as they are one by one."""
    own, (name, layout) = Context(spark, city.sf_dir), key.split("_mkg_")
    asked = own.asked(layout)
    asked.query(workload.QUERIES[name])
    read = {k: {a.source for a in own.virtual.parts[k]} for k in asked.written}
    assert len({*asked.written.values()}) < len(asked.written)
    assert all(asked.written[k] == asked.written[n] for k in read for n in read if read[k] & read[n])
    for k in asked.written:
        (got,) = asked._part_rows({k})
        want = own.virtual.part(k)
        assert got.exceptAll(want.select(got.columns)).isEmpty() and got.count() == want.count()


def test_keys_are_looked_up_as_bits(spark):
    """Keys that come twice are found, whatever numbers they are; those that bits can't tell are counted."""
    one = lambda *k: graph._no_key_twice(spark.createDataFrame([(x,) for x in k], "a long"), ("a",))
    two = lambda *k: graph._no_key_twice(spark.createDataFrame([*k], "a long, b long, c long"), ("a", "b", "c"))
    assert one(0, 63, 64, -1, 127, 1 << 40) and one(5, None) and one()
    assert not one(-1, 3, -1) and not one(None, 3, None)
    assert two((1, 0, 5), (1, 7, 5), (2, 0, 5), (-1, 0, 5)) and two((1, 8, 5), (2, 0, 5)) and two((1, 1, 5), (1, 1, 6)) and two((1, None, 5), (1, 1, 5))
    assert not two((1, 1, 5), (1, 1, 5)) and not two((1, 9, 5), (1, 9, 5)) and not two((None, 1, 5), (None, 1, 5))


@pytest.mark.parametrize("key", ["q2_address_contains_mkg_predicate", "q2_address_contains_mkg_triples", "q1_tall_addresses_mkg_triples"])
def test_addresses_are_made_distinct_at_once(spark, city, key):
    """The few addresses are not read for their keys before they are written, and one that comes twice is written once."""
    own, (name, layout) = Context(spark, city.sf_dir), key.split("_mkg_")
    address = own.store.sources["address"]
    own.store.sources["address"] = replace(address, frame=lambda: address.frame().unionAll(address.frame()))
    got = own.asked(layout).query(workload.QUERIES[name])
    assert "address" not in own.virtual._unique
    assert sorted(map(repr, got.collect())) == sorted(map(repr, city.virtual.query(workload.QUERIES[name]).collect()))


def test_graphs_are_compared_in_slices(spark, city, monkeypatch, tmp_path):
    """Each triple is in one slice of bounded size; what is missing, repeated or of no known predicate or class is told."""
    monkeypatch.setattr(graph, "COMPARED_ROWS", 8000, raising=False)
    odd = spark.createDataFrame([("cw:b/1", "cw:odd", "x", 1, None, None, None), ("cw:b/1", "rdf:type", "cw:Odd", 0, None, None, None)], graph.TRIPLE)
    again = city.triples.where("s = 'cw:b/3' and p = 'cw:height'")
    gone = city.triples.where("s = 'cw:b/7'").count()
    written = graph.MaterializedGraph.write(city.triples.where("s <> 'cw:b/7'").unionByName(again).unionByName(odd), city.ontology, "predicate", str(tmp_path / "graph"))
    slices = [each.collect() for each in graph.compared(written, city.virtual)]
    rows = [r for each in slices for r in each]
    assert len(slices) > 6 and all(sum(r["r"] for r in each) <= 9000 for each in slices)
    assert len({(r["s"], r["p"], r["o"]) for r in rows}) == len(rows)
    assert (sum(r["r"] for r in rows), sum(r["w"] for r in rows)) == (written.table.count(), city.triples.count())
    wrong = sorted((r["s"], r["p"], r["r"], r["w"]) for r in rows if r["r"] != r["w"])
    assert [x for x in wrong if x[0] != "cw:b/7"] == [("cw:b/1", "cw:odd", 1, 0), ("cw:b/1", "rdf:type", 1, 0), ("cw:b/3", "cw:height", 2, 1)]
    assert len(wrong) == gone + 3 and gone


def test_refresh_writes_the_graph_once(spark, city):
    """The graph that is refreshed is the one that was written, and goes when it has been compared."""
    own = Context(spark, city.sf_dir)
    assert [tuple(r) for r in registry._refresh_equal(own).collect()] == [(0, 0, 200)]
    assert "predicate" not in own._written
    place = spark._jvm.org.apache.hadoop.fs.Path(own.scratch.base)
    assert not [f.getPath().getName() for f in place.getFileSystem(spark._jsc.hadoopConfiguration()).listStatus(place) if f.getPath().getName().startswith("graph-")]


def test_support_writes_each_kind_once(spark, city, monkeypatch):
    """What several queries ask of a kind of subject, or of a source, is written at once and not again for a later query."""
    monkeypatch.setattr(measures, "TEN", {"Q1": ["q1_tall_addresses"], "Q3": ["q3_most_roofs"], "Q5": ["q5_tall_solids"]})
    own = Context(spark, city.sf_dir)
    done = measures.support(own)
    assert len(done) == 12 and len({(q, n) for _, q, _, n in done}) == 3 and {o for _, _, o, _ in done} == {"ok"}
    files = spark._jvm.org.apache.hadoop.fs.Path(own.scratch.base).getFileSystem(spark._jsc.hadoopConfiguration())
    listed = lambda path: [str(f.getPath()) for f in files.listStatus(spark._jvm.org.apache.hadoop.fs.Path(path))]
    kinds = listed(own.asked("wide").path)
    assert len(kinds) > 1 and all(len(listed(k)) == 1 for k in kinds)
    written = own.asked("triples").written
    passes = {written[k] for k in written if any(a.source == "building" for a in own.virtual.parts[k])}
    assert len(passes) == 1


def test_expressiveness_prepares_each_layout_once(spark, city, monkeypatch):
    """The spatial query is answered by all systems, from what was written at once for all queries."""
    monkeypatch.setattr(measures, "TEN", {"Q1": ["q1_tall_addresses"], "Q10": ["q10_road_impact_rows"]})
    own = Context(spark, city.sf_dir)
    rows = measures.QUERIES["m_expressiveness"](own).collect()
    assert [tuple(r) for r in rows] == [(s, 2, 2) for s in ("virtual", *graph.LAYOUTS)]
    for layout in ("triples", "predicate"):
        g = own.asked(layout)
        assert {path.split("/")[-1].split("-")[0] for path in g.written.values()} == {"0"}
