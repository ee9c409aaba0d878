"""The kernel on random shapes: laws that any right kernel keeps."""

import math
import random

import pytest
from pyspark.sql import functions as F

from cityweave.functions import crs, geom, wkt
from cityweave.operators import spatial


def star(rng, x=0.0, y=0.0, size=10.0):
    """A simple polygon, not convex as a rule."""
    n = rng.randint(3, 12)
    turns = sorted(rng.uniform(0, 2 * math.pi) for _ in range(n))
    while min(b - a for a, b in zip(turns, turns[1:] + [turns[0] + 2 * math.pi])) < 0.02 or max(b - a for a, b in zip(turns, turns[1:] + [turns[0] + 2 * math.pi])) > 3:
        turns = sorted(rng.uniform(0, 2 * math.pi) for _ in range(n))
        n = rng.randint(4, 12)
        turns = sorted(rng.uniform(0, 2 * math.pi) for _ in range(n))
    return [(x + size * r * math.cos(t), y + size * r * math.sin(t)) for t in turns for r in [rng.uniform(0.3, 1)]]


def inside(ring, x, y):
    hit = False
    for (x1, y1), (x2, y2) in zip(ring, ring[1:] + ring[:1]):
        if (y1 > y) != (y2 > y) and x < x1 + (y - y1) / (y2 - y1) * (x2 - x1):
            hit = not hit
    return hit


@pytest.fixture(scope="module")
def pairs(spark):
    rng = random.Random(5)
    rows = []
    for k in range(40):
        a, b = star(rng), star(rng, rng.uniform(-8, 8), rng.uniform(-8, 8))
        rows.append((k, [[dict(x=x, y=y) for x, y in a]], [[dict(x=x, y=y) for x, y in b]]))
    return spark.createDataFrame(rows, f"id int, a {geom.RINGS}, b {geom.RINGS}").cache(), rows


def common(a, b):
    return geom.intersection_area(geom.strips(a), geom.strips(b), F.lit(-100.0))


def test_intersection_laws(pairs):
    df, _ = pairs
    a, b = F.col("a"), F.col("b")
    moved = lambda c: F.transform(c, lambda r: F.transform(r, lambda p: geom.point(20 + 0.8 * p["x"] - 0.6 * p["y"], 20 + 0.6 * p["x"] + 0.8 * p["y"])))
    for r in df.select(common(a, b).alias("ab"), common(b, a).alias("ba"), common(a, a).alias("aa"), geom.area(a).alias("area"), geom.area(b).alias("other"), common(moved(a), moved(b)).alias("turned"), common(geom.ccw(a), F.transform(b, F.reverse)).alias("reversed")).collect():
        assert r.ab == pytest.approx(r.ba, abs=1e-6)
        assert r.aa == pytest.approx(r.area, abs=1e-6)
        assert -1e-6 <= r.ab <= min(r.area, r.other) + 1e-6
        assert r.turned == pytest.approx(r.ab, abs=1e-6)
        assert r.reversed == pytest.approx(r.ab, abs=1e-6)


def test_intersection_by_sampling(pairs):
    df, rows = pairs
    got = {r.id: r.ab for r in df.select("id", common(F.col("a"), F.col("b")).alias("ab")).collect()}
    rng = random.Random(1)
    for k, a, b in rows[:8]:
        a, b = ([(p["x"], p["y"]) for p in g[0]] for g in (a, b))
        n = 20_000
        hits = sum(inside(a, x, y) and inside(b, x, y) for x, y in ((rng.uniform(-10, 10), rng.uniform(-10, 10)) for _ in range(n)))
        assert got[k] == pytest.approx(400 * hits / n, abs=6)


def test_hole(spark):
    square = lambda lo, hi: [dict(x=x, y=y) for x, y in ((lo, lo), (hi, lo), (hi, hi), (lo, hi))]
    df = spark.createDataFrame([([square(0.0, 10.0), square(4.0, 6.0)], [square(3.0, 7.0)])], f"a {geom.RINGS}, b {geom.RINGS}")
    a, b = F.col("a"), F.col("b")
    row = df.select(geom.area(a).alias("area"), common(a, b).alias("ab"), geom.contains_point(geom.segments(a), F.lit(5.0), F.lit(5.0)).alias("hole"), geom.contains_point(geom.segments(a), F.lit(2.0), F.lit(5.0)).alias("solid"), geom.is_valid(a).alias("ok"), wkt.polygon_wkt(a, 0).alias("t")).first()
    assert (row.area, row.ab, row.hole, row.solid, row.ok) == (96.0, pytest.approx(12.0), False, True, True)
    assert row.t == "POLYGON ((0 0, 10 0, 10 10, 0 10, 0 0), (4 4, 6 4, 6 6, 4 6, 4 4))"


def test_empty_and_degenerate(spark):
    df = spark.createDataFrame([([],), ([[]],), ([[dict(x=1.0, y=1.0)]],), (None,)], f"a {geom.RINGS}")
    assert [r[0] for r in df.select(geom.area(F.col("a"))).collect()] == [0.0, 0.0, 0.0, None]


def test_distance_and_dwithin(pairs):
    df, _ = pairs
    a, b = geom.segments(F.col("a")), geom.segments(F.col("b"))
    rows = df.select(geom.distance(a, b).alias("d"), geom.intersects(a, b).alias("meet"), *[geom.dwithin(a, b, d).alias(f"w{d}") for d in (0, 2, 5)]).collect()
    for r in rows:
        assert (r.d == 0) == r.meet
        for d in (0, 2, 5):
            assert r[f"w{d}"] == (r.d <= d)


def test_text_and_binary_round_trip(pairs):
    df, _ = pairs
    text = wkt.polygon_wkt(F.col("a"), 9)
    rows = df.select(geom.area(F.col("a")).alias("x"), geom.area(wkt.from_polygon_wkt(text)).alias("y"), geom.area(wkt.from_polygon_wkb(wkt.polygon_wkb(text))).alias("z"), wkt.wkt_area(text).alias("u")).collect()
    for r in rows:
        assert r.x == pytest.approx(r.y, abs=1e-6) == pytest.approx(r.z, abs=1e-6) == pytest.approx(r.u, abs=1e-6)


def test_coordinate_systems_round_trip(spark):
    df = spark.createDataFrame([(x * 137.5, x * 91.25) for x in range(-20, 40)], "x double, y double")
    lon, lat = crs.reproject_xy("x", "y", crs.LOCAL, crs.GEOGRAPHIC)
    there = df.select("x", "y", lon.alias("lon"), lat.alias("lat"))
    x2, y2 = crs.reproject_xy("lon", "lat", crs.GEOGRAPHIC, crs.LOCAL)
    for r in there.select("x", "y", "lon", "lat", x2.alias("x2"), y2.alias("y2")).collect():
        assert math.hypot(r.x - r.x2, r.y - r.y2) < 1e-6
        assert 11 < r.lon < 12 and 48 < r.lat < 49


def test_buffer_area(spark):
    df = spark.createDataFrame([([dict(x=0.0, y=0.0), dict(x=100.0, y=0.0)],)], f"l {geom.LINE}")
    row = df.select(geom.area(F.get(geom.buffer(geom.line_segments(F.col("l")), 20.0, 64), F.lit(0))).alias("a")).first()
    assert row.a == pytest.approx(100 * 40 + math.pi * 400, rel=1e-3)


def test_clip_equals_intersection(pairs):
    df, _ = pairs
    box = F.array(geom.point(-5.0, -5.0), geom.point(5.0, -5.0), geom.point(5.0, 5.0), geom.point(-5.0, 5.0))
    rows = df.select(F.abs(geom.ring_area(geom.clip_convex(F.element_at("a", 1), box))).alias("x"), common(F.col("a"), F.array(box)).alias("y")).collect()
    for r in rows:
        assert r.x == pytest.approx(r.y, abs=1e-6)


def test_units():
    assert geom.to_metres(2, "kilometre") == 2000 and geom.to_metres(1, "degree") == pytest.approx(111319.49, abs=0.01)


def gap(a, b):
    """Least distance of two rings that don't overlap, by their corners and edges."""

    def to_edge(x, y, e):
        (x1, y1), (x2, y2) = e
        t = max(0, min(1, ((x - x1) * (x2 - x1) + (y - y1) * (y2 - y1)) / ((x2 - x1) ** 2 + (y2 - y1) ** 2)))
        return math.hypot(x1 + t * (x2 - x1) - x, y1 + t * (y2 - y1) - y)

    edges = lambda r: list(zip(r, r[1:] + r[:1]))
    return min(min(to_edge(x, y, e) for x, y in p for e in edges(q)) for p, q in ((a, b), (b, a)))


def test_distances_of_all_surfaces(spark, city):
    import __spark_entry__ as entry
    from conftest import SMALL

    rings = {r.surface_id: [(p["x"], p["y"]) for p in r.rings[0]] for r in city.city.ground.collect()}
    ids = sorted(rings)
    want = {(i, j): d for i in ids for j in ids if i != j and (d := gap(rings[i], rings[j])) <= 60}
    got = {(r.surface_id, r.neighbour_id): r.d for r in entry.queries()["geo_distance"](spark, SMALL).collect()}
    assert got.keys() == want.keys() and all(abs(got[k] - want[k]) < 1e-5 for k in want)
    assert any(i // 8 != j // 8 for i, j in want) and any(i // 8 % 5 == 3 for i, _ in want) and any(len(rings[i]) > 4 for i, _ in want)
    rows = entry.queries()["geo_dwithin"](spark, SMALL).collect()
    near = {(r.surface_id, r.neighbour_id) for r in rows}
    assert len(rows) == len(near) and near == {k for k, d in want.items() if d <= 5 + 1e-9}


def test_skewed_layers(spark):
    """One hot cell, one box over a million cells and one between: the same pairs as brute force, without a row for each cell."""
    rng = random.Random(12)
    box = lambda x, y, w, h: {"xmin": x, "ymin": y, "xmax": x + w, "ymax": y + h}
    schema = "id long, bbox struct<xmin:double,ymin:double,xmax:double,ymax:double>"
    side = lambda n: [(k, box(rng.uniform(0, 30), rng.uniform(0, 30), 0.5, 0.5)) for k in range(n)] + [(1000 + k, box(rng.uniform(0, 40_000), rng.uniform(0, 40_000), 10.0, 10.0)) for k in range(100)]
    a, b = side(300), side(250)
    a += [(5000, box(-100.0, -100.0, 40_000.0, 40_000.0)), (5001, box(50.0, 50.0, 3000.0, 10.0))]
    b += [(6000, box(100.0, 100.0, 35_000.0, 20_000.0)), (6001, None)]
    x, y = spark.createDataFrame(a, schema), spark.createDataFrame(b, schema)
    for pad, strict in ((0.0, False), (0.0, True), (25.0, False)):
        want = sorted((r.a_id, r.b_id) for r in spatial.candidates_brute(x, y, pad, strict).collect())
        got = spatial.pairs_by_box(x, y, 32.0, pad, strict, crowded=20)
        assert sorted((r.a_id, r.b_id) for r in got.collect()) == want and len(want) > 100
    assert spatial.pairs_by_box(x.limit(0), y).count() == 0
