"""The linker against the arrangement's known classes, and its laws."""

import random
from collections import Counter, defaultdict

import pytest
from pyspark.sql import functions as F

from cityweave.operators import linker, spatial
from cityweave.operators.components import components
from cityweave.scratch import Scratch

# Classes in five blocks, by threshold: unit is the crowd polygon, and the surface for 0:1.
TRUTH = {0.3: {"1:1": 10, "1:n": 6, "m:1": 10, "m:n": 2, "1:0": 2, "0:1": 11}, 0.5: {"1:1": 9, "1:n": 6, "m:1": 10, "m:n": 2, "1:0": 3, "0:1": 12}, 0.7: {"1:1": 9, "1:n": 6, "m:1": 10, "1:0": 5, "0:1": 14}}


def test_sweep_is_the_arrangement(city):
    got = defaultdict(dict)
    for r in linker.sweep(city.city.ground, city.city.crowd).collect():
        got[r.t][r.relation] = r.n
    for t, want in TRUTH.items():
        assert {k: v for k, v in got[t].items() if v} == {k: 5 * v for k, v in want.items()}


def test_steps(city):
    rows = {(r.stage, r.relation): r.n for r in linker.summary(city.links).collect()}
    assert rows["match", "0:1"] == 60 and rows["adjacent", "0:1"] == 35 and rows["adjacent", "0:1 adjacent"] == 25
    shares = defaultdict(float)
    for r in linker.summary(city.links).collect():
        shares[r.stage] += r.share
    assert all(s == pytest.approx(100, abs=0.01) for s in shares.values())
    far = linker.adjacent(city.city.ground, city.links.edges, hops=None)
    assert far.select("surface_id").distinct().count() == 30


def test_closed_form_equals_components(spark):
    rng = random.Random(3)
    rows, want = [], {}
    for g in range(300):
        n, m = rng.randint(1, 7), rng.randint(1, 7)
        edges = {(rng.randrange(n), rng.randrange(m)) for _ in range(rng.randint(1, 9))}
        root = {}

        def find(x):
            while root.setdefault(x, x) != x:
                x = root[x]
            return x

        for s, a in edges:
            root[find(("s", s))] = find(("a", a))
        size = defaultdict(set)
        for x in list(root):
            size[find(x)].add(x)
        for s, a in edges:
            kinds = Counter(k for k, _ in size[find(("s", s))])
            want[g * 10 + s, g * 10 + a] = "1:1" if kinds["s"] == kinds["a"] == 1 else "1:n" if kinds["a"] == 1 else "m:1" if kinds["s"] == 1 else "m:n"
            rows.append((g * 10 + s, g * 10 + a, 1.0))
    df = spark.createDataFrame(rows, "surface_id long, area_id long, ratio double")
    got = {(r.surface_id, r.area_id): r.relation for r in linker.relations(df).collect()}
    assert got == want


def test_components(spark):
    rng = random.Random(4)
    edges = [(rng.randrange(300), rng.randrange(300)) for _ in range(180)] + [(1000 + k, 1001 + k) for k in range(60)] + [(2000, 2000 + k) for k in range(1, 50)]
    root = {x: x for e in edges for x in e}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for a, b in edges:
        a, b = find(a), find(b)
        root[max(a, b)] = min(a, b)
    df = spark.createDataFrame(edges, "u long, v long")
    got = {r.node: r.root for r in components(df, Scratch(spark, "test")).collect()}
    assert got == {x: find(x) for x in root if find(x) != x}
    assert components(df.limit(0), Scratch(spark, "test")).count() == 0


def boxes(spark, n, seed, size):
    rng = random.Random(seed)
    rows = []
    for k in range(n):
        x, y = rng.uniform(-100, 100), rng.uniform(-100, 100)
        rows.append((k, x, y, x + rng.uniform(0, size), y + rng.uniform(0, size)))
    df = spark.createDataFrame(rows, "id long, xmin double, ymin double, xmax double, ymax double")
    return df.select("id", F.struct("xmin", "ymin", "xmax", "ymax").alias("bbox"))


@pytest.mark.parametrize("pad,strict", [(0.0, False), (3.0, False), (0.0, True)])
def test_candidates_agree(spark, pad, strict):
    a, b = boxes(spark, 150, 1, 40), boxes(spark, 150, 2, 25)
    pairs = lambda df: sorted((r.a_id, r.b_id) for r in df.collect())
    want = pairs(spatial.candidates_brute(a, b, pad, strict))
    assert want and pairs(spatial.candidates(a, b, 16.0, pad, strict)) == want
    assert pairs(spatial.candidates_adaptive(a, b, 64.0, pad, strict, max_per_cell=5)) == want


def test_grid_join_has_no_nested_loop(city):
    plan = linker.overlaps(city.city.ground, city.city.crowd)._jdf.queryExecution().executedPlan().toString()
    assert "NestedLoop" not in plan and "Cartesian" not in plan and "Python" not in plan


def test_audit_bound(city):
    row = linker.audit(city.links.edges, city.links.edges).first()
    assert (row.drawn, row.right, row.precision, row.recall) == (50, 50, 1.0, 1.0) and 0.92 < row.wilson_low < 0.95


def test_audit_sees_what_the_linker_gets_wrong(city):
    from types import SimpleNamespace

    from cityweave import registry

    edges = city.links.edges.select("surface_id", "area_id")
    n = edges.count()
    audit = lambda found: registry.LINKER["link_audit"](SimpleNamespace(links=SimpleNamespace(edges=found), city=city.city)).first()
    missed = edges.where("surface_id % 2 = 0")
    assert audit(missed).precision == 1 and audit(missed).recall == round(missed.count() / n, 6) < 1
    wrong = edges.withColumn("area_id", F.col("area_id") + 100_000)
    assert audit(wrong).precision == 0 and audit(wrong).recall == 0


def test_other_matcher(city):
    linker.register_matcher("whole", lambda a, b, t: linker.direct_match(a, b, 0.999))
    assert linker.run(city.city, matcher="whole").edges.count() < city.links.edges.count()
