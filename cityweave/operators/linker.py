"""Three-step linking of city ground surfaces and crowd polygons.

Step 1 matches by common area over the smaller area; step 2 hands unmatched
surfaces the links of matched neighbours; step 3 takes points of interest to
surfaces through the footprint they lie in.
"""

from __future__ import annotations

from collections.abc import Callable, Iterable
from dataclasses import dataclass
from functools import cached_property

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from cityweave.functions import geom
from cityweave.operators import spatial
from cityweave.operators.components import components
from cityweave.scratch import Scratch
from cityweave.sources.city import City

THRESHOLD = 0.5
#: A ratio this far below the threshold still counts: exact halves come out of rounding on either side.
SLACK = 1e-9


def overlap_ratio(common: Column, area_a: Column, area_b: Column) -> Column:
    """Common area over the smaller of two areas."""
    return common / F.least(area_a, area_b)


def _layer(df: DataFrame, key: str, name: str) -> DataFrame:
    return df.select(F.col(key).alias(f"{name}_id"), F.col("area_m2").alias(f"{name}_area"), geom.strips(F.col("rings")).alias(f"{name}_strips"))


def overlaps(city: DataFrame, crowd: DataFrame, cell_m: float = spatial.CELL_M) -> DataFrame:
    """(surface_id, area_id, ratio) of all pairs with a common area.

    The candidates carry ids and boxes only; strips come back by id for those
    pairs whose boxes meet.
    """
    pairs = spatial.pairs_by_box(city.select(F.col("surface_id").alias("id"), "bbox"), crowd.select(F.col("area_id").alias("id"), "bbox"), cell_m, strict=True)
    shaped = pairs.join(_layer(city, "surface_id", "a"), "a_id").join(_layer(crowd, "area_id", "b"), "b_id")
    common = geom.intersection_area(F.col("a_strips"), F.col("b_strips"), F.least("a_box.ymin", "b_box.ymin"))
    return shaped.select(F.col("a_id").alias("surface_id"), F.col("b_id").alias("area_id"), overlap_ratio(common, F.col("a_area"), F.col("b_area")).alias("ratio")).where(F.col("ratio") > SLACK)


def direct_match(city: DataFrame, crowd: DataFrame, t: float = THRESHOLD) -> DataFrame:
    """(surface_id, area_id, ratio) with ratio of at least t."""
    return overlaps(city, crowd).where(F.col("ratio") >= t - SLACK)


def relations(edges: DataFrame, mode: str = "group") -> DataFrame:
    """edges with `relation` 1:1, 1:n, m:1 or m:n.

    m counts crowd polygons, n city surfaces. In group mode the class is that
    of the connected group; a group is m:n just if it isn't a star, that is, if
    some edge has ends of degree two or more. An edge lies in such a group if
    a heavy edge meets one of its ends: no iteration is needed. In degree mode
    an edge is judged by its own ends.
    """
    by_area, by_surface = Window.partitionBy("area_id"), Window.partitionBy("surface_id")
    degrees = edges.withColumn("n_surfaces", F.count("*").over(by_area)).withColumn("n_areas", F.count("*").over(by_surface))
    heavy = (F.col("n_surfaces") > 1) & (F.col("n_areas") > 1)
    if mode == "group":
        flagged = degrees.withColumn("heavy", heavy)
        flagged = flagged.withColumn("knot", F.max("heavy").over(by_surface)).withColumn("knot", F.col("knot") | F.max("heavy").over(by_area))
    else:
        flagged = degrees.withColumn("knot", heavy)
    kind = F.when(F.col("knot"), "m:n").when(F.col("n_surfaces") > 1, "1:n").when(F.col("n_areas") > 1, "m:1").otherwise("1:1")
    return flagged.withColumn("relation", kind).drop("n_surfaces", "n_areas", "heavy", "knot")


_RANK = {"m:n": 3, "1:n": 2, "m:1": 1, "1:1": 0}


def classify(edges: DataFrame, city: DataFrame, crowd: DataFrame, mode: str = "group") -> DataFrame:
    """(layer, id, relation): every crowd polygon by its class or 1:0, every unmatched surface as 0:1.

    In degree mode a polygon has the weightiest class of its edges.
    """
    rank = F.create_map(*[F.lit(x) for pair in _RANK.items() for x in pair])
    areas = relations(edges, mode).groupBy("area_id").agg(F.max_by("relation", rank[F.col("relation")]).alias("relation"))
    crowd_side = crowd.select("area_id").join(areas, "area_id", "left").select(F.lit("crowd").alias("layer"), F.col("area_id").alias("id"), F.coalesce("relation", F.lit("1:0")).alias("relation"))
    rest = city.select("surface_id").join(edges, "surface_id", "left_anti").select(F.lit("city").alias("layer"), F.col("surface_id").alias("id"), F.lit("0:1").alias("relation"))
    return crowd_side.unionByName(rest)


def groups(edges: DataFrame, scratch: Scratch) -> DataFrame:
    """edges with group_id, the smallest surface of the connected group."""
    # one space of numbers for both layers: surfaces even, areas odd
    links = edges.select((F.col("surface_id") * 2).alias("u"), (F.col("area_id") * 2 + 1).alias("v"))
    nodes = components(links, scratch)
    least = nodes.unionByName(nodes.select(F.col("root").alias("node"), "root")).distinct()
    surface = least.where("node % 2 = 0").groupBy("root").agg((F.min("node") / 2).cast("long").alias("group_id"))
    named = least.where("node % 2 = 0").join(surface, "root").select((F.col("node") / 2).cast("long").alias("surface_id"), "group_id")
    return edges.join(named, "surface_id").select("surface_id", "area_id", "group_id")


def _neighbours(unmatched: DataFrame, matched: DataFrame, rule: str, eps: float, gap: float) -> DataFrame:
    """(surface_id, neighbour_id, shared_m) under one of three rules of adjacency."""
    pad = gap if rule == "gap" else eps
    pairs = spatial.pairs_by_box(unmatched.select(F.col("surface_id").alias("id"), "bbox"), matched.select(F.col("surface_id").alias("id"), "bbox"), spatial.CELL_M, pad)
    segs = lambda df, n: df.select(F.col("surface_id").alias(f"{n}_id"), geom.segments(F.col("rings")).alias(f"{n}_segs"))
    shaped = pairs.join(segs(unmatched, "a"), "a_id").join(segs(matched, "b"), "b_id")
    shared = geom.shared_length(F.col("a_segs"), F.col("b_segs"), eps)
    out = shaped.select(F.col("a_id").alias("surface_id"), F.col("b_id").alias("neighbour_id"), shared.alias("shared_m"), *(["a_segs", "b_segs"] if rule != "edge" else []))
    if rule == "edge":
        return out.where(F.col("shared_m") > eps)
    near = geom.dwithin(F.col("a_segs"), F.col("b_segs"), eps if rule == "touch" else gap)
    return out.where(near).drop("a_segs", "b_segs")


def adjacent(city: DataFrame, edges: DataFrame, rule: str = "edge", eps: float = 1e-6, gap: float = 2.0, hops: int | None = 1, pick: str = "all", scratch: Scratch | None = None) -> DataFrame:
    """(surface_id, area_id, shared_m, hop): links of unmatched surfaces through linked neighbours.

    rule: `edge` (a common stretch of boundary), `touch` (a common point is
    enough) or `gap` (at most `gap` metres apart). hops: how often surfaces
    linked so may hand links on; None until nothing is added. pick `longest`
    keeps for each surface the neighbour with the longest common boundary.
    """
    known = edges.select("surface_id", "area_id").distinct()
    found, hop = None, 0
    while hops is None or hop < hops:
        hop += 1
        open_ = city.join(known, "surface_id", "left_anti").select("surface_id", "bbox", "rings")
        front = known if hop == 1 else found.where(F.col("hop") == hop - 1).select("surface_id", "area_id")
        linked = city.join(front, "surface_id", "left_semi").select("surface_id", "bbox", "rings")
        near = _neighbours(open_, linked, rule, eps, gap)
        if pick == "longest":
            order = Window.partitionBy("surface_id").orderBy(F.desc(F.round("shared_m", 6)), "neighbour_id")
            near = near.withColumn("place", F.row_number().over(order)).where("place = 1").drop("place")
        new = near.join(front.withColumnRenamed("surface_id", "neighbour_id"), "neighbour_id").groupBy("surface_id", "area_id").agg(F.max("shared_m").alias("shared_m")).withColumn("hop", F.lit(hop))
        if hops == 1:
            return new
        scratch = scratch or Scratch(city.sparkSession, "adjacent")
        new = scratch.keep(new)
        found = new if found is None else found.unionByName(new)
        if new.isEmpty():
            break
        known = known.unionByName(new.select("surface_id", "area_id"))
    return found


def poi_match(pois: DataFrame, crowd: DataFrame, links: DataFrame, use: tuple[str, ...] = ("match", "adjacent")) -> DataFrame:
    """(poi_id, surface_id, area_id): points by way of the footprint they lie in and its links."""
    inside = spatial.points_in_polygons(pois.select(F.col("poi_id").alias("point_id"), "x", "y"), crowd)
    chosen = links.where(F.col("kind").isin(*use)).select("surface_id", "area_id").distinct()
    return inside.join(chosen, "area_id").select(F.col("point_id").alias("poi_id"), "surface_id", "area_id")


def poi_match_direct(pois: DataFrame, city: DataFrame) -> DataFrame:
    """The contrast: points that lie in a ground surface itself."""
    inside = spatial.points_in_polygons(pois.select(F.col("poi_id").alias("point_id"), "x", "y"), city.select(F.col("surface_id").alias("area_id"), "rings", "bbox"))
    return inside.select(F.col("point_id").alias("poi_id"), F.col("area_id").alias("surface_id"))


LINK_COLUMNS = ["surface_id", "area_id", "kind", "ratio", "shared_m", "relation"]

_matchers: dict[str, Callable[..., DataFrame]] = {"overlap": direct_match}


def register_matcher(name: str, matcher: Callable[..., DataFrame]) -> None:
    """Another first step: called with (city, crowd, t), gives (surface_id, area_id, ratio)."""
    _matchers[name] = matcher


@dataclass
class LinkResult:
    """What one run of the linker found; the parts are lazy and share their inputs."""

    city: DataFrame
    crowd: DataFrame
    pois: DataFrame
    edges: DataFrame
    adjacent: DataFrame

    @cached_property
    def links(self) -> DataFrame:
        matches = relations(self.edges).select("surface_id", "area_id", F.lit("match").alias("kind"), "ratio", F.lit(None).cast("double").alias("shared_m"), "relation")
        near = self.adjacent.select("surface_id", "area_id", F.lit("adjacent").alias("kind"), F.lit(None).cast("double").alias("ratio"), "shared_m", F.lit(None).cast("string").alias("relation"))
        return matches.unionByName(near)

    @cached_property
    def classes(self) -> DataFrame:
        return classify(self.edges, self.city, self.crowd)

    @cached_property
    def poi_links(self) -> DataFrame:
        return poi_match(self.pois, self.crowd, self.links)


def run(city: City, t: float = THRESHOLD, matcher: str = "overlap", rule: str = "edge", hops: int | None = 1, scratch: Scratch | None = None) -> LinkResult:
    """All three steps. The match edges are written once: every later step reads them."""
    scratch = scratch or Scratch(city.spark, "links")
    edges = scratch.keep(_matchers[matcher](city.ground, city.crowd, t))
    near = scratch.keep(adjacent(city.ground, edges, rule, hops=hops, scratch=scratch))
    return LinkResult(city.ground, city.crowd, city.pois, edges, near)


def _shares(classes: DataFrame) -> DataFrame:
    counted = classes.groupBy("stage", "relation").agg(F.count("*").alias("n"))
    whole = Window.partitionBy("stage")
    return counted.select("stage", "relation", "n", F.round(F.col("n") * 100.0 / F.sum("n").over(whole), 4).alias("share"))


def summary(result: LinkResult) -> DataFrame:
    """(stage, relation, n, share): crowd polygons by class and unmatched surfaces, before and after step 2.

    The unit is the crowd polygon, and the surface for 0:1; one denominator
    serves both stages, so surfaces that step 2 links are shown as adjacent.
    """
    before = result.classes.select(F.lit("match").alias("stage"), "relation", "layer", "id")
    near = result.adjacent.select(F.col("surface_id").alias("id"), F.lit("city").alias("layer")).distinct().withColumn("near", F.lit(True))
    after = result.classes.join(near, ["id", "layer"], "left").select(F.lit("adjacent").alias("stage"), F.when(F.col("near"), "0:1 adjacent").otherwise(F.col("relation")).alias("relation"), "layer", "id")
    return _shares(before.unionByName(after))


def sweep(city: DataFrame, crowd: DataFrame, ts: Iterable[float] = (0.3, 0.4, 0.5, 0.6, 0.7)) -> DataFrame:
    """(t, relation, n): classes at several thresholds from one pass over the overlaps."""
    ts = list(ts)
    steps = F.explode(F.filter(F.array(*[F.lit(t) for t in ts]), lambda t: F.col("ratio") >= t - SLACK)).alias("t")
    edges = overlaps(city, crowd).select("surface_id", "area_id", steps)
    by_area, by_surface = Window.partitionBy("t", "area_id"), Window.partitionBy("t", "surface_id")
    flagged = edges.withColumn("ns", F.count("*").over(by_area)).withColumn("na", F.count("*").over(by_surface)).withColumn("heavy", (F.col("ns") > 1) & (F.col("na") > 1))
    flagged = flagged.withColumn("k1", F.max("heavy").over(by_surface)).withColumn("knot", F.col("k1") | F.max("heavy").over(by_area))
    kind = F.when(F.col("knot"), "m:n").when(F.col("ns") > 1, "1:n").when(F.col("na") > 1, "m:1").otherwise("1:1")
    areas = flagged.select("t", "area_id", kind.alias("relation")).distinct().groupBy("t", "relation").agg(F.count("*").alias("n"))
    every = F.explode(F.array(*[F.lit(t) for t in ts]))
    hit = edges.groupBy("t").agg(F.count_distinct("area_id").alias("areas"), F.count_distinct("surface_id").alias("surfaces"))
    totals = crowd.agg(F.count("*").alias("n_crowd")).join(city.agg(F.count("*").alias("n_city"))).select(every.alias("t"), "n_crowd", "n_city").join(hit, "t", "left")
    alone = totals.select("t", F.expr("inline(array(struct('1:0' as relation, n_crowd - coalesce(areas, 0) as n), struct('0:1' as relation, n_city - coalesce(surfaces, 0) as n)))"))
    return areas.unionByName(alone.select("t", "relation", "n"))


def ablate_steps(result: LinkResult) -> DataFrame:
    """(step, surfaces, areas, pois): what is linked after step 1, after 2 and after 3."""
    match = result.links.where("kind = 'match'")
    none = F.lit(0).cast("long").alias("pois")
    reach = [F.count_distinct("surface_id").alias("surfaces"), F.count_distinct("area_id").alias("areas")]
    first = match.agg(*reach).select(F.lit("1").alias("step"), "surfaces", "areas", none)
    second = result.links.agg(*reach).select(F.lit("1+2").alias("step"), "surfaces", "areas", none)
    pois = result.poi_links.agg(F.count_distinct("poi_id").alias("pois"))
    third = result.links.agg(*reach).join(pois).select(F.lit("1+2+3").alias("step"), "surfaces", "areas", "pois")
    return first.unionByName(second).unionByName(third)


def audit(links: DataFrame, truth: DataFrame, n: int = 50, seed: int = 7) -> DataFrame:
    """One row: correctness of n links drawn by a hash, recall over all of truth, and a Wilson bound.

    links and truth: (surface_id, area_id). The draw is the same for any
    partitioning.
    """
    drawn = links.select("surface_id", "area_id").orderBy(F.xxhash64("surface_id", "area_id", F.lit(seed)), "surface_id", "area_id").limit(n)
    marked = drawn.join(truth.select("surface_id", "area_id").withColumn("true", F.lit(1)), ["surface_id", "area_id"], "left")
    right = marked.agg(F.count("*").alias("drawn"), F.count("true").alias("right"))
    found = truth.join(links.select("surface_id", "area_id").withColumn("hit", F.lit(1)), ["surface_id", "area_id"], "left").agg((F.count("hit") / F.count("*")).alias("recall"))
    p, z = F.col("right") / F.col("drawn"), 1.959963984540054
    bound = (p + z * z / (2 * F.col("drawn")) - z * F.sqrt((p * (1 - p) + z * z / (4 * F.col("drawn"))) / F.col("drawn"))) / (1 + z * z / F.col("drawn"))
    return right.join(found).select("drawn", "right", F.round(p, 6).alias("precision"), F.round("recall", 6).alias("recall"), F.round(bound, 6).alias("wilson_low"))
