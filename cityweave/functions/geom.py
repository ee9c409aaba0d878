"""Planar geometry as column expressions.

A polygon is an array of rings, outer ring first, each an array of (x, y)
points that closes implicitly; a line is an array of points. Everything here
stays inside the JVM. Work over pairs of edges runs in nested higher-order
functions; what goes into them (segments, strips, boxes) should be columns of
the layer, made once, and not be rebuilt for each pair.
"""

from __future__ import annotations

from collections.abc import Callable
from functools import reduce

from pyspark.sql import Column
from pyspark.sql import functions as F

POINT = "struct<x:double,y:double>"
LINE = f"array<{POINT}>"
RINGS = f"array<{LINE}>"
SEGMENT = "struct<x1:double,y1:double,x2:double,y2:double>"
STRIP = "struct<x1:double,y1:double,x2:double,y2:double,s:double>"
BOX = "struct<xmin:double,ymin:double,xmax:double,ymax:double>"


def let(value: Column, body: Callable[[Column], Column]) -> Column:
    """body(value) with value worked out once."""
    return F.element_at(F.transform(F.array(value), body), 1)


def total(values: Column, of: Callable[[Column], Column] = lambda v: v) -> Column:
    return F.aggregate(values, F.lit(0.0), lambda a, v: a + of(v))


def point(x, y) -> Column:
    return F.struct(F.lit(x).cast("double").alias("x") if not isinstance(x, Column) else x.cast("double").alias("x"), F.lit(y).cast("double").alias("y") if not isinstance(y, Column) else y.cast("double").alias("y"))


def box_ring(x0: Column, y0: Column, x1: Column, y1: Column) -> Column:
    return F.array(point(x0, y0), point(x1, y0), point(x1, y1), point(x0, y1))


def _segment(p: Column, q: Column) -> Column:
    return F.struct(p["x"].alias("x1"), p["y"].alias("y1"), q["x"].alias("x2"), q["y"].alias("y2"))


def line_segments(line: Column) -> Column:
    n = F.size(line)
    return F.when(n < 2, F.array().cast(f"array<{SEGMENT}>")).otherwise(F.zip_with(F.slice(line, 1, F.greatest(n - 1, F.lit(0))), F.slice(line, 2, F.greatest(n - 1, F.lit(0))), _segment))


def ring_segments(ring: Column) -> Column:
    return F.when(F.size(ring) < 2, F.array().cast(f"array<{SEGMENT}>")).otherwise(F.zip_with(ring, F.concat(F.slice(ring, 2, F.greatest(F.size(ring), F.lit(1))), F.slice(ring, 1, 1)), _segment))


def segments(rings: Column) -> Column:
    """All edges of a polygon."""
    return F.flatten(F.transform(rings, ring_segments))


def bbox(rings: Column) -> Column:
    return line_bbox(F.flatten(rings))


def line_bbox(points: Column) -> Column:
    xs, ys = F.transform(points, lambda p: p["x"]), F.transform(points, lambda p: p["y"])
    return F.struct(F.array_min(xs).alias("xmin"), F.array_min(ys).alias("ymin"), F.array_max(xs).alias("xmax"), F.array_max(ys).alias("ymax"))


def ring_area(ring: Column) -> Column:
    """Signed, positive if counter-clockwise; measured from the first point, which keeps digits."""

    def signed(r: Column) -> Column:
        o = F.element_at(r, 1)
        return total(ring_segments(r), lambda e: (e["x1"] - o["x"]) * (e["y2"] - o["y"]) - (e["x2"] - o["x"]) * (e["y1"] - o["y"])) / 2

    return F.when(F.size(ring) > 2, let(ring, signed)).otherwise(F.lit(0.0))


def area(rings: Column) -> Column:
    """Outer ring less holes; null for no geometry at all."""
    return F.when(rings.isNotNull(), _area(rings))


def _area(rings: Column) -> Column:
    return let(F.transform(rings, lambda r: F.abs(ring_area(r))), lambda a: F.when(F.size(a) > 0, 2 * F.element_at(a, 1) - total(a)).otherwise(F.lit(0.0)))


def length(segs: Column) -> Column:
    return total(segs, lambda e: F.hypot(e["x2"] - e["x1"], e["y2"] - e["y1"]))


def centroid(rings: Column) -> Column:
    """Of the outer ring."""

    def of(r: Column) -> Column:
        o = F.element_at(r, 1)

        def weigh(acc: Column, e: Column) -> Column:
            ax, ay, bx, by = e["x1"] - o["x"], e["y1"] - o["y"], e["x2"] - o["x"], e["y2"] - o["y"]
            cross = ax * by - bx * ay
            return F.struct((acc["a"] + cross).alias("a"), (acc["x"] + (ax + bx) * cross).alias("x"), (acc["y"] + (ay + by) * cross).alias("y"))

        start = F.struct(F.lit(0.0).alias("a"), F.lit(0.0).alias("x"), F.lit(0.0).alias("y"))
        return F.aggregate(ring_segments(r), start, weigh, lambda s: F.struct((o["x"] + s["x"] / (3 * s["a"])).alias("x"), (o["y"] + s["y"] / (3 * s["a"])).alias("y")))

    return let(F.element_at(rings, 1), of)


def ccw(rings: Column) -> Column:
    """Outer ring counter-clockwise, holes clockwise."""
    return F.transform(rings, lambda r, i: F.when((ring_area(r) > 0) == (i == 0), r).otherwise(F.reverse(r)))


def _cross(ox, oy, ax, ay, bx, by) -> Column:
    return (ax - ox) * (by - oy) - (ay - oy) * (bx - ox)


def segments_meet(e: Column, f: Column) -> Column:
    """Whether two segments have a point in common."""
    d1 = _cross(f["x1"], f["y1"], f["x2"], f["y2"], e["x1"], e["y1"])
    d2 = _cross(f["x1"], f["y1"], f["x2"], f["y2"], e["x2"], e["y2"])
    d3 = _cross(e["x1"], e["y1"], e["x2"], e["y2"], f["x1"], f["y1"])
    d4 = _cross(e["x1"], e["y1"], e["x2"], e["y2"], f["x2"], f["y2"])
    boxes = (F.greatest(e["x1"], e["x2"]) >= F.least(f["x1"], f["x2"])) & (F.greatest(f["x1"], f["x2"]) >= F.least(e["x1"], e["x2"])) & (F.greatest(e["y1"], e["y2"]) >= F.least(f["y1"], f["y2"])) & (F.greatest(f["y1"], f["y2"]) >= F.least(e["y1"], e["y2"]))
    return boxes & (F.signum(d1) * F.signum(d2) <= 0) & (F.signum(d3) * F.signum(d4) <= 0)


def is_valid(rings: Column) -> Column:
    """Outer ring with an area, and no two edges of a ring that cross (neighbours may share their end)."""

    def simple(r: Column) -> Column:
        def crosses(segs: Column) -> Column:
            n = F.size(segs)
            return F.exists(F.sequence(F.lit(1), n), lambda i: F.exists(F.sequence(F.lit(1), n), lambda j: (j > i + 1) & ~((i == 1) & (j == n)) & segments_meet(F.element_at(segs, i), F.element_at(segs, j))))

        return let(ring_segments(r), lambda s: ~crosses(s))

    return (F.size(rings) > 0) & (F.abs(ring_area(F.element_at(rings, 1))) > 0) & F.forall(rings, simple)


def contains_point(segs: Column, x: Column, y: Column) -> Column:
    """Crossing parity over the edges of a polygon; a hole's edges take part."""
    hits = F.filter(segs, lambda e: ((e["y1"] > y) != (e["y2"] > y)) & (x < e["x1"] + (y - e["y1"]) / (e["y2"] - e["y1"]) * (e["x2"] - e["x1"])))
    return F.size(hits) % 2 == 1


def strips(rings: Column) -> Column:
    """Edges for intersection_area: left to right, with the sign of the strip between edge and axis.

    With the inside on the left of each directed edge, an edge that runs from
    right to left bounds the polygon from above. Vertical edges bound nothing.
    """

    def of(r: Column, i: Column) -> Column:
        turn = F.signum(ring_area(r)) * F.when(i == 0, 1.0).otherwise(-1.0)

        def strip(e: Column, sign: Column) -> Column:
            back = e["x1"] > e["x2"]
            return F.struct(
                F.least(e["x1"], e["x2"]).alias("x1"),
                F.when(back, e["y2"]).otherwise(e["y1"]).alias("y1"),
                F.greatest(e["x1"], e["x2"]).alias("x2"),
                F.when(back, e["y1"]).otherwise(e["y2"]).alias("y2"),
                F.when(back, sign).otherwise(-sign).alias("s"),
            )

        return let(turn, lambda sign: F.transform(F.filter(ring_segments(r), lambda e: e["x1"] != e["x2"]), lambda e: strip(e, sign)))

    return F.flatten(F.transform(rings, of))


def _lower_area(e: Column, f: Column, x0: Column, y0: Column) -> Column:
    """Integral, over the x range of both edges, of the lower one's height above y0."""
    low, high = F.greatest(e["x1"], f["x1"]), F.least(e["x2"], f["x2"])

    def at(g: Column, x: Column) -> Column:
        return g["y1"] - y0 + (x - g["x1"]) * (g["y2"] - g["y1"]) / (g["x2"] - g["x1"])

    ends = F.struct(low.alias("l"), high.alias("h"), at(e, low).alias("el"), at(e, high).alias("eh"), at(f, low).alias("fl"), at(f, high).alias("fh"))

    def integral(v: Column) -> Column:
        left, right, width = v["el"] - v["fl"], v["eh"] - v["fh"], v["h"] - v["l"]
        lower_e, lower_f = width * (v["el"] + v["eh"]) / 2, width * (v["fl"] + v["fh"]) / 2

        def crossed(t: Column) -> Column:
            y = v["el"] + t * (v["eh"] - v["el"])
            first, last = F.least(v["el"], v["fl"]), F.least(v["eh"], v["fh"])
            return width * (t * (first + y) + (1 - t) * (y + last)) / 2

        return F.when((left <= 0) & (right <= 0), lower_e).when((left >= 0) & (right >= 0), lower_f).otherwise(let(left / (left - right), crossed))

    return F.when(low < high, let(ends, integral)).otherwise(F.lit(0.0))


def intersection_area(a: Column, b: Column, base_y: Column) -> Column:
    """Common area of two polygons given as strips; base_y lies below both.

    Each pair of strips adds, with the product of their signs, the area below
    both edges. No clipping takes place, so any simple polygons do, with holes
    or concave.
    """
    return F.aggregate(a, F.lit(0.0), lambda acc, e: acc + F.aggregate(b, F.lit(0.0), lambda inner, f: inner + e["s"] * f["s"] * _lower_area(e, f, F.lit(0.0), base_y)))


def box_overlap(a: Column, b: Column) -> Column:
    """Common area of two boxes."""
    return F.greatest(F.least(a["xmax"], b["xmax"]) - F.greatest(a["xmin"], b["xmin"]), F.lit(0.0)) * F.greatest(F.least(a["ymax"], b["ymax"]) - F.greatest(a["ymin"], b["ymin"]), F.lit(0.0))


def _on_axis(e: Column, f: Column, eps: float) -> Column:
    """Length of the part of f that runs along e."""
    dx, dy = e["x2"] - e["x1"], e["y2"] - e["y1"]
    run = F.hypot(dx, dy)

    def along(n: Column) -> Column:
        t1 = ((f["x1"] - e["x1"]) * dx + (f["y1"] - e["y1"]) * dy) / n
        t2 = ((f["x2"] - e["x1"]) * dx + (f["y2"] - e["y1"]) * dy) / n
        off1 = F.abs((f["x1"] - e["x1"]) * dy - (f["y1"] - e["y1"]) * dx) / n
        off2 = F.abs((f["x2"] - e["x1"]) * dy - (f["y2"] - e["y1"]) * dx) / n
        common = F.least(F.greatest(t1, t2), n) - F.greatest(F.least(t1, t2), F.lit(0.0))
        return F.when((off1 <= eps) & (off2 <= eps), F.greatest(common, F.lit(0.0))).otherwise(F.lit(0.0))

    return F.when(run > 0, let(run, along)).otherwise(F.lit(0.0))


def shared_length(a: Column, b: Column, eps: float = 1e-6) -> Column:
    """Length of common boundary of two polygons given as segments."""
    return total(a, lambda e: total(b, lambda f: _on_axis(e, f, eps)))


def _to_segment(x: Column, y: Column, e: Column) -> Column:
    dx, dy = e["x2"] - e["x1"], e["y2"] - e["y1"]
    norm = dx * dx + dy * dy
    t = F.when(norm > 0, F.least(F.greatest(((x - e["x1"]) * dx + (y - e["y1"]) * dy) / F.when(norm > 0, norm), F.lit(0.0)), F.lit(1.0))).otherwise(F.lit(0.0))
    return let(t, lambda u: F.hypot(x - e["x1"] - u * dx, y - e["y1"] - u * dy))


def segment_distance(e: Column, f: Column) -> Column:
    ends = F.least(_to_segment(e["x1"], e["y1"], f), _to_segment(e["x2"], e["y2"], f), _to_segment(f["x1"], f["y1"], e), _to_segment(f["x2"], f["y2"], e))
    return F.when(segments_meet(e, f), F.lit(0.0)).otherwise(ends)


def boundaries_meet(a: Column, b: Column) -> Column:
    return F.exists(a, lambda e: F.exists(b, lambda f: segments_meet(e, f)))


def _first(segs: Column) -> Column:
    return F.element_at(segs, 1)


def intersects(a: Column, b: Column, a_filled: bool = True, b_filled: bool = True) -> Column:
    """Whether two shapes given as segments have a point in common; filled shapes have an inside."""
    out = boundaries_meet(a, b)
    if a_filled:
        out = out | let(_first(b), lambda p: contains_point(a, p["x1"], p["y1"]))
    if b_filled:
        out = out | let(_first(a), lambda p: contains_point(b, p["x1"], p["y1"]))
    return out


def distance(a: Column, b: Column, a_filled: bool = True, b_filled: bool = True) -> Column:
    return F.when(intersects(a, b, a_filled, b_filled), F.lit(0.0)).otherwise(gap(a, b, a_filled, b_filled))


def gap(a: Column, b: Column, a_closed: bool = True, b_closed: bool = True) -> Column:
    """Distance of shapes, given as segments, that have no point in common: some corner of one is nearest. A closed one's corners are where its segments begin."""

    def corners(segs: Column, closed: bool) -> Column:
        starts = F.transform(segs, lambda e: point(e["x1"], e["y1"]))
        return starts if closed else F.concat(starts, F.transform(segs, lambda e: point(e["x2"], e["y2"])))

    def run(e: Column) -> Column:
        dx, dy = e["x2"] - e["x1"], e["y2"] - e["y1"]
        return F.struct(e["x1"].alias("x"), e["y1"].alias("y"), dx.alias("dx"), dy.alias("dy"), (dx * dx + dy * dy).alias("n"))

    def square(p: Column, r: Column) -> Column:
        x, y = p["x"] - r["x"], p["y"] - r["y"]
        t = F.when(r["n"] > 0, F.least(F.greatest((x * r["dx"] + y * r["dy"]) / F.nullif(r["n"], F.lit(0.0)), F.lit(0.0)), F.lit(1.0))).otherwise(F.lit(0.0))
        return let(t, lambda u: (x - u * r["dx"]) * (x - u * r["dx"]) + (y - u * r["dy"]) * (y - u * r["dy"]))

    def least(points: Column, segs: Column) -> Column:
        return let(F.transform(segs, run), lambda runs: F.array_min(F.transform(points, lambda p: F.array_min(F.transform(runs, lambda r: square(p, r))))))

    return F.sqrt(F.least(least(corners(a, a_closed), b), least(corners(b, b_closed), a)))


def box_gap(a: Column, b: Column) -> Column:
    """Distance of two boxes; 0 if they touch."""
    side = lambda low, high: F.greatest(a[low] - b[high], b[low] - a[high], F.lit(0.0))
    x, y = side("xmin", "xmax"), side("ymin", "ymax")
    return F.sqrt(x * x + y * y)


def point_distance(segs: Column, x: Column, y: Column) -> Column:
    """From a point to a line given as segments."""
    return F.array_min(F.transform(segs, lambda e: _to_segment(x, y, e)))


def dwithin(a: Column, b: Column, d: float | Column, a_filled: bool = True, b_filled: bool = True) -> Column:
    """distance(a, b) <= d, but ready at the first pair of edges that is near enough."""
    near = F.exists(a, lambda e: F.exists(b, lambda f: segment_distance(e, f) <= d))
    return near | intersects(a, b, a_filled, b_filled)


# Metres in a unit.
UNITS = {"metre": 1.0, "kilometre": 1000.0, "degree": 111319.49079327357}


def to_metres(d: float, unit: str) -> float:
    return d * UNITS[unit]


def capsule(e: Column, d: float | Column, quad: int = 8) -> Column:
    """The points within d of a segment, as a polygon with `quad` edges to a quarter circle."""
    heading = F.atan2(e["y2"] - e["y1"], e["x2"] - e["x1"])
    steps = F.sequence(F.lit(0), F.lit(2 * quad))

    def arc(x: Column, y: Column, start: Column) -> Column:
        return F.transform(steps, lambda k: point(x + d * F.cos(start + k * F.pi() / (2 * quad)), y + d * F.sin(start + k * F.pi() / (2 * quad))))

    return F.array(let(heading, lambda h: F.concat(arc(e["x2"], e["y2"], h - F.pi() / 2), arc(e["x1"], e["y1"], h + F.pi() / 2))))


def buffer(segs: Column, d: float | Column, quad: int = 8) -> Column:
    """A line's buffer as the polygons whose union it is, one for each segment."""
    return F.transform(segs, lambda e: capsule(e, d, quad))


# Solids: footprint and height.
def volume(footprint_area: Column, height: Column) -> Column:
    return footprint_area * height


def face_count(rings: Column) -> Column:
    """Floor, roof and one wall for each edge."""
    return (F.aggregate(rings, F.lit(0), lambda a, r: a + F.size(r)) + 2).cast("long")


def faces(rings: Column, height: Column) -> Column:
    """Faces of an extruded footprint (outer ring): arrays of (x, y, z)."""

    def at(p: Column, z: Column) -> Column:
        return F.struct(p["x"].alias("x"), p["y"].alias("y"), z.cast("double").alias("z"))

    outer = F.element_at(rings, 1)
    floor = F.reverse(F.transform(outer, lambda p: at(p, F.lit(0.0))))
    roof = F.transform(outer, lambda p: at(p, height))

    def wall(e: Column) -> Column:
        corner = lambda x, y, z: F.struct(x.alias("x"), y.alias("y"), z.cast("double").alias("z"))
        return F.array(corner(e["x1"], e["y1"], F.lit(0.0)), corner(e["x2"], e["y2"], F.lit(0.0)), corner(e["x2"], e["y2"], height), corner(e["x1"], e["y1"], height))

    return F.concat(F.array(floor), F.transform(ring_segments(outer), wall), F.array(roof))


def drop_z(face: Column) -> Column:
    """Ground projection of a ring of a solid."""
    return F.transform(face, lambda p: F.struct(p["x"].alias("x"), p["y"].alias("y")))


def members(collection: Column) -> Column:
    """Parts of a collection or multi-part geometry that aren't empty."""
    return F.filter(collection, lambda g: F.size(g) > 0)


# Grid cells.
def cells(box: Column, size: float, pad: float = 0.0) -> Column:
    """Grid cells that a box (grown by pad) touches, as (cx, cy)."""

    def axis(low: Column, high: Column) -> Column:
        return F.sequence(F.floor((low - pad) / size), F.floor((high + pad) / size))

    return F.flatten(F.transform(axis(box["xmin"], box["xmax"]), lambda x: F.transform(axis(box["ymin"], box["ymax"]), lambda y: F.struct(x.alias("cx"), y.alias("cy")))))


def _spread(v: Column) -> Column:
    """The low 16 bits of v at every other bit."""
    steps = [(8, 0x00FF00FF), (4, 0x0F0F0F0F), (2, 0x33333333), (1, 0x55555555)]
    return reduce(lambda x, s: x.bitwiseOR(F.shiftleft(x, s[0])).bitwiseAND(F.lit(s[1]).cast("long")), steps, v.cast("long").bitwiseAND(F.lit(0xFFFF).cast("long")))


def morton(ix: Column, iy: Column) -> Column:
    """Bits of two 16-bit cell numbers, interleaved."""
    return _spread(ix).bitwiseOR(F.shiftleft(_spread(iy), 1))


def clip_convex(subject: Column, clip: Column) -> Column:
    """Ring that is left of `subject` inside the convex counter-clockwise ring `clip`."""

    def inside(p: Column, e: Column) -> Column:
        return _cross(e["x1"], e["y1"], e["x2"], e["y2"], p["x"], p["y"]) >= 0

    def cut(s: Column, e: Column) -> Column:
        a, b = F.struct(s["x1"].alias("x"), s["y1"].alias("y")), F.struct(s["x2"].alias("x"), s["y2"].alias("y"))
        da = _cross(e["x1"], e["y1"], e["x2"], e["y2"], s["x1"], s["y1"])
        db = _cross(e["x1"], e["y1"], e["x2"], e["y2"], s["x2"], s["y2"])
        t = da / F.when(da != db, da - db)
        through = F.struct((s["x1"] + t * (s["x2"] - s["x1"])).alias("x"), (s["y1"] + t * (s["y2"] - s["y1"])).alias("y"))
        return F.when(inside(b, e), F.when(inside(a, e), F.array(b)).otherwise(F.array(through, b))).otherwise(F.when(inside(a, e), F.array(through)).otherwise(F.array().cast(LINE)))

    return F.aggregate(ring_segments(clip), subject.cast(LINE), lambda ring, e: F.flatten(F.transform(ring_segments(ring), lambda s: cut(s, e))).cast(LINE))
