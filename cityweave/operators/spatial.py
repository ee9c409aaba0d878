"""Spatial joins by grid cells.

A box goes to each cell it touches; boxes that share a cell are compared. A
pair that shares several cells counts only in the one that holds the lower
left corner of the boxes' common part, so no later distinct is needed. Cells
with more boxes than a bound are split into quarters, down to a depth, and
boxes over very many cells are dealt on coarser grids.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from cityweave.functions import geom
from cityweave.scratch import Scratch

CELL_M = 32.0


def boxes_touch(a: Column, b: Column, pad: float = 0.0) -> Column:
    return (a["xmin"] - pad <= b["xmax"]) & (b["xmin"] <= a["xmax"] + pad) & (a["ymin"] - pad <= b["ymax"]) & (b["ymin"] <= a["ymax"] + pad)


def boxes_overlap(a: Column, b: Column) -> Column:
    """Touching isn't enough: the boxes have an area in common."""
    return (a["xmin"] < b["xmax"]) & (b["xmin"] < a["xmax"]) & (a["ymin"] < b["ymax"]) & (b["ymin"] < a["ymax"])


def _meets(a: Column, b: Column, pad: float, strict: bool) -> Column:
    return boxes_overlap(a, b) if strict else boxes_touch(a, b, pad)


#: Boxes of one cell beyond which it is split; cells along a side of one box beyond which a coarser grid takes it.
CROWDED, WIDE = 10_000, 8


def _cells(box: Column, cell_m: float, pad: float = 0.0) -> Column:
    """A row for each cell of a box; null where there is no box, so that Spark doesn't work out all cells once more to leave such rows out, in the tasks that read the file."""
    return F.explode_outer(geom.cells(box, cell_m, pad))


def _told(condition: Column) -> Column:
    """A condition on boxes from which Spark doesn't infer that each bound is there, which it would work out from the geometry once more, in the tasks that read the file."""
    return F.coalesce(condition, F.lit(False))


def _level(box: Column, cell_m: float, pad: float) -> Column:
    """Doublings of the cell's size that bring a box to at most WIDE cells along its longer side."""
    side = F.greatest(box["xmax"] - box["xmin"], box["ymax"] - box["ymin"]) + 2 * pad
    return F.greatest(F.lit(0), F.ceil(F.log2(side / (WIDE * cell_m)))).cast("int")


def pairs_by_box(a: DataFrame, b: DataFrame, cell_m: float = CELL_M, pad: float = 0.0, strict: bool = False, crowded: int = CROWDED) -> DataFrame:
    """As candidates, whatever the layers look like: crowded cells are split, and large boxes are dealt on coarser grids.

    A pair is found on the grid of its larger box, to which the smaller one is
    dealt too. One pass over the boxes tells which grids there are and whether a
    cell is crowded; on even layers the plan is that of candidates.
    """
    sides = [a.select("bbox", F.lit(pad).alias("pad")), b.select("bbox", F.lit(0.0).alias("pad"))]
    level = _level(F.col("bbox"), cell_m, pad)
    # a handful of rows: powers of two between a cell and the extent of the layers
    levels = [sorted(r[0] for r in s.select(level.alias("k")).where("k is not null").distinct().collect()) for s in sides]
    both = sorted({*levels[0], *levels[1]})
    if len(both) < 2:
        return _split_if_crowded(a, b, cell_m * 2 ** sum(both), pad, strict, crowded)
    out = None
    for k in both:
        own = [s.where(_level(F.col("bbox"), cell_m, pad) == k) for s in (a, b)]
        upto = [s.where(_level(F.col("bbox"), cell_m, pad) <= k) for s in (a, b)]
        # boxes of a of this size against all up to it, then smaller ones of a against those of b
        todo = [(own[0], upto[1])] if k in levels[0] else []
        if k in levels[1] and (smaller := [x for x in levels[0] if x < k]):
            todo.append((a.where(_level(F.col("bbox"), cell_m, pad) <= max(smaller)), own[1]))
        for x, y in todo:
            part = _split_if_crowded(x, y, cell_m * 2**k, pad, strict, crowded)
            out = part if out is None else out.unionByName(part)
    return candidates(a, b, cell_m, pad, strict) if out is None else out


def _split_if_crowded(a: DataFrame, b: DataFrame, cell_m: float, pad: float, strict: bool, crowded: int) -> DataFrame:
    cells = a.select(_cells(F.col("bbox"), cell_m, pad).alias("c")).unionByName(b.select(_cells(F.col("bbox"), cell_m).alias("c")))
    most = cells.where("c is not null").groupBy("c.cx", "c.cy").count().agg(F.max("count")).first()[0] or 0
    return candidates_adaptive(a, b, cell_m, pad, strict, crowded) if most > crowded else candidates(a, b, cell_m, pad, strict)


def candidates(a: DataFrame, b: DataFrame, cell_m: float = CELL_M, pad: float = 0.0, strict: bool = False, broadcast: bool = False) -> DataFrame:
    """Pairs (a_id, b_id, a_box, b_box) whose boxes meet; a and b: (id, bbox).

    pad grows the boxes of a. With strict the boxes need a common area.
    broadcast sends b to all tasks, and is for sides whose size was checked.
    """
    left = a.select(F.col("id").alias("a_id"), F.col("bbox").alias("a_box"), _cells(F.col("bbox"), cell_m, pad).alias("cell"))
    right = b.select(F.col("id").alias("b_id"), F.col("bbox").alias("b_box"), _cells(F.col("bbox"), cell_m).alias("b_cell"))
    pairs = left.join(F.broadcast(right) if broadcast else right, (F.col("cell.cx") == F.col("b_cell.cx")) & (F.col("cell.cy") == F.col("b_cell.cy")))
    x, y = F.greatest(F.col("a_box.xmin") - pad, F.col("b_box.xmin")), F.greatest(F.col("a_box.ymin") - pad, F.col("b_box.ymin"))
    own = (F.floor(x / cell_m) == F.col("cell.cx")) & (F.floor(y / cell_m) == F.col("cell.cy"))
    return pairs.where(_told(_meets(F.col("a_box"), F.col("b_box"), pad, strict) & own)).select("a_id", "b_id", "a_box", "b_box")


#: Boxes of a side that may be sent to all tasks.
BROADCAST_ROWS = 200_000


def candidates_broadcast(a: DataFrame, b: DataFrame, cell_m: float = CELL_M, pad: float = 0.0, strict: bool = False) -> DataFrame:
    """As candidates, with b sent to all tasks if it is small; the shuffled way otherwise."""
    small = b.limit(BROADCAST_ROWS + 1).count() <= BROADCAST_ROWS
    return candidates(a, b, cell_m, pad, strict, broadcast=small)


def candidates_brute(a: DataFrame, b: DataFrame, pad: float = 0.0, strict: bool = False) -> DataFrame:
    """The baseline: every box of a against every box of b. Quadratic, for comparison only."""
    left = a.select(F.col("id").alias("a_id"), F.col("bbox").alias("a_box"))
    right = b.select(F.col("id").alias("b_id"), F.col("bbox").alias("b_box"))
    return left.join(right, _meets(F.col("a_box"), F.col("b_box"), pad, strict)).select("a_id", "b_id", "a_box", "b_box")


def candidates_adaptive(a: DataFrame, b: DataFrame, cell_m: float = CELL_M, pad: float = 0.0, strict: bool = False, max_per_cell: int = 10_000, depth: int = 4) -> DataFrame:
    """As candidates, with crowded cells split.

    A cell with n boxes is divided f x f, f the least power of two (up to
    2**depth) that brings n / f**2 under max_per_cell. The divisions are a table
    of the crowded cells only, joined to both sides.
    """
    both = a.select("bbox", F.lit(pad).alias("pad")).unionByName(b.select("bbox", F.lit(0.0).alias("pad")))
    counted = both.select(F.explode(geom.cells(F.col("bbox"), cell_m, pad)).alias("cell")).groupBy("cell.cx", "cell.cy").count()
    times = F.least(F.lit(depth), F.ceil(F.log2(F.col("count") / max_per_cell) / 2).cast("int"))
    crowded = counted.where(F.col("count") > max_per_cell).select("cx", "cy", F.pow(F.lit(2.0), times).cast("long").alias("f"))

    def deal(df: DataFrame, name: str, grow: float) -> DataFrame:
        base = df.select(F.col("id").alias(f"{name}_id"), F.col("bbox").alias(f"{name}_box"), F.explode(geom.cells(F.col("bbox"), cell_m, grow)).alias("cell")).select(f"{name}_id", f"{name}_box", "cell.cx", "cell.cy")
        split = base.join(crowded, ["cx", "cy"], "left").withColumn("f", F.coalesce("f", F.lit(1).cast("long")))
        box, size = F.col(f"{name}_box"), F.lit(cell_m) / F.col("f")

        def axis(low: Column, high: Column, c: str) -> Column:
            first, last = F.col(c) * F.col("f"), F.col(c) * F.col("f") + F.col("f") - 1
            return F.sequence(F.greatest(F.floor((low - grow) / size), first), F.least(F.floor((high + grow) / size), last))

        fine = F.flatten(F.transform(axis(box["xmin"], box["xmax"], "cx"), lambda x: F.transform(axis(box["ymin"], box["ymax"], "cy"), lambda y: F.struct(x.alias("fx"), y.alias("fy")))))
        return split.select(f"{name}_id", f"{name}_box", "f", F.explode(fine).alias("c")).select(f"{name}_id", f"{name}_box", "f", "c.fx", "c.fy")

    pairs = deal(a, "a", pad).join(deal(b, "b", 0.0), ["f", "fx", "fy"])
    x, y = F.greatest(F.col("a_box.xmin") - pad, F.col("b_box.xmin")), F.greatest(F.col("a_box.ymin") - pad, F.col("b_box.ymin"))
    size = F.lit(cell_m) / F.col("f")
    own = (F.floor(x / size) == F.col("fx")) & (F.floor(y / size) == F.col("fy"))
    return pairs.where(_meets(F.col("a_box"), F.col("b_box"), pad, strict) & own).select("a_id", "b_id", "a_box", "b_box")


def points_in_polygons(points: DataFrame, areas: DataFrame, cell_m: float = CELL_M) -> DataFrame:
    """(point_id, area_id) of points inside polygons; points (point_id, x, y), areas (area_id, rings, bbox)."""
    at = F.struct(F.col("x").alias("xmin"), F.col("y").alias("ymin"), F.col("x").alias("xmax"), F.col("y").alias("ymax"))
    pairs = pairs_by_box(points.select(F.col("point_id").alias("id"), at.alias("bbox")), areas.select(F.col("area_id").alias("id"), "bbox"), cell_m)
    near = pairs.select(F.col("a_id").alias("point_id"), F.col("a_box.xmin").alias("x"), F.col("a_box.ymin").alias("y"), F.col("b_id").alias("area_id"))
    shaped = near.join(areas.select("area_id", geom.segments(F.col("rings")).alias("segs")), "area_id")
    return shaped.where(geom.contains_point(F.col("segs"), F.col("x"), F.col("y"))).select("point_id", "area_id")


def lines_near_polygons(lines: DataFrame, areas: DataFrame, d: float, cell_m: float = CELL_M) -> DataFrame:
    """(line_id, area_id) within distance d; lines (line_id, pts, bbox), areas (area_id, rings, bbox).

    The lines' boxes grow by d, the grid join finds pairs by box, and the exact
    distance decides; no buffer polygon is made.
    """
    pairs = pairs_by_box(lines.select(F.col("line_id").alias("id"), "bbox"), areas.select(F.col("area_id").alias("id"), "bbox"), cell_m, d)
    shaped = pairs.join(lines.select(F.col("line_id").alias("a_id"), geom.line_segments(F.col("pts")).alias("l")), "a_id").join(areas.select(F.col("area_id").alias("b_id"), geom.segments(F.col("rings")).alias("s")), "b_id")
    return shaped.where(geom.dwithin(F.col("l"), F.col("s"), d, a_filled=False)).select(F.col("a_id").alias("line_id"), F.col("b_id").alias("area_id"))


def nearest_lines(points: DataFrame, lines: DataFrame, reach: float, cell_m: float = CELL_M) -> DataFrame:
    """(point_id, line_id, d): the nearest line within reach of each point; the smaller id if two are as near.

    Points look around in growing rings: those that find a line within a ring's
    distance are done, as no line outside is nearer; only the others look further.
    """
    at = F.struct(F.col("x").alias("xmin"), F.col("y").alias("ymin"), F.col("x").alias("xmax"), F.col("y").alias("ymax"))
    left = points.select(F.col("point_id").alias("id"), at.alias("bbox"))
    segments = lines.select(F.col("line_id").alias("b_id"), geom.line_segments(F.col("pts")).alias("l"))
    boxes = lines.select(F.col("line_id").alias("id"), "bbox")
    out, ring, scratch = None, min(cell_m, reach), Scratch(points.sparkSession, "nearest")
    while True:
        pairs = pairs_by_box(left, boxes, max(cell_m, ring), ring)
        d = geom.point_distance(F.col("l"), F.col("a_box.xmin"), F.col("a_box.ymin"))
        found = pairs.join(segments, "b_id").select(F.col("a_id").alias("point_id"), F.struct(F.round(d, 9).alias("d"), F.col("b_id").alias("line_id")).alias("m"))
        best = found.where(F.col("m.d") <= ring).groupBy("point_id").agg(F.min("m").alias("m")).select("point_id", "m.line_id", "m.d")
        if ring >= reach:
            return best if out is None else out.unionByName(best)
        best = scratch.keep(best)
        out = best if out is None else out.unionByName(best)
        left = left.join(best.select(F.col("point_id").alias("id")), "id", "left_anti")
        ring = min(2 * ring, reach)
