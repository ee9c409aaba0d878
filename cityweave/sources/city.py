"""The two layers of the city over the given tables.

Geometry is a function of keys: blocks of 64 m hold eight buildings and six
footprints in a fixed arrangement of five variants. Attributes come from the
tables' columns.
"""

from __future__ import annotations

from dataclasses import dataclass
from functools import cached_property

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from cityweave.functions import geom

BLOCK_M, BLOCKS_PER_ROW = 64, 50

# Slot boxes x0, y0, x1, y1 common to all variants, then by variant.
COMMON_CITY = {0: (0, 0, 10, 10), 1: (14, 0, 20, 10), 2: (20, 0, 26, 10), 3: (30, 0, 42, 10), 4: (10, 0, 13, 4), 5: (44, 30, 52, 38)}
COMMON_CROWD = {0: (0.5, 0.5, 10.5, 10.5), 1: (14, 1, 26, 11), 2: (30, 0, 36, 10), 3: (36, 0, 42, 10)}
VARIANT_CITY = {
    0: {6: (0, 20, 6, 30), 7: (6, 20, 12, 30)},
    1: {6: (0, 20, 12, 30), 7: (12, 20, 24, 30)},
    2: {6: (0, 20, 10, 30), 7: (16, 20, 26, 30)},
    3: {6: "L", 7: (5, 5, 11, 11)},
    4: {6: (11, 4, 13, 7), 7: (0, 20, 10, 30)},
}
VARIANT_CROWD = {
    0: {4: (0, 20, 12, 30), 5: (20, 40, 28, 48)},
    1: {4: (0, 20, 6, 30), 5: (6, 20, 18, 30)},
    2: {4: (6, 20, 16, 30), 5: (16, 20, 26, 30)},
    3: {4: "L", 5: (6, 6, 12, 12)},
    4: {4: (20, 40, 28, 48), 5: (0, 20, 10, 30)},
}
L_RING = ((0, 0), (12, 0), (12, 4), (4, 4), (4, 12), (0, 12))
# Variant with all its own shapes turned by the angle of the 3-4-5 triangle.
TURNED = 3

ROOF_CODES = {0: (1000, "flat roof"), 1: (2100, "lean-to roof"), 2: (3100, "gable roof"), 3: (3200, "hip roof"), 4: (3400, "mansard roof")}
ROAD_CLASSES = ("Secondary", "Tertiary", "Service", "Unclassified", "Primary", "Footway")
SURFACE_KINDS = {"R": "roof", "A": "wall", "N": "closure"}
RESIDENTIAL = ("HousingBlockA", "HousingBlockB", "HousingBlockC", "DetachedHomeA", "DetachedHomeB")
ROADS_OF_INTEREST = ROAD_CLASSES[:4]


def slot_ring(variant: int, shape) -> list[tuple[float, float]]:
    """Corner points of a slot relative to its block, after turning where that applies."""
    if shape == "L":
        ring = list(L_RING)
    else:
        x0, y0, x1, y1 = shape
        ring = [(x0, y0), (x1, y0), (x1, y1), (x0, y1)]
    return ring


def layout(common: dict, variants: dict) -> dict[tuple[int, int], list[tuple[float, float]]]:
    out = {}
    for v, own in variants.items():
        for slot, shape in (common | own).items():
            ring = slot_ring(v, shape)
            if v == TURNED and slot in own:
                ring = [(20 + 0.8 * x - 0.6 * y, 20 + 0.6 * x + 0.8 * y) for x, y in ring]
            out[v, slot] = [(float(x), float(y)) for x, y in ring]
    return out


CITY_LAYOUT, CROWD_LAYOUT = layout(COMMON_CITY, VARIANT_CITY), layout(COMMON_CROWD, VARIANT_CROWD)


def true_pairs(least: float = 0.5) -> list[tuple[int, int, int, float]]:
    """(variant, city slot, crowd slot, common part of the smaller) of the slots that match, from their boxes before turning."""
    boxes = lambda shape: [(0, 0, 12, 4), (0, 4, 4, 12)] if shape == "L" else [shape]
    size = lambda parts: sum((x1 - x0) * (y1 - y0) for x0, y0, x1, y1 in parts)
    out = []
    for v in VARIANT_CITY:
        for c, p in (COMMON_CITY | VARIANT_CITY[v]).items():
            for w, q in (COMMON_CROWD | VARIANT_CROWD[v]).items():
                if v == TURNED and (c in VARIANT_CITY[v]) != (w in VARIANT_CROWD[v]):
                    continue
                a, b = boxes(p), boxes(q)
                common = sum(max(min(i[2], j[2]) - max(i[0], j[0]), 0) * max(min(i[3], j[3]) - max(i[1], j[1]), 0) for i in a for j in b)
                if (ratio := common / min(size(a), size(b))) >= least - 1e-9:
                    out.append((v, c, w, float(ratio)))
    return out


def _literal(rings: dict, per_block: int) -> str:
    """Rings by variant and slot as one SQL literal."""
    array = lambda parts: f"array({', '.join(parts)})"
    return array(array(array(f"named_struct('x', {x!r}D, 'y', {y!r}D)" for x, y in rings[v, s]) for s in range(per_block)) for v in range(5))


def _ring_column(rings: dict, key: Column, per_block: int) -> Column:
    """Ring of a key by its block's variant and its slot: a literal table, looked up in the row."""
    block = F.floor(key / per_block)
    ring = F.get(F.get(F.expr(_literal(rings, per_block)), (block % 5).cast("int")), (key % per_block).cast("int"))
    ox, oy = block % BLOCKS_PER_ROW * BLOCK_M, F.floor(block / BLOCKS_PER_ROW) * BLOCK_M
    return F.transform(ring, lambda p: F.struct((p["x"] + ox).alias("x"), (p["y"] + oy).alias("y")))


def crowd_leaf(segment: Column, key: Column) -> Column:
    """Class of a footprint: two segments are split further, so that five residential leaves exist."""
    return (
        F.when(segment == "HOUSEHOLD", F.concat(F.lit("HousingBlock"), F.substring(F.lit("ABC"), (key % 3 + 1).cast("int"), F.lit(1))))
        .when(segment == "BUILDING", F.concat(F.lit("DetachedHome"), F.substring(F.lit("AB"), (key % 2 + 1).cast("int"), F.lit(1))))
        .when(segment == "FURNITURE", "Hotel")
        .when(segment == "MACHINERY", "Workshop")
        .otherwise("Garage")
    )


#: Rows that one task makes geometry of.
TASK_ROWS = 1 << 16


def _shape(df: DataFrame) -> DataFrame:
    """Adds what spatial work reads: box, area, edges and strips, made once for a layer."""
    return df.withColumns({"bbox": geom.bbox(F.col("rings")), "area_m2": geom.area(F.col("rings"))})


@dataclass
class City:
    """Relations of the city and the crowd layer over one folder of tables."""

    spark: SparkSession
    sf_dir: str

    def table(self, name: str) -> DataFrame:
        return self.spark.read.parquet(f"{self.sf_dir}/{name}.parquet")

    @cached_property
    def _counted(self) -> dict[str, int]:
        """Rows of the tables that were looked at."""
        return {}

    def dealt(self, name: str, key: str) -> DataFrame:
        """A table with its rows dealt to tasks by their number: its file may be small for the geometry and text that come of it, and be one task's.

        By a hash of the key, so that joins by the key are planned as they would be otherwise.
        """
        df = self.table(name)
        if name not in self._counted:
            self._counted[name] = df.count()
        tasks = -(-self._counted[name] // TASK_ROWS)
        return df.repartition(tasks, F.xxhash64(key)) if tasks > 1 else df

    @cached_property
    def buildings(self) -> DataFrame:
        brand = F.regexp_extract("p_brand", r"(\d+)", 1).cast("int") % 5
        codes = F.array(*[F.lit(ROOF_CODES[k][0]) for k in range(5)])
        labels = F.array(*[F.lit(ROOF_CODES[k][1]) for k in range(5)])
        return self.dealt("part", "p_partkey").select(
            F.col("p_partkey").cast("long").alias("building_id"),
            F.col("p_size").cast("double").alias("height_m"),
            F.get(codes, brand).alias("roof_code"),
            F.get(labels, brand).alias("roof_label"),
            F.col("p_type").alias("usage"),
            (F.floor(F.col("p_size") / 3) + 1).cast("int").alias("storeys"),
        )

    @cached_property
    def ground(self) -> DataFrame:
        """One ground surface for each building; its id is the building's."""
        key = F.col("p_partkey").cast("long")
        base = self.dealt("part", "p_partkey").select(key.alias("surface_id"), key.alias("building_id"), F.col("p_size").cast("double").alias("height_m"), F.array(_ring_column(CITY_LAYOUT, key, 8)).alias("rings"))
        return _shape(base)

    @cached_property
    def truth(self) -> DataFrame:
        """(surface_id, area_id, ratio) that match by the layout of their block, whatever a linker finds."""
        key = lambda table, name, out, per_block, slot: self.table(table).select(F.col(name).cast("long").alias(out), F.floor(F.col(name) / per_block).alias("b"), (F.col(name) % per_block).cast("long").alias(slot))
        pairs = self.spark.createDataFrame(true_pairs(), "v long, c long, w long, ratio double")
        both = key("part", "p_partkey", "surface_id", 8, "c").join(key("customer", "c_custkey", "area_id", 6, "w"), "b")
        return both.withColumn("v", F.col("b") % 5).join(F.broadcast(pairs), ["v", "c", "w"]).select("surface_id", "area_id", "ratio")

    @cached_property
    def faces(self) -> DataFrame:
        """Roof, wall and closure surfaces."""
        kind = F.when(F.col("l_returnflag") == "R", "roof").when(F.col("l_returnflag") == "A", "wall").otherwise("closure")
        keys = [F.col(c).cast("long").alias(a) for c, a in (("l_orderkey", "ord"), ("l_linenumber", "line"), ("l_partkey", "building_id"), ("l_suppkey", "supp"))]
        return self.table("lineitem").select(*keys, kind.alias("kind"))

    @cached_property
    def addresses(self) -> DataFrame:
        s = self.table("supplier").join(F.broadcast(self.table("nation")), F.col("s_nationkey") == F.col("n_nationkey")).join(F.broadcast(self.table("region")), F.col("n_regionkey") == F.col("r_regionkey"))
        label = F.concat_ws(", ", "s_name", "n_name", "r_name")
        return s.select(F.col("s_suppkey").cast("long").alias("address_id"), F.col("s_name").alias("street"), F.col("n_name").alias("city"), F.col("r_name").alias("country"), label.alias("label"))

    @cached_property
    def building_address(self) -> DataFrame:
        first = self.table("lineitem").where("l_linenumber = 1")
        return first.select(F.col("l_partkey").cast("long").alias("building_id"), F.col("l_suppkey").cast("long").alias("address_id")).distinct()

    @cached_property
    def crowd(self) -> DataFrame:
        key = F.col("c_custkey").cast("long")
        base = self.dealt("customer", "c_custkey").select(
            key.alias("area_id"),
            F.when(F.col("c_acctbal") >= 0, F.col("c_name")).alias("label"),
            crowd_leaf(F.col("c_mktsegment"), key).alias("class"),
            F.lit("way").alias("elem_kind"),
            F.array(_ring_column(CROWD_LAYOUT, key, 6)).alias("rings"),
        )
        return _shape(base)

    @cached_property
    def pois(self) -> DataFrame:
        """Points near the corner of the footprint they name; its box comes from the key alone."""
        host = F.col("o_custkey").cast("long")
        corner = geom.bbox(F.array(_ring_column(CROWD_LAYOUT, host, 6)))
        o = F.col("o_orderkey").cast("long")
        return self.dealt("orders", "o_orderkey").select(
            o.alias("poi_id"),
            host.alias("host_hint"),
            F.col("o_orderpriority").alias("class"),
            (corner["xmin"] + (7 * o) % 16 - 1.75).alias("x"),
            (corner["ymin"] + (11 * o) % 16 - 1.75).alias("y"),
        )

    @cached_property
    def roads(self) -> DataFrame:
        k = F.col("s_suppkey").cast("long")
        x, y = (k % 20 * 160).cast("double"), F.floor(k / 20) * 64 - 8.0
        pts = F.array(geom.point(x, y), geom.point(x + 80, y - 4), geom.point(x + 160, y))
        names = F.array(*[F.lit(c) for c in ROAD_CLASSES])
        return self.dealt("supplier", "s_suppkey").select(k.alias("road_id"), F.col("s_name").alias("label"), F.get(names, (F.col("s_nationkey") % 6).cast("int")).alias("class"), pts.alias("pts")).withColumn("bbox", geom.line_bbox(F.col("pts")))

    @cached_property
    def crowd_classes(self) -> DataFrame:
        """Which class an element of the crowd layer has: (elem_kind, elem_id, class)."""
        areas = self.crowd.select("elem_kind", F.col("area_id").alias("elem_id"), "class")
        pois = self.pois.select(F.lit("poi").alias("elem_kind"), F.col("poi_id").alias("elem_id"), F.lit("Poi").alias("class"))
        roads = self.roads.select(F.lit("road").alias("elem_kind"), F.col("road_id").alias("elem_id"), "class")
        return areas.unionByName(pois).unionByName(roads)
