"""Text and binary forms of geometry."""

from __future__ import annotations

import struct

import pandas as pd
from pyspark.sql import Column
from pyspark.sql import functions as F
from pyspark.sql import types as T

from cityweave.functions import geom
from cityweave.functions.geom import LINE, RINGS


def number(v: Column, digits: int = 3) -> Column:
    """Fixed decimals, and no minus sign on zero."""
    return F.format_string(f"%.{digits}f", F.when(F.abs(v) < 0.5 * 10.0**-digits, F.lit(0.0)).otherwise(v))


def _pair(p: Column, digits: int) -> Column:
    return F.concat_ws(" ", number(p["x"], digits), number(p["y"], digits))


def _triple(p: Column, digits: int) -> Column:
    return F.concat_ws(" ", number(p["x"], digits), number(p["y"], digits), number(p["z"], digits))


def _closed(ring: Column) -> Column:
    return F.concat(ring, F.slice(ring, 1, 1))


def _ring(points: Column, form) -> Column:
    return F.concat(F.lit("("), F.array_join(F.transform(_closed(points), form), ", "), F.lit(")"))


def point_wkt(x: Column, y: Column, digits: int = 3) -> Column:
    return F.concat(F.lit("POINT ("), number(x, digits), F.lit(" "), number(y, digits), F.lit(")"))


def line_wkt(points: Column, digits: int = 3) -> Column:
    return F.concat(F.lit("LINESTRING ("), F.array_join(F.transform(points, lambda p: _pair(p, digits)), ", "), F.lit(")"))


def polygon_wkt(rings: Column, digits: int = 3) -> Column:
    return F.concat(F.lit("POLYGON ("), F.array_join(F.transform(rings, lambda r: _ring(r, lambda p: _pair(p, digits))), ", "), F.lit(")"))


def polyhedral_wkt(faces: Column, digits: int = 3) -> Column:
    return F.concat(F.lit("POLYHEDRALSURFACE Z ("), F.array_join(F.transform(faces, lambda f: F.concat(F.lit("("), _ring(f, lambda p: _triple(p, digits)), F.lit(")"))), ", "), F.lit(")"))


def solid_wkt(rings: Column, height: Column, digits: int = 3) -> Column:
    """As polyhedral_wkt of geom.faces: each corner's numbers are written once for all faces that it is of."""
    at = lambda corner, z: F.concat_ws(" ", corner, z)
    face = lambda points: F.concat(F.lit("(("), F.array_join(points, ", "), F.lit("))"))

    def text(x: Column) -> Column:
        c, low, high = x["c"], x["low"], x["high"]
        level = lambda z: F.transform(c, lambda p: at(p, z))
        after = F.concat(F.slice(c, 2, F.greatest(F.size(c), F.lit(1))), F.slice(c, 1, 1))
        sides = F.zip_with(c, after, lambda p, q: face(F.array(at(p, low), at(q, low), at(q, high), at(p, high), at(p, low))))
        walls = F.when(F.size(c) < 2, F.array().cast("array<string>")).otherwise(sides)
        faces = F.concat(F.array(face(_closed(F.reverse(level(low))))), walls, F.array(face(_closed(level(high)))))
        return F.concat(F.lit("POLYHEDRALSURFACE Z ("), F.array_join(faces, ", "), F.lit(")"))

    corners = F.transform(F.element_at(rings, 1), lambda p: _pair(p, digits))
    return geom.let(F.struct(corners.alias("c"), number(F.lit(0.0), digits).alias("low"), number(height.cast("double"), digits).alias("high")), text)


def collection_wkt(parts: Column) -> Column:
    """parts: array of WKT strings."""
    return F.concat(F.lit("GEOMETRYCOLLECTION ("), F.array_join(parts, ", "), F.lit(")"))


def _point(text: Column) -> Column:
    return geom.let(F.split(F.trim(text), r"\s+"), lambda n: F.struct(F.element_at(n, 1).cast("double").alias("x"), F.element_at(n, 2).cast("double").alias("y")))


def from_polygon_wkt(text: Column) -> Column:
    """Rings of POLYGON text without Z; the closing point of a ring goes. Null for other text."""
    body = F.regexp_extract(text, r"^\s*POLYGON\s*\(\((.*)\)\)\s*$", 1)

    def ring(part: Column) -> Column:
        pts = F.transform(F.split(part, r"\s*,\s*"), _point)
        return geom.let(pts, lambda p: F.slice(p, F.lit(1), F.greatest(F.size(p) - 1, F.lit(0))))

    return F.when(body != "", F.transform(F.split(body, r"\)\s*,\s*\("), ring)).cast(RINGS)


def from_line_wkt(text: Column) -> Column:
    body = F.regexp_extract(text, r"^\s*LINESTRING\s*\((.*)\)\s*$", 1)
    return F.when(body != "", F.transform(F.split(body, r"\s*,\s*"), _point)).cast(LINE)


def parse_any(text: str | None) -> list[list[tuple[float, ...]]]:
    """Point lists of any WKT, nesting flattened; [] for null or empty."""
    out: list[list[tuple[float, ...]]] = []
    for part in (text or "").replace(")", "(").split("("):
        numbers = [tuple(map(float, p.split())) for p in part.split(",") if p.strip() and p.strip()[0] in "-+.0123456789"]
        if numbers:
            out.append(numbers)
    return out


@F.pandas_udf(T.DoubleType())
def wkt_area(texts: pd.Series) -> pd.Series:
    """Area of POLYGON text, in Arrow batches: for text that the expression parser doesn't know."""

    def area(text: str | None) -> float | None:
        if text is None:
            return None
        found = []
        for ring in parse_any(text):
            x, y = [p[0] - ring[0][0] for p in ring], [p[1] - ring[0][1] for p in ring]
            found.append(abs(sum(x[k - 1] * y[k] - x[k] * y[k - 1] for k in range(len(ring)))) / 2)
        return 2 * found[0] - sum(found) if found else 0.0

    return texts.map(area)


@F.pandas_udf(T.BinaryType())
def polygon_wkb(texts: pd.Series) -> pd.Series:
    """Little-endian well-known binary of POLYGON text."""

    def encode(text: str | None) -> bytes | None:
        if text is None:
            return None
        rings = parse_any(text)
        out = struct.pack("<BII", 1, 3, len(rings))
        for ring in rings:
            out += struct.pack("<I", len(ring)) + b"".join(struct.pack("<dd", *p[:2]) for p in ring)
        return out

    return texts.map(encode)


@F.pandas_udf(T.ArrayType(T.ArrayType(T.StructType().add("x", "double").add("y", "double"))))
def from_polygon_wkb(blobs: pd.Series) -> pd.Series:
    """Rings of little-endian well-known binary polygons; the closing point of a ring goes."""

    def decode(blob: bytes | None):
        if blob is None:
            return None
        at, rings = 9, []
        for _ in range(struct.unpack_from("<I", blob, 5)[0]):
            n = struct.unpack_from("<I", blob, at)[0]
            at += 4
            pts = [struct.unpack_from("<dd", blob, at + 16 * k) for k in range(n)]
            at += 16 * n
            rings.append([{"x": x, "y": y} for x, y in pts[:-1]])
        return rings

    return blobs.map(decode)
