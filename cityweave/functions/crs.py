"""Coordinate systems: a local plane in metres, a transverse Mercator zone, and WGS 84.

The local plane is a zone shifted to an origin. Expressions are SQL text of
plain functions, so that any engine with the usual trigonometry can run them.
"""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

# WGS 84 ellipsoid and transverse Mercator scale.
SEMI_MAJOR, FLATTENING, SCALE = 6378137.0, 1 / 298.257223563, 0.9996
FALSE_EASTING = 500000.0

LOCAL, GEOGRAPHIC, ZONE_32 = 0, 4326, 32632

#: Where the local plane's origin lies in zone 32.
ORIGIN = (690000.0, 5334000.0)
MERIDIAN = 9.0

_n = FLATTENING / (2 - FLATTENING)
_radius = SEMI_MAJOR / (1 + _n) * (1 + _n**2 / 4 + _n**4 / 64)
# Series coefficients as functions of the third flattening.
_forward = (_n / 2 - 2 * _n**2 / 3 + 5 * _n**3 / 16 + 41 * _n**4 / 180, 13 * _n**2 / 48 - 3 * _n**3 / 5 + 557 * _n**4 / 1440, 61 * _n**3 / 240 - 103 * _n**4 / 140, 49561 * _n**4 / 161280)
_backward = (_n / 2 - 2 * _n**2 / 3 + 37 * _n**3 / 96 - _n**4 / 360, _n**2 / 48 + _n**3 / 15 - 437 * _n**4 / 1440, 17 * _n**3 / 480 - 37 * _n**4 / 840, 4397 * _n**4 / 161280)
_latitude = (2 * _n - 2 * _n**2 / 3 - 2 * _n**3 + 116 * _n**4 / 45, 7 * _n**2 / 3 - 8 * _n**3 / 5 - 227 * _n**4 / 45, 56 * _n**3 / 15 - 136 * _n**4 / 35, 4279 * _n**4 / 630)
_ecc = 2 * _n**0.5 / (1 + _n)


def _series(terms, first: str, factor) -> str:
    return first + "".join(f" + ({c!r} * {factor(2 * (k + 1))})" for k, c in enumerate(terms))


def zone_to_lon_lat(e: str, n: str) -> tuple[str, str]:
    """SQL text for longitude and latitude in degrees from SQL text of easting and northing."""
    xi, eta = f"(({n}) / {SCALE * _radius!r})", f"((({e}) - {FALSE_EASTING!r}) / {SCALE * _radius!r})"
    xi1 = _series([-c for c in _backward], xi, lambda k: f"sin({k} * {xi}) * cosh({k} * {eta})")
    eta1 = _series([-c for c in _backward], eta, lambda k: f"cos({k} * {xi}) * sinh({k} * {eta})")
    chi = f"asin(sin({xi1}) / cosh({eta1}))"
    first = _series(_latitude, chi, lambda k: f"sin({k} * {chi})")
    # one step of the exact relation brings the series to full precision
    lat = f"asin(tanh(atanh(sin({chi})) + {_ecc!r} * atanh({_ecc!r} * sin({first}))))"
    return f"({MERIDIAN!r} + degrees(atan2(sinh({eta1}), cos({xi1}))))", f"degrees({lat})"


def lon_lat_to_zone(lon: str, lat: str) -> tuple[str, str]:
    phi, lam = f"radians({lat})", f"radians(({lon}) - {MERIDIAN!r})"
    t = f"sinh(atanh(sin({phi})) - {_ecc!r} * atanh({_ecc!r} * sin({phi})))"
    xi, eta = f"atan2({t}, cos({lam}))", f"atanh(sin({lam}) / sqrt(1 + ({t}) * ({t})))"
    e = _series(_forward, eta, lambda k: f"cos({k} * {xi}) * sinh({k} * {eta})")
    n = _series(_forward, xi, lambda k: f"sin({k} * {xi}) * cosh({k} * {eta})")
    return f"({FALSE_EASTING!r} + {SCALE * _radius!r} * ({e}))", f"({SCALE * _radius!r} * ({n}))"


def reproject_sql(x: str, y: str, src: int, dst: int) -> tuple[str, str]:
    """SQL text for a point's coordinates in another system."""
    if src == LOCAL:
        x, y, src = f"(({x}) + {ORIGIN[0]!r})", f"(({y}) + {ORIGIN[1]!r})", ZONE_32
    elif src == GEOGRAPHIC and dst != GEOGRAPHIC:
        (x, y), src = lon_lat_to_zone(x, y), ZONE_32
    if dst == GEOGRAPHIC and src != GEOGRAPHIC:
        x, y = zone_to_lon_lat(x, y)
    elif dst == LOCAL:
        x, y = f"(({x}) - {ORIGIN[0]!r})", f"(({y}) - {ORIGIN[1]!r})"
    return x, y


def reproject_xy(x: str, y: str, src: int, dst: int) -> tuple[Column, Column]:
    """Columns for a point whose coordinates are the columns x and y."""
    return tuple(F.expr(e) for e in reproject_sql(x, y, src, dst))


def reproject(points: str, src: int, dst: int) -> Column:
    """Another system for each point of a line column; reproject rings with one call per ring."""
    x, y = reproject_sql("p.x", "p.y", src, dst)
    return F.expr(f"transform({points}, p -> named_struct('x', {x}, 'y', {y}))")
