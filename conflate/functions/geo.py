"""Distances, cells, boxes and polygons as column expressions."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

EARTH_M = 6371000.0


def haversine(lat1: Column, lon1: Column, lat2: Column, lon2: Column) -> Column:
    """Great-circle metres."""
    a = F.pow(F.sin(F.radians(lat2 - lat1) / 2), F.lit(2.0)) + F.cos(F.radians(lat1)) * F.cos(F.radians(lat2)) * F.pow(F.sin(F.radians(lon2 - lon1) / 2), F.lit(2.0))
    return F.lit(2 * EARTH_M) * F.asin(F.sqrt(F.least(a, F.lit(1.0))))


def planar(lat1: Column, lon1: Column, lat2: Column, lon2: Column) -> Column:
    """Local equirectangular metres: arithmetic but for one cosine."""
    dx = F.radians(lon2 - lon1) * F.cos(F.radians((lat1 + lat2) / 2))
    return F.lit(EARTH_M) * F.sqrt(dx * dx + F.radians(lat2 - lat1) * F.radians(lat2 - lat1))


def band(lat: Column, side_m: float) -> Column:
    """Number of the latitude band of ``side_m`` metres."""
    return F.floor(F.radians(lat) * F.lit(EARTH_M / side_m)).cast("long")


def cell_width(band_no: Column, side_m: float) -> Column:
    """Degrees of longitude that ``side_m`` metres span at the band's poleward edge; cells end short of the poles."""
    edge = F.greatest(F.abs(band_no), F.abs(band_no + 1)) * F.lit(side_m / EARTH_M)
    return F.degrees(F.lit(side_m / EARTH_M) / F.greatest(F.cos(F.least(edge, F.lit(1.55))), F.lit(0.02)))


def point_in_polygon(x: Column, y: Column, polygon: list[tuple[float, float]]) -> Column:
    """Ray casting over the vertices (x, y); a ray to the right crosses an odd number of edges."""
    crossings = F.lit(0)
    for (ax, ay), (bx, by) in zip(polygon, polygon[1:] + polygon[:1]):
        if ay == by:
            continue
        spans = (F.lit(ay) > y) != (F.lit(by) > y)
        right = x < F.lit(bx - ax) * (y - F.lit(ay)) / F.lit(by - ay) + F.lit(ax)
        crossings = crossings + F.when(spans & right, 1).otherwise(0)
    return crossings % 2 == 1


def box_touches_polygon(west: Column, south: Column, east: Column, north: Column, polygon: list[tuple[float, float]]) -> Column:
    """A corner of one lies in the other, or an edge of the polygon crosses the box (Liang-Barsky interval)."""
    touch = point_in_polygon(west, south, polygon)
    for (ax, ay), (bx, by) in zip(polygon, polygon[1:] + polygon[:1]):
        lo, hi, ok = F.lit(0.0), F.lit(1.0), F.lit(True)
        for a, d, low, high in ((ax, bx - ax, west, east), (ay, by - ay, south, north)):
            if d == 0:
                ok = ok & (F.lit(a) >= low) & (F.lit(a) <= high)
            else:
                t1, t2 = (low - F.lit(a)) / F.lit(d), (high - F.lit(a)) / F.lit(d)
                lo, hi = F.greatest(lo, F.least(t1, t2)), F.least(hi, F.greatest(t1, t2))
        touch = touch | (ok & (lo <= hi))
    return touch
