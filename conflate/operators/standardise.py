"""Schema standardisation: per-source field mapping to one schema, GeoJSON out and in, provenance."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from conflate.functions import address
from conflate.schema import POI

GEOMETRIES = ("Point", "MultiPoint", "LineString", "MultiLineString", "Polygon", "MultiPolygon")


#: Each source's own field names, by the common name; a list field of the sources in ``JOINED`` is one text.
OWN_FIELDS = {
    "authority_map": {"uid": "OBJECT_ID", "name": "NAME", "address": "ADDRESS_TEXT", "place_type": "LAND_USE", "tags": "REMARKS", "lat": "LAT_WGS84", "lon": "LON_WGS84", "extraction_date": "FETCHED"},
    "authority_registry": {"uid": "reg_no", "name": "entity_name", "address": "reg_street_address", "place_type": "activity", "tags": "notes", "lat": "latitude", "lon": "longitude", "extraction_date": "as_of"},
    "social_places": {"uid": "place_id", "name": "title", "address": "vicinity", "place_type": "categories", "tags": "labels", "lat": "geo_lat", "lon": "geo_lng", "extraction_date": "crawled_on"},
    "commercial_map": {"uid": "poi_ref", "name": "displayName", "address": "addressLine", "place_type": "classification", "tags": "keywords", "lat": "position_lat", "lon": "position_lon", "extraction_date": "retrieved"},
    "open_map": {"uid": "element_id", "name": "tag_name", "address": "tag_addr", "place_type": "tag_kind", "tags": "tag_other", "lat": "node_lat", "lon": "node_lon", "extraction_date": "snapshot"},
}
JOINED = ("authority_map", "authority_registry")


def own_names(df: DataFrame, role: str) -> DataFrame:
    """Rows in the common names, put under a source's own ones (the reverse of ``conform``)."""
    fields = OWN_FIELDS[role]
    if role in JOINED:
        df = df.withColumns({c: F.array_join(c, ";") for c in ("place_type", "tags")})
    return df.drop("src").withColumnsRenamed(fields)


def conform(df: DataFrame, role: str) -> DataFrame:
    """A source's table under the common names, with the source's role; its other columns stay as they are."""
    out = df.withColumnsRenamed({own: common for common, own in OWN_FIELDS[role].items()}).withColumn("src", F.lit(role))
    if role in JOINED:
        out = out.withColumns({c: F.filter(F.split(c, ";"), lambda x: x != "") for c in ("place_type", "tags")})
    return out


def to_poi(df: DataFrame, mapping: dict[str, Column], used: list[str]) -> DataFrame:
    """One source in the common schema.

    ``mapping`` gives expressions for schema fields by name and ``used`` the columns they read; missing fields are
    null, every field is cast with a null for what can't be, and unused columns go to ``extras`` as strings.
    """
    rest = [c for c in df.columns if c not in used]
    extras = F.map_from_arrays(F.array(*map(F.lit, rest)), F.array(*[F.col(c).cast("string") for c in rest])) if rest else F.lit(None)
    out = []
    for f in POI:
        e = mapping.get(f.name, extras if f.name == "extras" else F.lit(None))
        out.append((e.try_cast(f.dataType) if isinstance(f.dataType, T.AtomicType) else e.cast(f.dataType)).alias(f.name))
    return df.select(*out)


def with_provenance(df: DataFrame, source: str, date: str) -> DataFrame:
    return df.withColumns({"source": F.lit(source), "extraction_date": F.coalesce("extraction_date", F.to_date(F.lit(date))), "requires_verification": F.lit(False)})


def standard(raw: DataFrame) -> DataFrame:
    """The place fixture in the common schema."""
    return to_poi(raw, {
        "uid": F.col("uid"), "source": F.col("src"), "rank": F.col("rank"), "geometry": F.struct(F.lit("Point").alias("type"), F.col("lat").alias("lat"), F.col("lon").alias("lon")),
        "bounds": F.col("bounds"), "name": F.col("name"), "address": F.when(F.col("address").isNotNull(), address.parse(F.col("address"))),
        "place_types": F.col("place_type"), "source_types": F.col("place_type"), "tags": F.col("tags"), "extraction_date": F.col("extraction_date"), "requires_verification": F.col("requires_verification"),
    }, ["uid", "src", "rank", "lat", "lon", "bounds", "name", "address", "place_type", "tags", "extraction_date", "requires_verification"])


def to_geojson(df: DataFrame) -> DataFrame:
    """(uid, feature): a GeoJSON point feature; coordinates are longitude, latitude."""
    props = F.struct("uid", "source", "name", "place_types", "tags", F.col("extraction_date").cast("string").alias("extraction_date"), "requires_verification", F.col("address.full").alias("address"))
    geometry = F.struct(F.lit("Point").alias("type"), F.array("geometry.lon", "geometry.lat").alias("coordinates"))
    return df.select("uid", F.to_json(F.struct(F.lit("Feature").alias("type"), geometry.alias("geometry"), props.alias("properties"))).alias("feature"))


def geometry_json(kind: str, points: Column) -> Column:
    """Geometry of any of the six kinds from an array of struct<lat, lon> (a point: its first)."""
    pair = F.transform(points, lambda p: F.array(p["lon"], p["lat"]))
    shape = {"Point": pair[0], "MultiPoint": pair, "LineString": pair, "MultiLineString": F.array(pair), "Polygon": F.array(pair), "MultiPolygon": F.array(F.array(pair))}[kind]
    return F.to_json(F.struct(F.lit(kind).alias("type"), shape.alias("coordinates")))


def from_geojson(df: DataFrame, column: str = "feature") -> DataFrame:
    """Point features back in columns; a broken feature gives nulls."""
    schema = "type string, geometry struct<type:string,coordinates:array<double>>, properties struct<uid:string,source:string,name:string,place_types:array<string>,tags:array<string>,extraction_date:date,requires_verification:boolean,address:string>"
    f = df.select(F.from_json(column, schema).alias("f"))
    return f.select("f.properties.*", F.col("f.geometry.coordinates")[1].alias("lat"), F.col("f.geometry.coordinates")[0].alias("lon"))


#: Nesting of a geometry's coordinates: 0 a position, 1 a list of them, 2 a list of lists, 3 one more.
DEPTH = {"Point": 0, "MultiPoint": 1, "LineString": 1, "MultiLineString": 2, "Polygon": 2, "MultiPolygon": 3}
SHAPE = "array<array<array<struct<lat:double,lon:double>>>>"


def shape_json(kind: str, shape: Column) -> Column:
    """Geometry of any of the six kinds from polygons of rings of points (lines are rings of their own polygon's
    place, holes are further rings)."""
    pair = lambda p: F.array(p["lon"], p["lat"])
    full = F.transform(shape, lambda polygon: F.transform(polygon, lambda ring: F.transform(ring, pair)))
    nested = {0: full[0][0][0], 1: full[0][0], 2: full[0], 3: full}[DEPTH[kind]]
    return F.to_json(F.struct(F.lit(kind).alias("type"), nested.alias("coordinates")))


def read_shape(geometry: Column) -> Column:
    """struct<type, shape> of a GeoJSON geometry of any of the six kinds, the reverse of ``shape_json``; a broken or
    unknown one gives a null shape."""
    head = F.from_json(geometry, "type string, coordinates string")
    position = "array<double>"
    out = F.lit(None).cast(SHAPE)
    point = lambda c: F.struct(c[1].alias("lat"), c[0].alias("lon"))
    ring = lambda r: F.transform(r, point)
    for kind, depth in DEPTH.items():
        read = F.from_json(head["coordinates"], "array<" * depth + position + ">" * depth)
        shape = {0: lambda c: F.array(F.array(F.array(point(c)))), 1: lambda c: F.array(F.array(ring(c))), 2: lambda c: F.array(F.transform(c, ring)), 3: lambda c: F.transform(c, lambda p: F.transform(p, ring))}[depth](read)
        out = F.when((head["type"] == kind) & read.isNotNull(), shape).otherwise(out)
    return F.struct(head["type"].alias("type"), out.alias("shape"))
