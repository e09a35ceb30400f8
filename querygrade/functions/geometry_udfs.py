"""Arrow functions over the geometry kernel, and their SQL names."""

from __future__ import annotations

from dataclasses import replace

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import types as T
from pyspark.sql.functions import pandas_udf

from querygrade.functions import geometry as g


def _shape(value):
    if value is None:
        return None
    try:
        return g.parse_wkb(value) if isinstance(value, (bytes, bytearray, memoryview)) else g.parse_text(value)
    except g.Invalid:
        return None


def _each(values: pd.Series, change) -> pd.Series:
    out = []
    for v in values:
        s = _shape(v)
        try:
            out.append(None if s is None else change(s))
        except g.SridMismatch:
            out.append(None)
    return pd.Series(out, dtype=object)


def _pairs(a: pd.Series, b: pd.Series, test) -> pd.Series:
    out = []
    for x, y in zip(a, b, strict=True):
        x, y = _shape(x), _shape(y)
        try:
            out.append(x is not None and y is not None and bool(test(x, y)))
        except g.SridMismatch:
            out.append(False)
    return pd.Series(out)


@pandas_udf(T.StringType())
def canonical_ewkt(text: pd.Series) -> pd.Series:
    """Canonical EWKT in 4326; null where the geometry is invalid or its SRID unknown."""
    return _each(text, lambda s: g.to_ewkt(g.transform(s, 4326)))


def _agree(ref, got, rule: str) -> int:
    x = _shape(ref)
    y = x if ref == got else _shape(got)
    if x is None or y is None:
        return 0
    try:
        a = g.transform(x, 4326)
        if y is x or g.to_ewkt(a) == g.to_ewkt(g.transform(y, 4326)):
            return 1
        if rule == "text":
            return 0
        if rule == "exact":
            return int(g.equals_snapped(x, y, 1e-12))
        return int(g.equals_snapped(x, y) and g.z_close(x, y))
    except g.SridMismatch:
        return 0


def verdict_of(rule: str):
    """Arrow function (ref, got) -> 0/1 by canonical text, then by topology and heights as ``rule`` says."""

    @pandas_udf(T.IntegerType())
    def verdict(ref: pd.Series, got: pd.Series) -> pd.Series:
        return pd.Series([_agree(x, y, rule) for x, y in zip(ref, got, strict=True)], dtype="int32")

    return verdict


@pandas_udf(T.BooleanType())
def equals_snapped(a: pd.Series, b: pd.Series) -> pd.Series:
    return _pairs(a, b, g.equals_snapped)


@pandas_udf(T.BooleanType())
def equals_exact(a: pd.Series, b: pd.Series) -> pd.Series:
    return _pairs(a, b, lambda x, y: g.equals_snapped(x, y, 1e-12))


@pandas_udf(T.BooleanType())
def z_close(a: pd.Series, b: pd.Series) -> pd.Series:
    return _pairs(a, b, g.z_close)


@pandas_udf(T.DoubleType())
def st_area(text: pd.Series) -> pd.Series:
    return _each(text, g.area).astype(float)


@pandas_udf(T.DoubleType())
def st_length(text: pd.Series) -> pd.Series:
    return _each(text, g.length).astype(float)


@pandas_udf(T.DoubleType())
def st_perimeter(text: pd.Series) -> pd.Series:
    return _each(text, g.perimeter).astype(float)


@pandas_udf(T.StringType())
def st_centroid(text: pd.Series) -> pd.Series:
    return _each(text, lambda s: g.to_ewkt(g.Shape("POINT", g.centroid(s) or (), s.srid)))


@pandas_udf(T.IntegerType())
def st_npoints(text: pd.Series) -> pd.Series:
    return _each(text, lambda s: len(g.dump_points(s))).astype("Int32")


@pandas_udf(T.IntegerType())
def st_srid(text: pd.Series) -> pd.Series:
    return _each(text, lambda s: s.srid).astype("Int32")


@pandas_udf(T.StringType())
def st_transform(text: pd.Series, srid: pd.Series) -> pd.Series:
    out = []
    for v, k in zip(text, srid, strict=True):
        s = _shape(v)
        try:
            out.append(None if s is None else g.to_ewkt(g.transform(s, int(k))))
        except g.SridMismatch:
            out.append(None)
    return pd.Series(out, dtype=object)


@pandas_udf(T.BooleanType())
def st_contains(area: pd.Series, point: pd.Series) -> pd.Series:
    return _pairs(area, point, lambda a, p: p.kind == "POINT" and p.coords and g.locate(p.coords, a) == 1)


@pandas_udf(T.BinaryType())
def st_asewkb(text: pd.Series) -> pd.Series:
    return _each(text, g.to_wkb)


@pandas_udf(T.StringType())
def convex_hull_agg(points: pd.Series) -> str:
    """Hull of a group's points (grouped aggregate)."""
    hull = g.convex_hull([p for s in map(_shape, points) if s is not None for p in g.dump_points(s)])
    if len(hull) < 4:
        return g.to_ewkt(g.Shape("MULTIPOINT", tuple(tuple(map(float, p)) for p in hull)))
    return g.to_ewkt(g.Shape("POLYGON", (tuple(tuple(map(float, p)) for p in hull),)))


def _numbers(a: pd.Series, b: pd.Series, measure) -> pd.Series:
    """Numbers of pairs; null for a null, an invalid or an unmeasured geometry, and for two SRIDs."""
    out = []
    for x, y in zip(map(_shape, a), map(_shape, b), strict=True):
        try:
            out.append(None if x is None or y is None else measure(x, y))
        except (g.SridMismatch, g.Invalid):
            out.append(None)
    return pd.Series(out, dtype="Float64")


def _test(measure):
    """Arrow predicate of two geometries; null where either is null, invalid or of another SRID."""

    @pandas_udf(T.BooleanType())
    def holds(a: pd.Series, b: pd.Series) -> pd.Series:
        return _numbers(a, b, lambda x, y: float(measure(x, y))).astype("boolean")

    return holds


@pandas_udf(T.DoubleType())
def st_distance(a: pd.Series, b: pd.Series) -> pd.Series:
    return _numbers(a, b, g.distance)


@pandas_udf(T.DoubleType())
def st_azimuth(a: pd.Series, b: pd.Series) -> pd.Series:
    return _numbers(a, b, lambda x, y: g.azimuth(x, y) if x.kind == y.kind == "POINT" and x.coords and y.coords else None)


@pandas_udf(T.BooleanType())
def st_dwithin(a: pd.Series, b: pd.Series, d: pd.Series) -> pd.Series:
    return _numbers(a, b, g.distance).le(d.astype("Float64"))


@pandas_udf(T.StringType())
def st_geometrytype(text: pd.Series) -> pd.Series:
    return _each(text, lambda s: f"ST_{s.kind}")


@pandas_udf(T.BooleanType())
def st_isvalid_text(text: pd.Series) -> pd.Series:
    """Can the text or the bytes be read as a geometry (rings closed, counts right); null stays null."""
    return pd.Series([None if v is None else _shape(v) is not None for v in text], dtype="boolean")


st_intersects, st_disjoint, st_touches = _test(g.intersects), _test(lambda a, b: not g.intersects(a, b)), _test(g.touches)
bbox_overlaps, bbox_within, bbox_contains = _test(g.bbox_overlaps), _test(g.bbox_within), _test(lambda a, b: g.bbox_within(b, a))
bbox_same = _test(lambda a, b: g.envelope(a) is not None and g.envelope(a) == g.envelope(b))

@pandas_udf(T.StructType([T.StructField(n, T.DoubleType()) for n in ("x1", "y1", "x2", "y2")]))
def envelope_of(text: pd.Series) -> pd.DataFrame:
    boxes = [None if s is None else g.envelope(s) for s in map(_shape, text)]
    return pd.DataFrame([b or (None,) * 4 for b in boxes], columns=["x1", "y1", "x2", "y2"], dtype="Float64")


@pandas_udf(T.StructType([T.StructField("dim", T.IntegerType()), *(T.StructField(n, T.DoubleType()) for n in ("w", "wx", "wy"))]))
def moment_of(text: pd.Series) -> pd.DataFrame:
    """Dimension, weight (area, length or number of points) and weighted centroid of a geometry."""
    out = []
    for s in map(_shape, text):
        at = None if s is None else g.centroid(s)
        if at is None:
            out.append((None, None, None, None))
            continue
        sizes = (len(g.dump_points(s)), g.length(s), g.area(s))
        dim = 2 if sizes[2] else 1 if sizes[1] else 0
        out.append((dim, sizes[dim], sizes[dim] * at[0], sizes[dim] * at[1]))
    return pd.DataFrame(out, columns=["dim", "w", "wx", "wy"], dtype="Float64").astype({"dim": "Int32"})


@pandas_udf(T.StringType())
def st_setsrid(text: pd.Series, srid: pd.Series) -> pd.Series:
    """The same coordinates under another SRID."""
    shapes = map(_shape, text)
    return pd.Series([None if s is None or pd.isna(k) else g.to_ewkt(replace(s, srid=int(k))) for s, k in zip(shapes, srid, strict=True)], dtype=object)


@pandas_udf(T.BooleanType())
def st_issimple(text: pd.Series) -> pd.Series:
    """Do lines neither cross nor touch themselves but at their ends; points differ; areas count as simple."""
    return _each(text, g.is_simple).astype("boolean")


NAMES = {"ST_SetSRID": st_setsrid, "ST_IsSimple": st_issimple, "ST_Distance": st_distance, "ST_Azimuth": st_azimuth, "ST_DWithin": st_dwithin, "ST_GeometryType": st_geometrytype, "ST_Readable": st_isvalid_text, "ST_Intersects": st_intersects, "ST_Disjoint": st_disjoint, "ST_Touches": st_touches, "ST_BBoxOverlaps": bbox_overlaps, "ST_BBoxWithin": bbox_within, "ST_BBoxContains": bbox_contains, "ST_BBoxSame": bbox_same}
NAMES |= {"ST_Area": st_area, "ST_Length": st_length, "ST_Perimeter": st_perimeter, "ST_Centroid": st_centroid, "ST_NPoints": st_npoints, "ST_SRID": st_srid, "ST_Transform": st_transform, "ST_Contains": st_contains, "ST_AsEWKB": st_asewkb, "ST_EqualsSnapped": equals_snapped, "ST_AsEWKT": canonical_ewkt}


def register(spark: SparkSession) -> None:
    for name, function in NAMES.items():
        spark.udf.register(name, function)
