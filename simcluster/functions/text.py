"""Well-known text and GeoJSON of geometries, as Column functions."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column
from pyspark.sql import functions as F

from .geom import GEOM, let

NUMBER = r"[-+]?[0-9]*\.?[0-9]+(?:[eE][-+]?[0-9]+)?"


def _ring(text: Column, role: Column, closed: bool) -> Column:
    """A part from 'x y, x y, ...'."""
    pairs = F.regexp_extract_all(text, F.lit(rf"({NUMBER})\s+({NUMBER})"), F.lit(0))
    xs = F.transform(pairs, lambda p: F.element_at(F.split(p, r"\s+"), 1).cast("double"))
    ys = F.transform(pairs, lambda p: F.element_at(F.split(p, r"\s+"), 2).cast("double"))
    n = F.size(pairs) - (1 if closed else 0)
    cut = (lambda v: F.slice(v, F.lit(1), F.greatest(n, F.lit(0)))) if closed else (lambda v: v)
    return F.struct(role.alias("role"), cut(xs).alias("xs"), cut(ys).alias("ys"))


def from_wkt(text: Column) -> Column:
    """Geometry from POINT, LINESTRING, POLYGON or MULTIPOLYGON text; null for other text."""
    upper = F.upper(F.trim(text))
    body = F.regexp_replace(upper, r"^[A-Z]+\s*", "")
    rings = F.regexp_extract_all(body, F.lit(r"\(\(?[^()]+\)"), F.lit(0))
    # a ring that opens with (( starts a polygon, others are its holes
    parts = F.transform(rings, lambda r: _ring(r, F.when(F.startswith(r, F.lit("((")), "shell").otherwise("hole"), True))
    path = F.array(_ring(body, F.lit("path"), False))
    made = lambda kind, own: F.struct(F.lit(kind).alias("kind"), own.alias("parts")).cast(GEOM)
    return F.when(upper.startswith("POLYGON"), made("polygon", parts)).when(upper.startswith("MULTIPOLYGON"), made("multipolygon", parts)).when(upper.startswith("LINESTRING"), made("linestring", path)).when(upper.startswith("POINT"), made("point", path))


def to_wkt(geom: Column) -> Column:
    point = lambda x, y: F.concat(x.cast("string"), F.lit(" "), y.cast("string"))

    def ring(p: Column) -> Column:
        all_points = F.zip_with(p["xs"], p["ys"], point)
        return F.when(p["role"] == "path", all_points).otherwise(F.concat(all_points, F.slice(all_points, F.lit(1), F.lit(1))))

    wrapped = F.transform(geom["parts"], lambda p: F.struct(p["role"].alias("r"), F.concat(F.lit("("), F.concat_ws(", ", ring(p)), F.lit(")")).alias("t")))
    # shells after the first close the polygon before them
    joined = F.aggregate(wrapped, F.lit(""), lambda acc, p: F.when(acc == "", p["t"]).when(p["r"] == "shell", F.concat(acc, F.lit("), ("), p["t"])).otherwise(F.concat(acc, F.lit(", "), p["t"])))
    return (
        F.when(geom["kind"] == "point", F.concat(F.lit("POINT "), joined))
        .when(geom["kind"] == "linestring", F.concat(F.lit("LINESTRING "), joined))
        .when(geom["kind"] == "polygon", F.concat(F.lit("POLYGON ("), joined, F.lit(")")))
        .otherwise(F.concat(F.lit("MULTIPOLYGON (("), joined, F.lit("))")))
    )


def from_geojson(text: Column) -> Column:
    """Geometry from a GeoJSON geometry object; null for other types."""
    kind = F.get_json_object(text, "$.type")
    at = F.get_json_object(text, "$.coordinates")
    axis = lambda ring, i: F.transform(ring, lambda p: p[i])
    cut = lambda v: F.slice(v, F.lit(1), F.greatest(F.size(v) - 1, F.lit(0)))
    rings = lambda polygon: F.transform(polygon, lambda r, i: F.struct(F.when(i == 0, "shell").otherwise("hole").alias("role"), cut(axis(r, 0)).alias("xs"), cut(axis(r, 1)).alias("ys")))
    path = lambda line: F.array(F.struct(F.lit("path").alias("role"), axis(line, 0).alias("xs"), axis(line, 1).alias("ys")))
    made = lambda name, parts: F.struct(F.lit(name).alias("kind"), parts.alias("parts")).cast(GEOM)
    return (
        F.when(kind == "Polygon", made("polygon", let(F.from_json(at, "array<array<array<double>>>"), rings)))
        .when(kind == "MultiPolygon", made("multipolygon", let(F.from_json(at, "array<array<array<array<double>>>>"), lambda ps: F.flatten(F.transform(ps, rings)))))
        .when(kind == "LineString", made("linestring", let(F.from_json(at, "array<array<double>>"), path)))
        .when(kind == "Point", made("point", let(F.from_json(at, "array<double>"), lambda p: path(F.array(p)))))
    )


def to_geojson(geom: Column) -> Column:
    """GeoJSON of points, linestrings and polygons of one shell."""
    ring = lambda p: F.zip_with(p["xs"], p["ys"], lambda x, y: F.array(x, y))
    closed = lambda p: F.concat(ring(p), F.slice(ring(p), F.lit(1), F.lit(1)))
    name = F.element_at(F.create_map(*[F.lit(x) for x in ("polygon", "Polygon", "linestring", "LineString", "point", "Point")]), geom["kind"])
    first = geom["parts"][0]
    at = F.when(geom["kind"] == "polygon", F.to_json(F.transform(geom["parts"], closed))).when(geom["kind"] == "linestring", F.to_json(ring(first))).otherwise(F.to_json(F.array(first["xs"][0], first["ys"][0])))
    return F.when(name.isNotNull(), F.concat(F.lit('{"type":"'), name, F.lit('","coordinates":'), at, F.lit("}")))


def _fewer(xs: list[float], ys: list[float], tolerance: float) -> list[int]:
    """Places of the vertices that stay: split where a chord is farthest from what it cuts off, while beyond the tolerance."""
    x, y = np.asarray(xs, float), np.asarray(ys, float)
    keep, todo = {0, len(x) - 1}, [(0, len(x) - 1)]
    while todo:
        a, b = todo.pop()
        if b - a < 2:
            continue
        dx, dy = x[b] - x[a], y[b] - y[a]
        px, py = x[a + 1 : b] - x[a], y[a + 1 : b] - y[a]
        far = np.abs(dx * py - dy * px) / np.hypot(dx, dy) if dx or dy else np.hypot(px, py)
        at = int(far.argmax())
        if far[at] > tolerance:
            keep.add(a + 1 + at)
            todo += [(a, a + 1 + at), (a + 1 + at, b)]
    return sorted(keep)


def simplify(geom: Column, tolerance: float) -> Column:
    """The geometry without vertices that lie within the tolerance of what stays; rings keep three at least."""

    @F.pandas_udf("array<array<int>>")
    def stay(parts: pd.Series) -> pd.Series:
        out = []
        for own in parts:
            rows = []
            for p in own if own is not None else ():
                xs, ys, ring = list(p["xs"]), list(p["ys"]), p["role"] != "path"
                if ring and len(xs) > 3:  # closed for the walk; the closing vertex goes again
                    kept = [i for i in _fewer([*xs, xs[0]], [*ys, ys[0]], tolerance) if i < len(xs)]
                    kept = kept if len(kept) >= 3 else list(range(len(xs)))
                else:
                    kept = _fewer(xs, ys, tolerance) if len(xs) > 2 else list(range(len(xs)))
                rows.append(kept)
            out.append(rows)
        return pd.Series(out, dtype="object")

    take = lambda p, i, axis: F.transform(i, lambda k: F.get(p[axis], k)).alias(axis)
    parts = F.zip_with(geom["parts"], stay(geom["parts"]), lambda p, i: F.struct(p["role"].alias("role"), take(p, i, "xs"), take(p, i, "ys")))
    return F.struct(geom["kind"].alias("kind"), parts.alias("parts"))
