"""Planar geometry as Column functions.

A geometry is a struct of its kind and its parts; a part is a role (shell, hole or path) with the coordinates
of its vertices, the closing vertex left out. All functions are built-in expressions; higher-order functions
run once per geometry, in frames that keep the resulting scalars.
"""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

PART = "struct<role:string,xs:array<double>,ys:array<double>>"
GEOM = f"struct<kind:string,parts:array<{PART}>>"
KINDS = ("polygon", "linestring", "multipolygon", "point")
EPS = 1e-9


def geometry(kind: Column, xs: Column, ys: Column) -> Column:
    """A geometry of a single part."""
    role = F.when(kind.isin("polygon", "multipolygon"), "shell").otherwise("path")
    return F.struct(kind.alias("kind"), F.array(F.struct(role.alias("role"), xs.alias("xs"), ys.alias("ys"))).alias("parts"))


def let(value: Column, body) -> Column:
    """body of a value that is evaluated once."""
    return F.element_at(F.transform(F.array(value), body), 1)


def _next(values: Column) -> Column:
    """The values turned by one, so that each vertex meets the one after it."""
    return F.concat(F.slice(values, F.lit(2), F.size(values)), F.slice(values, F.lit(1), F.lit(1)))


def _sum(values: Column) -> Column:
    return F.aggregate(values, F.lit(0.0), lambda acc, x: acc + x)


def edges(part: Column) -> Column:
    """array<struct<x1,y1,x2,y2>> of a part; paths have no closing edge."""
    ring = F.zip_with(
        F.zip_with(part["xs"], part["ys"], lambda x, y: F.struct(x.alias("x"), y.alias("y"))),
        F.zip_with(_next(part["xs"]), _next(part["ys"]), lambda x, y: F.struct(x.alias("x"), y.alias("y"))),
        lambda p, q: F.struct(p["x"].alias("x1"), p["y"].alias("y1"), q["x"].alias("x2"), q["y"].alias("y2")),
    )
    return F.when(part["role"] == "path", F.slice(ring, F.lit(1), F.greatest(F.size(ring) - 1, F.lit(0)))).otherwise(ring)


def _cross(e: Column) -> Column:
    return e["x1"] * e["y2"] - e["x2"] * e["y1"]


def _length(e: Column) -> Column:
    dx, dy = e["x2"] - e["x1"], e["y2"] - e["y1"]
    return F.sqrt(dx * dx + dy * dy)


def ring_area(part: Column) -> Column:
    """Signed area of a ring: positive if it turns to the left."""
    return _sum(F.transform(edges(part), _cross)) / 2


def _sign(part: Column) -> Column:
    return F.when(part["role"] == "hole", -1.0).otherwise(1.0)


def _shells(geom: Column) -> Column:
    return F.filter(geom["parts"], lambda p: p["role"] != "path")


def n_points(geom: Column) -> Column:
    return F.aggregate(geom["parts"], F.lit(0), lambda acc, p: acc + F.size(p["xs"]))


def area(geom: Column) -> Column:
    return _sum(F.transform(_shells(geom), lambda p: F.abs(ring_area(p)) * _sign(p)))


def perimeter(geom: Column) -> Column:
    return _sum(F.transform(geom["parts"], lambda p: _sum(F.transform(edges(p), _length))))


def centroid(geom: Column) -> Column:
    """struct<x, y>: weighted by area; without area by length; without length the mean of the vertices."""
    turned = F.transform(_shells(geom), lambda p: F.struct(edges(p).alias("es"), (F.signum(ring_area(p)) * _sign(p)).alias("s")))
    by_area = lambda axis: _sum(F.transform(turned, lambda t: t["s"] * _sum(F.transform(t["es"], lambda e: (e[f"{axis}1"] + e[f"{axis}2"]) * _cross(e))) / 6))
    all_edges = F.flatten(F.transform(geom["parts"], edges))
    by_length = lambda axis: _sum(F.transform(all_edges, lambda e: (e[f"{axis}1"] + e[f"{axis}2"]) / 2 * _length(e)))
    mean = lambda axis: _sum(F.flatten(F.transform(geom["parts"], lambda p: p[f"{axis}s"]))) / n_points(geom)
    return let(
        F.struct(area(geom).alias("a"), perimeter(geom).alias("l")),
        lambda m: F.struct(*[F.when(m["a"] > 0, by_area(x) / m["a"]).when(m["l"] > 0, by_length(x) / m["l"]).otherwise(mean(x)).alias(x) for x in ("x", "y")]),
    )


def translate(geom: Column, dx: Column, dy: Column) -> Column:
    moved = F.transform(geom["parts"], lambda p: F.struct(p["role"].alias("role"), F.transform(p["xs"], lambda x: x + dx).alias("xs"), F.transform(p["ys"], lambda y: y + dy).alias("ys")))
    return F.struct(geom["kind"].alias("kind"), moved.alias("parts"))


def center(geom: Column) -> Column:
    """The geometry with its centroid at the origin."""
    return let(centroid(geom), lambda c: translate(geom, -c["x"], -c["y"]))


def mbr(geom: Column) -> Column:
    """struct<x1, y1, x2, y2>; null for a geometry without vertices."""
    flat = lambda axis: F.flatten(F.transform(geom["parts"], lambda p: p[axis]))
    xs, ys = flat("xs"), flat("ys")
    box = F.struct(F.array_min(xs).alias("x1"), F.array_min(ys).alias("y1"), F.array_max(xs).alias("x2"), F.array_max(ys).alias("y2"))
    return F.when(n_points(geom) > 0, box)


def mbr_area(box: Column) -> Column:
    return (box["x2"] - box["x1"]) * (box["y2"] - box["y1"])


def mbr_intersects(a: Column, b: Column) -> Column:
    """Closed boxes: touching ones intersect."""
    return (a["x1"] <= b["x2"]) & (b["x1"] <= a["x2"]) & (a["y1"] <= b["y2"]) & (b["y1"] <= a["y2"])


def mbr_shared(a: Column, b: Column) -> Column:
    """Area that two boxes share."""
    side = lambda lo, hi: F.greatest(F.lit(0.0), F.least(a[hi], b[hi]) - F.greatest(a[lo], b[lo]))
    return side("x1", "x2") * side("y1", "y2")


def aspect_ratio(box: Column, unit: float = 1.0, elongation: bool = False) -> Column:
    w, h = box["x2"] - box["x1"] + EPS * unit, box["y2"] - box["y1"] + EPS * unit
    return F.greatest(w, h) / F.least(w, h) if elongation else w / h


def circularity(own_area: Column, own_perimeter: Column) -> Column:
    return F.when(own_perimeter > 0, 4 * F.pi() * own_area / (own_perimeter * own_perimeter)).otherwise(0.0)


def union_area(a: Column, b: Column, shared: Column) -> Column:
    return a + b - shared


def normalize_rings(geom: Column) -> Column:
    """Shells turned to the left, holes to the right; a repeated closing vertex is removed."""

    def turned(p: Column) -> Column:
        n = F.size(p["xs"])
        closed = (p["role"] != "path") & (n > 1) & (F.element_at(p["xs"], 1) == F.element_at(p["xs"], -1)) & (F.element_at(p["ys"], 1) == F.element_at(p["ys"], -1))
        cut = lambda v: F.when(closed, F.slice(v, F.lit(1), F.greatest(n - 1, F.lit(0)))).otherwise(v)
        opened = F.struct(p["role"].alias("role"), cut(p["xs"]).alias("xs"), cut(p["ys"]).alias("ys"))
        wrong = lambda q: (q["role"] != "path") & (ring_area(q) * F.when(q["role"] == "hole", -1.0).otherwise(1.0) < 0)
        return let(opened, lambda q: F.struct(q["role"].alias("role"), F.when(wrong(q), F.reverse(q["xs"])).otherwise(q["xs"]).alias("xs"), F.when(wrong(q), F.reverse(q["ys"])).otherwise(q["ys"]).alias("ys")))

    return F.struct(geom["kind"].alias("kind"), F.transform(geom["parts"], turned).alias("parts"))


def is_valid(geom: Column) -> Column:
    """Known kind, equally many finite x and y, at least three distinct vertices in a ring, two in a path."""
    distinct = lambda p: F.size(F.array_distinct(F.arrays_zip(p["xs"], p["ys"])))
    finite = lambda v: F.forall(v, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < 1e300))
    least = F.when(geom["kind"] == "point", 1).otherwise(2)
    enough = lambda p: distinct(p) >= F.when(p["role"] == "path", least).otherwise(3)
    return F.coalesce(geom["kind"].isin(*KINDS) & (F.size(geom["parts"]) > 0) & F.forall(geom["parts"], lambda p: (F.size(p["xs"]) == F.size(p["ys"])) & finite(p["xs"]) & finite(p["ys"]) & enough(p)), F.lit(False))


def convex_hull(geom: Column) -> Column:
    """The hull as a polygon, by a monotone chain over the sorted vertices (a fold each way)."""
    points = F.flatten(F.transform(geom["parts"], lambda p: F.zip_with(p["xs"], p["ys"], lambda x, y: F.struct(x.alias("x"), y.alias("y")))))
    kind = "array<struct<x:double,y:double>>"
    right = lambda o, a, b: (a["x"] - o["x"]) * (b["y"] - o["y"]) - (a["y"] - o["y"]) * (b["x"] - o["x"]) <= 0

    def step(chain: Column, p: Column) -> Column:
        # the longest head of the chain after which p still turns left
        keep = F.aggregate(F.sequence(F.lit(1), F.greatest(F.size(chain), F.lit(1))), F.size(chain), lambda n, _: F.when((n >= 2) & right(F.get(chain, n - 2), F.get(chain, n - 1), p), n - 1).otherwise(n))
        return F.concat(F.slice(chain, F.lit(1), keep), F.array(p))

    half = lambda ps: F.aggregate(ps, F.array().cast(kind), step)
    ordered = F.array_sort(F.array_distinct(points))
    ring = let(ordered, lambda ps: F.when(F.size(ps) < 3, ps).otherwise(F.concat(F.slice(half(ps), F.lit(1), F.size(half(ps)) - 1), F.slice(half(F.reverse(ps)), F.lit(1), F.size(half(F.reverse(ps))) - 1))))
    return let(ring, lambda r: geometry(F.lit("polygon"), F.transform(r, lambda p: p["x"]), F.transform(r, lambda p: p["y"])))
