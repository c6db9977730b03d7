import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from simcluster.functions import clip, fourier
from simcluster.functions import geom as G
from simcluster.functions import metrics as M
from simcluster.functions import text as X

SHAPES = {
    1: "POLYGON ((0 0, 1 0, 1 1, 0 1, 0 0))",
    2: "POLYGON ((0 0, 3 0, 0 4, 0 0))",
    3: "POLYGON ((0 0, 5 0, 5 2, 3 2, 3 5, 0 5, 0 0))",
    4: "POLYGON ((0 0, 10 0, 10 10, 0 10, 0 0), (2 2, 2 4, 4 4, 4 2, 2 2))",
    5: "LINESTRING (0 0, 3 4, 3 8)",
    6: "POINT (2 3)",
    7: "POLYGON ((0 0, 4 0, 8 0, 0 0))",
    8: "MULTIPOLYGON (((0 0, 1 0, 1 1, 0 1, 0 0)), ((5 5, 7 5, 7 7, 5 7, 5 5)))",
}


@pytest.fixture(scope="module")
def measured(spark):
    df = spark.createDataFrame(list(SHAPES.items()), "id long, wkt string").select("id", X.from_wkt(F.col("wkt")).alias("g"))
    g = F.col("g")
    out = df.select("id", G.n_points(g).alias("n"), G.area(g).alias("area"), G.perimeter(g).alias("length"), G.centroid(g).alias("c"), G.mbr(g).alias("box"), G.is_valid(g).alias("ok"), X.to_wkt(g).alias("wkt"), G.area(G.convex_hull(g)).alias("hull"), G.centroid(G.center(g)).alias("zero"))
    return {r["id"]: r for r in out.collect()}


def test_counts_areas_lengths_by_hand(measured):
    assert [measured[i]["n"] for i in (1, 2, 3, 4, 5, 6)] == [4, 3, 6, 8, 3, 1]
    assert [round(measured[i]["area"], 9) for i in (1, 2, 3, 4, 5, 6, 7, 8)] == [1, 6, 19, 96, 0, 0, 0, 5]
    assert [round(measured[i]["length"], 9) for i in (1, 2, 4, 5, 6)] == [4, 12, 48, 9, 0]


def test_centroids(measured):
    assert (measured[1]["c"]["x"], measured[1]["c"]["y"]) == (0.5, 0.5)
    assert math.isclose(measured[2]["c"]["x"], 1) and math.isclose(measured[2]["c"]["y"], 4 / 3)
    assert math.isclose(measured[5]["c"]["x"], (1.5 * 5 + 3 * 4) / 9) and math.isclose(measured[5]["c"]["y"], (2 * 5 + 6 * 4) / 9)
    assert (measured[6]["c"]["x"], measured[6]["c"]["y"]) == (2, 3)
    assert all(abs(r["zero"]["x"]) < 1e-9 and abs(r["zero"]["y"]) < 1e-9 for r in measured.values())


def test_validity_hull_text(measured):
    assert all(measured[i]["ok"] for i in SHAPES)
    assert math.isclose(measured[3]["hull"], 22) and math.isclose(measured[1]["hull"], 1)
    back = measured[4]["wkt"].replace(".0", "")
    assert back == SHAPES[4]


def test_circle_measures(spark):
    row = spark.range(1).select(G.circularity(F.lit(1.0), F.lit(4.0)).alias("a"), G.circularity(F.lit(0.0), F.lit(0.0)).alias("b")).head()
    assert math.isclose(row["a"], math.pi / 4) and row["b"] == 0


def _edges(points):
    x, y = np.array(points, float).T
    if np.dot(x, np.roll(y, -1)) < np.dot(y, np.roll(x, -1)):
        x, y = x[::-1], y[::-1]
    return [x, y, np.roll(x, -1), np.roll(y, -1)]


def _shared(a, b):
    a, b = _edges(a), _edges(b)
    i, j = np.meshgrid(range(len(a[0])), range(len(b[0])))
    i, j = i.ravel(), j.ravel()
    loop = sum(clip._one_wedge(*[v[p] for v in a], *[v[q] for v in b]) for p, q in zip(i, j, strict=True))
    fast = clip.shared_wedges(*[v[i] for v in a], *[v[j] for v in b]).sum()
    assert math.isclose(loop, fast, abs_tol=1e-9)
    return fast


def test_intersections_by_hand():
    ell = [(0, 0), (5, 0), (5, 2), (3, 2), (3, 5), (0, 5)]
    square = [(0, 0), (2, 0), (2, 2), (0, 2)]
    assert math.isclose(_shared(ell, ell), 19)
    assert math.isclose(_shared(square, [(1, 1), (3, 1), (3, 3), (1, 3)]), 1)
    assert abs(_shared(square, [(5, 5), (6, 5), (6, 6), (5, 6)])) < 1e-9
    assert math.isclose(_shared(square, [(-1, -1), (1, -1), (1, 1), (-1, 1)]), 1)


def test_intersection_against_sampling():
    rng = np.random.default_rng(4)

    def star(n):
        t = np.sort(rng.uniform(0, 2 * math.pi, n))
        r = rng.uniform(1, 3, n)
        return list(zip(r * np.cos(t) + rng.uniform(-1, 1), r * np.sin(t) + rng.uniform(-1, 1), strict=True))

    def inside(points, x, y):
        px, py = np.array(points).T
        qx, qy = np.roll(px, -1), np.roll(py, -1)
        odd = np.zeros(len(x), bool)
        for a, b, c, d in zip(px, py, qx, qy, strict=True):
            with np.errstate(divide="ignore", invalid="ignore"):
                odd ^= ((b > y) != (d > y)) & (x < (c - a) * (y - b) / (d - b) + a)
        return odd

    x, y = rng.uniform(-5, 5, (2, 60_000))
    for _ in range(6):
        a, b = star(7), star(9)
        want = (inside(a, x, y) & inside(b, x, y)).mean() * 100
        assert abs(_shared(a, b) - want) < 0.25


def test_backends_agree(d2):
    from simcluster.operators.simindex import member_pairs

    pairs = member_pairs(d2.members).select("a", "b").distinct().orderBy("a", "b").limit(300).persist()
    got = {k: {(r["a"], r["b"]): r["inter"] for r in clip.intersection_area(pairs, d2.shapes, k).collect()} for k in ("arrow", "sql", "python")}
    assert len(got["arrow"]) == 300
    for k in ("sql", "python"):
        assert max(abs(got["arrow"][p] - got[k][p]) for p in got["arrow"]) < 1e-9


def test_descriptor_ignores_place_turn_and_size():
    x, y = np.array([(0, 0), (4, 0), (4, 1), (1, 3)], float).T
    one = fourier.descriptor(x, y)
    c, s = math.cos(0.7), math.sin(0.7)
    other = fourier.descriptor(3 * (c * x - s * y) + 9, 3 * (s * x + c * y) - 2)
    assert np.allclose(one, other, atol=1e-9)
    assert np.allclose(fourier.descriptor(np.array([1.0]), np.array([1.0])), 0)


def test_measures_of_pairs(d2):
    from simcluster.operators.simindex import member_pairs, pair_similarities

    pairs = member_pairs(d2.members).select("a", "b").distinct().limit(500)
    for r in pair_similarities(pairs, d2.shapes, breakdown=True).collect():
        assert all(0 <= r[k] <= 1 + 1e-9 for k in M.NAMES)
        assert math.isclose(r["area"], 2 * r["jaccard"] / (1 + r["jaccard"]), abs_tol=1e-9)
        assert r["curvature"] >= math.exp(-1) and math.isclose(r["s"], sum(r[k] for k in M.NAMES) / 8, abs_tol=1e-9)
    same = d2.shapes.select(F.col("sid").alias("a"), F.col("sid").alias("b")).limit(50)
    assert all(math.isclose(r["s"], 1, abs_tol=1e-9) for r in pair_similarities(same, d2.shapes).collect())


def test_weights_are_checked():
    with pytest.raises(ValueError):
        M.check_weights({"jaccard": 0.5})
    with pytest.raises(ValueError):
        M.check_weights({"nothing": 1.0})


def test_shapes_by_batches_equal_expressions(spark, d2):
    from simcluster.operators import simindex as I

    odd = [
        ("polygon", [("shell", [0.0, 4, 4, 0, 0], [0.0, 0, 4, 4, 0]), ("hole", [1.0, 2, 2, 1], [1.0, 1, 2, 2])]),
        ("polygon", [("shell", [0.0, 0, 4, 4], [0.0, 4, 4, 0])]), ("linestring", [("path", [0.0, 1, 5], [0.0, 2, 2])]),
        ("linestring", [("path", [1.0, 1], [2.0, 2])]), ("point", [("path", [3.0], [4.0])]), ("polygon", []),
        ("polygon", [("shell", [0.0, 1, 2], [0.0, 1, 2])]), ("multipolygon", [("shell", [0.0, 1, 1], [0.0, 0, 1]), ("shell", [5.0, 5, 7], [5.0, 7, 7])]),
    ]
    rows = [(i, (kind, [(role, [float(v) for v in xs], [float(v) for v in ys]) for role, xs, ys in parts])) for i, (kind, parts) in enumerate(odd)]
    few = spark.createDataFrame(rows, f"sid long, geom {G.GEOM}")
    for table, kw in ((few, {}), (few, {"centered": False, "sampling": "vertices", "scale_free": False, "elongation": True}), (d2.sources.select("sid", "geom"), {}), (d2.targets.select(F.col("tid").alias("sid"), "geom"), {"harmonics": 4})):
        got = {r["sid"]: r for r in I.describe_shapes(table, **kw).collect()}
        want = {r["sid"]: r for r in I.describe_shapes_by_expressions(table.filter(F.size("geom.parts") > 0), **kw).collect()}
        assert want.keys() <= got.keys()
        for k, w in want.items():
            for c in w.asDict():
                assert got[k][c] == (w[c] if w[c] is None else pytest.approx(w[c], abs=1e-9)), (k, c)
    empty = {r["sid"]: r for r in I.describe_shapes(few).collect()}[5]
    assert empty["n"] == 0 and empty["area"] == 0 and empty["aspect"] is None and empty["ex1"] == []


def test_simplify(spark):
    line = ("linestring", [("path", [0.0, 1, 2, 3, 4], [0.0, 0.01, -0.01, 5, 0])])
    ring = ("polygon", [("shell", [0.0, 2, 4, 4, 2, 0], [0.0, 0.001, 0, 4, 4.001, 4])])
    floats = lambda g: (g[0], [(r, [float(v) for v in xs], [float(v) for v in ys]) for r, xs, ys in g[1]])
    rows = spark.createDataFrame([(1, floats(line)), (2, floats(ring)), (3, None)], f"id long, geom {G.GEOM}").select("id", X.simplify(F.col("geom"), 0.1).alias("g"))
    got = {r["id"]: r["g"] for r in rows.collect()}
    assert got[1]["parts"][0]["xs"] == [0, 2, 3, 4] and sorted(got[2]["parts"][0]["xs"]) == [0, 0, 4, 4] and got[3]["parts"] is None
