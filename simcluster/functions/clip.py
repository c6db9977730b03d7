"""Exact area of the intersection of two polygons, without a clipping library.

A ring is written as a signed fan of triangles with their apex at the origin; the shared area of two polygons
is the signed sum, over pairs of fan triangles, of what the triangles share. Two such triangles overlap on one
cone of directions, bounded on every ray by the nearer chord; the chords cross at most once in the cone, so
the shared part is one or two triangles. The arithmetic is the same in numpy, in Catalyst expressions and in
plain Python.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.functions import arrow_udf, udf
from pyspark.sql.types import DoubleType

from . import geom as G

#: Pairs of edges that are laid out at a time.
CHUNK = 65_536
EDGES = ("x1", "y1", "x2", "y2")


def edge_arrays(shape: Column) -> list[Column]:
    """Four arrays with the edges of all rings of a shape, for a frame of shapes; paths give none."""
    all_edges = F.flatten(F.transform(F.filter(shape["parts"], lambda p: p["role"] != "path"), G.edges))
    take = lambda k: F.transform(all_edges, lambda e: e[k])
    return [take(k).alias(f"e{k}") for k in EDGES]


def shared_wedges(px, py, qx, qy, sx, sy, tx, ty):
    """Signed shared area of fan triangles (origin, p, q) and (origin, s, t), element by element."""
    cpq, cst = px * qy - py * qx, sx * ty - sy * tx
    sign = np.sign(cpq) * np.sign(cst)
    flip, flop = cpq < 0, cst < 0
    px, qx, py, qy = np.where(flip, qx, px), np.where(flip, px, qx), np.where(flip, qy, py), np.where(flip, py, qy)
    sx, tx, sy, ty = np.where(flop, tx, sx), np.where(flop, sx, tx), np.where(flop, ty, sy), np.where(flop, sy, ty)
    cpq, cst = np.abs(cpq), np.abs(cst)
    ps, sq, sp, pt, qt, tq = px * sy - py * sx, sx * qy - sy * qx, sx * py - sy * px, px * ty - py * tx, qx * ty - qy * tx, tx * qy - ty * qx
    pt_t, s_q = px * ty - py * tx, sx * qy - sy * qx
    s_in, p_in = (ps >= 0) & (sq >= 0), (sp >= 0) & (pt >= 0)
    q_in, t_in = (s_q >= 0) & (qt >= 0), (pt_t >= 0) & (tq >= 0)
    live = (sign != 0) & (s_in | p_in) & (q_in | t_in)
    ax, ay = np.where(s_in, sx, px), np.where(s_in, sy, py)
    bx, by = np.where(q_in, qx, tx), np.where(q_in, qy, ty)
    return np.where(live, _pieces(px, py, qx, qy, cpq, sx, sy, tx, ty, cst, ax, ay, bx, by), 0.0) * sign


def _pieces(px, py, qx, qy, cpq, sx, sy, tx, ty, cst, ax, ay, bx, by):
    """What two overlapping triangles that turn left share between the rays to a and to b."""
    dx, dy, ex, ey = qx - px, qy - py, tx - sx, ty - sy
    with np.errstate(divide="ignore", invalid="ignore"):
        # along a ray to a (or b): multiples at which the two chords are met
        at, au = cpq / (ax * dy - ay * dx), cst / (ax * ey - ay * ex)
        bt, bu = cpq / (bx * dy - by * dx), cst / (bx * ey - by * ex)
        near_a, near_b = np.minimum(at, au), np.minimum(bt, bu)
        cross = (at < au) != (bt < bu)
        # where the chords cross: on the line through p with direction d
        den = dx * ey - dy * ex
        k = ((sx - px) * ey - (sy - py) * ex) / den
        x, y = px + k * dx, py + k * dy
        one = near_a * near_b * (ax * by - ay * bx)
        two = near_a * (ax * y - ay * x) + near_b * (x * by - y * bx)
        out = np.where(cross & (den != 0), two, one) / 2
    return np.where(np.isfinite(out), out, 0.0)


def _lists(column) -> tuple[np.ndarray, np.ndarray]:
    column = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    offsets = column.offsets.to_numpy()
    return column.values.to_numpy(zero_copy_only=False), offsets


def shared_areas(a: list, b: list) -> np.ndarray:
    """Shared areas of the shapes in two lists of four Arrow list arrays each, row by row."""
    ao, bo = _lists(a[0])[1], _lists(b[0])[1]
    fan = lambda x: turned(*[_lists(c)[0] for c in x])
    return shared_of(fan(a), ao[:-1], np.diff(ao), fan(b), bo[:-1], np.diff(bo))


def turned(px, py, qx, qy) -> tuple[np.ndarray, ...]:
    """Edges as fan triangles that turn left: p, q, twice the area, and the sign it had."""
    c = px * qy - py * qx
    back = c < 0
    return np.where(back, qx, px), np.where(back, qy, py), np.where(back, px, qx), np.where(back, py, qy), np.abs(c), np.sign(c)


def shared_of(a: tuple, a_at: np.ndarray, na: np.ndarray, b: tuple, b_at: np.ndarray, nb: np.ndarray) -> np.ndarray:
    """Shared areas of pairs of shapes that have na edges from a_at on in a and nb from b_at on in b (of `turned`).

    Pairs with equal numbers of edges are laid side by side. Only fan triangles that overlap are worked out.
    """
    out = np.zeros(len(na))
    na, nb = na.astype(np.int64), nb.astype(np.int64)
    kind = na * (int(nb.max(initial=0)) + 1) + nb
    order = np.argsort(kind, kind="stable")
    for own in np.split(order, np.flatnonzero(np.diff(kind[order])) + 1):
        n, m = (int(na[own[0]]), int(nb[own[0]])) if len(own) else (0, 0)
        if not n or not m:
            continue
        width = max(1, CHUNK // (n * m))
        tall = n if n * m <= CHUNK else max(1, CHUNK // m)
        for lo in range(0, len(own), width):
            rows = own[lo : lo + width]
            right = [v[b_at[rows] + np.arange(m)[:, None]] for v in b]
            for i in range(0, n, tall):
                left = [v[a_at[rows] + np.arange(i, min(n, i + tall))[:, None]] for v in a]
                out[rows] += _overlaps(left, right)
    return np.maximum(out, 0.0)


def _overlaps(left: list, right: list) -> np.ndarray:
    """The sum of `shared_wedges` over all edges of both sides, for every column; arrays of edges x pairs."""
    px, py, qx, qy, ca, _ = (v[:, None, :] for v in left)
    sx, sy, tx, ty, cb, _ = (v[None, :, :] for v in right)
    ps, sq, pt, qt = px * sy - py * sx, sx * qy - sy * qx, px * ty - py * tx, qx * ty - qy * tx
    q_after_s, t_after_p = sq >= 0, pt >= 0
    live = (((ps >= 0) & q_after_s) | ((ps <= 0) & t_after_p)) & ((q_after_s & (qt >= 0)) | (t_after_p & (qt <= 0))) & (ca > 0) & (cb > 0)
    width = live.shape[2]
    at = np.flatnonzero(live)
    edge, pair = np.divmod(at, width)
    i, j = np.divmod(edge, live.shape[1])
    i, j = i * width + pair, j * width + pair
    px, py, qx, qy, ca, sa = (v.ravel()[i] for v in left)
    sx, sy, tx, ty, cb, sb = (v.ravel()[j] for v in right)
    ps, sq, qt = (v.ravel()[at] for v in (ps, sq, qt))
    s_in, q_in = (ps >= 0) & (sq >= 0), (sq >= 0) & (qt >= 0)
    ax, ay = np.where(s_in, sx, px), np.where(s_in, sy, py)
    bx, by = np.where(q_in, qx, tx), np.where(q_in, qy, ty)
    return np.bincount(pair, _pieces(px, py, qx, qy, ca, sx, sy, tx, ty, cb, ax, ay, bx, by) * (sa * sb), width)


@arrow_udf(DoubleType())
def _arrow_shared(a1: pa.Array, a2: pa.Array, a3: pa.Array, a4: pa.Array, b1: pa.Array, b2: pa.Array, b3: pa.Array, b4: pa.Array) -> pa.Array:
    return pa.array(shared_areas([a1, a2, a3, a4], [b1, b2, b3, b4]))


@udf(DoubleType())
def _python_shared(a1, a2, a3, a4, b1, b2, b3, b4):
    """The plain loop, as a baseline: one pair of edges at a time."""
    total = 0.0
    for px, py, qx, qy in zip(a1, a2, a3, a4, strict=True):
        for sx, sy, tx, ty in zip(b1, b2, b3, b4, strict=True):
            total += _one_wedge(px, py, qx, qy, sx, sy, tx, ty)
    return max(0.0, total)


def _one_wedge(px, py, qx, qy, sx, sy, tx, ty) -> float:
    cpq, cst = px * qy - py * qx, sx * ty - sy * tx
    if cpq == 0 or cst == 0:
        return 0.0
    sign = 1.0
    if cpq < 0:
        px, py, qx, qy, cpq, sign = qx, qy, px, py, -cpq, -sign
    if cst < 0:
        sx, sy, tx, ty, cst, sign = tx, ty, sx, sy, -cst, -sign
    if px * sy - py * sx >= 0 and sx * qy - sy * qx >= 0:
        ax, ay = sx, sy
    elif sx * py - sy * px >= 0 and px * ty - py * tx >= 0:
        ax, ay = px, py
    else:
        return 0.0
    if sx * qy - sy * qx >= 0 and qx * ty - qy * tx >= 0:
        bx, by = qx, qy
    elif px * ty - py * tx >= 0 and tx * qy - ty * qx >= 0:
        bx, by = tx, ty
    else:
        return 0.0
    dx, dy, ex, ey = qx - px, qy - py, tx - sx, ty - sy
    dens = [ax * dy - ay * dx, ax * ey - ay * ex, bx * dy - by * dx, bx * ey - by * ex]
    if 0.0 in dens:
        return 0.0
    at, au, bt, bu = cpq / dens[0], cst / dens[1], cpq / dens[2], cst / dens[3]
    den = dx * ey - dy * ex
    if (at < au) != (bt < bu) and den != 0:
        k = ((sx - px) * ey - (sy - py) * ex) / den
        x, y = px + k * dx, py + k * dy
        return sign * (min(at, au) * (ax * y - ay * x) + min(bt, bu) * (x * by - y * bx)) / 2
    return sign * min(at, au) * min(bt, bu) * (ax * by - ay * bx) / 2


#: The wedge formula for engines that speak SQL: named steps over px..ty, each using the ones before it.
WEDGE_STEPS = (
    ("cpq", "px * qy - py * qx"),
    ("cst", "sx * ty - sy * tx"),
    ("px_", "CASE WHEN cpq < 0 THEN qx ELSE px END"), ("py_", "CASE WHEN cpq < 0 THEN qy ELSE py END"),
    ("qx_", "CASE WHEN cpq < 0 THEN px ELSE qx END"), ("qy_", "CASE WHEN cpq < 0 THEN py ELSE qy END"),
    ("sx_", "CASE WHEN cst < 0 THEN tx ELSE sx END"), ("sy_", "CASE WHEN cst < 0 THEN ty ELSE sy END"),
    ("tx_", "CASE WHEN cst < 0 THEN sx ELSE tx END"), ("ty_", "CASE WHEN cst < 0 THEN sy ELSE ty END"),
    ("s_in", "px_ * sy_ - py_ * sx_ >= 0 AND sx_ * qy_ - sy_ * qx_ >= 0"),
    ("p_in", "sx_ * py_ - sy_ * px_ >= 0 AND px_ * ty_ - py_ * tx_ >= 0"),
    ("q_in", "sx_ * qy_ - sy_ * qx_ >= 0 AND qx_ * ty_ - qy_ * tx_ >= 0"),
    ("t_in", "px_ * ty_ - py_ * tx_ >= 0 AND tx_ * qy_ - ty_ * qx_ >= 0"),
    ("ax", "CASE WHEN s_in THEN sx_ ELSE px_ END"), ("ay", "CASE WHEN s_in THEN sy_ ELSE py_ END"),
    ("bx", "CASE WHEN q_in THEN qx_ ELSE tx_ END"), ("by_", "CASE WHEN q_in THEN qy_ ELSE ty_ END"),
    ("at_", "abs(cpq) / nullif(ax * (qy_ - py_) - ay * (qx_ - px_), 0)"), ("au", "abs(cst) / nullif(ax * (ty_ - sy_) - ay * (tx_ - sx_), 0)"),
    ("bt", "abs(cpq) / nullif(bx * (qy_ - py_) - by_ * (qx_ - px_), 0)"), ("bu", "abs(cst) / nullif(bx * (ty_ - sy_) - by_ * (tx_ - sx_), 0)"),
    ("den", "(qx_ - px_) * (ty_ - sy_) - (qy_ - py_) * (tx_ - sx_)"),
    ("k", "((sx_ - px_) * (ty_ - sy_) - (sy_ - py_) * (tx_ - sx_)) / nullif(den, 0)"),
    ("x", "px_ + k * (qx_ - px_)"), ("y", "py_ + k * (qy_ - py_)"),
    ("wedge", "CASE WHEN cpq = 0 OR cst = 0 OR NOT (s_in OR p_in) OR NOT (q_in OR t_in) THEN 0.0 ELSE coalesce(sign(cpq) * sign(cst) * CASE WHEN (at_ < au) <> (bt < bu) AND den <> 0"
     " THEN least(at_, au) * (ax * y - ay * x) + least(bt, bu) * (x * by_ - y * bx) ELSE least(at_, au) * least(bt, bu) * (ax * by_ - ay * bx) END / 2, 0.0) END"),
)


def with_wedges(edge_pairs: DataFrame) -> DataFrame:
    """Add the signed shared area of each pair of edges (px..ty) as Catalyst expressions."""
    for name, sql in WEDGE_STEPS:
        edge_pairs = edge_pairs.withColumn(name, F.expr(sql))
    return edge_pairs


def intersection_area(pairs: DataFrame, shapes: DataFrame, backend: str = "arrow") -> DataFrame:
    """a, b and inter for pairs (a, b) of shape ids; shapes: sid and the four edge arrays ex1..ey2.

    arrow: one vectorised function call per batch; sql: pairs of edges as rows, summed per pair, no Python;
    python: the row-at-a-time loop that the vectorised form is measured against.
    """
    names = [f"e{k}" for k in EDGES]
    if backend == "sql":
        flat = shapes.select("sid", F.explode(F.arrays_zip(*names)).alias("e")).select("sid", *[F.col(f"e.{n}").alias(n) for n in names])
        left = flat.select(F.col("sid").alias("a"), *[F.col(n).alias(k) for n, k in zip(names, ("px", "py", "qx", "qy"), strict=True)])
        right = flat.select(F.col("sid").alias("b"), *[F.col(n).alias(k) for n, k in zip(names, ("sx", "sy", "tx", "ty"), strict=True)])
        summed = with_wedges(pairs.select("a", "b").join(left, "a").join(right, "b")).groupBy("a", "b").agg(F.greatest(F.lit(0.0), F.sum("wedge")).alias("inter"))
        return pairs.select("a", "b").join(summed, ["a", "b"], "left").select("a", "b", F.coalesce("inter", F.lit(0.0)).alias("inter"))
    left = shapes.select(F.col("sid").alias("a"), *[F.col(n).alias(f"a_{n}") for n in names])
    right = shapes.select(F.col("sid").alias("b"), *[F.col(n).alias(f"b_{n}") for n in names])
    joined = pairs.select("a", "b").join(left, "a").join(right, "b")
    return joined.select("a", "b", shared_column([F.col(f"a_{n}") for n in names], [F.col(f"b_{n}") for n in names], backend).alias("inter"))


def shared_column(a: list[Column], b: list[Column], backend: str = "arrow") -> Column:
    if backend == "arrow":
        return _arrow_shared(*a, *b)
    if backend == "python":
        return _python_shared(*a, *b)
    raise ValueError(f"unknown backend {backend!r}")
