"""Cheap features of clusters: sixteen numbers per pair of source and target, scaled twice."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.ml.feature import VectorAssembler
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import geom as G
from ..functions import shapes as S
from ..sources.stages import is_small, stage
from .grid import Grid, tile_range, tiles_of
from .simindex import NESTED_SIZE, Nested, has_larger

NAMES = tuple(f"f{i}" for i in range(1, 17))
SCALE = 10_000.0


def measured(rows: DataFrame, key: str) -> DataFrame:
    """key, box, vertices and boundary length of every geometry: all that joins and features need of it; a batch at a time."""
    kind = {c: rows.schema[c].dataType.simpleString() for c in (key, "mbr")}
    cast = rows.select(key, "mbr", F.col("geom").cast(G.GEOM).alias("geom"))
    return cast.mapInArrow(S.measurer, f"{key} {kind[key]}, mbr {kind['mbr']}, points long, length double")


def geometry_columns(rows: DataFrame, key: str, grid: Grid, closing: str = "floor") -> DataFrame:
    """key, box area, tiles, vertices and boundary length of every geometry, or of what `measured` gives of them."""
    rows, box = measured(rows, key) if "geom" in rows.columns else rows, F.col("mbr")
    return rows.select(F.col(key), G.mbr_area(box).alias("box_area"), "points", "length", *tile_range(box, grid, closing)).withColumn("tiles", tiles_of()).drop("i1", "j1", "i2", "j2")


SOURCE_SIDE = {"f1": "box_area", "f3": "tiles", "f6": "points", "f8": "length", "f10": "total", "f11": "distinct", "f12": "real"}
TARGET_SIDE = {"f2": "box_area", "f4": "tiles", "f7": "points", "f9": "length", "f13": "total", "f14": "distinct"}
PAIR_SIDE = {"f5": "common_tiles", "f15": "size", "f16": "shared"}


def source_side(sources: DataFrame, stats: DataFrame, grid: Grid, closing: str = "floor") -> DataFrame:
    """sid and the features that a source has in all its clusters."""
    rows = geometry_columns(sources, "sid", grid, closing).join(stats, "sid")
    return rows.select("sid", *[F.col(c).cast("double").alias(f) for f, c in SOURCE_SIDE.items()])


def target_side(targets: DataFrame, t_stats: DataFrame, grid: Grid, closing: str = "floor") -> DataFrame:
    """cid and the features that all members of a cluster have in common."""
    rows = geometry_columns(targets, "tid", grid, closing).join(t_stats.filter("real > 0"), "tid")
    return rows.select(F.col("tid").alias("cid"), *[F.col(c).cast("double").alias(f) for f, c in TARGET_SIDE.items()])


def raw_features(members: DataFrame, sources: DataFrame, targets: DataFrame, stats: DataFrame, t_stats: DataFrame, grid: Grid, closing: str = "floor") -> DataFrame:
    """cid, sid, f1..f16 of every member pair.

    f1/f2 box areas, f3/f4 tiles, f5 common tiles, f6/f7 vertices, f8/f9 boundary lengths of source and target;
    f10-f12 the source's total, distinct and real co-occurrences; f13-f15 the target's; f16 the boxes' overlap.
    """
    own = members.select("cid", "sid", *[F.col(c).cast("double").alias(f) for f, c in PAIR_SIDE.items()])
    return own.join(target_side(targets, t_stats, grid, closing), "cid").join(source_side(sources, stats, grid, closing), "sid").select("cid", "sid", *NAMES)


def pooled_features(members: DataFrame, s: DataFrame, t: DataFrame, n_features: int = 16, scaling: str = "both", rule: str = "max") -> DataFrame:
    """What cluster_features gives for the raw features, without making them: s and t from source_side and target_side."""
    return scaled_means(stage(pooled_means(members, s, t), "features-means"), n_features, scaling, rule)


#: Features in which the members of a cluster differ.
VARYING = tuple(f for f in NAMES if f not in TARGET_SIDE and f != "f15")


def pooled_means(members: DataFrame, s: DataFrame, t: DataFrame, nested: Nested | None = None) -> DataFrame:
    """cid, the unscaled means f1..f16, and the least and greatest lo_f and hi_f of those in which members differ.

    Means are taken of the members' own features only; what all members of a cluster share is joined to its one row.
    Few sources are broadcast, so that members are read cluster by cluster as they lie. Of many, nested gives the clusters as
    lists, and a task gets each source in its lists once; without it, and in clusters too large for lists, members are
    dealt once by source and once by cluster.
    """
    own = members.select("cid", "sid", *[F.col(c).cast("double").alias(f) for f, c in PAIR_SIDE.items()])
    if nested is None or is_small(s):
        joined = own.join(F.broadcast(s), "sid") if is_small(s) else own.join(s, "sid").repartition("cid")
        return joined.groupBy("cid").agg(*_spans(VARYING), F.first("f15").alias("f15")).join(t, "cid")
    pairwise = tuple(f for f in VARYING if f in PAIR_SIDE)
    of_pairs = own.filter(F.col("f15") <= NESTED_SIZE).groupBy("cid").agg(*_spans(pairwise), F.first("f15").alias("f15"))
    rows = _listed_spans(nested, s).join(of_pairs, "cid").join(t, "cid")
    if not has_larger(members, NESTED_SIZE):
        return rows
    return rows.unionByName(pooled_means(members.filter(F.col("size") > NESTED_SIZE), s, t))


def _spans(names: tuple[str, ...]) -> list:
    return [f(c).alias(f"{p}{c}") for c in names for p, f in (("", F.avg), ("lo_", F.min), ("hi_", F.max))]


def _listed_spans(nested: Nested, s: DataFrame) -> DataFrame:
    """cid and mean, least and greatest of the sources' own features in every list."""
    lists, names = nested.lists.select("cid", "m", "key"), tuple(SOURCE_SIDE)
    used = lists.select(F.col("key").alias("task"), F.explode("m").alias("sid")).distinct().join(s.select("sid", *names), "sid")
    out = ", ".join(f"{p}{f} double" for f in names for p in ("", "lo_", "hi_"))

    def run(left: pa.Table, right: pa.Table) -> pa.Table:
        right = right.sort_by("sid")
        m, ids = left["m"].combine_chunks(), right["sid"].to_numpy()
        sizes = pc.list_value_length(m).to_numpy(zero_copy_only=False)
        flat, row = pc.list_flatten(m).to_numpy(zero_copy_only=False), np.repeat(np.arange(len(sizes)), sizes)
        at = np.minimum(np.searchsorted(ids, flat), max(0, len(ids) - 1))
        known = ids[at] == flat if len(ids) else np.zeros(len(flat), bool)
        at, sizes = at[known], np.bincount(row[known], minlength=len(sizes))
        some = np.flatnonzero(sizes)
        sizes = sizes[some]
        starts, columns = np.cumsum(sizes) - sizes, [left["cid"].take(pa.array(some))]
        for f in names:
            value = right[f].to_numpy()[at]
            columns += [pa.array(x) for x in ((np.add.reduceat(value, starts) / sizes, np.minimum.reduceat(value, starts), np.maximum.reduceat(value, starts)) if len(at) else [np.zeros(0)] * 3)]
        return pa.table(columns, ["cid", *[f"{p}{f}" for f in names for p in ("", "lo_", "hi_")]])

    n = min(nested.keys, 4096)
    return lists.repartition(n, "key").groupBy("key").cogroup(used.repartition(n, "task").groupBy("task")).applyInArrow(run, f"cid {lists.schema['cid'].dataType.simpleString()}, {out}")


def scaled_means(rows: DataFrame, n_features: int = 16, scaling: str = "both", rule: str = "max") -> DataFrame:
    """The features of clusters from written pooled_means. Extremes over pairs are those of the members' extremes."""
    names = NAMES[:n_features]
    if scaling in ("both", "pair"):
        lows, highs = {f: (f"lo_{f}" if f in VARYING else f) for f in names}, {f: (f"hi_{f}" if f in VARYING else f) for f in names}
        row = rows.agg(*[F.min(c).alias(f"lo_{f}") for f, c in lows.items()], *[F.max(c).alias(f"hi_{f}") for f, c in highs.items()]).head()
        rows = scale(rows.select("cid", *names), {f: (row[f"lo_{f}"] or 0.0, row[f"hi_{f}"] or 0.0) for f in names}, rule)
    rows = rows.select("cid", *names)
    if scaling not in ("both", "cluster"):
        return rows
    return scale(rows, extremes(rows, names), rule)


def extremes(rows: DataFrame, names: tuple[str, ...] = NAMES) -> dict[str, tuple[float, float]]:
    """Least and greatest value of each feature over all rows: one row to the driver."""
    row = rows.agg(*[f(c).alias(f"{p}_{c}") for c in names for p, f in (("lo", F.min), ("hi", F.max))]).head()
    return {c: (row[f"lo_{c}"] or 0.0, row[f"hi_{c}"] or 0.0) for c in names}


def scale(rows: DataFrame, bounds: dict[str, tuple[float, float]], rule: str = "max") -> DataFrame:
    """(value - least) / greatest * 10000, or by the range; 0 where the divisor is 0."""
    by = {c: (hi if rule == "max" else hi - lo) for c, (lo, hi) in bounds.items()}
    return rows.withColumns({c: (F.col(c) - F.lit(lo)) / F.lit(by[c]) * SCALE if by[c] else F.lit(0.0) for c, (lo, _) in bounds.items()})


def cluster_means(rows: DataFrame, names: tuple[str, ...] = NAMES) -> DataFrame:
    return rows.groupBy("cid").agg(*[F.avg(c).alias(c) for c in names])


def cluster_features(raw: DataFrame, n_features: int = 16, scaling: str = "both", rule: str = "max") -> DataFrame:
    """cid and the features' means, scaled per pair, per cluster, both (default) or not at all.

    Scaling a pair's features is linear, so the scaled means are those of the raw features, scaled: the pair
    level costs no pass of its own besides its extremes.
    """
    names = NAMES[:n_features]
    rows = cluster_means(raw, names)
    if scaling in ("both", "pair"):
        rows = scale(rows, extremes(raw, names), rule)
    return scale(rows, extremes(rows, names), rule) if scaling in ("both", "cluster") else rows


def assemble(features: DataFrame, n_features: int = 16) -> DataFrame:
    """Adds the vector that classifiers read."""
    return VectorAssembler(inputCols=list(NAMES[:n_features]), outputCol="features").transform(features)
