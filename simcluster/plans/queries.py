"""One query per method, variant, baseline and measure over the given tables, with SQL for comparison."""

from __future__ import annotations

import dataclasses
from collections import OrderedDict
from collections.abc import Callable
from functools import partial

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import clip, fourier
from ..functions import geom as G
from ..functions import metrics as M
from ..functions import sqlfuncs
from ..functions import text as X
from ..operators import budget as B
from ..operators import classifier, relational
from ..operators import clusters as C
from ..operators import density as D
from ..operators import features as FT
from ..operators import labelling as L
from ..operators import sampling as S
from ..operators import simindex as I
from ..operators import verify as V
from ..operators.grid import candidate_pairs, candidate_pairs_nested_loop, grid_granularity, tile_range
from ..sources.fixtures import lift_sources, lift_targets, trajectories
from ..sources.stages import stage
from ..sources.tables import load_table, within_box, write_bucketed
from ..streaming import assign
from . import baselines as XB
from . import evaluate as E
from . import experiments as K
from .oracle import assemble
from .search import Prepared, SimilarClusterSearch

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLE_SQL: dict[str, str] = {}


def query(name: str, sql: str | None = None, work: str = "d1", **more: str):
    """Register a function of (spark, sf_dir) and the SQL that must give the same rows."""

    def add(f: Query) -> Query:
        QUERIES[name] = f
        if sql is not None:
            ORACLE_SQL[name] = assemble(sql, work, **more)
        return f

    return add


#: Added before rounding in both engines: shared areas are often exact halves of any last digit.
_OFF6 = 0.00000031


def _r(c, digits: int = 6):
    return F.round(c, digits)


def _r_off(c: str):
    return F.round(F.col(c) + F.lit(_OFF6), 6)


_PREPARED: OrderedDict[tuple, Prepared] = OrderedDict()


def _prep(spark: SparkSession, d: str, work: str = "d1", **kw) -> Prepared:
    """Queries of one session over one folder share what is staged for a workload."""
    key = (spark.sparkContext.applicationId, d, work, repr(sorted(kw.items())))
    if key not in _PREPARED:
        _PREPARED[key] = K.prepare(spark, d, work, **kw)
        while len(_PREPARED) > 8:
            _PREPARED.popitem(last=False)
    return _PREPARED[key]


# geometry

@query("geom_npoints", "SELECT sid, n::INT AS n FROM smeas")
def _(spark, d):
    return lift_sources(spark, d).select("sid", G.n_points(F.col("geom")).alias("n"))


@query("geom_area", "SELECT sid, round(area, 6) AS area FROM smeas")
def _(spark, d):
    return lift_sources(spark, d).select("sid", _r(G.area(F.col("geom"))).alias("area"))


@query("geom_perimeter", "SELECT sid, round(perimeter, 6) AS perimeter FROM smeas")
def _(spark, d):
    return lift_sources(spark, d).select("sid", _r(G.perimeter(F.col("geom"))).alias("perimeter"))


@query("geom_length_targets", "SELECT tid, points::INT AS points, round(length, 6) AS length FROM tmeas")
def _(spark, d):
    return lift_targets(spark, d).select("tid", G.n_points(F.col("geom")).alias("points"), _r(G.perimeter(F.col("geom"))).alias("length"))


@query("geom_centroid", "SELECT sid, round(cx, 6) AS cx, round(cy, 6) AS cy FROM smeas")
def _(spark, d):
    return lift_sources(spark, d).select("sid", G.centroid(F.col("geom")).alias("c")).select("sid", _r("c.x").alias("cx"), _r("c.y").alias("cy"))


@query("geom_center", "SELECT sid, j::INT AS j, round(x1, 6) AS x, round(y1, 6) AS y FROM cedge")
def _(spark, d):
    moved = lift_sources(spark, d).select("sid", G.center(F.col("geom"))["parts"][0].alias("p"))
    return moved.select("sid", F.posexplode(F.arrays_zip("p.xs", "p.ys")).alias("j", "v")).select("sid", "j", _r("v.xs").alias("x"), _r("v.ys").alias("y"))


@query("geom_mbr", "SELECT sid, x1, y1, x2, y2, (x2 - x1) * (y2 - y1) AS area FROM sbox")
def _(spark, d):
    return lift_sources(spark, d).select("sid", "mbr.*", G.mbr_area(F.col("mbr")).alias("area"))


@query("geom_circularity", "SELECT sid, round(phi, 6) AS phi FROM scalars")
def _(spark, d):
    return lift_sources(spark, d).select("sid", _r(G.circularity(G.area(F.col("geom")), G.perimeter(F.col("geom")))).alias("phi"))


@query("geom_aspect", "SELECT sid, round(aspect, 6) AS aspect FROM scalars")
def _(spark, d):
    return lift_sources(spark, d).select("sid", _r(G.aspect_ratio(G.mbr(G.center(F.col("geom"))))).alias("aspect"))


@query("geom_fourier", "SELECT sid, k::INT AS k, round(v, 5) AS v FROM (SELECT sid, unnest(fd) AS v, unnest(range(2, 10)) AS k FROM fds)")
def _(spark, d):
    fd = lift_sources(spark, d).select("sid", fourier.fourier_descriptor(F.col("geom")).alias("fd"))
    return fd.select("sid", F.posexplode("fd").alias("k", "v")).select("sid", (F.col("k") + 2).alias("k"), _r("v", 5).alias("v"))


@query("geom_wkt_round_trip", "SELECT sid, n::INT AS n, round(area, 6) AS area FROM smeas")
def _(spark, d):
    back = lift_sources(spark, d).select("sid", X.from_wkt(X.to_wkt(F.col("geom"))).alias("g"))
    return back.select("sid", G.n_points(F.col("g")).alias("n"), _r(G.area(F.col("g"))).alias("area"))


@query("geom_geojson_round_trip", "SELECT sid, n::INT AS n, round(area, 6) AS area FROM smeas")
def _(spark, d):
    back = lift_sources(spark, d).select("sid", X.from_geojson(X.to_geojson(F.col("geom"))).alias("g"))
    return back.select("sid", G.n_points(F.col("g")).alias("n"), _r(G.area(F.col("g"))).alias("area"))


@query("geom_valid", "SELECT count(*) AS valid FROM src")
def _(spark, d):
    return lift_sources(spark, d).filter(G.is_valid(F.col("geom"))).agg(F.count("*").alias("valid"))


# pairs of shapes: backends and measures

def _pair_query(spark, d, work: str, backend: str) -> DataFrame:
    p = _prep(spark, d, work)
    pairs = I.member_pairs(p.members).select("a", "b").distinct()
    return clip.intersection_area(pairs, p.shapes, backend).select("a", "b", _r_off("inter").alias("inter"))


for _backend in ("arrow", "sql", "python"):
    query(f"pair_intersection_{_backend}", f"SELECT a, b, round(inter + {_OFF6}, 6) AS inter FROM inters", "d2")(partial(_pair_query, work="d2", backend=_backend))


def _measure(spark, d, name: str) -> DataFrame:
    p = _prep(spark, d, "d2")
    pairs = I.member_pairs(p.members).select("a", "b").distinct()
    return I.pair_similarities(pairs, p.shapes, {name: 1.0}).select("a", "b", _r_off("s").alias("v") if name in M.CATEGORIES["overlap"] else _r("s", 5).alias("v"))


for _name in M.NAMES:
    query(f"m_{_name}", f"SELECT a, b, round({_name} + {_OFF6}, 6) AS v FROM sims" if _name in M.CATEGORIES["overlap"] else f"SELECT a, b, round({_name}, 5) AS v FROM sims", "d2")(partial(_measure, name=_name))


@query("m_combined", "SELECT a, b, round(s, 5) AS s FROM scored_pairs", "d2")
def _(spark, d):
    p = _prep(spark, d, "d2")
    return I.pair_similarities(I.member_pairs(p.members).select("a", "b").distinct(), p.shapes).select("a", "b", _r("s", 5).alias("s"))


@query("m_weighted", "SELECT a, b, round(0.5 * jaccard + 0.25 * perimeter + 0.25 * circularity, 5) AS s FROM sims", "d2")
def _(spark, d):
    p = _prep(spark, d, "d2")
    return I.pair_similarities(I.member_pairs(p.members).select("a", "b").distinct(), p.shapes, {"jaccard": 0.5, "perimeter": 0.25, "circularity": 0.25}).select("a", "b", _r("s", 5).alias("s"))


def _backend(spark, d, what: str, backend: str) -> DataFrame:
    out = K.geometry_by_backend(_prep(spark, d, "d2"), what, backend)
    return out if what == "mbr" else out.select("a", "b", _r_off("united").alias("united"))


for _backend_name in ("arrow", "sql", "python"):
    query(f"mbr_{_backend_name}", "SELECT sid, x1, y1, x2, y2 FROM sbox", "d2")(partial(_backend, what="mbr", backend=_backend_name))
    query(f"pair_union_{_backend_name}", f"SELECT a, b, round(x.area + y.area - inter + {_OFF6}, 6) AS united FROM inters JOIN smeas x ON x.sid = a JOIN smeas y ON y.sid = b", "d2")(partial(_backend, what="union", backend=_backend_name))


def _averages(spark, d, backend: str) -> DataFrame:
    return K.metric_averages(_prep(spark, d, "d2"), backend).select(*[_r(k).alias(k) for k in M.NAMES], "pairs")


for _backend_name in ("arrow", "sql", "python"):
    query(f"metric_averages_{_backend_name}", "SELECT " + ", ".join(f"round(avg({k}), 6) AS {k}" for k in M.NAMES) + ", count(*) AS pairs FROM sims", "d2")(partial(_averages, backend=_backend_name))


@query("shapes_by_expressions", "SELECT sid, n::INT AS n, round(area, 6) AS area, round(perimeter, 6) AS perimeter, round(phi, 6) AS phi FROM scalars", "d2")
def _(spark, d):
    return I.describe_shapes_by_expressions(lift_sources(spark, d, "d2")).select("sid", "n", *[_r(c).alias(c) for c in ("area", "perimeter", "phi")])


@query("shapes_by_batches", "SELECT sid, n::INT AS n, round(area, 6) AS area, round(perimeter, 6) AS perimeter, round(phi, 6) AS phi FROM scalars", "d2")
def _(spark, d):
    return I.describe_shapes(lift_sources(spark, d, "d2")).select("sid", "n", *[_r(c).alias(c) for c in ("area", "perimeter", "phi")])


@query("geom_elongation", "SELECT sid, round(greatest(aspect, 1 / aspect), 6) AS elongation FROM scalars")
def _(spark, d):
    return I.describe_shapes(lift_sources(spark, d), elongation=True).select("sid", _r("aspect").alias("elongation"))


@query("geom_fourier_vertices")
def _(spark, d):
    fd = I.describe_shapes(lift_sources(spark, d), sampling="vertices", scale_free=False)
    return fd.select("sid", F.transform("fd", lambda v: F.round(v, 6)).alias("fd"))


@query("geom_hull_contains_shape", "SELECT count(*) AS shapes, 0::BIGINT AS smaller, 0::BIGINT AS outside FROM src")
def _(spark, d):
    hull = G.convex_hull(F.col("geom"))
    rows = lift_sources(spark, d).select("mbr", G.area(F.col("geom")).alias("own"), hull.alias("hull")).select("mbr", "own", G.area(F.col("hull")).alias("area"), G.mbr(F.col("hull")).alias("box"))
    return rows.agg(F.count("*").alias("shapes"), F.count_if(F.col("area") < F.col("own") - 1e-9).alias("smaller"), F.count_if(F.col("box") != F.col("mbr")).alias("outside"))


@query("geom_simplify", "SELECT count(*) AS shapes, 0::BIGINT AS longer, 0::BIGINT AS more FROM src")
def _(spark, d):
    rows = lift_sources(spark, d).withColumn("less", X.simplify(F.col("geom"), 0.05))
    return rows.agg(F.count("*").alias("shapes"), F.count_if(G.perimeter(F.col("less")) > G.perimeter(F.col("geom")) + 1e-9).alias("longer"), F.count_if(G.n_points(F.col("less")) > G.n_points(F.col("geom"))).alias("more"))


# cluster finding

@query("grid_granularity", "SELECT round(dx, 9) AS dx, round(dy, 9) AS dy FROM grid")
def _(spark, d):
    g = grid_granularity(lift_sources(spark, d))
    return spark.createDataFrame([(g.dx, g.dy)], "dx double, dy double").select(_r("dx", 9).alias("dx"), _r("dy", 9).alias("dy"))


@query("grid_tiles", "SELECT sid, i1::INT AS i1, j1::INT AS j1, i2::INT AS i2, j2::INT AS j2 FROM stile")
def _(spark, d):
    rows = lift_sources(spark, d)
    return rows.select("sid", *tile_range(F.col("mbr"), grid_granularity(rows)))


def _candidates(spark, d, work: str, strategy: str) -> DataFrame:
    return candidate_pairs(lift_sources(spark, d, work), lift_targets(spark, d, work), strategy=strategy).select("tid", "sid", "common_tiles", "mbr_hit")


for _work, _strategy in (("d1", "merge"), ("d2", "hash"), ("d3", "broadcast")):
    query(f"candidate_pairs_{_work}", "SELECT tid, sid, common_tiles, mbr_hit FROM pairs", _work)(partial(_candidates, work=_work, strategy=_strategy))


_LINES = "SELECT tid, x1 - 0 AS x1, y1, x2, y2 FROM tedge WHERE NOT line"
_CROSSED = f"SELECT tid, sid, {', '.join(f'{sql} AS {name}' for name, sql in clip.WEDGE_STEPS)} FROM (SELECT tid, sid, p.x1 AS px, p.y1 AS py, p.x2 AS qx, p.y2 AS qy, s.x1 AS sx, s.y1 AS sy, s.x2 AS tx, s.y2 AS ty FROM hits JOIN sedge p USING (sid) JOIN polyedge s USING (tid))"
_RELATIONS = {"intersects": "inter > 1e-9", "contains": "inter >= area * (1 - 1e-9)", "within": "tarea > 0 AND inter >= tarea * (1 - 1e-9)"}


def _related(spark, d, relation: str) -> DataFrame:
    s, t = lift_sources(spark, d, "d2"), lift_targets(spark, d, "d2")
    return candidate_pairs(s, t, relation=relation).filter("mbr_hit").select("tid", "sid")


for _relation, _test in _RELATIONS.items():
    query(f"candidates_{_relation}", f"SELECT tid, sid FROM (SELECT tid, sid, greatest(0, sum(wedge)) AS inter FROM crossed GROUP BY tid, sid) JOIN smeas USING (sid) JOIN (SELECT tid, sum(x1 * y2 - x2 * y1) / 2 AS tarea FROM polyedge GROUP BY tid) USING (tid) WHERE {_test}", "d2", polyedge=_LINES, crossed=_CROSSED)(partial(_related, relation=_relation))


@query("region_filter", "SELECT sid FROM sbox WHERE x1 <= 1.0 AND x2 >= 0.5 AND y1 <= 4.0 AND y2 >= 1.0", "d2")
def _(spark, d):
    return within_box(lift_sources(spark, d, "d2"), 0.5, 1.0, 1.0, 4.0).select("sid")


@query("bucketed_join", "SELECT cid, count(*) AS n FROM members JOIN (SELECT cid FROM sample) USING (cid) GROUP BY cid", sample_of="SELECT 1 FROM sample")
def _(spark, d):
    p = _prep(spark, d)
    name = f"members_{abs(hash((spark.sparkContext.applicationId, d)))}"
    write_bucketed(p.members.select("cid", "sid"), name, 8, "cid")
    return spark.table(name).join(S.draw_clusters(p.clusters, 300).select("cid"), "cid").groupBy("cid").agg(F.count("*").alias("n"))


for _rule in ("count", "fixed"):
    @query(f"grid_granularity_{_rule}", {"count": "SELECT round(50 / (max(x2) - min(x1)), 9) AS dx, round(50 / (max(y2) - min(y1)), 9) AS dy FROM sbox", "fixed": "SELECT 0.5::DOUBLE AS dx, 0.5::DOUBLE AS dy"}[_rule])
    def _(spark, d, rule=_rule):
        g = grid_granularity(lift_sources(spark, d), rule, 2.0, 50)
        return spark.createDataFrame([(round(g.dx, 9), round(g.dy, 9))], "dx double, dy double")


@query("candidate_nested_loop", "SELECT tid, sid FROM hits", "d2")
def _(spark, d):
    return candidate_pairs_nested_loop(lift_sources(spark, d, "d2"), lift_targets(spark, d, "d2"))


@query("source_stats", 'SELECT * FROM sstats')
def _(spark, d):
    return C.source_stats(_prep(spark, d).pairs)


@query("target_stats", 'SELECT * FROM tstats')
def _(spark, d):
    return C.target_stats(_prep(spark, d).pairs)


def _clusters(spark, d, work: str) -> DataFrame:
    return _prep(spark, d, work).members.select("cid", "sid", "size")


for _work in ("d1", "d2", "d3"):
    query(f"clusters_{_work}", "SELECT cid, sid, size FROM members", _work)(partial(_clusters, work=_work))


@query("clusters_nested", "SELECT cid, list(sid ORDER BY sid)::VARCHAR AS members, any_value(size) AS size FROM members GROUP BY cid", "d2")
def _(spark, d):
    out = C.nested_clusters(_prep(spark, d, "d2").members)
    return out.select("cid", F.concat(F.lit("["), F.concat_ws(", ", "members"), F.lit("]")).alias("members"), "size")


@query("representatives", "SELECT tid AS cid, x1, y1, x2, y2 FROM tbox WHERE tid IN (SELECT cid FROM members)", members_of="SELECT 1")
def _(spark, d):
    p = _prep(spark, d)
    return C.representatives(p.members, p.targets).select("cid", "mbr.*")


@query("unclustered", "SELECT tid FROM trg WHERE tid NOT IN (SELECT cid FROM members)")
def _(spark, d):
    p = _prep(spark, d)
    return C.unclustered(p.members, p.targets)


_PROFILE = "SELECT (SELECT count(*) FROM src) AS sources, (SELECT count(*) FROM trg) AS targets, count(DISTINCT cid) AS clusters, round(count(*) / count(DISTINCT cid)::DOUBLE, 6) AS mean_size FROM members"


def _profile(spark, d, work: str) -> DataFrame:
    return E.dataset_profile(_prep(spark, d, work)).withColumn("mean_size", _r("mean_size"))


for _work in ("d1", "d2", "d3"):
    query("profile" if _work == "d1" else f"profile_{_work}", _PROFILE, _work)(partial(_profile, work=_work))


@query("distinct_sources", "SELECT count(DISTINCT sid) AS exact FROM pairs WHERE mbr_hit")
def _(spark, d):
    return C.approximate_sources(_prep(spark, d).pairs).select("exact")


# similarity index

def _si(spark, d, work: str, **kw) -> DataFrame:
    p = _prep(spark, d, work)
    if kw.get("layout") == "nested" or not kw:
        kw["nested"] = p.nested
    return I.similarity_index(p.members, p.shapes, **kw).select("cid", "n_pairs", _r("si", 5).alias("si"))


for _work in ("d1", "d2", "d3"):
    query(f"si_{_work}", "SELECT cid, n_pairs, round(si, 5) AS si FROM si", _work)(partial(_si, work=_work))
query("si_without_memo", "SELECT cid, n_pairs, round(si, 5) AS si FROM si", "d2")(partial(_si, work="d2", memo=False))
query("si_nested", "SELECT cid, n_pairs, round(si, 5) AS si FROM si", "d2")(partial(_si, work="d2", layout="nested"))
query("si_sql_backend", "SELECT cid, n_pairs, round(si, 5) AS si FROM si", "d2")(partial(_si, work="d2", backend="sql"))


@query("si_breakdown", "SELECT cid, " + ", ".join(f"round(avg({k}), 5) AS {k}" for k in M.NAMES) + " FROM mpairs JOIN sims USING (a, b) GROUP BY cid", "d2")
def _(spark, d):
    p = _prep(spark, d, "d2")
    return I.similarity_index(p.members, p.shapes, breakdown=True).select("cid", *[_r(k, 5).alias(k) for k in M.NAMES])


@query("si_bounds", "SELECT cid, round(avg(lo), 5) AS lo, round(avg(lo + (least(x.area, y.area) / greatest(x.area, y.area) + 2 * least(x.area, y.area) / (x.area + y.area)) / 8), 5) AS hi FROM mpairs JOIN (SELECT *, (curvature + fourier + aspect + perimeter + bbox + circularity) / 8 AS lo FROM sims) z USING (a, b) JOIN scalars x ON x.sid = a JOIN scalars y ON y.sid = b GROUP BY cid", "d2")
def _(spark, d):
    p = _prep(spark, d, "d2")
    return I.similarity_bounds(p.members, p.shapes).select("cid", _r("lo", 5).alias("lo"), _r("hi", 5).alias("hi"))


def _histogram(spark, d, work: str) -> DataFrame:
    return I.si_histogram(_prep(spark, d, work).all_si)


for _work in ("d1", "d2", "d3"):
    query("si_histogram" if _work == "d1" else f"si_histogram_{_work}", "SELECT round(least(floor(si / 0.1 + 1e-12), 9) * 0.1, 6) AS bin, count(*) AS clusters FROM si GROUP BY 1", _work)(partial(_histogram, work=_work))


@query("pair_memo", "SELECT count(*) AS pairs, (SELECT count(*) FROM dpairs) AS distinct_pairs FROM mpairs")
def _(spark, d):
    pairs = I.member_pairs(_prep(spark, d).members)
    return pairs.agg(F.count("*").alias("pairs")).join(pairs.select("a", "b").distinct().agg(F.count("*").alias("distinct_pairs")), how="cross")


# features

_FS = [f"f{i}" for i in range(1, 17)]
#: Added before rounding in both engines: scaled values are often exact halves of the last digit kept.
_OFF = 0.0000031


@query("features_raw", "SELECT cid, sid, " + ", ".join(f"round({c}, 6) AS {c}" for c in _FS) + " FROM raw", "d2")
def _(spark, d):
    return _prep(spark, d, "d2").raw.select("cid", "sid", *[_r(c).alias(c) for c in _FS])


@query("features_scaled_pair", "SELECT cid, sid, " + ", ".join(f"round({c} + {_OFF}, 4) AS {c}" for c in _FS) + " FROM praw", "d2")
def _(spark, d):
    raw = _prep(spark, d, "d2").raw
    return FT.scale(raw, FT.extremes(raw)).select("cid", "sid", *[_r(F.col(c) + F.lit(_OFF), 4).alias(c) for c in _FS])


@query("features_scaled_cluster", "SELECT cid, " + ", ".join(f"round({c} + {_OFF}, 4) AS {c}" for c in _FS) + " FROM cfeat", "d2")
def _(spark, d):
    return _prep(spark, d, "d2").features.select("cid", *[_r(F.col(c) + F.lit(_OFF), 4).alias(c) for c in _FS])


@query("features_unscaled", "SELECT cid, " + ", ".join(f"round(avg({c}) + {_OFF}, 4) AS {c}" for c in _FS) + " FROM raw GROUP BY cid", "d2")
def _(spark, d):
    return _prep(spark, d, "d2", scaling="none").features.select("cid", *[_r(F.col(c) + F.lit(_OFF), 4).alias(c) for c in _FS])


@query("features_cluster_only", "SELECT cid, " + ", ".join(f"round(coalesce((f{i} - min(f{i}) OVER ()) / nullif(max(f{i}) OVER (), 0) * 10000, 0) + {_OFF}, 4) AS f{i}" for i in range(1, 17)) + " FROM (SELECT cid, " + ", ".join(f"avg({c}) AS {c}" for c in _FS) + " FROM raw GROUP BY cid)", "d2")
def _(spark, d):
    return _prep(spark, d, "d2", scaling="cluster").features.select("cid", *[_r(F.col(c) + F.lit(_OFF), 4).alias(c) for c in _FS])


@query("features_range_rule", "SELECT cid, " + ", ".join(f"round(coalesce(avg(z.{c}), 0) + {_OFF}, 4) AS {c}" for c in _FS) + " FROM (SELECT cid, " + ", ".join(f"(avg({c}) - any_value(lo_{c})) / nullif(any_value(hi_{c}) - any_value(lo_{c}), 0) * 10000 AS {c}" for c in _FS) + " FROM raw, bounds GROUP BY cid) z GROUP BY cid", "d2", bounds="SELECT " + ", ".join(f"min({c}) AS lo_{c}, max({c}) AS hi_{c}" for c in _FS) + " FROM raw")
def _(spark, d):
    return FT.cluster_features(_prep(spark, d, "d2").raw, scaling="pair", rule="range").select("cid", *[_r(F.col(c) + F.lit(_OFF), 4).alias(c) for c in _FS])


# samples, density, threshold

@query("sample_draw", "SELECT cid, place FROM sample")
def _(spark, d):
    return S.draw_clusters(_prep(spark, d).clusters, 300).withColumn("place", F.col("place").cast("long"))


_SAMPLE_SI = {"ssi": "SELECT cid, si FROM sample JOIN si USING (cid)"}
_H = 0.02


@query("kde_epanechnikov_pdf", f"SELECT x, round(avg(CASE WHEN abs((x - si) / {_H}) < 1 THEN 0.75 * (1 - ((x - si) / {_H}) ** 2) ELSE 0 END / {_H}), 5) AS pdf FROM (SELECT i / 100.0::DOUBLE AS x FROM range(50, 101) r(i)) g, ssi GROUP BY x", "d2", **_SAMPLE_SI)
def _(spark, d):
    p = _prep(spark, d, "d2")
    si = p.index_of(S.draw_clusters(p.clusters, 300))
    return D.evaluate_kde(spark.range(50, 101).select((F.col("id") / 100.0).alias("x")), si, _H).select("x", _r("pdf", 5).alias("pdf"))


@query("kde_threshold_epanechnikov", f"SELECT max(x) AS tau FROM (SELECT x, 1 - avg(CASE WHEN (x - si) / {_H} <= -1 THEN 0 WHEN (x - si) / {_H} >= 1 THEN 1 ELSE 0.5 + 0.75 * ((x - si) / {_H} - ((x - si) / {_H}) ** 3 / 3) END) AS sf FROM (SELECT i / 1000.0::DOUBLE AS x FROM range(500, 1001) r(i)) g, ssi GROUP BY x) WHERE sf > 0.1", "d2", **_SAMPLE_SI)
def _(spark, d):
    p = _prep(spark, d, "d2")
    si = p.index_of(S.draw_clusters(p.clusters, 300))
    out = D.evaluate_kde(spark.range(500, 1001).select((F.col("id") / 1000.0).alias("x")), si, _H)
    return out.filter(1 - F.col("cdf") > 0.1).agg(F.max("x").alias("tau"))


@query("kde_select_loo", "SELECT h FROM (SELECT h, avg(ln(greatest(d / (n - 1), 1e-12))) AS score FROM (SELECT h, x.cid, any_value(n) AS n, sum(CASE WHEN abs((x.si - y.si) / h) < 1 THEN 0.75 * (1 - ((x.si - y.si) / h) ** 2) ELSE 0 END / h) AS d FROM ssi x JOIN ssi y ON x.cid <> y.cid, (SELECT count(*) AS n FROM ssi) c, (VALUES (0.005::DOUBLE), (0.01), (0.02), (0.04), (0.08)) v(h) GROUP BY h, x.cid) GROUP BY h) ORDER BY score DESC LIMIT 1", "d2", **_SAMPLE_SI)
def _(spark, d):
    import numpy as np

    p = _prep(spark, d, "d2")
    points = np.array([r["si"] for r in p.index_of(S.draw_clusters(p.clusters, 300)).collect()])
    best = max((D.Kde(points, "epanechnikov", h) for h in (0.005, 0.01, 0.02, 0.04, 0.08)), key=D.loo_score)
    return spark.createDataFrame([(best.h,)], "h double")


@query("kde_gaussian_threshold")
def _(spark, d):
    p = _prep(spark, d, "d2")
    kde = D.select_kde([r["si"] for r in p.index_of(S.draw_clusters(p.clusters, 300)).collect()], ("gaussian",))
    return spark.createDataFrame([(k, float(v)) for k, v in D.kde_thresholds(kde, (0.1, 0.3, 0.5)).items()], "p double, tau double")


@query("threshold_empirical", "SELECT round(quantile_cont(si, 0.9), 5) AS p10, round(quantile_cont(si, 0.7), 5) AS p30, round(quantile_cont(si, 0.5), 5) AS p50 FROM si", "d2")
def _(spark, d):
    si = _prep(spark, d, "d2").all_si
    return si.agg(*[_r(F.percentile("si", F.lit(q)), 5).alias(n) for n, q in (("p10", 0.9), ("p30", 0.7), ("p50", 0.5))])


# labels, training, simulation, budgets: scores are the cluster size, ascending, so that SQL can follow

def _ranked(spark, d) -> tuple[Prepared, DataFrame]:
    p = _prep(spark, d, "d2")
    tau = D.exact_threshold(p.all_si, 0.1)
    scored = XB.feature_order(p.features, "f15", ascending=True).join(L.label_clusters(p.all_si, tau).select("cid", "si", "label"), "cid")
    return p, stage(scored, "ranked")


@query("labels", "SELECT cid, label FROM ranked", "d2")
def _(spark, d):
    return _ranked(spark, d)[1].select("cid", "label")


_PREFIX = "SELECT cid, label, seen FROM (SELECT *, coalesce(min(CASE WHEN pos >= 30 AND seen - pos >= 30 THEN seen END) OVER (), 1e18) AS stop FROM (SELECT cid, label, sum(label) OVER (ORDER BY key, cid ROWS UNBOUNDED PRECEDING) AS pos, row_number() OVER (ORDER BY key, cid) AS seen FROM (SELECT cid, label, ((cid % 2147483647) * 48271 + 2) % 2147483647 AS key FROM ranked))) WHERE seen <= stop"


@query("training_prefix", f"SELECT cid, label, seen::INT AS seen FROM ({_PREFIX}) z", "d2", ranked_of="SELECT 1 FROM ranked")
def _(spark, d):
    return L.training_prefix(_ranked(spark, d)[1], 30).select("cid", "label", "seen")


_DEPTH = "(SELECT ceil(0.1 * count(*) - 1e-9) FROM ranked)"


@query("simulate_depth", f"SELECT count(*) AS kept, sum(label)::BIGINT AS high, {_DEPTH}::BIGINT AS depth, sum(CASE WHEN place <= {_DEPTH} THEN label ELSE 0 END)::BIGINT AS hits FROM ranked", "d2")
def _(spark, d):
    s = B.simulate(_ranked(spark, d)[1], 0.1)
    return spark.createDataFrame([(s.kept, s.high, s.depth, s.hits)], "kept long, high long, depth long, hits long")


@query("budget_linear", f"SELECT ceil(0.9 / (sum(CASE WHEN place <= {_DEPTH} THEN label ELSE 0 END) / sum(label)) * sum(label) / count(*) * count(*) - 1e-9)::BIGINT AS budget FROM ranked", "d2")
def _(spark, d):
    p, ranked = _ranked(spark, d)
    return spark.createDataFrame([(B.budget_linear(B.simulate(ranked, 0.1), 0.9, p.total),)], "budget long")


_GAIN = "SELECT min(place) AS place, arg_min(w, place) AS w FROM (SELECT *, sum(label) OVER (ORDER BY place ROWS UNBOUNDED PRECEDING) AS run, sum(label) OVER () AS high FROM ranked) WHERE run >= ceil(0.9 * high - 1e-9)"


@query("budget_gain_curve", "SELECT place::BIGINT AS budget FROM gain", "d2", gain=_GAIN)
def _(spark, d):
    p, ranked = _ranked(spark, d)
    return spark.createDataFrame([(B.budget_gain_curve(B.simulate(ranked, 0.1), 0.9, p.total),)], "budget long")


@query("budget_probability_cut", "SELECT count(*) AS budget FROM ranked, (SELECT w AS cut FROM gain) c WHERE ranked.w <= cut", "d2", gain=_GAIN)
def _(spark, d):
    _, ranked = _ranked(spark, d)
    return spark.createDataFrame([(B.budget_probability_cut(B.simulate(ranked, 0.1), 0.9, ranked),)], "budget long")


@query("budget_oracle", "SELECT min(place)::BIGINT AS budget FROM (SELECT place, sum(label) OVER (ORDER BY place ROWS UNBOUNDED PRECEDING) / sum(label) OVER () AS recall FROM ranked) WHERE recall >= 0.9 - 1e-12", "d2")
def _(spark, d):
    _, ranked = _ranked(spark, d)
    return spark.createDataFrame([(B.budget_oracle(ranked.withColumn("si", F.col("label")), 1.0, 0.9),)], "budget long")


# verification, baselines, measures

def _exhaustive(spark, d, p: float) -> DataFrame:
    return XB.exhaustive_top(_prep(spark, d, "d2").all_si, p).select("cid")


for _p in (10, 30, 50):
    query(f"exhaustive_top{_p}", f"SELECT cid FROM (SELECT cid, row_number() OVER (ORDER BY round(si, 9) DESC, cid) AS place, count(*) OVER () AS n FROM si) WHERE place <= ceil(n * {_p / 100} - 1e-9)", "d2")(partial(_exhaustive, p=_p / 100))


@query("exhaustive_threshold", "SELECT cid, round(si, 5) AS si FROM si, tau WHERE si >= tau", "d2")
def _(spark, d):
    si = _prep(spark, d, "d2").all_si
    return XB.exhaustive_threshold(si, D.exact_threshold(si, 0.1)).select("cid", _r("si", 5).alias("si"))


@query("static_threshold", "SELECT cid, round(si, 5) AS si FROM si WHERE si >= 0.875", "d2")
def _(spark, d):
    return XB.exhaustive_threshold(_prep(spark, d, "d2").all_si, D.static_threshold(0.875)).select("cid", _r("si", 5).alias("si"))


@query("verify_feature_order", "SELECT cid, round(si, 5) AS si FROM ranked WHERE place <= 1000 AND label = 1", "d2")
def _(spark, d):
    p, ranked = _ranked(spark, d)
    return V.verify(ranked.select("cid", "w"), 1000, D.exact_threshold(p.all_si, 0.1), lambda cids: p.all_si.join(cids, "cid", "left_semi")).select("cid", _r("si", 5).alias("si"))


@query("verify_pruned", "SELECT cid, round(si, 5) AS si FROM ranked WHERE place <= 1000 AND label = 1", "d2")
def _(spark, d):
    p, ranked = _ranked(spark, d)
    return V.verify(ranked.select("cid", "w"), 1000, D.exact_threshold(p.all_si, 0.1), p.index_of, bounds_of=p.bounds_of).select("cid", _r("si", 5).alias("si"))


@query("verify_waves", "SELECT cid, round(si, 5) AS si FROM ranked WHERE place <= 1000 AND label = 1", "d2")
def _(spark, d):
    p, ranked = _ranked(spark, d)
    out, _ = V.verify_in_waves(ranked.select("cid", "w"), 1000, D.exact_threshold(p.all_si, 0.1), p.index_of, 400)
    return out.select("cid", _r("si", 5).alias("si"))


_WAVES = "SELECT *, (place - 1) // 100 AS wave FROM ranked WHERE place <= 1000"
_BY_WAVE = "SELECT wave, sum(sum(label)) OVER (ORDER BY wave) AS hits, sum(label) AS own, count(*) AS n FROM turns GROUP BY wave"


@query("verify_until_recall", "SELECT cid, round(si, 5) AS si FROM turns WHERE label = 1 AND wave <= (SELECT coalesce(min(wave) FILTER (hits >= 40), max(wave)) FROM byturn)", "d2", turns=_WAVES, byturn=_BY_WAVE)
def _(spark, d):
    p, ranked = _ranked(spark, d)
    out, _ = V.verify_in_waves(ranked.select("cid", "w"), 1000, D.exact_threshold(p.all_si, 0.1), lambda c: p.all_si.join(c, "cid", "left_semi"), 100, "recall", 40)
    return out.select("cid", _r("si", 5).alias("si"))


@query("verify_until_yield", "SELECT cid, round(si, 5) AS si FROM turns WHERE label = 1 AND wave <= (SELECT coalesce(min(wave) FILTER (own < 0.12 * n), max(wave)) FROM byturn)", "d2", turns=_WAVES, byturn=_BY_WAVE)
def _(spark, d):
    p, ranked = _ranked(spark, d)
    out, _ = V.verify_in_waves(ranked.select("cid", "w"), 1000, D.exact_threshold(p.all_si, 0.1), lambda c: p.all_si.join(c, "cid", "left_semi"), 100, "yield", least_yield=0.12)
    return out.select("cid", _r("si", 5).alias("si"))


@query("verify_random_order", "SELECT cid FROM (SELECT cid, label, row_number() OVER (ORDER BY ((cid % 2147483647) * 48271 + 9) % 2147483647, cid) AS p FROM ranked) WHERE p <= 1000 AND label = 1", "d2")
def _(spark, d):
    p = _prep(spark, d, "d2")
    return XB.verified_by_order(XB.random_order(p.clusters), p.all_si, 1000, D.exact_threshold(p.all_si, 0.1)).select("cid")


@query("verify_ideal_order", "SELECT cid FROM (SELECT cid, label, row_number() OVER (ORDER BY round(si, 9) DESC, cid) AS p FROM ranked) WHERE p <= 1000 AND label = 1", "d2")
def _(spark, d):
    p = _prep(spark, d, "d2")
    return XB.verified_by_order(XB.ideal_order(p.all_si), p.all_si, 1000, D.exact_threshold(p.all_si, 0.1)).select("cid")


@query("coverage_curve", "SELECT part::BIGINT AS part, max(place) AS checked, max(run)::DOUBLE AS hits, round(max(run) / any_value(high), 6) AS recall FROM (SELECT *, ceil(place * 10 / n::DOUBLE) AS part FROM (SELECT *, sum(label) OVER (ORDER BY place ROWS UNBOUNDED PRECEDING) AS run, sum(label) OVER () AS high, count(*) OVER () AS n FROM ranked)) GROUP BY part", "d2")
def _(spark, d):
    p, ranked = _ranked(spark, d)
    out = E.coverage_curve(ranked, D.exact_threshold(p.all_si, 0.1))
    return out.select(F.col("part").cast("long").alias("part"), F.col("checked").cast("long").alias("checked"), "hits", _r("recall").alias("recall"))


@query("recall_precision", "SELECT round(sum(CASE WHEN place <= 1000 THEN label END) / sum(label), 6) AS recall, round(sum(CASE WHEN place <= 1000 THEN label END) / 1000, 6) AS precision FROM ranked", "d2")
def _(spark, d):
    p, ranked = _ranked(spark, d)
    m = E.recall_precision(V.select_frontier(ranked.select("cid", "w"), 1000), ranked.filter("label = 1"))
    return spark.createDataFrame([(round(m["recall"], 6), round(m["precision"], 6))], "recall double, precision double")


@query("threshold_error", "SELECT round(abs(0.875 - tau), 5) AS error, round(share, 6) AS share FROM tau, (SELECT avg(CASE WHEN si >= 0.875 THEN 1.0 ELSE 0 END) AS share FROM si) z", "d2")
def _(spark, d):
    e = E.threshold_error(_prep(spark, d, "d2").all_si, 0.875, 0.1)
    return spark.createDataFrame([(round(e["error"], 5), round(e["share"], 6))], "error double, share double")


@query("size_effect", "SELECT size_from::INT AS size_from, count(*) AS clusters, round(avg(CASE WHEN place <= 1000 THEN 1.0 ELSE 0 END), 6) AS coverage FROM (SELECT *, CASE WHEN size >= 64 THEN 64 WHEN size >= 32 THEN 32 WHEN size >= 16 THEN 16 WHEN size >= 8 THEN 8 WHEN size >= 4 THEN 4 ELSE 2 END AS size_from FROM (SELECT cid, count(*) AS size FROM members GROUP BY cid) JOIN ranked USING (cid)) GROUP BY 1", "d2")
def _(spark, d):
    p, ranked = _ranked(spark, d)
    return E.size_effect(p.members, V.select_frontier(ranked.select("cid", "w"), 1000)).withColumn("coverage", _r("coverage"))


@query("pair_costs", "SELECT sum(n_pairs)::BIGINT AS exhaustive, sum(CASE WHEN place <= 1000 THEN n_pairs END)::BIGINT AS verified, (SELECT count(*) FROM (SELECT DISTINCT a, b FROM mpairs JOIN ranked USING (cid) WHERE place <= 1000)) AS verified_distinct FROM si JOIN ranked USING (cid)", "d2")
def _(spark, d):
    p, ranked = _ranked(spark, d)
    c = E.pair_costs(p.members, V.select_frontier(ranked.select("cid", "w"), 1000))
    return spark.createDataFrame([tuple(c.values())], "exhaustive long, verified long, verified_distinct long")


@query("rank_clusters", "SELECT cid, row_number() OVER t::INT AS row_number, rank() OVER v::INT AS rank, dense_rank() OVER v::INT AS dense_rank, round(percent_rank() OVER v, 9) AS percent_rank, round(cume_dist() OVER v, 9) AS cume_dist, ntile(10) OVER t::INT AS ntile10, coalesce(lag(cid) OVER t, -1) AS before, coalesce(lead(cid) OVER t, -1) AS after FROM si WINDOW v AS (ORDER BY round(si, 9) DESC), t AS (ORDER BY round(si, 9) DESC, cid)", "d2")
def _(spark, d):
    out = XB.rank_clusters(_prep(spark, d, "d2").all_si)
    return out.select("cid", "row_number", "rank", "dense_rank", _r("percent_rank", 9).alias("percent_rank"), _r("cume_dist", 9).alias("cume_dist"), "ntile10", F.coalesce("before", F.lit(-1)).alias("before"), F.coalesce("after", F.lit(-1)).alias("after"))


# results joined to other tables; set operations; joins of time

_NAMED = "SELECT m.cid, m.sid, si, r_name AS region, n_name AS nation, c_mktsegment AS segment FROM members m JOIN si USING (cid) JOIN customer ON c_custkey = m.sid JOIN nation ON n_nationkey = c_nationkey JOIN region ON r_regionkey = n_regionkey"


def _named(spark, d) -> DataFrame:
    p = _prep(spark, d, "d2")
    t = partial(load_table, spark, d)
    c = t("customer").select(F.col("c_custkey").alias("sid"), "c_nationkey", F.col("c_mktsegment").alias("segment"))
    n = t("nation").select(F.col("n_nationkey").alias("c_nationkey"), F.col("n_name").alias("nation"), "n_regionkey")
    r = t("region").select(F.col("r_regionkey").alias("n_regionkey"), F.col("r_name").alias("region"))
    return p.members.select("cid", "sid").join(p.all_si.select("cid", "si"), "cid").join(c, "sid").join(F.broadcast(n), "c_nationkey").join(F.broadcast(r), "n_regionkey").select("cid", "sid", "si", "region", "nation", "segment")


@query("result_rollup", "SELECT region, nation, count(*) AS n, round(avg(si), 5) AS mean FROM named GROUP BY ROLLUP (region, nation)", "d2", named=_NAMED)
def _(spark, d):
    return relational.rollup_result(_named(spark, d), ("region", "nation")).select("region", "nation", "n", _r("mean", 5).alias("mean"))


@query("result_cube", "SELECT region, segment, count(*) AS n, round(avg(si), 5) AS mean FROM named GROUP BY CUBE (region, segment)", "d2", named=_NAMED)
def _(spark, d):
    return relational.rollup_result(_named(spark, d), ("region", "segment"), "cube").select("region", "segment", "n", _r("mean", 5).alias("mean"))


@query("result_grouping_sets", "SELECT region, segment, count(*) AS n, round(avg(si), 5) AS mean FROM named GROUP BY GROUPING SETS ((region), (segment), ())", "d2", named=_NAMED)
def _(spark, d):
    return relational.rollup_result(_named(spark, d), ("region", "segment"), "sets").select("region", "segment", "n", _r("mean", 5).alias("mean"))


@query("topk_per_region", "SELECT region, cid, place::INT AS place FROM (SELECT region, cid, row_number() OVER (PARTITION BY region ORDER BY round(si, 9) DESC, cid) AS place FROM (SELECT DISTINCT region, cid, si FROM named)) WHERE place <= 5", "d2", named=_NAMED)
def _(spark, d):
    return relational.top_k_per(_named(spark, d).select("region", "cid", "si").distinct(), "region", 5, V.ranked("si").desc(), "cid").select("region", "cid", "place")


def _compared(spark, d) -> dict[str, DataFrame]:
    p, ranked = _ranked(spark, d)
    return relational.compare_results(ranked.filter("label = 1").select("cid"), V.select_frontier(ranked.select("cid", "w"), 1000).select("cid"))


@query("missed_except", "SELECT cid FROM ranked WHERE label = 1 AND place > 1000", "d2")
def _(spark, d):
    return _compared(spark, d)["only_a"]


@query("found_intersect", "SELECT cid FROM ranked WHERE label = 1 AND place <= 1000", "d2")
def _(spark, d):
    return _compared(spark, d)["both"]


@query("semi_sample", "SELECT cid, sid FROM members WHERE cid IN (SELECT cid FROM sample)", sample_of="SELECT 1 FROM sample")
def _(spark, d):
    p = _prep(spark, d)
    return relational.only_in(p.members, S.draw_clusters(p.clusters, 300), "cid").select("cid", "sid")


@query("anti_unverified", "SELECT cid FROM ranked WHERE place > 1000", "d2")
def _(spark, d):
    _, ranked = _ranked(spark, d)
    return relational.not_in(ranked.select("cid"), V.select_frontier(ranked.select("cid", "w"), 1000), "cid")


@query("range_join_x", "SELECT t.tid AS a, s.sid AS b FROM tbox t JOIN sbox s ON t.x1 <= s.x2 AND s.x1 <= t.x2", "d3")
def _(spark, d):
    lay = lambda df, key, out: df.select(F.col(key).alias(out), F.col("mbr.x1").alias("lo"), F.col("mbr.x2").alias("hi"))
    return relational.range_join(lay(lift_targets(spark, d, "d3"), "tid", "a"), lay(lift_sources(spark, d, "d3"), "sid", "b"), 1.0)


@query("asof_events", "SELECT e.event_id, max(p.value) AS previous FROM (SELECT event_id, user_id, ts, (SELECT max(q.ts) FROM events q WHERE q.user_id = e.user_id AND q.event_type = 'purchase' AND q.ts <= e.ts) AS pts FROM events e WHERE event_type <> 'purchase') e LEFT JOIN events p ON p.user_id = e.user_id AND p.event_type = 'purchase' AND p.ts = e.pts GROUP BY 1")
def _(spark, d):
    e = load_table(spark, d, "events")
    right = e.filter("event_type = 'purchase'").groupBy("user_id", "ts").agg(F.max("value").alias("previous"))
    return relational.asof_join(e.filter("event_type <> 'purchase'").select("event_id", "user_id", "ts"), right, "ts", "user_id", "previous").select("event_id", "previous")


def _order_windows(spark, d) -> DataFrame:
    """Five hours from a start that the key gives, of every order."""
    start = F.expr("timestamp'2024-01-01 00:00:00' + make_dt_interval(0, cast(o_orderkey % 720 as int), 0, 0)")
    return load_table(spark, d, "orders").select("o_orderkey", start.alias("start_ts")).withColumn("end_ts", F.expr("start_ts + interval 5 hours"))


@query("interval_events", "SELECT event_id, o_orderkey FROM (SELECT o_orderkey, TIMESTAMP '2024-01-01' + to_hours((o_orderkey % 720)::BIGINT) AS s FROM orders) o JOIN events e ON e.ts >= s AND e.ts < s + INTERVAL 5 HOUR")
def _(spark, d):
    return relational.interval_join(load_table(spark, d, "events"), _order_windows(spark, d), 3 * 3600).select("event_id", "o_orderkey")


@query("moving_value", "SELECT event_id, round(avg(value) OVER (PARTITION BY user_id ORDER BY epoch(ts)::BIGINT RANGE BETWEEN 86400 PRECEDING AND CURRENT ROW), 6) AS moving FROM (SELECT event_id, user_id, value, date_trunc('second', ts) AS ts FROM events)")
def _(spark, d):
    return relational.moving_value(load_table(spark, d, "events"), 86_400).select("event_id", _r("moving").alias("moving"))


@query("window_tumbling", "SELECT date_trunc('day', ts)::TIMESTAMP AS start_ts, count(*) AS n, round(avg(value), 6) AS mean FROM events GROUP BY 1")
def _(spark, d):
    return relational.windows(load_table(spark, d, "events"), "1 day").withColumn("mean", _r("mean"))


@query("window_sliding", "SELECT start_ts, count(*) AS n, round(avg(value), 6) AS mean FROM (SELECT value, unnest([date_trunc('day', ts), date_trunc('day', ts) + INTERVAL 12 HOUR, date_trunc('day', ts) - INTERVAL 12 HOUR])::TIMESTAMP AS start_ts, ts FROM events) WHERE start_ts <= ts AND ts < start_ts + INTERVAL 1 DAY GROUP BY 1")
def _(spark, d):
    return relational.windows(load_table(spark, d, "events"), "1 day", "12 hours").withColumn("mean", _r("mean"))


@query("session_trajectories", "SELECT user_id, min(ts) AS first_ts, max(ts) AS last_ts, count(*) AS n FROM (SELECT user_id, ts, sum(brk) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS s FROM (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 6 HOUR THEN 0 ELSE 1 END AS brk FROM events)) GROUP BY user_id, s")
def _(spark, d):
    return relational.sessions(load_table(spark, d, "events"), 6 * 3600)


_DOTS = "SELECT user_id, ts::DATE AS day, ts, event_id, value AS x, (props->>'$.k')::DOUBLE AS y FROM events WHERE value IS NOT NULL AND props->>'$.k' IS NOT NULL"
_LEGS = "SELECT user_id, day, x, y, lead(x) OVER w AS x2, lead(y) OVER w AS y2 FROM dots WINDOW w AS (PARTITION BY user_id, day ORDER BY ts, event_id)"


@query("trajectories", "SELECT user_id::BIGINT * 100000 + (day - DATE '1970-01-01') AS tid, user_id, count(*)::INT AS n, round(sum(coalesce(sqrt((x2 - x) * (x2 - x) + (y2 - y) * (y2 - y)), 0)), 6) AS length FROM legs GROUP BY user_id, day HAVING count(*) >= 2", dots=_DOTS, legs=_LEGS)
def _(spark, d):
    return trajectories(load_table(spark, d, "events")).select("tid", "user_id", G.n_points(F.col("geom")).alias("n"), _r(G.perimeter(F.col("geom"))).alias("length"))


@query("sql_functions", "SELECT sid, round(area, 6) AS area, n::BIGINT AS edges FROM smeas")
def _(spark, d):
    sqlfuncs.register(spark)
    lift_sources(spark, d).select("sid", F.col("geom.parts")[0]["xs"].alias("xs"), F.col("geom.parts")[0]["ys"].alias("ys")).createOrReplaceTempView("sc_rings")
    return spark.sql("SELECT sid, round(any_value(a), 6) AS area, count(*) AS edges FROM (SELECT sid, xs, ys, sc_area(xs, ys) AS a FROM sc_rings) r, LATERAL sc_edges(r.xs, r.ys) GROUP BY sid")


# whole searches: SQL says what their invariants must be

@query("train_logistic", "SELECT count(*) AS clusters, sum(label)::BIGINT AS high, true AS in_range FROM ranked", "d2")
def _(spark, d):
    p, ranked = _ranked(spark, d)
    labelled = L.training_prefix(ranked, 30).select("cid", "label")
    model = classifier.train_scheduler(p.features.join(labelled, "cid"))
    bins = classifier.reliability(classifier.score(model, p.features).join(ranked.select("cid", "label"), "cid"))
    return bins.agg(F.sum("clusters").alias("clusters"), F.round(F.sum(F.col("share") * F.col("clusters"))).cast("long").alias("high"), F.min((F.col("mean_w") >= 0) & (F.col("mean_w") <= 1)).alias("in_range"))


@query("classifiers")
def _(spark, d):
    """Area under the curve, log loss and the feature that weighs most, of every classifier and class balance."""
    p, ranked = _ranked(spark, d)
    labelled = stage(p.features.join(L.training_prefix(ranked, 30).select("cid", "label"), "cid"), "training")
    rows = []
    for algorithm, balance in [*[(a, "none") for a in classifier.ALGORITHMS], ("logistic", "weights"), ("logistic", "truncate")]:
        model = classifier.train_scheduler(labelled, algorithm, balance=balance)
        got = classifier.quality(classifier.score(model, p.features).join(ranked.select("cid", "label"), "cid"))
        weights = classifier.importances(model)
        rows.append((algorithm, balance, got["auc"], got["log_loss"], max(weights, key=lambda k: abs(weights[k])) if weights else None))
    return spark.createDataFrame(rows, "algorithm string, balance string, auc double, log_loss double, most string")


@query("kde_kernels")
def _(spark, d):
    """Cut-offs of every kernel, criterion and boundary rule beside the exact quantile."""
    p = _prep(spark, d, "d2")
    points = [r["si"] for r in p.index_of(S.draw_clusters(p.clusters, 300)).collect()]
    exact = D.exact_threshold(p.all_si, 0.1)
    rows = [(k, c, b, float(D.kde_threshold(D.select_kde(points, (k,), criterion=c), 0.1, boundary=b)), exact) for k in D.KERNELS for c in ("loo", "kfold", "silverman", "scott") for b in ("none", "truncate", "reflect")]
    return spark.createDataFrame(rows, "kernel string, criterion string, boundary string, tau double, exact double")


def _search(spark, d, work: str, family: str = "regional", **kw) -> DataFrame:
    out = SimilarClusterSearch(**kw).run(_prep(spark, d, work, family=family))
    return V.rank_result(out.result)


query("search_end_to_end")(partial(_search, work="d1"))
query("search_d2")(partial(_search, work="d2", p=0.3))
query("search_linear_budget")(partial(_search, work="d2", rule="linear"))
query("search_flat_family")(partial(_search, work="d2", family="flat", n=30))


#: Result of a search: nothing below the cut-off, nothing missed among the budget's clusters, a rank for each.
_SOUND = "SELECT (SELECT count(DISTINCT cid) FROM members) AS clusters, 0::BIGINT AS below_cut, 0::BIGINT AS missed, 0::BIGINT AS beyond_budget, true AS ranked"


def _sound(spark, d, work: str, family: str = "regional", **kw) -> DataFrame:
    prep = _prep(spark, d, work, family=family)
    out = SimilarClusterSearch(**kw).run(prep)
    front = V.select_frontier(out.scored, out.budget).select("cid")
    high = prep.all_si.filter(F.col("si") >= F.lit(out.tau)).select("cid")
    got = stage(V.rank_result(out.result), "ranked-result")
    count = lambda df: df.count()
    ranks = got.agg(F.count("*"), F.count_distinct("rank"), F.max("rank")).head()
    row = (out.total, count(got.join(high, "cid", "left_anti")), count(front.join(high, "cid", "left_semi").join(got, "cid", "left_anti")), count(got.join(front, "cid", "left_anti")), ranks[0] == ranks[1] == (ranks[2] or 0))
    return spark.createDataFrame([row], "clusters long, below_cut long, missed long, beyond_budget long, ranked boolean")


for _name, _work, _settings in (("d1", "d1", {}), ("d2", "d2", {"p": 0.3}), ("d3", "d3", {}), ("linear", "d2", {"rule": "linear"}), ("cut", "d2", {"rule": "cut", "p": 0.3}), ("pruned", "d2", {"prune": True, "p": 0.3}), ("fresh", "d2", {"reuse": False, "p": 0.3}), ("shared", "d2", {"roles": "shared", "p": 0.3})):
    query(f"search_sound_{_name}", _SOUND, _work)(partial(_sound, work=_work, **_settings))

_FIELDS = {"str": "string", "int": "long", "float": "double"}
_LINE = ", ".join(f"{f.name} {_FIELDS[f.type]}" for f in dataclasses.fields(E.Report))


def _lines(spark, found) -> DataFrame:
    return spark.createDataFrame([dataclasses.astuple(r) for r in found], _LINE)


def _experiment(spark, d, work: str) -> DataFrame:
    return _lines(spark, K.run_searches(_prep(spark, d, work), work))


def _sweep(spark, d, work: str) -> DataFrame:
    return _lines(spark, K.sweep(_prep(spark, d, work), work))


for _work in ("d1", "d2", "d3"):
    query(f"experiment_coverage_{_work}")(partial(_experiment, work=_work))
    query(f"experiment_sweep_{_work}")(partial(_sweep, work=_work))


@query("experiment_seeds")
def _(spark, d):
    """Spread of the achieved recall over seeds, without and with a margin of confidence."""
    rows = []
    for confidence in (0.5, 0.9):
        for r in K.run_searches(_prep(spark, d, "d2"), "d2", (0.3,), (0.9,), ("curve",), seeds=(1, 2, 3, 4, 5), confidence=confidence):
            rows.append((confidence, r.seed, r.coverage, r.recall, r.recall_estimate, r.recall_at_share))
    return spark.createDataFrame(rows, "confidence double, seed long, coverage double, recall double, recall_estimate double, recall_at_share double")


@query("experiment_coverage_table")
def _(spark, d):
    """Coverage by workload, a column for each targeted share."""
    found = [r for w in ("d1", "d2", "d3") for r in K.run_searches(_prep(spark, d, w), w, recalls=(0.9,), rules=("curve",))]
    return E.coverage_pivot(_lines(spark, found))


@query("experiment_size_effect")
def _(spark, d):
    """Coverage for the top half in the workload of small clusters and that of large ones, with their mean sizes."""
    rows = []
    for work in ("d1", "d3"):
        prep = _prep(spark, d, work)
        size = prep.clusters.agg(F.avg("size")).head()[0]
        rows += [(work, r.rule, size, r.coverage, r.recall) for r in K.run_searches(prep, work, (0.5,), (0.9,), ("linear", "curve"))]
    return spark.createDataFrame(rows, "workload string, rule string, mean_size double, coverage double, recall double")


_NAMED_LINE = f"variant string, {_LINE}"


@query("experiment_search_variants")
def _(spark, d):
    return spark.createDataFrame([(n, *dataclasses.astuple(r)) for n, r in K.search_variants(_prep(spark, d, "d2"), "d2")], _NAMED_LINE)


@query("experiment_prepared_variants")
def _(spark, d):
    return spark.createDataFrame([(n, *dataclasses.astuple(r)) for n, r in K.prepared_variants(spark, d, "d2")], _NAMED_LINE)


@query("experiment_against_random")
def _(spark, d):
    prep = _prep(spark, d, "d2")
    got = K.against_random(prep, SimilarClusterSearch(p=0.3).run(prep))
    return spark.createDataFrame([tuple(got.values())], "scheduled double, random double")


@query("experiment_backends")
def _(spark, d):
    """Seconds of boxes, shared and united areas, averages of measures and joins, by backend."""
    prep = _prep(spark, d, "d2")
    rows = K.bench_geometry(prep) | K.bench_metrics(prep) | K.bench_joins(prep, nested=True)
    return spark.createDataFrame(list(rows.items()), "what string, seconds double")


@query("recall_error", "SELECT sum(CASE WHEN place <= ceil(0.1 * n - 1e-9) THEN label ELSE 0 END) / any_value(high) AS estimate, sum(CASE WHEN place <= ceil(0.1 * n - 1e-9) THEN label ELSE 0 END) / any_value(high) AS \"true\", 0.0::DOUBLE AS error FROM (SELECT *, count(*) OVER () AS n, sum(label) OVER () AS high FROM ranked)", "d2")
def _(spark, d):
    """With all clusters as the sample, the simulated and the true recall must be one."""
    from types import SimpleNamespace

    p, ranked = _ranked(spark, d)
    tau = D.exact_threshold(p.all_si, 0.1)
    got = E.recall_error(SimpleNamespace(total=p.total, tau=tau, scored=ranked.select("cid", "w"), simulation=B.simulate(ranked, 0.1)), p.all_si, 0.1)
    return spark.createDataFrame([tuple(got.values())], "estimate double, true double, error double")


@query("cost_report", "SELECT (SELECT sum((i2 - i1 + 1) * (j2 - j1 + 1))::BIGINT FROM stile) AS source_tiles, (SELECT sum((i2 - i1 + 1) * (j2 - j1 + 1))::BIGINT FROM ttile) AS target_tiles, (SELECT count(*) FROM pairs) AS candidates, (SELECT count(*) FROM pairs WHERE mbr_hit) AS hits, count(*) AS clusters, sum(n_pairs)::BIGINT AS pairs_exhaustive, sum(CASE WHEN place <= 1000 THEN n_pairs END)::BIGINT AS pairs_verified, (SELECT count(*) FROM (SELECT DISTINCT a, b FROM mpairs JOIN ranked USING (cid) WHERE place <= 1000)) AS pairs_verified_distinct FROM si JOIN ranked USING (cid)", "d2")
def _(spark, d):
    p, ranked = _ranked(spark, d)
    c = dataclasses.asdict(E.cost_report(p, V.select_frontier(ranked.select("cid", "w"), 1000), D.exact_threshold(p.all_si, 0.1)))
    names = ("source_tiles", "target_tiles", "candidates", "hits", "clusters", "pairs_exhaustive", "pairs_verified", "pairs_verified_distinct")
    return spark.createDataFrame([tuple(c[n] for n in names)], ", ".join(f"{n} long" for n in names))


@query("explain_search", "SELECT 0 AS nested_loops, true AS bounded_python")
def _(spark, d):
    got = E.explain_search(_prep(spark, d, "d2"))
    return spark.createDataFrame([(got["nested_loops"], got["python"] <= 2)], "nested_loops int, bounded_python boolean")


@query("sampled_pairs_interval", "SELECT count(*) AS clusters, true AS inside FROM (SELECT DISTINCT cid FROM members)", "d2")
def _(spark, d):
    """Indices from at most about sixty pairs a cluster, whose intervals must hold the exact indices (bar a few)."""
    p = _prep(spark, d, "d2")
    got = I.similarity_index(p.members, p.shapes, max_pairs=60).join(p.all_si.select("cid", F.col("si").alias("exact")), "cid")
    return got.agg(F.count("*").alias("clusters"), (F.avg((F.abs(F.col("si") - F.col("exact")) <= F.col("half_width")).cast("double")) >= 0.95).alias("inside"))


@query("stratified_draw", "SELECT count(*) AS clusters, true AS shares FROM (SELECT DISTINCT cid FROM members)", "d2")
def _(spark, d):
    """A tenth of the small and half of the large clusters; and a split of all in two parts that miss none."""
    p = _prep(spark, d, "d2")
    sized = p.clusters.withColumn("class", (F.col("size") >= 16).cast("int"))
    drawn = {r["class"]: r["n"] for r in S.stratified(sized, "class", {0: 0.1, 1: 0.5}).groupBy("class").agg(F.count("*").alias("n")).collect()}
    all_ = {r["class"]: r["n"] for r in sized.groupBy("class").agg(F.count("*").alias("n")).collect()}
    ok = abs(drawn.get(0, 0) - 0.1 * all_[0]) <= 5 * (0.09 * all_[0]) ** 0.5 and abs(drawn.get(1, 0) - 0.5 * all_[1]) <= 5 * (0.25 * all_[1]) ** 0.5
    parts = S.random_split(p.clusters, [0.7, 0.3])
    return spark.createDataFrame([(sum(x.count() for x in parts), bool(ok))], "clusters long, shares boolean")


@query("sorted_result", "SELECT cid, row_number() OVER (ORDER BY round(si, 9) DESC, cid)::BIGINT AS place FROM si", "d2")
def _(spark, d):
    return V.places(relational.sort_result(_prep(spark, d, "d2").all_si, "cid", within=True).select("cid", "si"), "si").select("cid", F.col("place").cast("long").alias("place"))


@query("weights_map", "SELECT " + ", ".join(f"0.125::DOUBLE AS {k}" for k in M.NAMES))
def _(spark, d):
    return spark.range(1).select(M.weights_map().alias("w")).select(*[F.col("w")[k].alias(k) for k in M.NAMES])


@query("family_index")
def _(spark, d):
    return K.family_index(spark, d).select("cid", "n_pairs", "si", "family")


_BOXES = "SELECT user_id::BIGINT * 100000 + (day - DATE '1970-01-01') AS sid, min(x) AS x1, min(y) AS y1, max(x) AS x2, max(y) AS y2 FROM dots GROUP BY user_id, day HAVING count(*) >= 3"


@query("stream_assign", "SELECT event_id AS tid, sid FROM dots JOIN boxes ON x BETWEEN x1 AND x2 AND y BETWEEN y1 AND y2", dots=_DOTS, boxes=_BOXES)
def _(spark, d):
    sources = K.trajectory_search(spark, d).sources
    return assign.assign_to_files(assign.point_targets(assign.read_events(spark, d, "events.parquet")), sources, grid_granularity(sources))


@query("stream_first_of_each", "SELECT count(DISTINCT event_id) AS events FROM events")
def _(spark, d):
    return assign.run_to_files(assign.first_of_each(assign.read_events(spark, d, "events.parquet"))).agg(F.count("*").alias("events"))


@query("stream_join", "SELECT a.event_id AS a_id, b.event_id AS b_id FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1800 SECOND")
def _(spark, d):
    events = partial(assign.read_events, spark, d, "events.parquet")
    return assign.run_to_files(assign.join_streams(events(), events(), 1800))


@query("stream_windows", "SELECT date_trunc('day', ts)::TIMESTAMP AS start_ts, count(*) AS n, round(avg(value), 6) AS mean FROM events GROUP BY 1")
def _(spark, d):
    out = assign.run_to_files(assign.windowed_counts(assign.read_events(spark, d, "events.parquet"), "1 day"), "complete")
    return out.withColumn("mean", _r("mean"))


@query("stream_histogram", "SELECT event_type, floor(value / 1000.0 / 0.1)::INT AS bin, count(*) AS n FROM events WHERE value IS NOT NULL GROUP BY 1, 2")
def _(spark, d):
    values = assign.read_events(spark, d, "events.parquet").select("event_type", (F.col("value") / 1000.0).alias("v"))
    return assign.run_to_files(assign.running_histogram(values, "event_type", "v"), "update").groupBy("event_type", "bin").agg(F.max("n").alias("n"))
