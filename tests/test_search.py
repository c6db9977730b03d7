import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from simcluster.functions import geom as G
from simcluster.operators import budget as B
from simcluster.operators import clusters as C
from simcluster.operators import density as D
from simcluster.operators import features as FT
from simcluster.operators import labelling as L
from simcluster.operators import sampling as S
from simcluster.operators import simindex as I
from simcluster.operators import verify as V
from simcluster.operators.grid import candidate_pairs, candidate_pairs_nested_loop, grid_granularity
from simcluster.plans import baselines as XB
from simcluster.plans import evaluate as E
from simcluster.plans.search import Prepared, SimilarClusterSearch


@pytest.mark.parametrize("factor,closing,strategy", [(0.25, "floor", None), (1.0, "ceil", "merge"), (4.0, "floor", "broadcast")])
def test_grid_join_equals_nested_loop(d2, factor, closing, strategy):
    grid = grid_granularity(d2.sources, factor=factor)
    got = candidate_pairs(d2.sources, d2.targets, grid, strategy, closing)
    rows = [(r["tid"], r["sid"]) for r in got.filter("mbr_hit").select("tid", "sid").collect()]
    want = {(r["tid"], r["sid"]) for r in candidate_pairs_nested_loop(d2.sources, d2.targets).collect()}
    assert len(rows) == len(set(rows)) == 4659 and set(rows) == want


def test_nested_loop_compares_blocks(spark, monkeypatch):
    from simcluster.operators import grid

    monkeypatch.setattr(grid, "BLOCK", 3)
    box = "struct<x1:double,y1:double,x2:double,y2:double>"
    lay = lambda key, boxes: spark.createDataFrame(list(enumerate(boxes)), f"{key} long, mbr {box}")
    s = lay("sid", [(float(i), 0.0, i + 1.0, 1.0) for i in range(8)])
    t = lay("tid", [(2.0, 1.0, 2.0, 3.0), None, (7.5, 0.5, 90.0, 0.6), (0.0, 1.1, 9.0, 2.0), (-5.0, -5.0, 50.0, 50.0)])
    got = candidate_pairs_nested_loop(s, t)
    assert sorted(map(tuple, got.collect())) == [(0, 1), (0, 2), (2, 7)] + [(4, i) for i in range(8)]
    assert 3 <= grid._blocks(s, "sid", "s").count() <= 8 and grid._blocks(s, "sid", "s").filter(F.size("sid") > 3).isEmpty()
    assert candidate_pairs_nested_loop(s.limit(0), t).isEmpty() and candidate_pairs_nested_loop(s, t.limit(0)).isEmpty()


def test_clusters_and_statistics(d2):
    assert d2.total == 454
    assert math.isclose(d2.clusters.agg(F.avg("size")).head()[0], 10.18, abs_tol=0.01)
    stats = C.source_stats(d2.pairs)
    assert stats.filter("real > distinct or distinct > total").isEmpty()
    assert stats.agg(F.sum("distinct")).head()[0] == C.target_stats(d2.pairs).agg(F.sum("distinct")).head()[0]
    g = C.representatives(d2.members, d2.targets)
    meets = d2.members.join(g.select("cid", F.col("mbr").alias("g")), "cid").join(d2.sources.select("sid", "mbr"), "sid")
    assert meets.filter(~G.mbr_intersects(F.col("g"), F.col("mbr"))).isEmpty()
    assert C.unclustered(d2.members, d2.targets).count() == d2.targets.count() - 454


def _si(df):
    return {r["cid"]: r["si"] for r in df.collect()}


def test_index_layouts_agree(d2):
    long = _si(d2.all_si)
    some = d2.clusters.orderBy("cid").limit(60)
    for kw in ({"memo": False}, {"layout": "nested"}):
        got = _si(I.similarity_index(d2.members, d2.shapes, cids=some, **kw))
        assert len(got) == 60 and all(math.isclose(v, long[k], abs_tol=1e-9) for k, v in got.items())
    bounds = I.similarity_bounds(d2.members, d2.shapes).collect()
    assert all(r["lo"] - 1e-9 <= long[r["cid"]] <= r["hi"] + 1e-9 for r in bounds)
    assert abs(float(np.median(list(long.values()))) - 0.809) < 0.005


def test_sampled_pairs_and_histogram(d2):
    got = I.similarity_index(d2.members, d2.shapes, max_pairs=40).collect()
    long = _si(d2.all_si)
    assert all(abs(r["si"] - long[r["cid"]]) <= r["half_width"] for r in got)
    assert sum(r["clusters"] for r in I.si_histogram(d2.all_si).collect()) == 454


def test_features_are_scaled(d2):
    low = d2.features.agg(*[F.min(c).alias(c) for c in FT.NAMES]).head()
    high = d2.features.agg(*[F.max(c).alias(c) for c in FT.NAMES]).head()
    assert all(abs(v) < 1e-6 for v in low) and all(v <= 10_000 for v in high)
    assert len(FT.cluster_features(d2.raw, 15).columns) == 16


def test_draws_are_deterministic(d2):
    one = [r["cid"] for r in S.draw_clusters(d2.clusters, 50).orderBy("place").collect()]
    two = [r["cid"] for r in S.draw_clusters(d2.clusters.repartition(7), 50).orderBy("place").collect()]
    assert one == two and len(set(one)) == 50
    a, b = S.draw_roles(d2.clusters, 100)
    assert a.join(b, "cid").isEmpty() and a.count() == b.count() == 100
    assert S.draw_clusters(d2.clusters, 80, method="pair", pairs=d2.pairs).count() <= 80


POINTS = np.array([0.55, 0.6, 0.6, 0.62, 0.64, 0.64, 0.7, 0.72, 0.72, 0.8, 0.9, 0.97])


@pytest.mark.parametrize("kernel", list(D.KERNELS))
def test_density_is_a_density(kernel):
    kde = D.Kde(POINTS, kernel, 0.05)
    x = np.linspace(-2, 4, 60_001)  # fine enough for the jumps of the flat kernel
    assert math.isclose(np.trapezoid(kde.pdf(x), x), 1, abs_tol=2e-3)
    assert np.all(np.diff(kde.cdf(x)) >= -1e-12)
    for boundary in ("none", "truncate", "reflect"):
        for p in (0.1, 0.5):
            tau = D.kde_threshold(kde, p, boundary=boundary)
            assert math.isclose(kde.sf(tau, boundary=boundary)[0], p, abs_tol=1e-6)
    for boundary in ("truncate", "reflect"):
        assert math.isclose(kde.sf(0.0, boundary=boundary)[0], 1, abs_tol=1e-9) and abs(kde.sf(1.0, boundary=boundary)[0]) < 1e-9


def test_density_selection_and_edges():
    assert D.select_kde(POINTS).kernel in D.KERNELS
    assert D.select_kde([0.5] * 9).h == 1e-4
    assert abs(D.kde_threshold(D.select_kde([0.5] * 9), 0.1) - 0.5) < 1e-3
    assert D.kde_threshold(D.select_kde(POINTS), 0) == float("inf")
    normal = np.random.default_rng(1).normal(0.5, 0.1, 4000)
    assert abs(D.kde_threshold(D.select_kde(normal, ("gaussian",), criterion="silverman"), 0.1) - (0.5 + 1.2816 * 0.1)) < 0.01


def test_training_prefix_stops_at_first_full_pair_of_classes(spark):
    rows = spark.createDataFrame([(i, 0.0, float(i % 5 == 0)) for i in range(200)], "cid long, si double, label double")
    got = L.training_prefix(rows, 10).orderBy("seen").collect()
    pos = [r["label"] for r in got]
    assert min(pos.count(1.0), pos.count(0.0)) == 10 and pos[-1] == 1.0
    assert L.training_prefix(rows, 150).count() == 200


def test_budgets_by_hand(spark):
    rows = [(i, 1 - i / 100, 1.0 if i < 8 or i in (20, 30, 40, 50) else 0.0) for i in range(100)]
    sim = B.simulate(spark.createDataFrame(rows, "cid long, w double, label double"), 0.1)
    assert (sim.kept, sim.high, sim.depth, sim.hits) == (100, 12, 10, 8)
    assert B.budget_linear(sim, 0.9, 25_284) == 4097
    assert B.budget_gain_curve(sim, 0.9, 100) == 41  # 11 of 12
    assert math.isclose(B.probability_cut(sim, 0.9), 0.6)
    none = B.Simulation(100, 0, 10, 0, ())
    assert B.budget_linear(none, 0.9, 77) == B.budget_gain_curve(none, 0.9, 77) == 77
    assert B.budget_gain_curve(sim, 1.0, 100) >= B.budget_gain_curve(sim, 0.5, 100)


def test_verification_is_precise_and_complete(d2):
    tau = D.exact_threshold(d2.all_si, 0.3)
    scored = XB.feature_order(d2.features, "f15", ascending=True)
    truth = {r["cid"] for r in XB.exhaustive_threshold(d2.all_si, tau).collect()}
    found = lambda budget, **kw: {r["cid"] for r in V.verify(scored, budget, tau, d2.index_of, **kw).collect()}
    assert found(454) == truth
    some = found(150)
    assert some <= truth and some == found(150, bounds_of=d2.bounds_of) == found(150, memo=d2.all_si.limit(100))
    waves, checked = V.verify_in_waves(scored, 150, tau, d2.index_of, 60)
    assert {r["cid"] for r in waves.collect()} == some and checked == 150
    big = V.select_frontier(scored, 150, top_k=10)
    assert {r["cid"] for r in big.collect()} == {r["cid"] for r in V.select_frontier(scored, 150).collect()}


def test_search_reaches_recall_below_random_cost(d2):
    search = SimilarClusterSearch(p=0.3, r_d=0.9, m=150, n=25)
    plan = search.plan(d2)
    got = {r.rule: r for r in E.reports(d2, search, plan, "d2", (0.9,), ("linear", "curve", "cut"))}
    assert got["curve"].recall >= 0.75 and got["curve"].coverage < 0.9
    out = search.run(d2)
    truth = XB.exhaustive_threshold(d2.all_si, out.tau)
    true = E.recall_precision(out.result, truth)
    assert true["precision"] == 1.0 and true["recall"] == got["curve"].recall and out.budget == got["curve"].budget
    plain = XB.verified_by_order(XB.random_order(d2.clusters), d2.all_si, out.budget, out.tau)
    assert E.recall_precision(plain, truth)["recall"] < true["recall"]
    error = E.recall_error(plan, d2.all_si, 0.3)
    first = V.select_frontier(plan.scored, math.ceil(0.3 * 454))
    assert error["true"] == E.recall_precision(first, truth)["recall"] and error["error"] == error["estimate"] - error["true"]


def test_a_margin_only_adds_to_the_budget():
    sim = B.Simulation(500, 100, 50, 40, tuple((3 * i, i, 1 - i / 200) for i in range(1, 101)))
    plain = B.budget_gain_curve(sim, 0.9, 500)
    safe = B.budget_gain_curve(sim, 0.9, 500, B.margin(sim, 0.9, 0.95))
    assert B.margin(sim, 0.9, 0.5) == 0 and plain == 270 and safe == 3 * (90 + 5)
    assert B.margin(sim, 0.99, 0.999) <= 1


def test_places_and_largest_against_a_sort(spark):
    import random

    rows = [(i, random.Random(i).choice([0.1, 0.2, 0.2 + 1e-13, 0.3, i / 1000])) for i in range(3000)]
    df = spark.createDataFrame(rows, "cid long, v double").repartition(7)
    order = [c for c, v in sorted(rows, key=lambda r: (-round(r[1], 9), r[0]))]
    placed = {r["cid"]: r["place"] for r in V.places(df, "v").collect()}
    assert [c for c, _ in sorted(placed.items(), key=lambda x: x[1])] == order and sorted(placed.values()) == list(range(1, 3001))
    for k in (0, 1, 700, 2999, 5000):
        for top_k in (10_000, 50):
            assert {r["cid"] for r in V.largest(df, "v", k, top_k).collect()} == set(order[:k])
    for q in (0.0, 0.1, 0.5, 0.987, 1.0):
        assert D.exact_quantile(df, "v", q, band_rows=10) == pytest.approx(float(np.quantile([v for _, v in rows], q)), abs=1e-12)


def test_pairs_of_large_clusters_and_samples(d2):
    want = {tuple(r) for r in I.member_pairs(d2.members).select("cid", "a", "b").collect()}
    assert len(want) == 29_218
    got = [tuple(r) for r in I.member_pairs(d2.members, largest=8).select("cid", "a", "b").collect()]
    assert len(got) == len(want) and set(got) == want
    few = [tuple(r) for r in I.sampled_pairs(d2.members, 30).select("cid", "a", "b").collect()]
    sizes = {r["cid"]: r["size"] for r in d2.clusters.collect()}
    assert len(few) == len(set(few)) and set(few) <= want
    for cid, size in sizes.items():
        n = sum(1 for x in few if x[0] == cid)
        assert n == size * (size - 1) // 2 if size * (size - 1) <= 60 else 30 - size <= n <= 30 + size
    nested = C.nested_clusters(d2.members, 10).collect()
    assert all(len(r["members"]) <= r["size"] for r in nested) and {(r["cid"], s) for r in nested for s in r["members"]} == {(r["cid"], r["sid"]) for r in d2.members.collect()}


def test_boxes_of_many_tiles_go_to_a_coarse_grid(d2):
    fine = grid_granularity(d2.sources, factor=0.02)
    rows = candidate_pairs(d2.sources, d2.targets, fine).select("tid", "sid", "common_tiles", "mbr_hit").collect()
    i = lambda v, d: math.floor(v * d)
    spans = lambda df, key: {r[key]: tuple(i(r["mbr"][k], fine.dx if k[0] == "x" else fine.dy) for k in ("x1", "y1", "x2", "y2")) for r in df.select(key, "mbr").collect()}
    s, t = spans(d2.sources, "sid"), spans(d2.targets, "tid")
    assert max(max(b[2] - b[0], b[3] - b[1]) for b in s.values()) > 64
    want = {}
    for a, p in t.items():
        for b, q in s.items():
            w, h = min(p[2], q[2]) - max(p[0], q[0]) + 1, min(p[3], q[3]) - max(p[1], q[1]) + 1
            if w > 0 and h > 0:
                want[a, b] = w * h
    assert {(r["tid"], r["sid"]): r["common_tiles"] for r in rows} == want and len(rows) == len(want)
    assert sum(r["mbr_hit"] for r in rows) == 4659


def test_pooled_features_equal_raw_ones(d2):
    for scaling in ("both", "pair", "cluster", "none"):
        want = {r["cid"]: tuple(r)[1:] for r in FT.cluster_features(d2.raw, scaling=scaling).select("cid", *FT.NAMES).collect()}
        s, t = FT.source_side(d2.sources, C.source_stats(d2.pairs), d2.grid), FT.target_side(d2.targets, C.target_stats(d2.pairs), d2.grid)
        got = {r["cid"]: tuple(r)[1:] for r in FT.pooled_features(d2.members, s, t, scaling=scaling).select("cid", *FT.NAMES).collect()}
        assert got.keys() == want.keys() and all(np.allclose(got[k], want[k]) for k in got)


def test_empty_and_single(spark, d2):
    empty = Prepared(d2.sources.limit(0), d2.targets)
    assert empty.total == 0 and SimilarClusterSearch().run(empty) is None
    one = d2.clusters.limit(1).collect()[0]["cid"]
    alone = Prepared(d2.sources, d2.targets.filter(F.col("tid") == one))
    with pytest.warns(UserWarning):
        assert SimilarClusterSearch(m=5, n=2).run(alone).total == 1


def test_plans_have_no_cross_product(d2):
    plan = candidate_pairs(d2.sources, d2.targets, d2.grid)._jdf.queryExecution().executedPlan().toString()
    assert "CartesianProduct" not in plan and "NestedLoop" not in plan
    sims = I.pair_similarities(I.member_pairs(d2.members).select("a", "b").distinct(), d2.shapes)._jdf.queryExecution().executedPlan().toString()
    assert sims.count("ArrowEvalPython") == 1


def test_nested_index_deals_clusters_and_equals_the_long_form(spark, d2, monkeypatch):
    """Lists dealt to many tasks, hot stretches dealt again, large clusters by pairs; members without a shape or value."""
    monkeypatch.setattr(I, "PART_PAIRS", 4000)
    monkeypatch.setattr(I, "LEAST_PAIRS", 10_000)
    places = d2.clusters.select("cid", F.lit(7).alias("place"))  # all in one place
    assert I.nest(d2.members, places).keys > 2
    lost = d2.members.agg(F.min("sid")).head()[0]
    shapes = d2.shapes.filter(F.col("sid") != lost).withColumn("aspect", F.when(F.col("sid") % 5 > 0, F.col("aspect")))
    twice = d2.members.unionByName(d2.members.filter("cid % 3 = 0"))  # sizes as before
    want = _si(I.similarity_index(twice, shapes))
    for largest in (2048, 6):
        monkeypatch.setattr(I, "NESTED_SIZE", largest)
        got = _si(I.similarity_index(twice, shapes, layout="nested", nested=I.nest(twice, places, largest)))
        assert got.keys() == want.keys() and all(got[k] == pytest.approx(want[k], nan_ok=True) for k in want)
    monkeypatch.setattr(I, "PART_PAIRS", 50)  # one cluster in many tasks
    some = twice.filter("cid % 7 = 0")
    striped = I.stripes(some)
    assert not striped.lists.filter("stripes > 2").isEmpty()
    got = _si(I.nested_index(striped, shapes))
    assert got.keys() == {k for k in want if k % 7 == 0} and all(got[k] == pytest.approx(want[k], nan_ok=True) for k in got)


def test_shared_areas_of_mixed_shapes_equal_the_sum_over_edges():
    """Pairs of equal numbers of edges are laid side by side, more pairs of edges than fit at once included."""
    import pyarrow as pa

    from simcluster.functions import clip

    rng = np.random.default_rng(1)

    def rings(sizes):
        xs, ys = ([list(rng.normal(size=n)) for n in sizes] for _ in range(2))
        turn = lambda v: [x[1:] + x[:1] for x in v]
        return [pa.array(v, pa.list_(pa.float64())) for v in (xs, ys, turn(xs), turn(ys))]

    a, b = rings([3, 0, 5, 8, 5, 300, 3]), rings([4, 3, 0, 8, 8, 400, 4])
    want = [max(0.0, sum(clip._one_wedge(*p, *q) for p in zip(*(v[k].as_py() for v in a), strict=True) for q in zip(*(v[k].as_py() for v in b), strict=True))) for k in range(7)]
    assert np.allclose(clip.shared_areas(a, b), want)


def test_geometries_are_made_once_for_joins_and_features(spark, d2):
    seen = {k: spark.sparkContext.accumulator(0) for k in ("s", "t")}

    def counted(rows, counter):
        def run(batches):
            for batch in batches:
                counter.add(batch.num_rows)
                yield batch

        return rows.mapInArrow(run, rows.schema)

    prep = Prepared(counted(d2.sources, seen["s"]), counted(d2.targets, seen["t"]))
    assert prep.features.count() == d2.total and prep.nested.lists.count() == d2.total
    assert seen["s"].value == d2.sources.count() and seen["t"].value == d2.targets.count()


def test_plans_of_several_shares_draw_one_sample(d2, monkeypatch):
    drawn = []
    own = Prepared.index_of
    monkeypatch.setattr(Prepared, "index_of", lambda self, cids: (drawn.append(cids), own(self, cids))[1])
    prep = d2.variant()
    a, b = (SimilarClusterSearch(p=p, m=100, n=20, seed=11).plan(prep) for p in (0.2, 0.6))
    assert len(drawn) == 1 and a.tau > b.tau


def test_variants_share_what_they_do_not_change(d2):
    plain, jaccard = d2.variant(scaling="none"), d2.variant(weights={"jaccard": 1.0})
    assert plain.pairs is d2.pairs and plain.all_si is d2.all_si and plain.features is not d2.features
    assert jaccard.features is d2.features and jaccard.shapes is d2.shapes and jaccard.all_si is not d2.all_si
    fresh = Prepared(d2.sources, d2.targets, scaling="none").features
    both = plain.features.join(fresh.select("cid", *[F.col(f).alias(f"o{f}") for f in FT.NAMES]), "cid")
    assert both.count() == d2.total and both.filter(" OR ".join(f"abs({f} - o{f}) > 1e-6" for f in FT.NAMES)).isEmpty()
    with pytest.raises(ValueError, match="no variant"):
        d2.variant(min_size=3)


def test_reports_equal_the_measures_one_by_one(d2):
    search = SimilarClusterSearch(p=0.3)
    plan = search.plan(d2)
    (line,) = E.reports(d2, search, plan, "d2", (0.9,), ("curve",))
    assert line.recall_at_share == E.recall_error(plan, d2.all_si, 0.3)["true"]
    found = XB.verified_by_order(plan.scored, d2.all_si, line.budget, plan.tau)
    assert line.recall == E.recall_precision(found, XB.exhaustive_threshold(d2.all_si, plan.tau))["recall"]
    assert line.recall_top == E.recall_precision(found, XB.exhaustive_top(d2.all_si, 0.3))["recall"]


def test_backends_read_pairs_that_are_written_once(d2, monkeypatch):
    from simcluster.plans import experiments as K

    made = []
    own = I.member_pairs
    monkeypatch.setattr(I, "member_pairs", lambda *args: (made.append(args), own(*args))[1])
    prep = d2.variant()
    areas = [{(r["a"], r["b"]): r["inter"] for r in K.geometry_by_backend(prep, "intersection", b).collect()} for b in ("arrow", "python")]
    assert len(made) == 1 and areas[0].keys() == areas[1].keys() and len(areas[0]) == prep.distinct_pairs.count() > 0
    assert all(math.isclose(areas[0][k], areas[1][k], abs_tol=1e-9) for k in areas[0])
    assert K.metric_averages(prep, "arrow").head()["pairs"] == len(areas[0]) and len(made) == 1
