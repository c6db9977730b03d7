"""Findings of round 3: what must not be shuffled, broadcast or left on disk."""

import time

import numpy as np
import pytest
from pyspark.sql import functions as F

from simcluster.functions import alike
from simcluster.operators import clusters as C
from simcluster.operators import features as FT
from simcluster.operators import grid as GR
from simcluster.operators import simindex as I
from simcluster.sources.fixtures import lift_sources, lift_targets
from simcluster.sources.stages import CLEANUP, shared_folder, stage


def _plan(df) -> str:
    return df._jdf.queryExecution().executedPlan().toString()


class Counted:
    """Shapes whose likeness is a function of both places, and that count what is computed."""

    def __init__(self, n):
        self.ids, self.asked = np.arange(n) * 3, []

    def likeness(self, i, j):
        self.asked += list(zip(i.tolist(), j.tolist(), strict=True))
        return np.where((i + j) % 7 == 0, np.nan, 1 / (1 + i + 2 * j))


@pytest.mark.parametrize("most", [3, 50, 10**6])
def test_owners_compute_each_pair_once_and_all_of_them(monkeypatch, most):
    """the sums of all owners are those of all pairs, also where an id has more pairs than are held at a time."""
    monkeypatch.setattr(alike, "PAIRS", most)
    rng = np.random.default_rng(1)
    lists = [np.sort(rng.choice(20, rng.integers(0, 12), replace=False)) * 3 for _ in range(30)]
    members, sizes = np.concatenate(lists), np.array([len(x) for x in lists])
    shapes, every = Counted(20), Counted(20)
    ones = np.ones(len(sizes), int)
    want = alike.cluster_sums(every, members, sizes, 0 * ones, ones)
    got = [alike.owned_sums(shapes, members, sizes, shapes.ids[k::3]) for k in range(3)]
    for g, w in zip(zip(*got, strict=True), want, strict=True):
        assert np.allclose(sum(g), w)
    assert len(shapes.asked) == len(set(shapes.asked))
    assert set(shapes.asked) == set(every.asked)


def test_index_with_memo_shuffles_no_pairs(spark, d2, monkeypatch):
    """lists travel, not the shapes of every pair; many tasks give what rows of pairs give."""
    monkeypatch.setattr(I, "LEAST_PAIRS", 200)
    nested = I.nest(d2.members)
    assert nested.keys > 1
    got = I.similarity_index(d2.members, d2.shapes, nested=nested)
    assert "a_e1" not in _plan(got) and "a_area" not in _plan(got)
    want = {r["cid"]: r for r in I.similarity_index(d2.members, d2.shapes, memo=False).collect()}
    rows = got.collect()
    assert len(rows) == len(want) > 0
    for r in rows:
        assert r["n_pairs"] == want[r["cid"]]["n_pairs"] and abs(r["si"] - want[r["cid"]]["si"]) < 1e-9
    some = d2.clusters.limit(20)
    assert {r["cid"] for r in I.similarity_index(d2.members, d2.shapes, cids=some, nested=nested).collect()} <= set(want)


def test_many_sources_are_never_broadcast_by_the_size_of_their_file(spark, sf_dir, monkeypatch):
    """the optimizer takes boxes on tiles for as large as the file that they come from."""
    s, t = lift_sources(spark, sf_dir, "d3"), lift_targets(spark, sf_dir, "d3")
    few = GR.candidate_pairs(s, t, strategy="broadcast")
    assert "BroadcastHashJoin" in _plan(few)
    monkeypatch.setattr(GR, "is_small", lambda df: False, raising=False)
    many = GR.candidate_pairs(s, t, strategy="broadcast")
    assert "BroadcastHashJoin" not in _plan(many)
    assert few.exceptAll(many).isEmpty() and many.exceptAll(few).isEmpty()


def test_boxes_beyond_the_other_sides_tiles_are_left_out_before_the_join(spark):
    rows = lambda key, at: spark.createDataFrame([(i, float(x)) for i, x in enumerate(at)], f"{key} long, x double")
    s = rows("sid", [0, 1, 2]).select("sid", F.struct("x", F.lit(0.0).alias("y1"), (F.col("x") + 1).alias("x2"), F.lit(1.0).alias("y2")).alias("m")).select("sid", F.struct(F.col("m.x").alias("x1"), "m.y1", "m.x2", "m.y2").alias("mbr"))
    t = rows("tid", [-5, -1, 0.5, 3, 3.5, 9]).select("tid", F.struct(F.col("x").alias("x1"), F.lit(0.0).alias("y1"), (F.col("x") + 0.5).alias("x2"), F.lit(1.0).alias("y2")).alias("mbr"))
    grid = GR.Grid(1.0, 1.0)
    _, *ends = GR._extent(s, grid, "floor")
    assert ends == [0, 0, 3, 1]
    assert [r["tid"] for r in GR._reaching(t, ends, grid, "floor").orderBy("tid").collect()] == [2, 3, 4]
    assert {(r["tid"], r["sid"]) for r in GR.candidate_pairs(s, t, grid).collect()} == {(2, 0), (2, 1), (3, 2), (4, 2)}
    assert GR.candidate_pairs(s.limit(0), t, grid).isEmpty() and GR.candidate_pairs(s, t.limit(0), grid).isEmpty()


def test_a_written_stage_leaves_no_shuffle_files(spark):
    """F2, F3, F6, F8, F9: they would stay until the driver's heap is collected, which may be never."""
    files = lambda: {f.getName() for f in _java(spark._jvm.org.apache.spark.SparkEnv.get().blockManager().diskBlockManager().getAllFiles()) if f.getName().startswith("shuffle_")}

    def _java(seq):
        return [seq.apply(i) for i in range(seq.size())]

    before, was = files(), spark.conf.get(CLEANUP, None)
    kept = stage(spark.range(100_000).groupBy((F.col("id") % 5000).alias("k")).agg(F.count("*").alias("n")), "no-shuffle")
    for _ in range(50):
        if not files() - before:
            break
        time.sleep(0.2)
    assert not files() - before
    assert kept.agg(F.sum("n")).head()[0] == 100_000 and spark.conf.get(CLEANUP, None) == was


def test_lists_are_written_once_in_the_end(spark, d2, monkeypatch):
    """The first writing of the lists goes as soon as they lie in parts."""
    monkeypatch.setattr(I, "LEAST_PAIRS", 200)
    folder = spark._jvm.org.apache.hadoop.fs.Path(shared_folder(spark))
    names = lambda: {f.getPath().getName() for f in folder.getFileSystem(spark._jsc.hadoopConfiguration()).listStatus(folder)}
    members, before = d2.members, names()
    assert I.nest(members).lists.count() > 0
    new = names() - before
    assert [n.rsplit("-", 1)[0] for n in new] == ["nested-parts"]


def test_features_of_many_sources_come_from_lists(spark, d2, monkeypatch):
    """F2, F3, F8: the sources' features of every member are neither joined nor shuffled; the means are the same."""
    s = FT.source_side(d2.source_boxes, C.source_stats(d2.pairs), d2.grid)
    t = FT.target_side(d2.target_boxes, C.target_stats(d2.pairs), d2.grid)
    names = sorted(FT.pooled_means(d2.members, s, t).columns)
    want = FT.pooled_means(d2.members, s, t).select(names).toPandas().set_index("cid").sort_index()
    monkeypatch.setattr(FT, "is_small", lambda df: False)
    monkeypatch.setattr(I, "LEAST_PAIRS", 200)
    sizes = sorted(r["size"] for r in d2.clusters.collect())
    for largest in (I.NESTED_SIZE, sizes[len(sizes) // 2]):
        monkeypatch.setattr(FT, "NESTED_SIZE", largest)
        rows = FT.pooled_means(d2.members, s, t, I.nest(d2.members, largest=largest))
        got = rows.select(names).toPandas().set_index("cid").sort_index()
        assert (got.index == want.index).all() and len(got) > 0
        assert np.allclose(got, want, rtol=1e-12, atol=1e-12)
