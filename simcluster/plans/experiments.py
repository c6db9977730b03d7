"""The experiments: coverage and ratio by targeted share, sweeps, size effect, ablations, backends, joins.

`python -m simcluster.plans.experiments SF_DIR [WORKLOAD...]` prints one JSON line per search.
"""

from __future__ import annotations

import dataclasses
import json
import sys
import time
from collections.abc import Iterator
from concurrent.futures import ThreadPoolExecutor

from pyspark import inheritable_thread_target
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import clip
from ..functions import geom as G
from ..functions import metrics as M
from ..functions import shapes as S
from ..operators import simindex as I
from ..operators.grid import candidate_pairs, candidate_pairs_nested_loop
from ..sources.fixtures import embedding_rings, lift_sources, lift_targets, trajectories
from ..sources.stages import stage
from ..sources.tables import load_table
from . import evaluate as E
from .baselines import exhaustive_threshold, random_order, verified_by_order
from .search import Prepared, SimilarClusterSearch


#: Searches of an experiment that run at a time: training and simulation are many short jobs of one task each.
SEARCHES = 4


def prepare(spark: SparkSession, sf_dir: str, workload: str = "d1", family: str = "regional", **settings) -> Prepared:
    return Prepared(lift_sources(spark, sf_dir, workload, family), lift_targets(spark, sf_dir, workload), **settings)


def run_searches(prep: Prepared, workload: str, shares=(0.1, 0.3, 0.5), recalls=(0.8, 0.9, 0.95), rules=("linear", "curve", "cut"), seeds=(1,), **settings) -> Iterator[E.Report]:
    """Coverage, ratio and achieved recall for each targeted share, seed, wanted recall and budget rule.

    Samples, training and scores depend on neither the wanted recall nor the rule, so each plan is made once; some
    plans at a time. What all of them read is written before.
    """
    if not prep.total:
        return
    _ = prep.features, prep.nested, prep.si_places

    def lines(search: SimilarClusterSearch) -> list[E.Report]:
        return E.reports(prep, search, search.plan(prep), workload, tuple(recalls), tuple(rules))

    searches = [SimilarClusterSearch(p=p, seed=seed, **settings) for p in shares for seed in seeds]
    with ThreadPoolExecutor(SEARCHES) as pool:
        for made in [pool.submit(inheritable_thread_target(lines), search) for search in searches]:
            yield from made.result()


def sweep(prep: Prepared, workload: str, r_d: float = 0.9, rules=("linear", "curve")) -> Iterator[E.Report]:
    """Nine targeted shares, as the curves of ratio and share checked need."""
    yield from run_searches(prep, workload, tuple(i / 10 for i in range(1, 10)), (r_d,), rules)


#: Changes of the search, one at a time.
SEARCH_VARIANTS = {"base": {}, "shared roles": {"roles": "shared"}, "gaussian": {"kernels": ("gaussian",)}, "epanechnikov": {"kernels": ("epanechnikov",)}, "tophat": {"kernels": ("tophat",)}, "logistic kernel": {"kernels": ("logistic",)}, "kfold": {"criterion": "kfold"}, "scott": {"criterion": "scott"}, "no reflection": {"boundary": "none"}, "weighted classes": {"balance": "weights"}, "truncated classes": {"balance": "truncate"}, **{a: {"algorithm": a} for a in ("random_forest", "gbt", "naive_bayes", "decision_tree", "mlp")}}
#: Changes of clusters, features and measures.
PREPARED_VARIANTS = {"15 features": {"n_features": 15}, "no scaling": {"scaling": "none"}, "pair scaling": {"scaling": "pair"}, "cluster scaling": {"scaling": "cluster"}, "uncentred": {"centered": False}, "flat family": {"family": "flat"}, **{f"only {c}": {"weights": M.equal_weights(names)} for c, names in M.CATEGORIES.items()}}


def search_variants(prep: Prepared, workload: str, p: float = 0.3, r_d: float = 0.9, names: tuple[str, ...] | None = None) -> Iterator[tuple[str, E.Report]]:
    """Roles, kernels, criteria, class balance and classifiers, one change at a time, with all budget rules."""
    for name, change in SEARCH_VARIANTS.items():
        if names is None or name in names:
            for line in run_searches(prep, workload, (p,), (r_d,), ("linear", "curve", "cut") if name == "base" else ("curve",), **change):
                yield f"{name}, {line.rule}" if name == "base" else name, line


def prepared_variants(spark: SparkSession, sf_dir: str, workload: str, p: float = 0.3, r_d: float = 0.9, names: tuple[str, ...] | None = None) -> Iterator[tuple[str, E.Report]]:
    """Scaling, features, centring, families and measure categories, one change at a time, of the same clusters where
    the sources stay."""
    base = prepare(spark, sf_dir, workload)
    for name, change in PREPARED_VARIANTS.items():
        if names is None or name in names:
            prep = prepare(spark, sf_dir, workload, **change) if "family" in change else base.variant(**change)
            for line in run_searches(prep, workload, (p,), (r_d,), ("curve",)):
                yield name, line


def against_random(prep: Prepared, out) -> dict[str, float]:
    """Recall of the scheduled search and of a random order with the same budget."""
    truth = exhaustive_threshold(prep.all_si, out.tau)
    plain = verified_by_order(random_order(prep.clusters), prep.all_si, out.budget, out.tau)
    return {"scheduled": E.recall_precision(out.result, truth)["recall"], "random": E.recall_precision(plain, truth)["recall"]}


def _seconds(df: DataFrame) -> float:
    began = time.perf_counter()
    df.write.format("noop").mode("overwrite").save()
    return time.perf_counter() - began


def _python_box(xs, ys):
    return [min(xs), min(ys), max(xs), max(ys)]


def geometry_by_backend(prep: Prepared, what: str, backend: str) -> DataFrame:
    """MBRs of all sources, or shared and united areas of all distinct member pairs, by a backend.

    arrow: a batch at a time; sql: expressions only; python: one row at a time.
    """
    if what == "mbr":
        first = F.col("geom.parts")[0]
        if backend == "python":
            box = F.udf(_python_box, "array<double>")(first["xs"], first["ys"])
            return prep.sources.select("sid", *[box[i].alias(c) for i, c in enumerate(("x1", "y1", "x2", "y2"))])
        if backend == "arrow":
            return prep.sources.select("sid", "geom").mapInArrow(S.boxer, "sid long, x1 double, y1 double, x2 double, y2 double")
        return prep.sources.select("sid", G.mbr(F.col("geom")).alias("b")).select("sid", "b.*")
    inter = clip.intersection_area(prep.distinct_pairs, prep.shapes, backend)
    if what == "intersection":
        return inter
    area = lambda p: prep.shapes.select(F.col("sid").alias(p), F.col("area").alias(f"area_{p}"))
    return inter.join(area("a"), "a").join(area("b"), "b").select("a", "b", G.union_area(F.col("area_a"), F.col("area_b"), F.col("inter")).alias("united"))


def bench_geometry(prep: Prepared, backends=("arrow", "sql", "python")) -> dict[str, float]:
    """Seconds of MBRs, shared and united areas by backend; shapes and pairs are written before."""
    _ = prep.shapes, prep.distinct_pairs
    return {f"{what} {b}": _seconds(geometry_by_backend(prep, what, b)) for what in ("mbr", "intersection", "union") for b in backends}


def metric_averages(prep: Prepared, backend: str) -> DataFrame:
    """The mean of each measure over all distinct member pairs, outside the search."""
    return I.pair_similarities(prep.distinct_pairs, prep.shapes, backend=backend, breakdown=True).agg(*[F.avg(k).alias(k) for k in M.NAMES], F.count("*").alias("pairs"))


def bench_metrics(prep: Prepared, backends=("arrow", "sql", "python")) -> dict[str, float]:
    """Seconds of the means of all measures, by backend; shapes and pairs are written before."""
    _ = prep.shapes, prep.distinct_pairs
    return {f"averages {b}": _seconds(metric_averages(prep, b)) for b in backends}


def bench_joins(prep: Prepared, nested: bool = False) -> dict[str, float]:
    """Seconds of the grid join by strategy, and of the join without an index."""
    out = {f"join {s}": _seconds(candidate_pairs(prep.sources, prep.targets, prep.grid, s)) for s in ("merge", "hash", "broadcast")}
    if nested:
        out["join nested loop"] = _seconds(candidate_pairs_nested_loop(prep.sources, prep.targets))
    return out


def trajectory_search(spark: SparkSession, sf_dir: str) -> Prepared:
    """Users' days as open lines that probe rings around the same values."""
    lines = trajectories(load_table(spark, sf_dir, "events"))
    rings = lines.select(F.col("tid").alias("sid"), F.struct(F.lit("polygon").alias("kind"), F.transform("geom.parts", lambda p: F.struct(F.lit("shell").alias("role"), p["xs"].alias("xs"), p["ys"].alias("ys"))).alias("parts")).alias("geom"), "mbr").filter(F.size(F.col("geom.parts")[0]["xs"]) >= 3)
    return Prepared(rings, lines)


def family_index(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Index of the rings of each embedding label, and of equally many rings across labels."""
    rings = embedding_rings(load_table(spark, sf_dir, "embeddings"))
    shapes = stage(I.describe_shapes(rings), "family-shapes")
    count = rings.select("label").distinct().count()
    within = rings.select(F.col("label").cast("long").alias("cid"), "sid")
    across = rings.select((F.col("sid") % count + 1_000_000).alias("cid"), "sid")
    return I.nested_index(I.stripes(within.unionByName(across)), shapes).withColumn("family", F.col("cid") < 1_000_000)


def main(args: list[str]) -> None:
    spark = SparkSession.builder.getOrCreate()
    for workload in args[1:] or ("d1", "d2", "d3"):
        prep = prepare(spark, args[0], workload)
        for line in run_searches(prep, workload):
            print(json.dumps(dataclasses.asdict(line)), flush=True)


if __name__ == "__main__":
    main(sys.argv[1:])
