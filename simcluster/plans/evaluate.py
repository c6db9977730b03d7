"""Measures of a search: coverage, ratio, recall, precision, threshold and recall errors, cost, profiles."""

from __future__ import annotations

import math
import re
from dataclasses import dataclass

from pyspark.sql import DataFrame, Observation, Window
from pyspark.sql import functions as F

from ..operators.density import exact_quantile
from ..operators.grid import tile_range, tiles_of
from ..operators.simindex import member_pairs
from ..operators.verify import places, select_frontier
from .baselines import top_count
from .search import Prepared


def coverage(checked: int, total: int) -> float:
    return checked / total if total else 0.0


def checked_ratio(checked: int, total: int, p: float) -> float:
    """Share checked over share targeted."""
    return coverage(checked, total) / p


def recall_precision(found: DataFrame, truth: DataFrame) -> dict[str, float]:
    """Recall, precision and F1 of found clusters (cid) against true ones."""
    both = found.select("cid").distinct().withColumn("f", F.lit(1)).join(truth.select("cid").distinct().withColumn("t", F.lit(1)), "cid", "full")
    row = both.agg(F.count("f").alias("f"), F.count("t").alias("t"), F.count(F.when(F.col("f").isNotNull() & F.col("t").isNotNull(), 1)).alias("h")).head()
    recall = row["h"] / row["t"] if row["t"] else 1.0
    precision = row["h"] / row["f"] if row["f"] else 1.0
    return {"found": row["f"], "true": row["t"], "recall": recall, "precision": precision, "f1": 2 * recall * precision / (recall + precision) if recall + precision else 0.0}


def threshold_error(all_si: DataFrame, tau: float, p: float) -> dict[str, float]:
    """Distance of the cut-off from the exact quantile, and of the realised share from the wanted one."""
    exact, share = exact_quantile(all_si, "si", 1 - p), all_si.agg(F.avg((F.col("si") >= F.lit(tau)).cast("double"))).head()[0]
    return {"tau": tau, "exact": exact, "error": abs(tau - exact), "share": share, "share_error": share - p}


def recall_error(plan, all_si: DataFrame, p: float) -> dict[str, float]:
    """The recall that the simulation estimates for the share p of its queue, and that of the same share of all clusters."""
    depth = math.ceil(p * plan.total - 1e-9)
    high = all_si.filter(F.col("si") >= F.lit(plan.tau)).select("cid")
    hits = select_frontier(plan.scored, depth).select("cid").join(high, "cid", "left_semi").count()
    total = high.count()
    true = hits / total if total else 0.0
    return {"estimate": plan.simulation.recall, "true": true, "error": plan.simulation.recall - true}


def dataset_profile(prep: Prepared) -> DataFrame:
    """Sources, targets, clusters and their mean size, as one row."""
    m = prep.clusters.agg(F.count("*").alias("clusters"), F.avg("size").alias("mean_size"))
    return prep.sources.agg(F.count("*").alias("sources")).join(prep.targets.agg(F.count("*").alias("targets")), how="cross").join(m, how="cross")


def pair_costs(members: DataFrame, verified: DataFrame) -> dict[str, int]:
    """Pair similarities of all clusters and of the verified ones, with and without computing pairs once."""
    sizes = members.groupBy("cid").agg((F.count("*") * (F.count("*") - 1) / 2).cast("long").alias("n"))
    own = sizes.join(verified.select("cid"), "cid", "left_semi")
    return {
        "exhaustive": sizes.agg(F.sum("n")).head()[0] or 0,
        "verified": own.agg(F.sum("n")).head()[0] or 0,
        "verified_distinct": member_pairs(members, verified).select("a", "b").distinct().count(),
    }


@dataclass
class CostReport:
    """What a search does: tiles and candidate pairs of the join, pair similarities by way of computing them, shuffles."""

    source_tiles: int
    target_tiles: int
    candidates: int
    hits: int
    clusters: int
    pairs_exhaustive: int
    pairs_verified: int
    pairs_verified_distinct: int
    pairs_after_bounds: int
    exchanges: int


def cost_report(prep: Prepared, verified: DataFrame, tau: float) -> CostReport:
    """Counts observed while the stages of a search are read; verified: the clusters within the budget."""
    own = Observation()
    prep.pairs.observe(own, F.count("*").alias("candidates"), F.count_if("mbr_hit").alias("hits")).write.format("noop").mode("overwrite").save()
    tiles = lambda rows, key: rows.select(*tile_range(F.col("mbr"), prep.grid, prep.closing)).agg(F.sum(tiles_of())).head()[0] or 0
    costs = pair_costs(prep.members, verified)
    possible = prep.bounds_of(verified.select("cid")).filter(F.col("hi") >= F.lit(tau - 1e-9)).select("cid")
    left = pair_costs(prep.members, possible)["verified"]
    seen = own.get
    return CostReport(tiles(prep.sources, "sid"), tiles(prep.targets, "tid"), seen["candidates"], seen["hits"], prep.total, costs["exhaustive"], costs["verified"], costs["verified_distinct"], left, explain_search(prep)["exchanges"])


def explain_search(prep: Prepared) -> dict[str, int | str]:
    """The plan of the similarity index of all clusters: its text, exchanges, joins and Python calls."""
    plan = prep.index_of(None)._jdf.queryExecution().executedPlan().toString()
    count = lambda word: len(re.findall(word, plan))
    return {"plan": plan, "exchanges": count(r"Exchange hashpartitioning"), "joins": count("Join"), "python": count("ArrowEvalPython|BatchEvalPython|MapInArrow"), "nested_loops": count("NestedLoop|Cartesian")}


@dataclass
class Report:
    """One row of an experiment."""

    workload: str
    p: float
    r_d: float
    rule: str
    seed: int
    total: int
    budget: int
    coverage: float
    ratio: float
    tau: float
    threshold_error: float
    share: float
    recall_estimate: float
    recall_at_share: float
    recall_error: float
    recall: float
    recall_top: float
    precision: float
    found: int


def reports(prep: Prepared, search, plan, workload: str, recalls: tuple[float, ...], rules: tuple[str, ...]) -> list[Report]:
    """Measures of one plan under several wanted recalls and budget rules, against the exhaustive truth.

    Places in the verification's order are computed once, those by index once for all plans; each budget, the share's
    own depth (as in recall_error) and the top share are then counts over them.
    """
    p = search.p
    error = threshold_error(prep.all_si, plan.tau, p)
    indices = prep.si_places.select("cid", "si", F.col("place").alias("si_place"))
    rows = places(plan.scored, "w").join(indices, "cid")
    rows = rows.select("place", (F.col("si") >= F.lit(plan.tau)).alias("high"), (F.col("si_place") <= top_count(indices.count(), p)).alias("top"))
    depth = math.ceil(p * plan.total - 1e-9)
    budgets = {(rule, r_d): search.budget(plan, r_d, rule) for rule in rules for r_d in recalls}
    within = lambda b: F.col("place") <= b
    counts = rows.agg(F.count_if("high").alias("high"), F.count_if(within(depth) & F.col("high")).alias("own"), F.count_if("top").alias("top"), *[x for i, b in enumerate(budgets.values()) for x in (F.count_if(within(b) & F.col("high")).alias(f"h{i}"), F.count_if(within(b) & F.col("high") & F.col("top")).alias(f"t{i}"))]).head()
    share = lambda a, b: a / b if b else 1.0
    estimate, true = plan.simulation.recall, counts["own"] / counts["high"] if counts["high"] else 0.0
    # what is verified is compared with the cut-off itself, so all that is found is above it
    return [Report(workload, p, r_d, rule, search.seed, plan.total, b, coverage(b, plan.total), checked_ratio(b, plan.total, p), plan.tau, error["error"], error["share"], estimate, true, estimate - true, share(counts[f"h{i}"], counts["high"]), share(counts[f"t{i}"], counts["top"]), 1.0, counts[f"h{i}"]) for i, ((rule, r_d), b) in enumerate(budgets.items())]


def coverage_curve(scored_si: DataFrame, tau: float, steps: int = 10) -> DataFrame:
    """Recall after each tenth (or other part) of the clusters in order of w."""
    total = scored_si.count()
    placed = places(scored_si.select("cid", "w", F.when(F.col("si") >= F.lit(tau), 1.0).otherwise(0.0).alias("label")), "w")
    parts = placed.groupBy(F.ceil(F.col("place") * steps / F.lit(total)).alias("part")).agg(F.max("place").alias("checked"), F.sum("label").alias("own"))
    run = Window.orderBy("part").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return parts.withColumn("hits", F.sum("own").over(run)).withColumn("recall", F.col("hits") / F.nullif(F.sum("own").over(Window.partitionBy()), F.lit(0.0))).drop("own")


def coverage_pivot(reports: DataFrame) -> DataFrame:
    """Coverage by workload, a column for each targeted share."""
    return reports.groupBy("workload").pivot("p").agg(F.round(F.avg("coverage"), 4))


def size_effect(members: DataFrame, verified: DataFrame, edges: tuple[int, ...] = (2, 4, 8, 16, 32, 64)) -> DataFrame:
    """Share of clusters that are verified, by size class."""
    sizes = members.groupBy("cid").agg(F.count("*").alias("size"))
    bucket = F.lit(edges[0])
    for e in edges[1:]:
        bucket = F.when(F.col("size") >= e, e).otherwise(bucket)
    flagged = sizes.join(verified.select("cid").withColumn("v", F.lit(1)), "cid", "left")
    return flagged.groupBy(bucket.alias("size_from")).agg(F.count("*").alias("clusters"), F.avg(F.coalesce("v", F.lit(0)).cast("double")).alias("coverage"))
