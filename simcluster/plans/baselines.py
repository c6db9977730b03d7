"""What the scheduled search is compared with."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..operators.sampling import draw_key
from ..operators.verify import largest, ranked, select_frontier


def exhaustive_top(all_si: DataFrame, p: float) -> DataFrame:
    """The ceil(p * clusters) clusters with the largest index, ties by cid."""
    return largest(all_si.select("cid", "si"), "si", top_count(all_si.count(), p))


def top_count(total: int, p: float) -> int:
    return int(-(-p * total // 1)) if (p * total) % 1 > 1e-9 else round(p * total)


def exhaustive_threshold(all_si: DataFrame, tau: float) -> DataFrame:
    return all_si.select("cid", "si").filter(F.col("si") >= F.lit(tau))


def random_order(clusters: DataFrame, seed: int = 9) -> DataFrame:
    """Scores that put clusters in a seeded order that knows nothing."""
    return clusters.select("cid", (-draw_key(seed)).cast("double").alias("w"))


def feature_order(features: DataFrame, column: str, ascending: bool = False) -> DataFrame:
    """Scores that put clusters in order of one feature."""
    return features.select("cid", (-F.col(column) if ascending else F.col(column)).cast("double").alias("w"))


def ideal_order(all_si: DataFrame) -> DataFrame:
    """The perfect order, as a bound."""
    return all_si.select("cid", F.col("si").alias("w"))


def verified_by_order(scored: DataFrame, all_si: DataFrame, budget: int, tau: float) -> DataFrame:
    """What an order finds within a budget, for orders whose indices are known already."""
    return select_frontier(scored, budget).join(all_si.select("cid", "si"), "cid").filter(F.col("si") >= F.lit(tau)).select("cid", "si", "w")


def rank_clusters(all_si: DataFrame) -> DataFrame:
    """Every ranking function over the index, rounded so that equal indices tie; a total order, for reports of bounded size."""
    own = all_si.select("cid", "si", ranked("si").alias("v"))
    w, total = Window.orderBy(F.desc("v")), Window.orderBy(F.desc("v"), "cid")
    ranks = {"row_number": F.row_number().over(total), "rank": F.rank().over(w), "dense_rank": F.dense_rank().over(w), "percent_rank": F.percent_rank().over(w), "cume_dist": F.cume_dist().over(w), "ntile10": F.ntile(10).over(total), "before": F.lag("cid").over(total), "after": F.lead("cid").over(total)}
    return own.select("cid", "si", *[v.alias(k) for k, v in ranks.items()])
