"""Deterministic draws of clusters: the same in every engine and for every partitioning."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

MULTIPLIER, MODULUS = 48271, 2147483647


def draw_key(seed: int, id_col: str = "cid") -> Column:
    """A linear congruential hash of the id and the seed."""
    k = F.pmod(F.col(id_col), F.lit(MODULUS))
    return F.pmod(k * MULTIPLIER + F.lit(seed), F.lit(MODULUS))


def draw_clusters(clusters: DataFrame, m: int, seed: int = 1, method: str = "hash", pairs: DataFrame | None = None) -> DataFrame:
    """m clusters at most, as cid and place in the draw.

    hash: in order of the key (a bounded top-k, no shuffle of all clusters). pair: clusters that the m first
    member pairs belong to, which favours large clusters. fraction: about m by a cut of the key, without order.
    """
    ids = clusters.select("cid").distinct() if method != "pair" else None
    if method == "pair":
        hits = pairs.filter("mbr_hit").select(F.col("tid").alias("cid"), "sid").withColumn("key", F.pmod(draw_key(seed) + F.pmod(F.col("sid"), F.lit(MODULUS)) * 16807, F.lit(MODULUS)))
        ids = hits.orderBy("key", "cid", "sid").limit(m).select("cid").distinct()
    if method == "fraction":
        n = ids.count()
        return ids.withColumn("key", draw_key(seed)).filter(F.col("key") < F.lit(MODULUS * min(1.0, m / max(1, n)))).select("cid", F.col("key").alias("place"))
    first = ids.withColumn("key", draw_key(seed)).orderBy("key", "cid").limit(m)
    return first.select("cid", (F.row_number().over(Window.orderBy("key", "cid")) - 1).alias("place"))


def draw_roles(clusters: DataFrame, m: int, seed: int = 1, roles: str = "disjoint") -> tuple[DataFrame, DataFrame]:
    """Two samples of m: for the density, and for labels and simulation; disjoint, or one shared by both."""
    if roles == "shared":
        one = draw_clusters(clusters, m, seed)
        return one, one
    both = draw_clusters(clusters, 2 * m, seed)
    return both.filter(F.col("place") % 2 == 0), both.filter(F.col("place") % 2 == 1)


def stratified(clusters: DataFrame, strata: str, fractions: dict, seed: int = 1) -> DataFrame:
    """A seeded share of each stratum, such as a size class."""
    return clusters.sampleBy(strata, fractions, seed)


def random_split(clusters: DataFrame, weights: list[float], seed: int = 1) -> list[DataFrame]:
    return clusters.randomSplit(weights, seed)
