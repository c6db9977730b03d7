"""Clusters: the sources whose boxes meet a target's box; statistics of sources and targets."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def build_clusters(pairs: DataFrame, min_size: int = 2, max_size: int | None = None) -> DataFrame:
    """cid and sid in long form, with the cluster's size and what the pair shares: one shuffle by cluster, nothing collected."""
    size = F.count("*").over(Window.partitionBy("tid"))
    out = pairs.filter("mbr_hit").select(F.col("tid").alias("cid"), "sid", size.alias("size"), "common_tiles", "shared").filter(F.col("size") >= min_size)
    return out if max_size is None else out.filter(F.col("size") <= max_size)


def nested_clusters(members: DataFrame, max_size: int = 100_000) -> DataFrame:
    """cid, part, members, size: the nested form. A cluster has one row per max_size members, dealt by their hash."""
    part = F.pmod(F.xxhash64("sid"), F.ceil(F.col("size") / max_size)).cast("int")
    return members.groupBy("cid", part.alias("part")).agg(F.array_sort(F.collect_set("sid")).alias("members"), F.first("size").alias("size"))


def source_stats(pairs: DataFrame) -> DataFrame:
    """Per source: total (common tiles), distinct (targets with a common tile), real (targets with a hit)."""
    return pairs.groupBy("sid").agg(F.sum("common_tiles").alias("total"), F.count("*").alias("distinct"), F.count_if("mbr_hit").alias("real"))


def target_stats(pairs: DataFrame) -> DataFrame:
    """Per target: sum of common tiles over its candidates, their number, and the number of hits."""
    return pairs.groupBy("tid").agg(F.sum("common_tiles").alias("total"), F.count("*").alias("distinct"), F.count_if("mbr_hit").alias("real"))


def approximate_sources(pairs: DataFrame, rsd: float = 0.02) -> DataFrame:
    """Exact and approximate numbers of distinct sources with a hit."""
    hits = pairs.filter("mbr_hit")
    return hits.agg(F.count_distinct("sid").alias("exact"), F.approx_count_distinct("sid", rsd).alias("approximate"))


def representatives(members: DataFrame, targets: DataFrame) -> DataFrame:
    """cid and the target's geometry and box, which meet all members' boxes."""
    return targets.select(F.col("tid").alias("cid"), "geom", "mbr").join(members.select("cid").distinct(), "cid", "left_semi")


def unclustered(members: DataFrame, targets: DataFrame) -> DataFrame:
    """Targets that have no cluster."""
    return targets.join(members.select(F.col("cid").alias("tid")).distinct(), "tid", "left_anti").select("tid")
