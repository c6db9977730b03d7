"""Verification of clusters in order of their scores, within a budget."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..sources.stages import stage

TOP_K = 100_000
#: Decimals of a score or an index that decide a rank.
PLACES = 9


def ranked(column: str) -> Column:
    """The value by which clusters are ranked: rounded, so that the order of summation never changes places."""
    return F.round(F.col(column), PLACES)


def largest(rows: DataFrame, column: str, k: int, top_k: int = TOP_K) -> DataFrame:
    """The k rows with the largest value of the column (rounded), ties by cid.

    A small k is a top-k. A large one is cut at approximate quantiles that keep too many by a little, counts
    what lies surely above, and orders only the narrow band around the cut: no sort of all rows, no task with all of them.
    """
    if k <= 0:
        return rows.limit(0)
    if k <= top_k:
        return rows.orderBy(ranked(column).desc(), "cid").limit(k)
    total = rows.count()
    if k >= total:
        return rows
    share, slack = k / total, 0.002
    low, high = rows.select(ranked(column).alias("_value")).agg(F.percentile_approx("_value", [max(0.0, 1 - share - slack), min(1.0, 1 - share + slack)], 10_000)).head()[0]
    above = rows.filter(ranked(column) > F.lit(high))
    missing = k - above.count()
    band = rows.filter((ranked(column) >= F.lit(low)) & (ranked(column) <= F.lit(high)))
    if missing < 0 or band.count() < missing:  # the quantiles were off: the exact way
        return rows.orderBy(ranked(column).desc(), "cid").limit(k)
    if missing > top_k:  # many values close to the cut
        return above.unionByName(places(band, column).filter(F.col("place") <= missing).drop("place"))
    return above.unionByName(band.orderBy(ranked(column).desc(), "cid").limit(missing))


def select_frontier(scored: DataFrame, budget: int, top_k: int = TOP_K) -> DataFrame:
    """The budget clusters with the largest w, ties by cid."""
    return largest(scored, "w", budget, top_k)


def verify(scored: DataFrame, budget: int, tau: float, index_of: Callable[[DataFrame], DataFrame], memo: DataFrame | None = None, bounds_of: Callable[[DataFrame], DataFrame] | None = None) -> DataFrame:
    """cid, si, w of clusters within the budget whose index reaches tau.

    index_of computes cid, si of some clusters. memo holds indices that are known already. bounds_of gives lo
    and hi without clipping: clusters whose hi is below tau are rejected unseen, which never changes the result.
    """
    front = select_frontier(scored, budget)
    todo = front
    if bounds_of is not None:
        possible = bounds_of(front.select("cid")).filter(F.col("hi") >= F.lit(tau - 1e-9)).select("cid")
        todo = front.join(possible, "cid", "left_semi")
    if memo is None:
        si = index_of(todo.select("cid")).select("cid", "si")
    else:
        known = memo.select("cid", "si").join(todo.select("cid"), "cid", "left_semi")
        si = known.unionByName(index_of(todo.select("cid").join(memo.select("cid"), "cid", "left_anti")).select("cid", "si"))
    return todo.select("cid", "w").join(si, "cid").filter(F.col("si") >= F.lit(tau)).select("cid", "si", "w")


def verify_in_waves(scored: DataFrame, budget: int, tau: float, index_of: Callable[[DataFrame], DataFrame], batch: int, stop: str = "budget", target: int | None = None, least_yield: float = 0.0, keep: Callable[[DataFrame], DataFrame] = lambda df: stage(df, "wave")) -> tuple[DataFrame, int]:
    """Result and number of clusters checked, verifying `batch` clusters at a time in order of w.

    stop: budget (only there), recall (once `target` clusters are found) or yield (once a wave finds less than
    the share least_yield).
    """
    placed = keep(places(select_frontier(scored, budget), "w").withColumnRenamed("place", "rank"))
    found, checked, hits = None, 0, 0
    while checked < budget:
        wave = placed.filter((F.col("rank") > checked) & (F.col("rank") <= checked + batch))
        size = wave.count()
        if not size:
            break
        got = keep(wave.join(index_of(wave.select("cid")).select("cid", "si"), "cid").filter(F.col("si") >= F.lit(tau)).select("cid", "si", "w"))
        n = got.count()
        checked, hits = checked + size, hits + n
        found = got if found is None else found.unionByName(got)
        if stop == "recall" and target is not None and hits >= target or stop == "yield" and n < least_yield * size:
            break
    return found if found is not None else scored.select("cid", F.lit(0.0).alias("si"), "w").limit(0), checked


def places(rows: DataFrame, column: str) -> DataFrame:
    """rows with their place in rank order, from ranges of the value that are each ordered by themselves.

    The only thing that one task sees whole is the list of the ranges' sizes.
    """
    parts = rows.select("*", ranked(column).alias("_value")).repartitionByRange(F.desc("_value"), "cid").withColumn("_part", F.spark_partition_id())
    parts = stage(parts, "ranges")
    sizes = parts.groupBy("_part").agg(F.count("*").alias("n"))  # ranges are numbered in their order
    before = Window.orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)
    starts = sizes.select("_part", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("_before"))
    inside = F.row_number().over(Window.partitionBy("_part").orderBy(F.desc("_value"), "cid"))
    return parts.withColumn("_at", inside).join(F.broadcast(starts), "_part").select(*rows.columns, (F.col("_before") + F.col("_at")).alias("place"))


def rank_result(result: DataFrame) -> DataFrame:
    """The result with its rank by index."""
    return places(result, "si").withColumn("rank", F.col("place").cast("int")).drop("place")


def result_pairs(result: DataFrame, members: DataFrame) -> DataFrame:
    """The result as pairs of cluster and source."""
    return members.select("cid", "sid").join(result.select("cid", "si"), "cid")
