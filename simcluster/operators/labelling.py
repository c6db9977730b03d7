"""Labels of sampled clusters, drawn until both classes have enough."""

from __future__ import annotations

import warnings
from collections.abc import Callable

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .sampling import draw_key


def label_clusters(si: DataFrame, tau: float) -> DataFrame:
    """label 1 where the index reaches the cut-off."""
    return si.withColumn("label", F.when(F.col("si") >= F.lit(tau), 1.0).otherwise(0.0))


def training_prefix(labelled: DataFrame, n: int, seed: int = 2) -> DataFrame:
    """The shortest head of a seeded order in which both classes have n clusters; all, if none has.

    The window is over a sample of bounded size.
    """
    order = Window.orderBy("key", "cid").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    keyed = labelled.withColumn("key", draw_key(seed))
    run = keyed.withColumns({"pos": F.sum("label").over(order), "seen": F.row_number().over(Window.orderBy("key", "cid"))})
    run = run.withColumn("enough", (F.col("pos") >= n) & (F.col("seen") - F.col("pos") >= n))
    stop = F.coalesce(F.min(F.when(F.col("enough"), F.col("seen"))).over(Window.partitionBy()), F.lit(1 << 60))
    return run.withColumn("stop", stop).filter(F.col("seen") <= F.col("stop")).drop("stop", "enough", "key")


def collect_training(sample: DataFrame, index_of: Callable[[DataFrame], DataFrame], tau: float, n: int, seed: int = 2, first: int | None = None) -> DataFrame:
    """cid, si, label of sample clusters in a seeded order, their indices computed in growing chunks until both
    classes have n. index_of computes cid, si of some clusters; each chunk is twice the one before."""
    order = Window.orderBy("key", "cid")
    keyed = sample.select("cid").withColumn("key", draw_key(seed)).withColumn("at", F.row_number().over(order) - 1)
    total = keyed.count()
    lo, size, parts = 0, first or 2 * n, []
    while lo < total:
        chunk = keyed.filter((F.col("at") >= lo) & (F.col("at") < lo + size)).select("cid")
        parts.append(index_of(chunk).select("cid", "si"))
        got = parts[0]
        for x in parts[1:]:
            got = got.unionByName(x)
        counts = label_clusters(got, tau).agg(F.sum("label"), F.count("*")).head()
        pos = counts[0] or 0
        if pos >= n and counts[1] - pos >= n:
            break
        lo, size = lo + size, size * 2
    else:
        warnings.warn("the sample ended before both classes were full", stacklevel=2)
    return training_prefix(label_clusters(got, tau), n, seed)
