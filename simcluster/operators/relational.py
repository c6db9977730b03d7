"""General operators around the search: range, interval and as-of joins, roll-ups, top-k, comparison of results."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

#: Windows of equal bounds that a row of an interval join holds.
WINDOWS_AT_ONCE = 4096


def range_join(a: DataFrame, b: DataFrame, width: float, lo: str = "lo", hi: str = "hi", a_key: str = "a", b_key: str = "b") -> DataFrame:
    """a_key and b_key of rows whose closed ranges meet: an equi-join of bins of the given width.

    A pair is kept in the first bin that both ranges reach, so it appears once.
    """
    cut = lambda c: F.floor(F.col(c) / F.lit(width)).cast("long")

    def binned(df: DataFrame, key: str, p: str) -> DataFrame:
        own = df.select(F.col(key), F.col(lo).alias(f"{p}lo"), F.col(hi).alias(f"{p}hi"), cut(lo).alias(f"{p}first"), cut(hi).alias(f"{p}last")).filter(F.col(f"{p}lo") <= F.col(f"{p}hi"))
        return own.withColumn("bin", F.explode(F.sequence(f"{p}first", f"{p}last")))

    both = binned(a, a_key, "x").join(binned(b, b_key, "y"), "bin").filter((F.col("bin") == F.greatest("xfirst", "yfirst")) & (F.col("xlo") <= F.col("yhi")) & (F.col("ylo") <= F.col("xhi")))
    return both.select(a_key, b_key)


def interval_join(events: DataFrame, windows: DataFrame, seconds: int, ts: str = "ts", start: str = "start_ts", end: str = "end_ts") -> DataFrame:
    """Events with the windows that hold them (start inclusive, end exclusive), by bins of time.

    Windows of equal bounds are joined as one, in lists of at most WINDOWS_AT_ONCE, and unfolded afterwards.
    """
    at = lambda c: F.floor(F.col(c).cast("double") / seconds).cast("long")
    last = F.floor((F.col(end).cast("double") - 1e-6) / seconds).cast("long")
    rest = [c for c in windows.columns if c not in (start, end)]
    place = F.row_number().over(Window.partitionBy(start, end).orderBy(F.lit(0)))
    part = F.floor((place - 1) / WINDOWS_AT_ONCE).alias("_part")
    lists = windows.filter(F.col(start) < F.col(end)).select("*", part).groupBy(start, end, "_part").agg(F.collect_list(F.struct(*rest) if rest else F.lit(0)).alias("_rows")).drop("_part")
    spread = lists.withColumn("bin", F.explode(F.sequence(at(start), last)))
    spark = events.sparkSession  # few bytes go in and many rows come out: adaptive execution must not put the bins into a task or two
    tasks = max(4 * spark.sparkContext.defaultParallelism, int(spark.conf.get("spark.sql.shuffle.partitions")))
    held = events.withColumn("bin", at(ts)).repartition(tasks, "bin").join(spread.repartition(tasks, "bin"), "bin").filter((F.col(ts) >= F.col(start)) & (F.col(ts) < F.col(end)))
    return held.select(*events.columns, F.explode("_rows").alias("_row"), start, end).select(*events.columns, *[F.col(f"_row.{c}").alias(c) if c in rest else F.col(c) for c in windows.columns])


def asof_join(left: DataFrame, right: DataFrame, on: str, by: str, value: str, tie: str | None = None) -> DataFrame:
    """Each left row with the value of the last right row of its key at or before its time.

    One union, one shuffle by key, one running frame; no join.
    """
    names = [c for c in left.columns if c not in (on, by)]
    l_rows = left.select(by, on, F.lit(1).alias("_side"), F.lit(None).cast(right.schema[value].dataType).alias(value), F.struct(*names).alias("_row"))
    r_rows = right.select(by, on, F.lit(0).alias("_side"), value, F.lit(None).cast(l_rows.schema["_row"].dataType).alias("_row"))
    order = Window.partitionBy(by).orderBy(on, "_side").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    out = r_rows.unionByName(l_rows).withColumn("_last", F.last(value, ignorenulls=True).over(order)).filter("_side = 1")
    return out.select(by, on, "_row.*", F.col("_last").alias(value))


def only_in(a: DataFrame, b: DataFrame, key: str) -> DataFrame:
    """Rows of a whose key b has."""
    return a.join(b.select(key).distinct(), key, "left_semi")


def not_in(a: DataFrame, b: DataFrame, key: str) -> DataFrame:
    """Rows of a whose key b does not have."""
    return a.join(b.select(key), key, "left_anti")


def rollup_result(rows: DataFrame, keys: tuple[str, ...], mode: str = "rollup", value: str = "si") -> DataFrame:
    """Counts and means of a value over rollup, cube or all single keys (grouping sets) of the keys."""
    aggs = [F.count("*").alias("n"), F.avg(value).alias("mean"), F.grouping_id().alias("gid")]
    if mode == "sets":
        return rows.groupingSets([[F.col(k)] for k in keys] + [[]], *[F.col(k) for k in keys]).agg(*aggs)
    return (rows.rollup(*keys) if mode == "rollup" else rows.cube(*keys)).agg(*aggs)


def top_k(df: DataFrame, k: int, *by: Column | str) -> DataFrame:
    """The k first rows in an order: k rows per task travel, not all."""
    return df.orderBy(*by).limit(k)


def top_k_per(df: DataFrame, key: str, k: int, *by: Column | str) -> DataFrame:
    """The k first rows of each key; the optimizer cuts groups before the shuffle."""
    return df.withColumn("_n", F.row_number().over(Window.partitionBy(key).orderBy(*by))).filter(F.col("_n") <= k).withColumnRenamed("_n", "place")


def sort_result(df: DataFrame, *by: Column | str, within: bool = False) -> DataFrame:
    """A total order, or an order inside partitions only."""
    return df.sortWithinPartitions(*by) if within else df.orderBy(*by)


def compare_results(a: DataFrame, b: DataFrame, multiset: bool = False) -> dict[str, DataFrame]:
    """What is in both, in a only, in b only, and in any."""
    if multiset:
        return {"both": a.intersectAll(b), "only_a": a.exceptAll(b), "only_b": b.exceptAll(a), "any": a.unionByName(b)}
    return {"both": a.intersect(b), "only_a": a.subtract(b), "only_b": b.subtract(a), "any": a.unionByName(b).distinct()}


def moving_value(events: DataFrame, seconds: int, key: str = "user_id", ts: str = "ts", value: str = "value") -> DataFrame:
    """Mean of a value over each row's last seconds, of the same key."""
    frame = Window.partitionBy(key).orderBy(F.col(ts).cast("timestamp").cast("long")).rangeBetween(-seconds, 0)
    return events.withColumn("moving", F.avg(value).over(frame))


def sessions(events: DataFrame, gap_seconds: int, key: str = "user_id", ts: str = "ts") -> DataFrame:
    """key, session start, end and number of events: a session ends where nothing follows for the gap."""
    w = F.session_window(F.col(ts), f"{gap_seconds} seconds")
    return events.groupBy(key, w.alias("w")).agg(F.count("*").alias("n"), F.min(ts).alias("first_ts"), F.max(ts).alias("last_ts")).drop("w")


def windows(events: DataFrame, width: str, slide: str | None = None, ts: str = "ts", value: str = "value") -> DataFrame:
    """Counts and mean of a value by tumbling or sliding windows."""
    w = F.window(F.col(ts), width, slide) if slide else F.window(F.col(ts), width)
    return events.groupBy(w.alias("w")).agg(F.count("*").alias("n"), F.avg(value).alias("mean")).select(F.col("w.start").alias("start_ts"), "n", "mean")
