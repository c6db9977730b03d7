"""Geometries lifted from the given tables by whole-number arithmetic; see FIXTURES.md for the rules."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import geom as G
from .tables import load_table

# Directions of vertices, the whole-number points of a circle of radius 5 from east, leftwards.
DIRECTIONS = ((5, 0), (4, 3), (3, 4), (0, 5), (-3, 4), (-4, 3), (-5, 0), (-4, -3), (-3, -4), (0, -5), (3, -4), (4, -3))


@dataclass(frozen=True)
class Workload:
    """Width of the domain at scale 1 is `base`; sources lie in the first `permille` thousandths of it."""

    name: str
    sources: str
    targets: str
    base: int
    permille: int


WORKLOADS = {w.name: w for w in (Workload("d1", "orders", "lineitem", 113000, 500), Workload("d2", "customer", "orders", 25500, 226), Workload("d3", "part", "lineitem", 24000, 180))}


def domain(spark: SparkSession, sf_dir: str, work: Workload) -> tuple[int, int]:
    """Width of the domain and of the part with sources, from the number of orders."""
    rows = load_table(spark, sf_dir, "orders").count()
    width = int(work.base * (rows / 1_500_000) ** 0.5 + 1e-6)
    return width, width * work.permille // 1000


_PLACES = np.array(DIRECTIONS)
_BOX = "struct<x1:double,y1:double,x2:double,y2:double>"


def _rings(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """id, geom and mbr from id, cx, cy, h, n, line: all vertices of a batch at once. Null numbers give null coordinates."""
    for batch in batches:
        k, cx, cy, h, n = (pc.fill_null(c, 0).to_numpy(zero_copy_only=False) for c in batch.columns[:5])
        void = np.logical_or.reduce([c.is_null().to_numpy(zero_copy_only=False) for c in batch.columns[:5]])
        n = np.where(void, 0, n)
        ends = np.cumsum(n)
        row, j = np.repeat(np.arange(len(n)), n), np.arange(int(n.sum())) - np.repeat(ends - n, n)
        radius = 1 + h[row] * (5 + np.fmod(np.fmod(k[row], 6) * (j + 1), 6)) // 50  # k * (j + 1) may fit no long
        place = _PLACES[12 * j // n[row]]
        axes = [(c[row] + radius * place[:, i]) / 128.0 for i, c in enumerate((cx, cy))]
        cuts, line = pa.array(np.r_[0, ends].astype(np.int32)), pc.fill_null(batch.column(5), False)
        lists = [pa.ListArray.from_arrays(cuts, pa.array(v), mask=pa.array(void)) for v in axes]
        part = pa.StructArray.from_arrays([pc.if_else(line, "path", "shell"), *lists], ["role", "xs", "ys"])
        parts = pa.ListArray.from_arrays(pa.array(np.arange(len(n) + 1, dtype=np.int32)), part)
        geom = pa.StructArray.from_arrays([pc.if_else(line, "linestring", "polygon"), parts], ["kind", "parts"])
        box = np.zeros((4, len(n)))
        if len(row):
            at = np.flatnonzero(~void)
            box[:, at] = [f.reduceat(v, (ends - n)[at]) for f in (np.minimum, np.maximum) for v in axes]
        mbr = pa.StructArray.from_arrays([pa.array(v) for v in box], ["x1", "y1", "x2", "y2"], mask=pa.array(void))
        yield pa.RecordBatch.from_arrays([batch.column(0), geom, mbr], [batch.schema.names[0], "geom", "mbr"])


def _lifted(rows: DataFrame, key: str, line: Column) -> DataFrame:
    numbers = [F.col(c).cast("long").alias(c) for c in (key, "cx", "cy", "h", "n")]
    return rows.select(*numbers, line.alias("line")).mapInArrow(_rings, f"{key} long, geom {G.GEOM}, mbr {_BOX}")


def lift_sources(spark: SparkSession, sf_dir: str, name: str = "d1", family: str = "regional") -> DataFrame:
    """sid, geom and mbr of a workload's sources."""
    work = WORKLOADS[name]
    w, m = domain(spark, sf_dir, work)
    first, second = {"orders": ("o_orderkey", "o_custkey"), "customer": ("c_custkey", "c_nationkey"), "part": ("p_partkey", "p_size")}[work.sources]
    rows = load_table(spark, sf_dir, work.sources).select(F.col(first).cast("long").alias("sid"), F.col(second).cast("long").alias("o"))
    rows = rows.select("sid", ((F.col("sid") * 7919 + F.col("o") * 104729) % m).alias("cx"), ((F.col("sid") * 6151 + F.col("o") * 3571) % w).alias("cy"))
    k = F.col("sid")
    if family == "flat":
        h, n = 20 + k % 60, 3 + (7 * k) % 10
    else:
        band = F.floor(8 * F.col("cx") / m).cast("long")
        h, n = 30 + (k * 11) % (5 + 6 * band), 4 + (k * 7) % (1 + band)
    return _lifted(rows.withColumns({"h": h, "n": n}), "sid", F.lit(False))


def packing(rows: DataFrame) -> tuple[int, int]:
    """Factors that pack the four keys of a line item into one long without collisions; an error if none can."""
    o, p, s = rows.agg(F.max("l_orderkey"), F.max("l_partkey"), F.max("l_suppkey")).head()
    step, width = max(1_000_000_000, 8 * (o or 0) + 8), max(1001, (s or 0) + 1)
    if step * ((p or 0) * width + width) >= 1 << 63:
        raise ValueError("the keys of line items do not fit one long; number the items and lift those numbers")
    return step, width


def item_factors(items: DataFrame) -> tuple[int, int]:
    """Factors of the packed keys of line items: those of the comparison SQL as long as no two items of these tables
    get one number by them, larger ones (`packing`) if some do. One aggregate, and one more where keys exceed the factors."""
    step, width = 1_000_000_000, 1001
    o, p, s = items.agg(F.max("l_orderkey"), F.max("l_partkey"), F.max("l_suppkey")).head()
    if 8 * (o or 0) + 8 <= step and (s or 0) < width and step * ((p or 0) * width + width) < 1 << 63:
        return step, width
    if step * ((p or 0) * width + (s or 0) + 1) + 8 * (o or 0) + 8 >= 1 << 63:
        return packing(items)
    names = ("l_orderkey", "l_linenumber", "l_partkey")  # equal in these and in the number: equal in the fourth
    several = F.lit(False)
    for c in names:
        several = several | (F.min(c) < F.max(c))
    clash = items.groupBy(_packed(step, width)).agg(several.alias("several")).filter("several")
    return (step, width) if clash.isEmpty() else packing(items)


def _packed(step: int, width: int) -> Column:
    ok, ln, pk, sk = (F.col(f"l_{c}").cast("long") for c in ("orderkey", "linenumber", "partkey", "suppkey"))
    return (ok * 8 + ln + F.lit(step) * (pk * width + sk)).alias("tid")


def lift_targets(spark: SparkSession, sf_dir: str, name: str = "d1") -> DataFrame:
    """tid, geom and mbr of a workload's targets; every second kind is an open line."""
    work = WORKLOADS[name]
    w, _ = domain(spark, sf_dir, work)
    if work.targets == "orders":
        rows = load_table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("tid"), F.col("o_custkey").alias("o"), (5 + F.floor("o_totalprice").cast("long") % 60).alias("h"), (F.col("o_orderkey") % 2 == 0).alias("line"))
        rows = rows.select("tid", ((F.col("tid") * 7919 + F.col("o") * 104729) % w).alias("cx"), ((F.col("tid") * 6151 + F.col("o") * 3571) % w).alias("cy"), "h", "line")
    else:
        keys = ["l_orderkey", "l_linenumber", "l_partkey", "l_suppkey"]
        items = load_table(spark, sf_dir, "lineitem")
        rows = items.groupBy(*keys).agg(F.max("l_quantity").alias("q"), F.max("l_linestatus").alias("status"))
        ok, ln, pk, sk = (F.col(c).cast("long") for c in keys)
        rows = rows.select(_packed(*item_factors(items)), ((ok * 7919 + pk * 104729 + ln * 613) % w).alias("cx"), ((ok * 6151 + sk * 3571 + ln * 977) % w).alias("cy"), (2 * F.floor("q").cast("long")).alias("h"), (F.col("status") == "O").alias("line"))
    return _lifted(rows.withColumn("n", 3 + F.col("tid") % 10), "tid", F.col("line"))


def trajectories(events: DataFrame) -> DataFrame:
    """One open line per user and day: x is the value, y the number in the properties, in order of time."""
    rows = events.withColumn("k", F.get_json_object("props", "$.k").cast("double")).filter("value is not null and k is not null")
    paths = rows.groupBy("user_id", F.to_date("ts").alias("day")).agg(F.array_sort(F.collect_list(F.struct("ts", "event_id", "value", "k"))).alias("p")).filter(F.size("p") >= 2)
    xs, ys = F.transform("p", lambda e: e["value"]), F.transform("p", lambda e: e["k"])
    return paths.select((F.col("user_id") * 100_000 + F.datediff("day", F.lit("1970-01-01"))).alias("tid"), "user_id", "day", G.geometry(F.lit("linestring"), xs, ys).alias("geom")).withColumn("mbr", G.mbr(F.col("geom")))


def embedding_rings(embeddings: DataFrame) -> DataFrame:
    """Closed rings from eight pairs of coordinates, put in order of their angle about the mean; family: label."""
    pairs = F.transform(F.sequence(F.lit(0), F.lit(7)), lambda i: F.struct(F.get("embedding", (2 * i).cast("int")).cast("double").alias("x"), F.get("embedding", (2 * i + 1).cast("int")).cast("double").alias("y")))
    mean = lambda axis: F.aggregate("p", F.lit(0.0), lambda acc, q: acc + q[axis]) / 8
    rows = embeddings.filter(F.size("embedding") >= 16).select("vec_id", "label", pairs.alias("p")).withColumns({"mx": mean("x"), "my": mean("y")})
    turned = F.array_sort(F.transform("p", lambda q: F.struct(F.atan2(q["y"] - F.col("my"), q["x"] - F.col("mx")).alias("t"), q["x"].alias("x"), q["y"].alias("y"))))
    rows = rows.select(F.col("vec_id").alias("sid"), "label", turned.alias("p"))
    return rows.select("sid", "label", G.geometry(F.lit("polygon"), F.transform("p", lambda q: q["x"]), F.transform("p", lambda q: q["y"])).alias("geom")).withColumn("mbr", G.mbr(F.col("geom")))
