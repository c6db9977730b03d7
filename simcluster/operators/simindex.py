"""The similarity index of clusters: the mean likeness over the unordered pairs of members."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions import alike as A
from ..functions import clip
from ..functions import fourier as D
from ..functions import geom as G
from ..functions import metrics as M
from ..functions import shapes as S
from ..sources.stages import drop_stage, stage, stage_path

#: Members up to which a cluster's pairs are unfolded from a list.
NESTED_SIZE = 2048
#: Pairs of members that a task of the nested layout gets, about, and fewer than which are not dealt out.
PART_PAIRS = 8_000_000
LEAST_PAIRS = 50_000
SCALARS = ("n", "area", "perimeter", "aspect", "phi", "bx", "by", "fd")


def describe_shapes(sources: DataFrame, key: str = "sid", centered: bool = True, harmonics: int = D.HARMONICS, samples: int = D.SAMPLES, sampling: str = "arclength", scale_free: bool = True, elongation: bool = False) -> DataFrame:
    """Everything a pair needs of a shape, computed once per geometry: scalars, descriptor, edges; a batch at a time."""
    rows = sources.select(F.col(key).alias("sid"), F.col("geom").cast(G.GEOM).alias("geom"))
    run = S.describer(centered=centered, harmonics=harmonics, samples=samples, sampling=sampling, scale_free=scale_free, elongation=elongation)
    return rows.mapInArrow(run, f"sid {sources.schema[key].dataType.simpleString()}, {S.SCHEMA}")


def describe_shapes_by_expressions(sources: DataFrame, key: str = "sid", centered: bool = True, harmonics: int = D.HARMONICS, samples: int = D.SAMPLES, sampling: str = "arclength", scale_free: bool = True, elongation: bool = False) -> DataFrame:
    """The same columns from the geometry expressions: the scalar form that the batches are measured against."""
    shaped = sources.select(F.col(key).alias("sid"), G.normalize_rings(F.col("geom")).alias("geom"))
    shaped = shaped.withColumn("shape", G.center(F.col("geom")) if centered else F.col("geom"))
    g, box = F.col("shape"), F.col("box")
    boxed = shaped.withColumn("box", G.mbr(g)).withColumns({"area": G.area(g), "perimeter": G.perimeter(g)})
    return boxed.select(
        "sid",
        G.n_points(g).alias("n"),
        "area",
        "perimeter",
        G.aspect_ratio(box, elongation=elongation).alias("aspect"),
        G.circularity(F.col("area"), F.col("perimeter")).alias("phi"),
        ((box["x1"] + box["x2"]) / 2).alias("bx"),
        ((box["y1"] + box["y2"]) / 2).alias("by"),
        D.fourier_descriptor(F.col("geom"), harmonics, samples, sampling, scale_free).alias("fd"),
        *clip.edge_arrays(g),
    )


def _sides(shapes: DataFrame, with_edges: bool) -> tuple[DataFrame, DataFrame]:
    names = SCALARS + (tuple(f"e{k}" for k in clip.EDGES) if with_edges else ())
    return tuple(shapes.select(F.col("sid").alias(p), *[F.col(c).alias(f"{p}_{c}") for c in names]) for p in ("a", "b"))


def pair_similarities(pairs: DataFrame, shapes: DataFrame, weights: dict[str, float] | None = None, backend: str = "arrow", unit: float = 1.0, breakdown: bool = False) -> DataFrame:
    """a, b, s (and the measures) of pairs of shape ids. Clipping is left out if no weight needs it."""
    own = M.check_weights(weights)
    clipped = breakdown or any(name in own for name in M.CATEGORIES["overlap"])
    inter = None
    if clipped and backend == "sql":
        inter = clip.intersection_area(pairs, shapes, "sql")
        joined = pairs.select("a", "b").join(inter, ["a", "b"])
        left, right = _sides(shapes, False)
    else:
        joined = pairs.select("a", "b")
        left, right = _sides(shapes, clipped)
    joined = joined.join(left, "a").join(right, "b")
    if clipped and backend != "sql":
        joined = joined.withColumn("inter", clip.shared_column([F.col(f"a_e{k}") for k in clip.EDGES], [F.col(f"b_e{k}") for k in clip.EDGES], backend))
    values = measure_columns(unit, clipped)
    named = joined.select("a", "b", *[values[k].alias(k) for k in M.NAMES if k in values and (breakdown or k in own)])
    out = named.withColumn("s", M.combined_similarity({k: F.col(k) for k in own}, own))
    return out if breakdown else out.select("a", "b", "s")


def measure_columns(unit: float = 1.0, clipped: bool = True) -> dict[str, Column]:
    """The measures over columns a_* and b_* (and inter)."""
    a, b = ({c: F.col(f"{p}_{c}") for c in SCALARS} for p in ("a", "b"))
    values = {
        "curvature": M.curvature_similarity(a["n"], b["n"]),
        "fourier": M.fourier_similarity(a["fd"], b["fd"]),
        "aspect": M.aspect_similarity(a["aspect"], b["aspect"]),
        "perimeter": M.perimeter_similarity(a["perimeter"], b["perimeter"], unit),
        "bbox": M.bbox_similarity(a["bx"], a["by"], b["bx"], b["by"], unit),
        "circularity": M.circularity_similarity(a["phi"], b["phi"]),
    }
    if clipped:
        values |= {"jaccard": M.jaccard(F.col("inter"), a["area"], b["area"]), "area": M.area_similarity(F.col("inter"), a["area"], b["area"])}
    return values


def member_pairs(members: DataFrame, cids: DataFrame | None = None, largest: int = NESTED_SIZE) -> DataFrame:
    """cid, a, b of all unordered pairs of members with a < b, of all clusters or of those in cids.

    Clusters up to `largest` members are gathered and unfolded, one shuffle of the members; larger ones are joined
    with themselves, where adaptive execution splits a hot cluster.
    """
    own = members.select("cid", "sid", *(["size"] if "size" in members.columns else []))
    if cids is not None:
        own = own.join(cids.select("cid"), "cid", "left_semi")
    if "size" not in own.columns:
        own = own.withColumn("size", F.lit(None).cast("long"))
    lists = own.filter(F.col("size") <= largest).groupBy("cid").agg(F.array_sort(F.collect_list("sid")).alias("m"))
    first = lists.select("cid", "m", F.posexplode(F.slice("m", F.lit(1), F.size("m") - 1)).alias("at", "a"))
    pairs = first.select("cid", "a", F.explode(F.slice("m", F.col("at") + 2, F.size("m"))).alias("b")).filter("a < b")
    if "size" in members.columns and not has_larger(members, largest):
        return pairs
    big = own.filter(F.coalesce(F.col("size") > largest, F.lit(True))).select("cid", "sid")
    return pairs.unionByName(big.withColumnRenamed("sid", "a").join(big.withColumnRenamed("sid", "b"), "cid").filter("a < b"))


def has_larger(members: DataFrame, largest: int) -> bool:
    return not members.filter(F.col("size") > largest).isEmpty()


def similarity_index(members: DataFrame, shapes: DataFrame, weights: dict[str, float] | None = None, cids: DataFrame | None = None, backend: str = "arrow", memo: bool = True, breakdown: bool = False, max_pairs: int | None = None, unit: float = 1.0, layout: str = "long", nested: Nested | None = None) -> DataFrame:
    """cid, n_pairs and si of every cluster.

    memo computes each distinct pair once, however many clusters hold it: by owners (`owned_index`) with the arrow backend,
    else by a join that brings the value back.
    breakdown adds the mean of each measure. max_pairs takes a seeded share of the pairs of larger clusters and
    adds the half width of a 95 % interval. layout `nested` computes clusters up to NESTED_SIZE members from lists
    instead of joining pairs; nested holds them if they are known.
    """
    if layout == "nested":
        if "size" not in members.columns:
            members = members.withColumn("size", F.count("*").over(Window.partitionBy("cid")))
        small = nested_index(nested or nest(members), shapes, weights, cids, unit)
        if not has_larger(members, NESTED_SIZE):
            return small
        return small.unionByName(nested_index(stripes(members.filter(F.col("size") > NESTED_SIZE)), shapes, weights, cids, unit))
    if memo and backend == "arrow" and not breakdown and max_pairs is None and "size" in members.columns:
        small = owned_index(nested or nest(members), shapes, weights, cids, unit)
        if not has_larger(members, NESTED_SIZE):
            return small
        return small.unionByName(nested_index(stripes(members.filter(F.col("size") > NESTED_SIZE)), shapes, weights, cids, unit))
    pairs = member_pairs(members, cids) if max_pairs is None else sampled_pairs(members, max_pairs, cids)
    if memo:
        sims = pair_similarities(pairs.select("a", "b").distinct(), shapes, weights, backend, unit, breakdown)
        joined = pairs.join(sims, ["a", "b"])
    else:
        keyed = pairs.withColumnsRenamed({"a": "x", "b": "y"})
        left, right = _sides(shapes, True)
        joined = keyed.join(left.withColumnRenamed("a", "x"), "x").join(right.withColumnRenamed("b", "y"), "y")
        joined = joined.withColumn("inter", clip.shared_column([F.col(f"a_e{k}") for k in clip.EDGES], [F.col(f"b_e{k}") for k in clip.EDGES], backend))
        joined = joined.select("cid", *[v.alias(k) for k, v in measure_columns(unit).items()]).withColumn("s", M.combined_similarity({k: F.col(k) for k in M.NAMES}, weights))
    means = [F.avg(k).alias(k) for k in M.NAMES] if breakdown else []
    out = joined.groupBy("cid").agg(F.count("*").alias("n_pairs"), F.avg("s").alias("si"), *means)
    return out.withColumn("half_width", F.sqrt(F.log(F.lit(2 / 0.05)) / (2 * F.col("n_pairs")))) if max_pairs is not None else out


@dataclass(frozen=True)
class Nested:
    """Clusters of bounded size as lists of members: cid, m and the key of the task that computes them; number of keys."""

    lists: DataFrame
    keys: int
    striped: bool = False


def nest(members: DataFrame, places: DataFrame | None = None, largest: int = NESTED_SIZE) -> Nested:
    """Clusters whose size is `largest` at most, dealt to tasks with about PART_PAIRS pairs each; written once.

    places gives cid and a number `place` that is close for clusters close to each other: tasks get stretches of it,
    so that pairs which several clusters hold meet in one task. Where a stretch holds many pairs its clusters are dealt.
    """
    lists = members.filter(F.col("size") <= largest).groupBy("cid").agg(F.array_sort(F.collect_list("sid")).alias("m"))
    lists = lists.join(places.select("cid", "place"), "cid", "left") if places is not None else lists.withColumn("place", F.xxhash64("cid"))
    path = stage_path(lists.sparkSession, "nested")
    lists = stage(lists, "nested", path)
    n = F.size("m").cast("long")
    pairs = F.sum(n * (n - 1) / 2)
    total = lists.agg(pairs).head()[0] or 0
    tasks = lists.sparkSession.sparkContext.defaultParallelism
    parts = int(max(1, total // PART_PAIRS, min(4 * tasks, total // LEAST_PAIRS)))
    if parts == 1:
        return Nested(lists.select("cid", "m", F.lit(0).cast("long").alias("key")), 1)
    lists = stage(lists.repartitionByRange(parts, "place", "cid").withColumn("part", F.spark_partition_id()), "nested-parts")
    drop_stage(lists.sparkSession, path)
    heavy = {r[0]: int(r[1] // PART_PAIRS) + 1 for r in lists.groupBy("part").agg(pairs.alias("pairs")).filter(F.col("pairs") > 2 * PART_PAIRS).collect()}
    key = F.col("part").cast("long") * 1_000_000
    if heavy:
        pieces = F.create_map(*[F.lit(x) for kv in heavy.items() for x in kv])
        key = key + F.pmod(F.xxhash64("cid"), F.coalesce(pieces[F.col("part")], F.lit(1)))
    return Nested(lists.select("cid", "m", key.alias("key")), parts + sum(heavy.values()))


def stripes(members: DataFrame) -> Nested:
    """Clusters of any size, each dealt to tasks of about PART_PAIRS pairs: a task has the whole list and compares
    every stripes-th member from stripe on with those after it."""
    lists = members.filter("cid is not null").groupBy("cid").agg(F.array_sort(F.collect_list("sid")).alias("m"))
    n = F.size("m").cast("long")
    lists = stage(lists.withColumn("stripes", F.ceil((n * (n - 1) / 2 + 1) / PART_PAIRS).cast("long")), "striped")
    keys = int(lists.agg(F.sum("stripes")).head()[0] or 1)
    dealt = lists.withColumn("stripe", F.explode(F.sequence(F.lit(0).cast("long"), F.col("stripes") - 1)))
    return Nested(dealt.select("cid", "m", "stripe", "stripes", F.xxhash64("cid", "stripe").alias("key")), keys, True)


def nested_index(nested: Nested, shapes: DataFrame, weights: dict[str, float] | None = None, cids: DataFrame | None = None, unit: float = 1.0) -> DataFrame:
    """cid, n_pairs and si of nested clusters: a task reads the lists of its clusters and each shape in them once.

    No pair is written or shuffled; pairs that several clusters of a task hold are computed once.
    """
    own_weights = M.check_weights(weights)
    lists = nested.lists if cids is None else nested.lists.join(cids.select("cid"), "cid", "left_semi")
    used = lists.select(F.col("key").alias("task"), F.explode("m").alias("sid")).distinct().join(shapes.select(*A.COLUMNS), "sid")
    kind = lists.schema["cid"].dataType.simpleString()

    def run(left: pa.Table, right: pa.Table) -> pa.Table:
        m = left["m"].combine_chunks()
        sizes = pc.list_value_length(m).to_numpy(zero_copy_only=False)
        part = [left[c].to_numpy() for c in ("stripe", "stripes")] if striped else [np.zeros(len(sizes), np.int64), np.ones(len(sizes), np.int64)]
        pairs, valued, sums = A.cluster_sums(A.Shapes(right, own_weights, unit), pc.list_flatten(m).to_numpy(zero_copy_only=False), sizes, *part)
        return pa.table([left["cid"], pa.array(pairs), pa.array(valued), pa.array(sums)], ["cid", "n_pairs", "valued", "sums"]).filter(pa.array(pairs > 0))

    n, striped = min(nested.keys, 4096), nested.striped
    sums = lists.repartition(n, "key").groupBy("key").cogroup(used.repartition(n, "task").groupBy("task")).applyInArrow(run, f"cid {kind}, n_pairs long, valued long, sums double")
    if striped:
        sums = sums.groupBy("cid").agg(*[F.sum(c).alias(c) for c in ("n_pairs", "valued", "sums")])
    return sums.select("cid", "n_pairs", F.when(F.col("valued") > 0, F.col("sums") / F.col("valued")).alias("si"))


def owned_index(nested: Nested, shapes: DataFrame, weights: dict[str, float] | None = None, cids: DataFrame | None = None, unit: float = 1.0) -> DataFrame:
    """cid, n_pairs and si of nested clusters, each distinct pair computed once in all.

    A shape belongs to one of the tasks whose clusters hold it (a seeded choice), and all pairs with it as the first to that
    task. A list goes to the owners of its members, every one adds up its own pairs, and a cluster's sums meet at the end: lists
    and sums are shuffled, pairs are not. Clusters beyond `largest` of nest are not here.
    """
    own_weights = M.check_weights(weights)
    lists = nested.lists if cids is None else nested.lists.join(cids.select("cid"), "cid", "left_semi")
    kind, item = (lists.schema[c].dataType.simpleString() for c in ("cid", "m"))
    n = min(nested.keys, 4096)
    unfold = lambda rows: rows.select(F.col("key").alias("task"), F.explode("m").alias("sid")).distinct()
    owner = unfold(lists).groupBy("sid").agg(F.min_by("task", F.xxhash64("task", "sid")).alias("owner"))
    dealt = stage(lists, "owned-lists") if cids is not None else lists
    if nested.keys > 1:
        homes = unfold(dealt).join(owner, "sid").select("task", "sid", "owner")

        def deal(left: pa.Table, right: pa.Table) -> pa.Table:
            right = right.sort_by("sid")
            m = left["m"].combine_chunks()
            m = m.chunk(0) if isinstance(m, pa.ChunkedArray) else m
            sizes = pc.list_value_length(m).to_numpy(zero_copy_only=False)
            flat, row = pc.list_flatten(m).to_numpy(zero_copy_only=False), np.repeat(np.arange(len(sizes)), sizes)
            first = np.arange(len(flat)) != np.cumsum(sizes)[row] - 1  # the last one of a list is the first of no pair
            tasks, place = np.unique(right["owner"].to_numpy()[np.searchsorted(right["sid"].to_numpy(), flat[first])], return_inverse=True)
            at, to = np.divmod(np.unique(row[first] * max(1, len(tasks)) + place), max(1, len(tasks)))
            return pa.table([left["cid"].take(pa.array(at)), left["m"].take(pa.array(at)), pa.array(tasks[to])], ["cid", "m", "key"])

        dealt = stage(dealt.repartition(n, "key").groupBy("key").cogroup(homes.repartition(n, "task").groupBy("task")).applyInArrow(deal, f"cid {kind}, m {item}, key long"), "owned-lists")
    used = unfold(dealt).join(owner, "sid").select("task", "sid", (F.col("owner") == F.col("task")).alias("mine")).join(shapes.select(*A.COLUMNS), "sid")

    def run(left: pa.Table, right: pa.Table) -> pa.Table:
        m = left["m"].combine_chunks()
        sizes = pc.list_value_length(m).to_numpy(zero_copy_only=False)
        mine = np.sort(right.filter(right["mine"])["sid"].to_numpy())
        pairs, valued, sums = A.owned_sums(A.Shapes(right, own_weights, unit), pc.list_flatten(m).to_numpy(zero_copy_only=False), sizes, mine)
        return pa.table([left["cid"], pa.array(pairs), pa.array(valued), pa.array(sums)], ["cid", "n_pairs", "valued", "sums"]).filter(pa.array(pairs > 0))

    sums = dealt.repartition(n, "key").groupBy("key").cogroup(used.repartition(n, "task").groupBy("task")).applyInArrow(run, f"cid {kind}, n_pairs long, valued long, sums double")
    sums = sums.groupBy("cid").agg(*[F.sum(c).alias(c) for c in ("n_pairs", "valued", "sums")])
    return sums.select("cid", "n_pairs", F.when(F.col("valued") > 0, F.col("sums") / F.col("valued")).alias("si"))


def sampled_pairs(members: DataFrame, max_pairs: int, cids: DataFrame | None = None, seed: int = 5) -> DataFrame:
    """cid, a, b: all pairs of clusters that have max_pairs at most, and about so many seeded ones of larger clusters.

    The other pairs are never made: each member of a large cluster meets members at a few distances in a seeded order.
    """
    sized = members.select("cid", "sid").join(cids.select("cid"), "cid", "left_semi") if cids is not None else members.select("cid", "sid")
    placed = sized.select("cid", "sid", F.row_number().over(Window.partitionBy("cid").orderBy(F.xxhash64("sid", F.lit(seed)), "sid")).alias("at"), F.count("*").over(Window.partitionBy("cid")).cast("int").alias("size"))
    whole = F.col("size") * (F.col("size") - 1) <= 2 * max_pairs
    half = F.floor(F.col("size") / 2).cast("int")  # farther distances are those from the other side
    each = F.least(half, F.ceil(F.lit(max_pairs) / F.col("size")).cast("int"))
    picks = F.transform(F.sequence(F.lit(1), each), lambda i: 1 + F.pmod(F.xxhash64("cid", F.lit(seed)) + i, half).cast("int"))
    large = placed.filter(~whole).withColumn("step", F.explode(picks))
    other = placed.select(F.col("cid"), F.col("sid").alias("other"), F.col("at").alias("there"))
    met = large.withColumn("there", F.pmod(F.col("at") - 1 + F.col("step"), F.col("size")) + 1).join(other, ["cid", "there"])
    some = met.select("cid", F.least("sid", "other").alias("a"), F.greatest("sid", "other").alias("b")).distinct()
    return member_pairs(placed.filter(whole).select("cid", "sid", "size")).unionByName(some)


def similarity_bounds(members: DataFrame, shapes: DataFrame, weights: dict[str, float] | None = None, cids: DataFrame | None = None, unit: float = 1.0) -> DataFrame:
    """cid, lo, hi: bounds of the index without clipping: six measures exactly, the overlap from areas alone."""
    own = M.check_weights(weights)
    pairs = member_pairs(members, cids)
    left, right = _sides(shapes, False)
    sims = pairs.select("a", "b").distinct().join(left, "a").join(right, "b")
    values = measure_columns(unit, clipped=False)
    jaccard_cap, area_cap = M.overlap_bounds(F.col("a_area"), F.col("b_area"))
    low = sum((F.lit(own[k]) * v for k, v in values.items() if k in own), F.lit(0.0))
    high = low + F.lit(own.get("jaccard", 0.0)) * jaccard_cap + F.lit(own.get("area", 0.0)) * area_cap
    return pairs.join(sims.select("a", "b", low.alias("lo"), high.alias("hi")), ["a", "b"]).groupBy("cid").agg(F.avg("lo").alias("lo"), F.avg("hi").alias("hi"))


def si_histogram(si: DataFrame, width: float = 0.1) -> DataFrame:
    """bin (lower end), clusters: counts by steps of the index; the last step holds its upper end."""
    last = round(1 / width) - 1
    at = F.least(F.floor(F.col("si") / F.lit(width) + 1e-12), F.lit(last))
    return si.groupBy(F.round(at * width, 6).alias("bin")).agg(F.count("*").alias("clusters"))
