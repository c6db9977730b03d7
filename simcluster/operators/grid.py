"""Grid-filtered join of the boxes of sources and targets."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions import geom as G
from ..sources.stages import is_small

#: Tiles along an axis beyond which a box goes to the coarser grid.
MOST_TILES = 64
#: Boxes in a block of the join that compares all with all.
BLOCK = 4096


@dataclass(frozen=True)
class Grid:
    """Tiles per unit along both axes, and the corner that tile (0, 0) starts from."""

    dx: float
    dy: float
    x0: float = 0.0
    y0: float = 0.0


def grid_granularity(sources: DataFrame, rule: str = "mean_extent", factor: float = 1.0, tiles: int = 1000) -> Grid:
    """Tile size from the sources' boxes: mean_extent (times factor), count (tiles along each axis), or fixed
    (factor units). One aggregate, one row to the driver; without extents tiles are one unit wide."""
    if rule == "fixed":
        return Grid(1 / factor, 1 / factor)
    b = F.col("mbr")
    row = sources.agg(F.avg(b["x2"] - b["x1"]), F.avg(b["y2"] - b["y1"]), F.max(b["x2"]) - F.min(b["x1"]), F.max(b["y2"]) - F.min(b["y1"])).head()
    w, h = (row[2], row[3]) if rule == "count" else (row[0], row[1])
    w, h = (w / tiles, h / tiles) if rule == "count" and w and h else (w, h)
    scale = 1.0 if rule == "count" else factor
    return Grid(1 / (w * scale) if w else 1.0, 1 / (h * scale) if h else 1.0)


def tile_range(box: Column, grid: Grid, closing: str = "floor") -> list[Column]:
    """i1, j1, i2, j2: tiles that a box meets. `floor` takes those it touches, `ceil` one more at the far ends."""
    low = lambda v, o, d: F.floor((v - F.lit(o)) * F.lit(d)).cast("int")
    high = low if closing == "floor" else lambda v, o, d: F.ceil((v - F.lit(o)) * F.lit(d)).cast("int")
    return [low(box["x1"], grid.x0, grid.dx).alias("i1"), low(box["y1"], grid.y0, grid.dy).alias("j1"), high(box["x2"], grid.x0, grid.dx).alias("i2"), high(box["y2"], grid.y0, grid.dy).alias("j2")]


def tiles_of(prefix: str = "") -> Column:
    """Number of tiles of a range."""
    c = lambda k: F.col(f"{prefix}{k}").cast("long")
    return (c("i2") - c("i1") + 1) * (c("j2") - c("j1") + 1)


def z_order(box: Column, grid: Grid) -> Column:
    """A number that is close for most boxes whose centres lie close: bits of both tile numbers in turn (a hint, no index)."""

    def spread(v: Column) -> Column:
        v = v.bitwiseAND(F.lit(0x7FFFFFFF))
        for shift, mask in ((16, 0x0000FFFF0000FFFF), (8, 0x00FF00FF00FF00FF), (4, 0x0F0F0F0F0F0F0F0F), (2, 0x3333333333333333), (1, 0x5555555555555555)):
            v = v.bitwiseOR(F.shiftleft(v, shift)).bitwiseAND(F.lit(mask))
        return v

    tile = lambda a, b, o, d: F.floor(((box[a] + box[b]) / 2 - F.lit(o)) * F.lit(d)).cast("long")
    return spread(tile("x1", "x2", grid.x0, grid.dx)).bitwiseOR(F.shiftleft(spread(tile("y1", "y2", grid.y0, grid.dy)), 1))


def index_geometries(rows: DataFrame, key: str, grid: Grid, closing: str = "floor") -> DataFrame:
    """key, box, tile range, and one row for every tile (i, j)."""
    placed = rows.filter("mbr is not null").select(F.col(key), F.col("mbr"), *tile_range(F.col("mbr"), grid, closing))
    return placed.withColumn("i", F.explode(F.sequence("i1", "i2"))).withColumn("j", F.explode(F.sequence("j1", "j2")))


def candidate_pairs(sources: DataFrame, targets: DataFrame, grid: Grid | None = None, strategy: str | None = None, closing: str = "floor", relation: str = "mbr") -> DataFrame:
    """tid, sid, common_tiles, mbr_hit, shared (area of the boxes' overlap) of pairs that have a tile in common.

    Only ids, boxes and tile ranges are shuffled. A pair appears once: it is kept in the first tile that both
    ranges hold, so no distinct is needed. Boxes of more than MOST_TILES tiles along an axis are joined on a coarser
    grid, so that no box has many rows. Boxes whose tiles lie outside all tiles of the other side's boxes meet none and are
    not shuffled. strategy: None leaves the join to the optimizer; merge and hash force one, broadcast does if a count
    shows that the sources are few, and sorts both sides if they are not: from the size of files the optimizer cannot know
    how many rows the boxes become. relation: `mbr`, or `intersects` to make mbr_hit the exact test on polygons' areas.
    """
    grid = grid or grid_granularity(sources)
    (wide, *of_sources), (far, *of_targets) = (_extent(rows, grid, closing) for rows in (sources, targets))
    wide = max(wide, far)
    sources, targets = _reaching(sources, of_targets, grid, closing), _reaching(targets, of_sources, grid, closing)
    if wide <= MOST_TILES:
        pairs = _joined(sources, targets, grid, grid, strategy, closing)
    else:  # boxes of many tiles meet all others on a coarse grid, the rest each other on the fine one
        coarse = Grid(grid.dx / -(-wide // MOST_TILES), grid.dy / -(-wide // MOST_TILES), grid.x0, grid.y0)
        big = _tiles_along(F.col("mbr"), grid, closing) > MOST_TILES
        small_s, small_t = sources.filter(~big), targets.filter(~big)
        pairs = _joined(small_s, small_t, grid, grid, strategy, closing)
        pairs = pairs.unionByName(_joined(sources.filter(big), targets, coarse, grid, None, closing))
        pairs = pairs.unionByName(_joined(small_s, targets.filter(big), coarse, grid, None, closing))
    return pairs if relation == "mbr" else refine(pairs, sources, targets, relation)


def _tiles_along(box: Column, grid: Grid, closing: str) -> Column:
    """The larger number of tiles of a box along an axis."""
    i1, j1, i2, j2 = tile_range(box, grid, closing)
    return F.greatest(i2 - i1, j2 - j1) + 1


def _extent(rows: DataFrame, grid: Grid, closing: str) -> tuple:
    """The most tiles of a box along an axis, and least i1 and j1 and greatest i2 and j2 of all boxes (none without boxes)."""
    i1, j1, i2, j2 = tile_range(F.col("mbr"), grid, closing)
    wide, *ends = rows.agg(F.max(_tiles_along(F.col("mbr"), grid, closing)), F.min(i1), F.min(j1), F.max(i2), F.max(j2)).head()
    return wide or 1, *ends


def _reaching(rows: DataFrame, ends: list, grid: Grid, closing: str) -> DataFrame:
    """Rows of which a tile lies between the ends that _extent gives of the other side."""
    if ends[0] is None:
        return rows
    i1, j1, i2, j2 = tile_range(F.col("mbr"), grid, closing)
    return rows.filter((i2 >= ends[0]) & (j2 >= ends[1]) & (i1 <= ends[2]) & (j1 <= ends[3]))


def _joined(sources: DataFrame, targets: DataFrame, by: Grid, grid: Grid, strategy: str | None, closing: str) -> DataFrame:
    """Pairs that have a tile of `grid` in common, joined on the tiles of `by`."""
    s, t = index_geometries(sources, "sid", by, closing), index_geometries(targets, "tid", by, closing)
    s = s.select("sid", "i", "j", *[F.col(c).alias(f"s_{c}") for c in ("mbr", "i1", "j1", "i2", "j2")])
    t = t.select("tid", "i", "j", *[F.col(c).alias(f"t_{c}") for c in ("mbr", "i1", "j1", "i2", "j2")])
    if strategy == "broadcast":
        s = F.broadcast(s) if is_small(s) else s.hint("merge")
    elif strategy:
        s = s.hint({"merge": "merge", "hash": "shuffle_hash"}[strategy])
    first = (F.col("i") == F.greatest("s_i1", "t_i1")) & (F.col("j") == F.greatest("s_j1", "t_j1"))
    both = t.join(s, ["i", "j"]).filter(first)
    if by != grid:
        for p in ("s", "t"):
            both = both.withColumns({f"{p}_{k}": v for k, v in zip(("i1", "j1", "i2", "j2"), tile_range(F.col(f"{p}_mbr"), grid, closing), strict=True)})
    width, height = F.least("s_i2", "t_i2") - F.greatest("s_i1", "t_i1") + 1, F.least("s_j2", "t_j2") - F.greatest("s_j1", "t_j1") + 1
    if by != grid:
        both = both.filter((width > 0) & (height > 0))
    return both.select("tid", "sid", (width.cast("long") * height).alias("common_tiles"), G.mbr_intersects(F.col("s_mbr"), F.col("t_mbr")).alias("mbr_hit"), G.mbr_shared(F.col("s_mbr"), F.col("t_mbr")).alias("shared"))


def refine(pairs: DataFrame, sources: DataFrame, targets: DataFrame, relation: str, backend: str = "arrow") -> DataFrame:
    """mbr_hit narrowed to polygons that intersect, or of which the target contains or is within the source.

    Exact on areas: pairs that only touch, and lines, have no shared area and do not intersect here.
    """
    from ..functions import clip

    lay = lambda rows, key, p: rows.select(F.col(key), *[c.alias(f"{p}{k}") for c, k in zip(clip.edge_arrays(G.normalize_rings(F.col("geom"))), clip.EDGES, strict=True)], G.area(F.col("geom")).alias(f"{p}area"))
    hit = pairs.filter("mbr_hit").join(lay(sources, "sid", "s"), "sid").join(lay(targets, "tid", "t"), "tid")
    inter = clip.shared_column([F.col(f"s{k}") for k in clip.EDGES], [F.col(f"t{k}") for k in clip.EDGES], backend)
    tests = {"intersects": F.col("inter") > 1e-9, "contains": F.col("inter") >= F.col("sarea") * (1 - 1e-9), "within": (F.col("tarea") > 0) & (F.col("inter") >= F.col("tarea") * (1 - 1e-9))}
    exact = hit.withColumn("inter", inter).select("tid", "sid", tests[relation].alias("ok"))
    return pairs.join(exact, ["tid", "sid"], "left").withColumn("mbr_hit", F.coalesce("ok", F.lit(False))).drop("ok")


def candidate_pairs_nested_loop(sources: DataFrame, targets: DataFrame) -> DataFrame:
    """tid and sid of pairs whose boxes meet, without an index: the baseline that compares all with all.

    Boxes travel in blocks of at most BLOCK, every block of targets meets every block of sources, and a pair of blocks
    is compared at once. A task holds a pair of blocks and its hits.
    """
    tasks = 4 * sources.sparkSession.sparkContext.defaultParallelism
    s, t = _blocks(sources, "sid", "s"), _blocks(targets, "tid", "t").repartition(tasks)
    kind = lambda rows, key: f"{key} {rows.schema[key].dataType.simpleString()}"
    return t.crossJoin(s).mapInArrow(_all_with_all, f"{kind(targets, 'tid')}, {kind(sources, 'sid')}")


def _blocks(rows: DataFrame, key: str, p: str) -> DataFrame:
    """Ids and corners of boxes as lists, a row for each block."""
    names = [f"{p}_{c}" for c in ("x1", "y1", "x2", "y2")]

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, BLOCK):
                part = batch.slice(at, BLOCK)
                lists = [pa.ListArray.from_arrays(pa.array([0, part.num_rows], pa.int32()), c) for c in part.columns]
                yield pa.RecordBatch.from_arrays(lists, [key, *names])

    flat = rows.filter("mbr is not null").select(key, *[F.col(f"mbr.{n[2:]}").cast("double").alias(n) for n in names])
    return flat.mapInArrow(pack, f"{key} array<{rows.schema[key].dataType.simpleString()}>, " + ", ".join(f"{n} array<double>" for n in names))


def _all_with_all(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """tid and sid of boxes that meet, from pairs of blocks; some rows of the one against all of the other at a time."""
    for batch in batches:
        for k in range(batch.num_rows):
            own = {n: batch.column(n)[k].values for n in batch.schema.names}
            x1, y1, x2, y2 = (own[f"t_{c}"].to_numpy(zero_copy_only=False)[:, None] for c in ("x1", "y1", "x2", "y2"))
            u1, v1, u2, v2 = (own[f"s_{c}"].to_numpy(zero_copy_only=False) for c in ("x1", "y1", "x2", "y2"))
            pairs, held = [], 0
            for at in range(0, len(x1), 64):
                to = slice(at, at + 64)
                hit = x1[to] <= u2
                for meets in (u1 <= x2[to], y1[to] <= v2, v1 <= y2[to]):
                    hit &= meets
                pairs.append(np.flatnonzero(hit) + at * len(u1))
                held += len(pairs[-1])
                if held and (held > 100_000 or to.stop >= len(x1)):
                    i, j = np.divmod(np.concatenate(pairs), len(u1))
                    yield pa.RecordBatch.from_arrays([own["tid"].take(pa.array(i)), own["sid"].take(pa.array(j))], ["tid", "sid"])
                    pairs, held = [], 0
