"""Exact Jaccard similarity join of documents on word shingles, and its connected groups.

The join works in the metric space of shingle sets under Jaccard distance d. Documents are pivots: a region's
members are measured against some of them, each goes to the region of its nearest pivot (a Voronoi cell), and
triangle-inequality windows replicate it to each earlier cell whose members it may still be linked with: with the
reach r = 1 - t, x of the cell of p can only be linked with a member of the cell of q if
d(x, q) <= d(x, p) + 2 r and d(x, q) <= r + the radius of q's cell. Cells are divided again until they are small or
stop shrinking; then their members are compared as matrix products. Every pair is compared in one cell only: a
replica is a guest there, and two members that are guests of the same division are not compared.

Before that, an exact pre-step forms blocks, because unrelated texts are all at distance 1 from each other and
windows part nothing among them. Two linked sets share one of the first `n - ceil(t n) + 1` shingles of their
global order, rare shingles first; so all links lie inside the connected parts of the graph of documents and those
shingles, each shingle a star around one document. This reads entries, never pairs. Frequencies cover all
documents; what workers hold of them are bitmaps, whose false positives change the order only, never the result.

Blocks up to `REGION_SETS` sets are divided inside one task. Larger ones are divided by all tasks in rounds: first by
the sizes of sets, since unrelated texts that rare shingles chain to one block differ in those; then members in chunks meet the region's pivots, a dozen or so whatever its size. Members farther than `CORE` from every
pivot form a cell of their own, so that distance 1 is replicated nowhere. A region that does not shrink (its members
are all about as far from each other) is compared in blocks of which each two meet in one task; only there the work
grows with the square of the region, never the rows that are made.

Documents with equal sets collapse to one class first, so groups of copies are one member. Classes have numbers of
their own: ids may be null, and one id may have several texts.

Defined cases: documents of fewer words than a shingle have their whole sequence as one shingle; without words
or text: size 0, linked with nothing, a component of their own; a null id is linked like any other, and is never a
component's smallest id unless all are null; several rows with one id count as one document per text.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass
from functools import reduce

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import drop_shuffles, keep_rows, materialize, maybe_among, narrow, release, small_side

SHINGLE = 4
PERCENT = 85
SUB_BATCH = 500_000  # bytes of text handled at once; a longer text is handled by itself
HELD_TOKENS = 1_000_000  # shingles that a task holds before it passes their counts on
#: Document frequencies from which a shingle falls into the next class of the order, with bits of its bitmap for 1 GB.
CLASSES = ((2, 26), (5, 25), (17, 24), (65, 24))
MOST_BITS = 27
BUCKET_TOKENS = 2_000_000
#: Sets and shingles up to which a region is divided inside one task.
REGION_SETS, REGION_TOKENS = 1024, 2_000_000
PIVOTS = 8
CORE = 0.7
CHUNK_SETS, CHUNK_TOKENS = 256, 250_000
LEAF_SETS = 32
BLOCK_SETS = 384
MATRIX_CELLS = 2_000_000

_P = 0x9E3779B97F4A7C15 | 1
_MASK = (1 << 64) - 1


def _mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[ord("A") : ord("Z") + 1] += 32
_SPACE = np.zeros(256, bool)
_SPACE[[9, 10, 11, 12, 13, 32]] = True
_BYTE = _mix(np.arange(1, 257, dtype=np.uint64) * np.uint64(_P))
_POWERS = np.ones(1, np.uint64)
_INVERSE = np.ones(1, np.uint64)


def _powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    """The first n powers of an odd base and of its inverse, modulo 2**64."""
    global _POWERS, _INVERSE
    if len(_POWERS) < n:
        size = 1 << (n - 1).bit_length()
        with np.errstate(over="ignore"):
            _POWERS = np.multiply.accumulate(np.r_[np.ones(1, np.uint64), np.full(size - 1, _P, np.uint64)])
            _INVERSE = np.multiply.accumulate(np.r_[np.ones(1, np.uint64), np.full(size - 1, pow(_P, -1, 1 << 64), np.uint64)])
    return _POWERS, _INVERSE


def shingles(data: np.ndarray, lens: np.ndarray, size: int = SHINGLE) -> tuple[np.ndarray, np.ndarray]:
    """Sorted distinct shingle hashes of texts that lie one after the other in UTF-8, and where each one's end."""
    doc_end = np.cumsum(lens)
    low = _LOWER[data]
    solid = ~_SPACE[low]
    cut = np.zeros(len(data) + 1, bool)  # places at which a text begins
    cut[doc_end] = True
    before, after = np.zeros(len(data), bool), np.zeros(len(data), bool)
    before[1:], after[:-1] = solid[:-1], solid[1:]
    begin = np.flatnonzero(solid & (~before | cut[:-1]))
    end = np.flatnonzero(solid & (~after | cut[1:])) + 1
    if not len(begin):
        return np.zeros(0, np.uint64), np.zeros(len(lens), np.int64)
    with np.errstate(over="ignore"):
        powers, inverse = _powers(len(data) + 1)
        total = np.r_[np.zeros(1, np.uint64), np.cumsum(_BYTE[low] * powers[: len(low)], dtype=np.uint64)]
        word = _mix(((total[end] - total[begin]) * inverse[begin]) ^ ((end - begin).astype(np.uint64) * np.uint64(0xD6E8FEB86659FD93)))
        doc = np.searchsorted(doc_end, begin, side="right")
        first = np.searchsorted(doc, np.arange(len(lens) + 1))
        counts = np.diff(first)
        h = np.zeros(max(0, len(word) - size + 1), np.uint64)
        for i in range(size):
            h = _mix(h * np.uint64(_P) + word[i : i + len(h)] + np.uint64(i + 1))
        whole = doc[: len(h)] == doc[size - 1 :] if len(h) else np.zeros(0, bool)
        out_doc, out = [doc[: len(h)][whole]], [h[whole]]
        few = np.flatnonzero((counts > 0) & (counts < size))
        if len(few):
            short = np.zeros(len(few), np.uint64)
            for i in range(size - 1):
                more = counts[few] > i
                short[more] = _mix(short[more] * np.uint64(_P) + word[first[few[more]] + i] + np.uint64(i + 101))
            out_doc.append(few)
            out.append(short)
    d, h = np.concatenate(out_doc), np.concatenate(out)
    order = np.lexsort((h, d))
    d, h = d[order], h[order]
    keep = np.r_[True, (d[1:] != d[:-1]) | (h[1:] != h[:-1])] if len(d) else np.zeros(0, bool)
    d, h = d[keep], h[keep]
    return h, np.cumsum(np.bincount(d, minlength=len(lens))) if len(d) else np.zeros(len(lens), np.int64)


def shingles_of(texts: list[str | None], size: int = SHINGLE) -> list[np.ndarray]:
    """Hashes of each text's shingles, for tests and single texts."""
    raw = [x.encode("utf-8", "surrogatepass") if isinstance(x, str) else b"" for x in texts]
    h, ends = shingles(np.frombuffer(b"".join(raw), np.uint8), np.fromiter(map(len, raw), np.int64, len(raw)), size)
    return np.split(h, ends[:-1]) if raw else []


def _parts(batch: pa.RecordBatch, size: int) -> Iterator[tuple[pa.RecordBatch, np.ndarray, np.ndarray, np.ndarray]]:
    """Row blocks of about SUB_BATCH bytes with their shingles, and where each row's begin and end.

    Texts are read in place from the batch's buffers; no Python string is made.
    """
    column = batch.column(batch.schema.get_field_index("text")).cast(pa.large_string())
    if column.null_count:
        column = column.fill_null("")
    offsets = np.frombuffer(column.buffers()[1], np.int64)[column.offset : column.offset + len(column) + 1]
    data = np.frombuffer(column.buffers()[2] or b"", np.uint8)
    lo = 0
    while lo < len(column):
        hi = max(lo + 1, int(np.searchsorted(offsets, offsets[lo] + SUB_BATCH, side="right")) - 1)
        h, ends = shingles(data[offsets[lo] : offsets[hi]], np.diff(offsets[lo : hi + 1]), size)
        yield batch.slice(lo, hi - lo), h, np.r_[0, ends[:-1]], ends
        lo = hi


def prefix_length(n: np.ndarray, percent: int) -> np.ndarray:
    """Pivots to which a set of n shingles is replicated: n - ceil(t n) + 1."""
    return n - (percent * n + 99) // 100 + 1


@dataclass
class Frequencies:
    """Bitmaps of shingles whose document frequency reaches the bounds of CLASSES, with their bits."""

    maps: list[np.ndarray]
    bits: list[int]

    def classes(self, h: np.ndarray) -> np.ndarray:
        out = np.zeros(len(h), np.int64)
        for bits, bitmap in zip(self.bits, self.maps, strict=True):
            at = h >> np.uint64(64 - bits)
            out += (bitmap[(at >> np.uint64(3)).astype(np.int64)] >> (at & np.uint64(7)).astype(np.uint8)) & 1
        return out


def count_shingles(rows: DataFrame, size: int) -> Frequencies:
    """Document frequencies over all rows: packed counts per task, summed per bucket of hashes.

    A bucket owns one stretch of every bitmap, so tasks return stretches and the driver only puts them side by
    side. Bitmaps double with the input up to 2**MOST_BITS bits each; beyond that more rare shingles count as frequent.
    """
    total = rows.agg(F.coalesce(F.sum(F.octet_length("text")), F.lit(0))).head()[0]
    bucket_bits = min(20, max(5, math.ceil(math.log2(max(1, total / 6 / BUCKET_TOKENS)))))
    more = max(0, math.ceil(math.log2(max(1, total / (1 << 30)))))
    sizes = [max(bucket_bits + 3, min(MOST_BITS, bits + more)) for _, bits in CLASSES]

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[np.ndarray] = []

        def flush() -> pa.RecordBatch:
            h = np.concatenate(held)
            held.clear()
            h.sort()
            first = np.flatnonzero(np.r_[True, h[1:] != h[:-1]])
            n = np.minimum(np.diff(np.r_[first, len(h)]), 255).astype(np.uint8)
            h = h[first]
            ids = ((h << np.uint64(bucket_bits)) >> np.uint64(32)).astype(np.uint32)
            cuts = np.searchsorted(h >> np.uint64(64 - bucket_bits), np.arange((1 << bucket_bits) + 1, dtype=np.uint64))
            full = [b for b in range(1 << bucket_bits) if cuts[b + 1] > cuts[b]]
            return pa.RecordBatch.from_arrays([pa.array(full, pa.int32()), pa.array([ids[cuts[b] : cuts[b + 1]].tobytes() for b in full], pa.binary()), pa.array([n[cuts[b] : cuts[b + 1]].tobytes() for b in full], pa.binary())], ["bucket", "ids", "counts"])

        for batch in batches:
            for _, h, _, _ in _parts(batch, size):
                held.append(h)
                if sum(map(len, held)) > HELD_TOKENS:
                    yield flush()
        if sum(map(len, held)):
            yield flush()

    def tally(key: tuple, pdf: pd.DataFrame) -> pd.DataFrame:
        ids = np.concatenate([np.frombuffer(x, np.uint32) for x in pdf["ids"]])
        counts = np.concatenate([np.frombuffer(x, np.uint8) for x in pdf["counts"]])
        order = np.argsort(ids, kind="stable")
        ids, counts = ids[order], counts[order].astype(np.int64)
        starts = np.flatnonzero(np.r_[True, ids[1:] != ids[:-1]])
        ids, counts = ids[starts], np.add.reduceat(counts, starts)
        out = []
        for (least, _), bits in zip(CLASSES, sizes, strict=True):
            own = bits - bucket_bits
            hot = ids[counts >= least] >> np.uint32(32 - own)
            flags = np.zeros(1 << own, np.uint8)
            flags[hot] = 1
            out.append(np.packbits(flags, bitorder="little").tobytes() if len(hot) else b"")
        return pd.DataFrame({"bucket": [key[0]], "maps": [out]})

    packed = rows.select("text").mapInArrow(pack, "bucket int, ids binary, counts binary")
    got = packed.groupBy("bucket").applyInPandas(tally, "bucket int, maps array<binary>")
    maps = [np.zeros(1 << (bits - 3), np.uint8) for bits in sizes]
    for row in got.collect():
        for full, part in zip(maps, row["maps"], strict=True):
            if part:
                full[row["bucket"] * len(full) >> bucket_bits :][: len(full) >> bucket_bits] = np.frombuffer(bytes(part), np.uint8)
    return Frequencies(maps, sizes)


META = "id {id}, mark long, digest long, digest2 long, n int, regions array<long>"


def describe(rows: DataFrame, freq: Frequencies, size: int, percent: int, id_type: str) -> DataFrame:
    """Per row (id, mark, text): class digest (128 bits), set size, shingles that others have among the first ones."""
    held = rows.sparkSession.sparkContext.broadcast(freq)

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = held.value
        for batch in batches:
            for part, h, starts, ends in _parts(batch, size):
                n = ends - starts
                doc = np.repeat(np.arange(len(n)), n)
                rank = own.classes(h)
                one, two = _digests(h, starts, ends)
                order = np.lexsort((h, rank, doc))
                first = np.arange(len(h)) - starts[doc] < prefix_length(n, percent)[doc]
                pick = order[first & (rank[order] > 0)]
                cuts = np.searchsorted(doc[pick], np.arange(len(n) + 1)).astype(np.int32)
                regions = pa.ListArray.from_arrays(pa.array(cuts), pa.array(h[pick].view(np.int64)))
                yield pa.RecordBatch.from_arrays([part.column("id"), part.column("mark"), pa.array(one), pa.array(two), pa.array(n.astype(np.int32)), regions], ["id", "mark", "digest", "digest2", "n", "regions"])

    return rows.mapInArrow(work, META.format(id=id_type))


def _digests(h: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Two sums over mixed hashes per set, which together tell sets apart."""
    with np.errstate(over="ignore"):
        return _sums(_mix(h + np.uint64(0x1234567)), starts, ends), _sums(_mix(h ^ np.uint64(0xABCDEF987654321)), starts, ends)


def _sums(values: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """Sums of stretches of hashes, as signed numbers."""
    total = np.r_[np.zeros(1, np.uint64), np.cumsum(values, dtype=np.uint64)]
    return (total[ends] - total[starts]).view(np.int64)


def fetch_sets(rows: DataFrame, wanted: DataFrame, size: int) -> DataFrame:
    """region, node and packed shingles of the wanted classes (region, node, id, digests).

    Only texts whose id may be one of a class are read; classes are told by both digests.
    """

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for _, h, starts, ends in _parts(batch, size):
                one, two = _digests(h, starts, ends)
                yield pa.RecordBatch.from_arrays([pa.array(one), pa.array(two), pa.array([h[a:b].tobytes() for a, b in zip(starts, ends, strict=True)], pa.binary())], ["digest", "digest2", "packed"])

    some = maybe_among(rows, "id", wanted.select("id")).select("text").mapInArrow(pack, "digest long, digest2 long, packed binary")
    return some.join(wanted.drop("id"), ["digest", "digest2"]).select("region", "node", "packed").dropDuplicates(["node"])


def components(links: DataFrame) -> DataFrame:
    """node and root (smallest node reachable) of nodes with links (a, b): large and small stars until only stars are left."""
    edges, before = links.filter("a <> b").select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).distinct(), []
    while True:
        both = edges.unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
        low = both.groupBy("u").agg(F.min("v").alias("m")).withColumn("m", F.least("u", "m"))
        large = both.filter("v > u").join(low, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).filter("u <> v")
        least = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).filter("u <> v").unionByName(least.select("u", F.col("m").alias("v")))
        edges = narrow(small.distinct(), "links")
        release(*before)
        before = [edges]
        several = edges.groupBy("u").agg(F.count("*").alias("n")).filter("n > 1").select("u")
        deeper = edges.select("u").join(edges.select(F.col("v").alias("u")).distinct(), "u", "left_semi")
        if several.unionByName(deeper).isEmpty():  # every node has one edge, to a node that has none
            return edges.select(F.col("u").alias("node"), F.col("v").alias("root"))


def common_counts(left: list[np.ndarray], right: list[np.ndarray] | None = None) -> np.ndarray:
    """Sizes of the intersections of all sets on the left with all on the right (None: with each other), by matrix products."""
    sets = left if right is None else left + right
    n = np.array([len(x) for x in sets])
    h = np.concatenate(sets)
    order = np.argsort(h, kind="stable")
    h, doc = h[order], np.repeat(np.arange(len(n)), n)[order]
    column = np.cumsum(np.r_[True, h[1:] != h[:-1]]) - 1
    shared = np.bincount(column) > 1  # other shingles add nothing to any pair
    keep = shared[column]
    doc, column = doc[keep], (np.cumsum(shared) - 1)[column[keep]]
    common = np.zeros((len(left), len(sets) - (len(left) if right is not None else 0)))
    width = max(1, MATRIX_CELLS // len(n))
    for lo in range(0, int(shared.sum()), width):
        a, b = np.searchsorted(column, (lo, lo + width))
        held = np.zeros((len(n), width), np.float32)
        held[doc[a:b], column[a:b] - lo] = 1
        common += held @ held.T if right is None else held[: len(left)] @ held[len(left) :].T
    return common


def distances(sets: list[np.ndarray], pivot: np.ndarray) -> np.ndarray:
    """Jaccard distance of every set to the pivot."""
    sizes = np.array([len(x) for x in sets])
    h = np.concatenate(sets)
    at = np.minimum(np.searchsorted(pivot, h), len(pivot) - 1)
    hits = np.r_[0, np.cumsum(pivot[at] == h)]
    ends = np.cumsum(sizes)
    common = hits[ends] - hits[ends - sizes]
    return 1 - common / (sizes + len(pivot) - common)


def cells_of(far: np.ndarray, reach: float, core: float | None = None) -> list[tuple[int, np.ndarray, np.ndarray]]:
    """(cell, members, whether they are guests) from distances of members to pivots (rows: members).

    A member's home is the cell of its nearest pivot; it is a guest of earlier cells that its window reaches. With a
    core, members beyond it from every pivot have the last cell for home; without, a cell's radius is that of its members.
    """
    home = far.argmin(axis=1)
    near = far[np.arange(len(far)), home]
    if core is not None:
        home = np.where(near <= core, home, far.shape[1])
    out = []
    for j in range(far.shape[1]):
        own = home == j
        if core is None and not own.any():  # with a core, other tasks may hold the cell's own members
            continue
        radius = core if core is not None else far[own, j].max()
        inner = 0.0 if core is not None else far[own, j].min()
        guest = (home > j) & (far[:, j] <= radius + reach) & (far[:, j] >= inner - reach)
        guest &= (home == far.shape[1]) | (far[:, j] <= near + 2 * reach)
        if len(at := np.flatnonzero(own | guest)):
            out.append((j, at, guest[at]))
    if len(at := np.flatnonzero(home == far.shape[1])):
        out.append((far.shape[1], at, np.zeros(len(at), bool)))
    return out


class Region:
    """Join of one region's sets inside a task; links are counted per set, and sets linked by any chain share a root."""

    def __init__(self, sets: list[np.ndarray], guests: np.ndarray, percent: int, leaf: int = LEAF_SETS):
        self.sets, self.percent, self.leaf = sets, percent, leaf
        self.sizes = np.array([len(x) for x in sets])
        self.reach = 1 - percent / 100 + 1e-9
        self.links = np.zeros(len(sets), np.int64)
        self.root = np.arange(len(sets))
        self.divide(np.arange(len(sets)), guests.astype(np.int64), int(max(0, guests.max(initial=0))).bit_length())

    def divide(self, at: np.ndarray, guests: np.ndarray, depth: int) -> None:
        """Compare the members at; guests has a bit for each division that made a member a guest, depth the next bit."""
        if len(at) > self.leaf and depth < 62:
            sets = [self.sets[i] for i in at]
            far = [distances(sets, sets[0])]
            least = far[0]
            while len(far) < PIVOTS and least.max() > 2 * self.reach:  # the next pivot is the member farthest from all
                far.append(distances(sets, sets[int(least.argmax())]))
                least = np.minimum(least, far[-1])
            cells = cells_of(np.stack(far, axis=1), self.reach) if len(far) > 1 else []
            if cells and max(len(x) for _, x, _ in cells) <= 0.8 * len(at):
                for _, own, guest in cells:
                    self.divide(at[own], guests[own] | (guest.astype(np.int64) << depth), depth + 1)
                return
        for lo in range(0, len(at), BLOCK_SETS):
            for hi in range(lo, len(at), BLOCK_SETS):
                self.compare(at[lo : lo + BLOCK_SETS], guests[lo : lo + BLOCK_SETS], at[hi : hi + BLOCK_SETS], guests[hi : hi + BLOCK_SETS], lo == hi)

    def compare(self, a: np.ndarray, ga: np.ndarray, b: np.ndarray, gb: np.ndarray, same: bool) -> None:
        common = common_counts([self.sets[i] for i in a], None if same else [self.sets[i] for i in b])
        linked = 100 * common >= self.percent * (self.sizes[a][:, None] + self.sizes[b][None, :] - common)
        linked &= (ga[:, None] & gb[None, :]) == 0
        if same:
            np.fill_diagonal(linked, False)
        if not linked.any():
            return
        self.links[a] += linked.sum(axis=1)
        if not same:
            self.links[b] += linked.sum(axis=0)
        while True:  # roots spread over links until no link joins two of them
            ra, rb = self.root[a], self.root[b]
            low_a = np.minimum(ra, np.where(linked, rb[None, :], len(self.root)).min(axis=1, initial=len(self.root)))
            low_b = np.minimum(rb, np.where(linked, ra[:, None], len(self.root)).min(axis=0, initial=len(self.root)))
            moves = np.unique(np.concatenate([np.stack([ra, low_a], 1), np.stack([rb, low_b], 1)]), axis=0)
            moves = moves[moves[:, 0] != moves[:, 1]]
            if not len(moves):
                return
            target = np.arange(len(self.root))
            np.minimum.at(target, moves[:, 0], moves[:, 1])
            while not np.array_equal(target, jumped := target[target]):
                target = jumped
            self.root = target[self.root]


def _sets(packed: pd.Series) -> list[np.ndarray]:
    return [np.frombuffer(p, np.uint64) for p in packed]


def divide_large(todo: DataFrame, percent: int, depth: int, chunk_sets: int) -> DataFrame:
    """One round for regions (region, node, packed, guest, c, t) too large for a task: members in chunks meet the pivots.

    Pivots are members whose hash falls below 2 * PIVOTS / c, about as many in every region.
    """
    reach = 1 - percent / 100 + 1e-9
    chunks = F.ceil(F.greatest(F.col("c") / chunk_sets, F.col("t") / CHUNK_TOKENS)).cast("int")
    todo = todo.withColumn("chunks", chunks)
    members = todo.withColumn("chunk", F.pmod(F.xxhash64(F.lit(depth), "node"), "chunks").cast("int"))
    pivots = todo.filter(F.pmod(F.xxhash64("node", F.lit(depth)), "c") < 2 * PIVOTS).select(F.col("region").alias("of"), F.col("node").alias("pivot"), F.col("packed").alias("held"), F.explode(F.sequence(F.lit(0), F.col("chunks") - 1)).alias("part"))

    def assign(key: tuple, own: pd.DataFrame, chosen: pd.DataFrame) -> pd.DataFrame:
        if not len(own):
            return pd.DataFrame(columns=["region", "cell", "node", "packed", "guest", "parent"])
        sets, chosen = _sets(own["packed"]), chosen.sort_values("pivot")
        far = np.stack([np.ones(len(sets)), *[distances(sets, p) for p in _sets(chosen["held"])]], axis=1)[:, 1:]
        cells = cells_of(far, reach, CORE) if far.shape[1] else [(0, np.arange(len(sets)), np.zeros(len(sets), bool))]
        parts = [pd.DataFrame({"region": own["region"].iloc[at], "cell": cell, "node": own["node"].iloc[at], "packed": own["packed"].iloc[at], "guest": own["guest"].iloc[at] | (guest.astype(np.int64) << depth), "parent": own["c"].iloc[at]}) for cell, at, guest in cells]
        return pd.concat(parts)

    cells = members.select("region", "chunk", "node", "packed", "guest", "c").groupBy("region", "chunk").cogroup(pivots.groupBy("of", "part")).applyInPandas(assign, "region long, cell long, node long, packed binary, guest long, parent long")
    return cells.select(F.xxhash64("region", "cell", F.lit(depth)).alias("region"), "node", "packed", "guest", "parent")


def divide_by_size(todo: DataFrame, percent: int, depth: int) -> DataFrame:
    """The first round for regions too large for a task: cells of sets of about one size.

    Linked sets differ by a factor of 100 / percent at most, so by one class of sizes at most: a cell has one class for
    members and the next larger one for guests. Sets have two rows at most, whatever the size of the region.
    """
    step = math.log(100 / percent) * (1 + 1e-9)
    kind = F.floor(F.log(F.length("packed") / 8) / F.lit(step)).cast("long")
    placed = todo.withColumn("kind", kind)
    held = placed.select("region", F.col("kind").alias("cell")).distinct()
    guests = placed.withColumns({"cell": F.col("kind") - 1, "guest": F.col("guest").bitwiseOR(F.lit(1 << depth))}).join(small_side(held), ["region", "cell"], "left_semi")
    cells = placed.withColumn("cell", F.col("kind")).unionByName(guests)
    return cells.select(F.xxhash64("region", "cell", F.lit("size")).alias("region"), "node", "packed", "guest", F.lit(None).cast("long").alias("parent"))


def sized(todo: DataFrame) -> DataFrame:
    """Regions with their number of sets (c), shingles (t) and their parent's sets."""
    return todo.groupBy("region").agg(F.count("*").alias("c"), F.sum(F.length("packed") / 8).alias("t"), F.max("parent").alias("parent"))


def link_blocks(blocks: DataFrame, percent: int, region_sets: int = REGION_SETS, chunk_sets: int = CHUNK_SETS) -> tuple[DataFrame, bool]:
    """node, root (a node of the same component) and n_links (to be summed) from blocks (region, node, packed), written.

    And whether every region was joined inside a task, so that roots are final. Each round's sets are joined and deleted
    before the next round's are joined: of sets there are two rounds' at most, however many rounds there are.
    """
    def work(pdf: pd.DataFrame) -> pd.DataFrame:
        nodes, roots, counts = [], [], []
        for (_, i, j), part in pdf.groupby(["region", "i", "j"], sort=False):
            guests = part["guest"].to_numpy()
            if i != j:  # only pairs of one member of each block are new here
                block = part["block"].to_numpy()
                at = [np.flatnonzero(block == x) for x in (i, j)]
                got = Region([], np.zeros(0, np.int64), percent)
                got.sets, got.sizes = _sets(part["packed"]), part["packed"].map(len).to_numpy() // 8
                got.links, got.root = np.zeros(len(part), np.int64), np.arange(len(part))
                for lo in range(0, len(at[0]), BLOCK_SETS):
                    for hi in range(0, len(at[1]), BLOCK_SETS):
                        a, b = at[0][lo : lo + BLOCK_SETS], at[1][hi : hi + BLOCK_SETS]
                        got.compare(a, guests[a], b, guests[b], False)
            else:
                got = Region(_sets(part["packed"]), guests, percent)
            own = part["node"].to_numpy()
            some = got.links > 0
            nodes.append(own[some])
            roots.append(own[got.root[some]])
            counts.append(got.links[some])
        return pd.DataFrame({"node": np.concatenate(nodes), "root": np.concatenate(roots), "n_links": np.concatenate(counts)})

    def join(cells: DataFrame) -> DataFrame:
        return materialize(cells.groupBy("cell").applyInPandas(work, "node long, root long, n_links long"), "ngram-links")

    todo, depth, found = blocks.select("region", "node", "packed", F.lit(0).cast("long").alias("guest"), F.lit(None).cast("long").alias("parent")), 0, []
    while True:
        sizes = narrow(sized(todo), "ngram-sizes")
        large = (F.col("c") > region_sets) | (F.col("t") > REGION_TOKENS)
        shrinks = (F.col("c") > 2) & (F.col("parent").isNull() | (F.col("c") <= 0.8 * F.col("parent"))) & F.lit(depth < 40)
        apart = sizes.filter(large)
        if apart.isEmpty():
            found.append(join(_cells(todo, sizes, F.lit(1))))
            break
        parts = F.ceil(F.greatest(F.col("c") / (4 * chunk_sets), F.col("t") / (4 * CHUNK_TOKENS))).cast("int")
        found.append(join(_cells(todo, sizes.filter(~large), F.lit(1)).unionByName(_cells(todo, apart.filter(~shrinks), parts))))
        more = apart.filter(shrinks)
        if more.isEmpty():
            break
        own = todo.drop("parent").join(small_side(more.drop("parent")), "region")
        before, todo = todo, materialize(divide_large(own, percent, depth, chunk_sets) if depth or not 0 < percent < 100 else divide_by_size(own, percent, depth), "ngram-cells")
        if depth:
            release(before)
        depth += 1
    if depth:
        release(todo)
    return reduce(DataFrame.unionByName, found), len(found) == 1


def _cells(todo: DataFrame, sizes: DataFrame, blocks: Column) -> DataFrame:
    """Members of the regions in sizes, dealt to cells of a task each: small regions share cells, blocks of one meet pairwise."""
    cells = 8 * int(todo.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    own = todo.drop("parent").join(sizes.select("region", blocks.alias("blocks")), "region")
    own = own.withColumn("block", F.pmod(F.xxhash64("node"), "blocks").cast("int")).withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    own = own.withColumn("i", F.least("block", "other")).withColumn("j", F.greatest("block", "other"))
    cell = F.when(F.col("blocks") > 1, F.xxhash64("region", "i", "j")).otherwise(F.pmod(F.xxhash64("region"), F.lit(cells)))
    return own.select(cell.alias("cell"), "region", "node", "packed", "guest", "block", "i", "j")


def grouped(docs: DataFrame, id_col: str, text_col: str, shingle: int, percent: int, region_sets: int = REGION_SETS, chunk_sets: int = CHUNK_SETS) -> DataFrame:
    """id, mark (hash of the text), n_shingles, component (smallest id), group (null: alone) and n_links of every row."""
    id_type = docs.schema[id_col].dataType.simpleString()
    rows = docs.select(F.col(id_col).alias("id"), F.xxhash64(F.col(text_col).cast("string")).alias("mark"), F.col(text_col).cast("string").alias("text"))
    freq = count_shingles(rows, shingle)
    drop_shuffles(docs.sparkSession)
    meta = materialize(describe(rows, freq, shingle, percent, id_type), "ngram-meta")
    classes = meta.filter("n > 0").groupBy("digest", "digest2").agg(F.min("id").alias("id"), F.first("regions").alias("regions"))
    classes = narrow(classes.withColumn("node", F.monotonically_increasing_id()), "ngram-classes")
    entries = classes.select("node", F.explode("regions").alias("shingle"))
    stars = entries.groupBy("shingle").agg(F.min("node").alias("a"), F.max("node").alias("most")).filter("a < most").select("shingle", "a")
    edges = entries.join(stars, "shingle").filter("node <> a").select("a", F.col("node").alias("b")).distinct()
    whole = _with_roots(components(edges))
    wanted = narrow(whole.withColumnRenamed("root", "region").join(classes.drop("regions"), "node"), "ngram-wanted")
    blocks = materialize(fetch_sets(rows, wanted, shingle), "ngram-sets")
    drop_shuffles(docs.sparkSession)
    links, final = link_blocks(blocks, percent, region_sets, chunk_sets)
    release(blocks, wanted)
    roots = links.select("node", "root") if final else _with_roots(components(links.select(F.col("node").alias("a"), F.col("root").alias("b"))))
    degree = links.groupBy("node").agg(F.sum("n_links").alias("n_links"))
    linked = roots.join(degree, "node", "left").join(classes.drop("regions"), "node")
    linked = narrow(linked.select("digest", "digest2", "id", "root", "n_links"), "ngram-linked")
    least = linked.groupBy("root").agg(F.min("id").alias("least"))
    named = narrow(linked.join(least, "root").select("digest", "digest2", "root", "least", "n_links"), "ngram-groups")
    alone = classes.select("digest", "digest2", "id", F.col("node").alias("own"))
    out = meta.drop("regions").withColumnRenamed("id", "row_id").join(alone, ["digest", "digest2"], "left").join(named, ["digest", "digest2"], "left")
    component = F.when(F.col("n") == 0, F.col("row_id")).when(F.col("root").isNull(), F.col("id")).otherwise(F.col("least"))
    return out.select(F.col("row_id").alias("id"), "mark", F.col("n").cast("long").alias("n_shingles"), component.alias("component"), F.when(F.col("n") > 0, F.coalesce("root", "own")).alias("group"), F.when(F.col("n") > 0, F.coalesce("n_links", F.lit(0))).otherwise(0).cast("long").alias("n_links"))


def _with_roots(placed: DataFrame) -> DataFrame:
    return placed.unionByName(placed.select(F.col("root").alias("node"), "root").distinct())


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", shingle: int = SHINGLE, percent: int = PERCENT, region_sets: int = REGION_SETS, chunk_sets: int = CHUNK_SETS) -> DataFrame:
    """id, n_shingles, component_id (smallest id reachable by links) and n_links of every row.

    n_links is the number of other classes (different shingle sets) that the row's class is linked with.
    """
    found = grouped(docs, id_col, text_col, shingle, percent, region_sets, chunk_sets)
    return found.select(F.col("id").alias(id_col), "n_shingles", F.col("component").alias("component_id"), "n_links")


def drop_near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", shingle: int = SHINGLE, percent: int = PERCENT) -> DataFrame:
    """Rows of docs, all columns: one of each component, that with the smallest id, and every row without words.

    Rows are told by id and text, so a repeated or null id costs no other text its row; where whole rows repeat in
    both, one of them stays.
    """
    found = materialize(grouped(docs, id_col, text_col, shingle, percent).filter("group is not null").select("id", "mark", "group"), "near-rows")
    order = F.struct(F.col("id").isNull(), F.col("id"), F.col("mark"))
    first = found.groupBy("group").agg(F.min(order).alias("first"), F.count("*").alias("rows")).filter("rows > 1")
    placed = found.join(first, "group").withColumn("stays", order == F.col("first"))
    marks = materialize(placed.groupBy("id", "mark").agg(F.max("stays").alias("stays"), F.count("*").alias("rows")), "near-marks")
    return keep_rows(docs, id_col, F.xxhash64(F.col(text_col).cast("string")), marks)
