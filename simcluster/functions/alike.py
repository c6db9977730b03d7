"""The similarity of many pairs of described shapes at once, in numpy: what `metrics` says in expressions."""

from __future__ import annotations

import numpy as np
import pyarrow as pa

from . import clip
from . import metrics as M

#: Pairs that are held at a time.
PAIRS = 4_000_000
#: Shapes up to which similarities are kept in a square table.
SQUARE = 4096
COLUMNS = ("sid", "n", "area", "perimeter", "aspect", "phi", "bx", "by", "fd", *(f"e{k}" for k in clip.EDGES))


class Shapes:
    """Described shapes in flat arrays, in order of their ids."""

    def __init__(self, rows: pa.Table, weights: dict[str, float], unit: float = 1.0):
        self.weights, self.unit = weights, unit
        rows = rows.combine_chunks().sort_by("sid")
        number = lambda c: rows[c].to_numpy().astype(float)
        self.ids = rows["sid"].to_numpy()
        self.n, self.area, self.perimeter, self.aspect, self.phi, self.bx, self.by = (number(c) for c in COLUMNS[1:8])
        fds = [x.as_py() for x in rows["fd"].slice(0, 1)]
        self.fd = np.stack(rows["fd"].to_numpy(zero_copy_only=False)) if fds else np.zeros((0, 1))
        self.clipped = any(c in weights for c in M.CATEGORIES["overlap"])
        if self.clipped:
            lists = [rows[f"e{k}"].combine_chunks() for k in clip.EDGES]
            lists = [x.chunk(0) if isinstance(x, pa.ChunkedArray) else x for x in lists] if len(self.ids) else [pa.array([], pa.list_(pa.float64()))] * 4
            offsets = lists[0].offsets.to_numpy()
            self.at, self.edges = offsets[:-1], np.diff(offsets)
            self.fan = clip.turned(*[x.values.to_numpy(zero_copy_only=False) for x in lists])

    def likeness(self, i: np.ndarray, j: np.ndarray) -> np.ndarray:
        """The weighted similarity of shapes i and j, element by element; nan where a measure has no value."""
        near = lambda v: 1 / (1 + np.abs(v[i] - v[j]))
        out = np.zeros(len(i))
        if self.clipped:
            inter = clip.shared_of(self.fan, self.at[i], self.edges[i], self.fan, self.at[j], self.edges[j])
            both = self.area[i] + self.area[j]
        for name in M.NAMES:
            if name not in self.weights:
                continue
            with np.errstate(divide="ignore", invalid="ignore"):
                if name == "jaccard":
                    value = np.where(both - inter > 0, inter / (both - inter), 0.0)
                elif name == "area":
                    value = np.where(both > 0, 2 * inter / both, 0.0)
                elif name == "curvature":
                    most = np.maximum(self.n[i], self.n[j])
                    value = np.where(most > 0, np.exp(-np.abs(self.n[i] - self.n[j]) / most), 1.0)
                elif name == "fourier":
                    value = 1 / (1 + np.sqrt(((self.fd[i] - self.fd[j]) ** 2).sum(axis=1)))
                elif name == "bbox":
                    value = 1 / (1 + np.hypot(self.bx[i] - self.bx[j], self.by[i] - self.by[j]) / self.unit)
                elif name == "perimeter":
                    value = near(self.perimeter / self.unit)
                else:
                    value = near(self.aspect if name == "aspect" else self.phi)
            out += self.weights[name] * value
        return out


def cluster_sums(shapes: Shapes, members: np.ndarray, sizes: np.ndarray, stripe: np.ndarray, stripes: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Of clusters that follow each other in members (ids, in order within a cluster): their pairs of different ids,
    the pairs that have a similarity, and the sum of these. Of a cluster only pairs count whose first member's place
    is its stripe modulo its stripes. Some members' pairs at a time; a pair that occurs several times there is computed once."""
    at = np.minimum(np.searchsorted(shapes.ids, members), max(0, len(shapes.ids) - 1))
    known = shapes.ids[at] == members if len(shapes.ids) else np.zeros(len(members), bool)
    row = np.repeat(np.arange(len(sizes)), sizes)[known]
    at, sizes = at[known], np.bincount(row, minlength=len(sizes))
    here = np.arange(len(at))
    ends = np.cumsum(sizes)
    left = (ends[row] - here - 1).astype(np.int64)  # members that follow in the cluster
    left[(here - (ends - sizes)[row]) % stripes[row] != stripe[row]] = 0
    loads = np.cumsum(left)
    pairs, valued, sums = np.zeros(len(sizes), np.int64), np.zeros(len(sizes), np.int64), np.zeros(len(sizes))
    lo = 0
    while lo < len(at):
        hi = max(lo + 1, int(np.searchsorted(loads, (loads[lo - 1] if lo else 0) + PAIRS, side="right")))
        last = ends[row[hi - 1]]
        own, place = np.unique(at[lo:last], return_inverse=True)
        reps = left[lo:hi]
        i = np.repeat(np.arange(hi - lo), reps)
        j = i + 1 + np.arange(len(i)) - np.repeat(np.cumsum(reps) - reps, reps)
        first, kinds = row[lo], row[hi - 1] - row[lo] + 1
        of, i, j = row[lo:hi][i] - first, place[i], place[j]
        if len(i) and (i == j).any():
            of, i, j = (v[i != j] for v in (of, i, j))
        key = i * len(own) + j
        if len(own) <= SQUARE:
            seen = np.zeros(len(own) ** 2, bool)
            seen[key] = True
            each = np.flatnonzero(seen)
            table = np.empty(len(seen))
        else:
            each, key = np.unique(key, return_inverse=True)
            table = np.empty(len(each))
        values = np.concatenate([shapes.likeness(own[k // len(own)], own[k % len(own)]) for k in np.array_split(each, len(each) // 200_000 + 1)])
        table[each if len(own) <= SQUARE else slice(None)] = values
        value = table[key]
        void = np.isnan(value)
        to = slice(first, first + kinds)
        pairs[to] += np.bincount(of, minlength=kinds)
        valued[to] += np.bincount(of, ~void, kinds).astype(np.int64)
        sums[to] += np.bincount(of, np.where(void, 0.0, value), kinds)
        lo = hi
    return pairs, valued, sums


def owned_sums(shapes: Shapes, members: np.ndarray, sizes: np.ndarray, mine: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """What cluster_sums gives, of the pairs alone whose first id is in mine (ids in order): each of them is computed
    once, however many clusters hold it. Pairs are taken by their first id, some ids' pairs at a time; of an id with
    more pairs than that the similarities are kept until all its pairs are taken."""
    at = np.minimum(np.searchsorted(shapes.ids, members), max(0, len(shapes.ids) - 1))
    known = shapes.ids[at] == members if len(shapes.ids) else np.zeros(len(members), bool)
    row = np.repeat(np.arange(len(sizes)), sizes)[known]
    at, sizes = at[known], np.bincount(row, minlength=len(sizes))
    left = np.cumsum(sizes)[row] - np.arange(len(at)) - 1  # members that follow in the cluster
    first = np.flatnonzero((left > 0) & np.isin(shapes.ids[at], mine))
    first = first[np.argsort(at[first], kind="stable")]
    loads, own = np.cumsum(left[first]), at[first]
    pairs, valued, sums = np.zeros(len(sizes), np.int64), np.zeros(len(sizes), np.int64), np.zeros(len(sizes))
    kept, lo, n = None, 0, max(1, len(shapes.ids))
    while lo < len(first):
        hi = max(lo + 1, int(np.searchsorted(loads, (loads[lo - 1] if lo else 0) + PAIRS, side="right")))
        if hi < len(first) and own[hi] == own[hi - 1]:  # up to the end of an id, or a part of one id only
            start = int(np.searchsorted(own, own[hi]))
            hi = start if start > lo else hi
        if kept is not None:
            hi = min(hi, int(np.searchsorted(own, own[lo], side="right")))
        hot = own[lo] == own[hi - 1] and (kept is not None or hi < len(first) and own[hi] == own[lo])
        reps = left[first[lo:hi]]
        here = np.repeat(np.arange(hi - lo), reps)
        i, j = own[lo:hi][here], at[first[lo:hi][here] + 1 + np.arange(len(here)) - np.repeat(np.cumsum(reps) - reps, reps)]
        of = row[first[lo:hi]][here]
        if (i == j).any():
            of, i, j = (v[i != j] for v in (of, i, j))
        if hot:
            kept = np.full(n, -1.0) if kept is None else kept  # no similarity is below 0
            each = np.unique(j[kept[j] == -1.0])
            kept[each] = _in_parts(shapes, np.full(len(each), own[lo]), each)
            value = kept[j]
            kept = kept if hi < len(first) and own[hi] == own[lo] else None
        else:
            each, key = _distinct((i - own[lo]) * n + j, int(own[hi - 1] - own[lo] + 1) * n)
            value = _in_parts(shapes, own[lo] + each // n, each % n)[key]
        void = np.isnan(value)
        pairs += np.bincount(of, minlength=len(sizes))
        valued += np.bincount(of, ~void, len(sizes)).astype(np.int64)
        sums += np.bincount(of, np.where(void, 0.0, value), len(sizes))
        lo = hi
    return pairs, valued, sums


def _distinct(key: np.ndarray, most: int) -> tuple[np.ndarray, np.ndarray]:
    """The different keys in order, and the place of every key among them; keys are below most."""
    if most > SQUARE**2 * 4:
        return np.unique(key, return_inverse=True)
    seen = np.zeros(most, bool)
    seen[key] = True
    each = np.flatnonzero(seen)
    place = np.empty(most, np.int32)
    place[each] = np.arange(len(each))
    return each, place[key]


def _in_parts(shapes: Shapes, i: np.ndarray, j: np.ndarray) -> np.ndarray:
    return np.concatenate([shapes.likeness(a, b) for a, b in zip(*(np.array_split(v, len(i) // 200_000 + 1) for v in (i, j)), strict=True)])
