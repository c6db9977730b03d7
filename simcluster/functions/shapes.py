"""Everything that pairs of shapes need of a geometry, computed batch by batch in numpy over Arrow buffers.

The expressions of `geom` say the same for single columns; here the vertices of a whole batch lie in flat arrays, so
that rings are turned, centred and measured once for all outputs, and all boundaries are sampled and transformed
together.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

from . import fourier as D
from .geom import EPS

SCHEMA = "n int, area double, perimeter double, aspect double, phi double, bx double, by double, fd array<double>, ex1 array<double>, ey1 array<double>, ex2 array<double>, ey2 array<double>"
GROUP_CELLS = 4_000_000


class Rings:
    """The vertices of a batch of geometries: x, y, the part of each vertex, the row of each part; keep: as they are,
    neither opened nor turned."""

    def __init__(self, geom: pa.Array, keep: bool = False):
        parts = pc.struct_field(geom, "parts")
        counts = pc.fill_null(pc.list_value_length(parts), 0).to_numpy(zero_copy_only=False)
        flat = pc.list_flatten(parts)
        xs, ys = pc.struct_field(flat, "xs"), pc.struct_field(flat, "ys")
        role = pc.struct_field(flat, "role")
        self.rows = len(geom)
        self.path = pc.fill_null(pc.equal(role, "path"), False).to_numpy(zero_copy_only=False)
        self.sign = np.where(pc.fill_null(pc.equal(role, "hole"), False).to_numpy(zero_copy_only=False), -1.0, 1.0)
        self.row = np.repeat(np.arange(self.rows), counts)
        self.first = np.where(counts > 0, np.cumsum(counts) - counts, -1)  # each row's first part
        self.n = pc.fill_null(pc.list_value_length(xs), 0).to_numpy(zero_copy_only=False).astype(np.int64)
        self.x = pc.list_flatten(xs).to_numpy(zero_copy_only=False).astype(float)
        self.y = pc.list_flatten(ys).to_numpy(zero_copy_only=False).astype(float)
        if keep:
            self._place()
            return
        self._open()
        self._turn()

    def _place(self) -> None:
        self.start = np.cumsum(self.n) - self.n
        self.part = np.repeat(np.arange(len(self.n)), self.n)
        self.next = np.arange(1, len(self.x) + 1)
        full = self.n > 0
        self.next[(self.start + self.n - 1)[full]] = self.start[full]

    def _open(self) -> None:
        """Drop the closing vertex of rings that repeat it."""
        self._place()
        at = np.flatnonzero((self.n > 1) & ~self.path)
        a, b = self.start[at], self.start[at] + self.n[at] - 1
        closed = at[(self.x[a] == self.x[b]) & (self.y[a] == self.y[b])]
        keep = np.ones(len(self.x), bool)
        keep[self.start[closed] + self.n[closed] - 1] = False
        self.x, self.y = self.x[keep], self.y[keep]
        self.n[closed] -= 1
        self._place()

    def _turn(self) -> None:
        """Shells to the left, holes to the right."""
        wrong = ~self.path & (self.ring_areas() * self.sign < 0)
        at = np.arange(len(self.x))
        back = 2 * self.start[self.part] + self.n[self.part] - 1 - at
        at = np.where(wrong[self.part], back, at)
        self.x, self.y = self.x[at], self.y[at]

    def crosses(self) -> np.ndarray:
        return self.x * self.y[self.next] - self.x[self.next] * self.y

    def ring_areas(self) -> np.ndarray:
        return np.bincount(self.part, self.crosses(), len(self.n)) / 2

    def by_part(self, values: np.ndarray) -> np.ndarray:
        return np.bincount(self.part, values, len(self.n))

    def by_row(self, values: np.ndarray) -> np.ndarray:
        return np.bincount(self.row, values, self.rows)

    def lengths(self) -> np.ndarray:
        """Length of the edge after each vertex; paths have no closing edge."""
        own = np.hypot(self.x[self.next] - self.x, self.y[self.next] - self.y)
        last = np.zeros(len(self.x), bool)
        full = self.n > 0
        last[(self.start + self.n - 1)[full]] = True
        return np.where(last & self.path[self.part], 0.0, own)

    def areas(self) -> np.ndarray:
        return self.by_row(np.where(self.path, 0.0, np.abs(self.ring_areas()) * self.sign))

    def points(self) -> np.ndarray:
        return np.bincount(self.row, self.n, self.rows).astype(np.int64)

    def centre(self) -> None:
        """Move every geometry's centroid to the origin: by area, else by length, else by vertices."""
        area, lengths, n, crosses = self.areas(), self.lengths(), self.points(), self.crosses()
        length, turn = self.by_row(self.by_part(lengths)), np.where(self.path, 0.0, np.sign(self.ring_areas()) * self.sign)
        moved = []
        for v in (self.x, self.y):
            pair = v + v[self.next]
            with np.errstate(divide="ignore", invalid="ignore"):
                by_area = self.by_row(turn * self.by_part(pair * crosses) / 6) / area
                by_length = self.by_row(self.by_part(pair / 2 * lengths)) / length
                mean = self.by_row(self.by_part(v)) / n
            own = np.where(area > 0, by_area, np.where(length > 0, by_length, mean))
            moved.append(v - own[self.row[self.part]])
        self.x, self.y = moved

    def boxes(self) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """Least and greatest x and y of each row; nan without vertices."""
        n = self.points()
        full, ends = n > 0, np.cumsum(n)
        out = [np.full(self.rows, np.nan) for _ in range(4)]
        if full.any():
            starts = (ends - n)[full]
            for box, f, v in zip(out, (np.minimum, np.minimum, np.maximum, np.maximum), (self.x, self.y, self.x, self.y), strict=True):
                box[full] = f.reduceat(v, starts)
        return tuple(out)

    def edges(self) -> list[pa.Array]:
        """Four list arrays with the edges of all rings of each row; paths give none."""
        keep = ~self.path[self.part]
        ends = np.cumsum(np.bincount(self.row[self.part[keep]], minlength=self.rows))
        offsets = pa.array(np.r_[0, ends].astype(np.int32))
        to = self.next
        return [pa.ListArray.from_arrays(offsets, pa.array(v[keep])) for v in (self.x, self.y, self.x[to], self.y[to])]

    def descriptors(self, k: int, samples: int, sampling: str, scale_free: bool) -> np.ndarray:
        """Fourier descriptor of each row's first part, rows with boundaries of one length together."""
        out = np.zeros((self.rows, k))
        have = np.flatnonzero((self.first >= 0) & (np.where(self.first >= 0, self.n[self.first], 0) > 0)) if len(self.n) else np.zeros(0, int)
        n, path = self.n[self.first[have]], self.path[self.first[have]]
        twice = path & (n > 2)
        walk = np.where(twice, 2 * n - 2, n)
        for m in np.unique(walk):
            rows = np.flatnonzero(walk == m)
            step = max(1, GROUP_CELLS // (max(samples, 1) * (int(m) + 1)))
            for lo in range(0, len(rows), step):
                part = rows[lo : lo + step]
                at = np.arange(m)[None, :]
                own = n[part][:, None]
                at = self.start[self.first[have[part]]][:, None] + np.where(at < own, at, 2 * own - 2 - at)
                out[have[part]] = _spectrum(self.x[at] + 1j * self.y[at], k, samples, sampling, scale_free)
        return out


def _spectrum(z: np.ndarray, k: int, samples: int, sampling: str, scale_free: bool) -> np.ndarray:
    """Magnitudes of harmonics 2 to k + 1 of closed boundaries, one per row."""
    live = np.ones(len(z), bool)
    if sampling == "arclength":
        closed = np.concatenate([z, z[:, :1]], axis=1)
        steps = np.diff(closed, axis=1)
        at = np.concatenate([np.zeros((len(z), 1)), np.cumsum(np.abs(steps), axis=1)], axis=1)
        live = at[:, -1] > 0
        want = np.arange(samples)[None, :] * (at[:, -1:] / samples)
        j = np.minimum((at[:, None, :] <= want[:, :, None]).sum(axis=2) - 1, steps.shape[1] - 1)
        with np.errstate(divide="ignore", invalid="ignore"):
            slope = np.where(np.diff(at, axis=1) > 0, steps / np.diff(at, axis=1), 0)
        z = np.take_along_axis(closed, j, 1) + np.take_along_axis(slope, j, 1) * (want - np.take_along_axis(at, j, 1))
    m = np.abs(np.fft.fft(z, axis=1)) / z.shape[1]
    if m.shape[1] < k + 2:
        m = np.concatenate([m, np.zeros((len(m), k + 2 - m.shape[1]))], axis=1)
    out = m[:, 2 : k + 2]
    if scale_free:
        live &= m[:, 1] > 1e-12
        out = out / np.where(live, m[:, 1], 1.0)[:, None]
    return np.where(live[:, None], out, 0.0)


def describe(geom: pa.Array, centered: bool = True, harmonics: int = D.HARMONICS, samples: int = D.SAMPLES, sampling: str = "arclength", scale_free: bool = True, elongation: bool = False) -> list[pa.Array]:
    """The columns of SCHEMA for an array of geometries."""
    own = Rings(geom)
    fd = own.descriptors(harmonics, samples, sampling, scale_free)
    if centered:
        own.centre()
    area, perimeter = own.areas(), own.by_row(own.by_part(own.lengths()))
    x1, y1, x2, y2 = own.boxes()
    w, h = x2 - x1 + EPS, y2 - y1 + EPS
    aspect = np.maximum(w, h) / np.minimum(w, h) if elongation else w / h
    with np.errstate(divide="ignore", invalid="ignore"):
        phi = np.where(perimeter > 0, 4 * np.pi * area / (perimeter * perimeter), 0.0)
    some = lambda v: pa.array(v, mask=np.isnan(v))
    fds = pa.ListArray.from_arrays(pa.array(np.arange(own.rows + 1, dtype=np.int32) * harmonics), pa.array(fd.ravel()))
    return [pa.array(own.points().astype(np.int32)), pa.array(area), pa.array(perimeter), some(aspect), pa.array(phi), some((x1 + x2) / 2), some((y1 + y2) / 2), fds, *own.edges()]


def describer(**options):
    """For mapInArrow: from a key and geom to the key and the columns of SCHEMA."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names = ["sid", *(x.split()[0] for x in SCHEMA.split(", "))]
        for batch in batches:
            yield pa.RecordBatch.from_arrays([batch.column(0), *describe(batch.column(1), **options)], names)

    return run


def boxer(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """For mapInArrow: from a key and geom to the key and the box."""
    for batch in batches:
        box = Rings(batch.column(1)).boxes()
        yield pa.RecordBatch.from_arrays([batch.column(0), *[pa.array(v, mask=np.isnan(v)) for v in box]], ["sid", "x1", "y1", "x2", "y2"])


def measurer(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """For mapInArrow: from a key, mbr and geom to the key, mbr, vertices (a closing one too) and boundary length."""
    for batch in batches:
        own = Rings(batch.column(2), keep=True)
        void = pc.or_(pc.is_null(batch.column(2)), pc.is_null(batch.column(1))).to_numpy(zero_copy_only=False)
        values = [pa.array(own.points(), mask=void), pa.array(own.by_row(own.by_part(own.lengths())), mask=void)]
        yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), *values], [*batch.schema.names[:2], "points", "length"])
