"""Fourier descriptors of shapes: magnitudes of low harmonics of the sampled boundary.

The boundary is walked counter-clockwise and sampled at equal steps of arc length (or at its vertices); the
magnitudes of harmonics 2 to k + 1 of the complex samples, over that of harmonic 1, neither change with the
place, the turn nor the starting point of a shape, nor with its size. A path is walked forth and back.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column
from pyspark.sql import functions as F

from . import geom as G

HARMONICS = 8
SAMPLES = 64


def descriptor(x: np.ndarray, y: np.ndarray, path: bool = False, k: int = HARMONICS, samples: int = SAMPLES, sampling: str = "arclength", scale_free: bool = True) -> np.ndarray:
    if path and len(x) > 2:
        x, y = np.r_[x, x[-2:0:-1]], np.r_[y, y[-2:0:-1]]
    z = np.r_[x, x[:1]] + 1j * np.r_[y, y[:1]]
    if sampling == "arclength":
        at = np.r_[0.0, np.cumsum(np.abs(np.diff(z)))]
        if len(z) < 2 or at[-1] <= 0:
            return np.zeros(k)
        z = np.interp(np.arange(samples) * (at[-1] / samples), at, z)
    else:
        z = z[:-1]
    m = np.abs(np.fft.fft(z)) / len(z)
    m = np.r_[m, np.zeros(max(0, k + 2 - len(m)))]
    if not scale_free:
        return m[2 : k + 2]
    return m[2 : k + 2] / m[1] if m[1] > 1e-12 else np.zeros(k)


def fourier_descriptor(geom: Column, k: int = HARMONICS, samples: int = SAMPLES, sampling: str = "arclength", scale_free: bool = True) -> Column:
    """array<double> of the first part, its ring turned to the left; one call per geometry."""

    @F.pandas_udf("array<double>")
    def run(batches: Iterator[tuple[pd.Series, pd.Series, pd.Series]]) -> Iterator[pd.Series]:
        for xs, ys, roles in batches:
            yield pd.Series([descriptor(np.asarray(x, float), np.asarray(y, float), r == "path", k, samples, sampling, scale_free) for x, y, r in zip(xs, ys, roles, strict=True)], dtype="object")

    first = G.normalize_rings(geom)["parts"][0]
    return run(first["xs"], first["ys"], first["role"])
