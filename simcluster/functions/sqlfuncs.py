"""Functions for SQL users, under the prefix sc_."""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql.functions import pandas_udf, udtf
from pyspark.sql.types import ArrayType, DoubleType

from .clip import EDGES, shared_areas
from .fourier import descriptor


def _ring_area(x: np.ndarray, y: np.ndarray) -> float:
    return float(abs(np.dot(x, np.roll(y, -1)) - np.dot(y, np.roll(x, -1))) / 2) if len(x) else 0.0


@pandas_udf(DoubleType())
def sc_area(xs: pd.Series, ys: pd.Series) -> pd.Series:
    """Area of a ring given by its coordinates."""
    return pd.Series([_ring_area(np.asarray(x, float), np.asarray(y, float)) if x is not None else None for x, y in zip(xs, ys, strict=True)], dtype="float64")


def _edges(x, y) -> list[np.ndarray]:
    x, y = np.asarray(x, float), np.asarray(y, float)
    if len(x) and np.dot(x, np.roll(y, -1)) < np.dot(y, np.roll(x, -1)):
        x, y = x[::-1], y[::-1]
    return [x, y, np.roll(x, -1), np.roll(y, -1)]


@pandas_udf(DoubleType())
def sc_intersection(ax: pd.Series, ay: pd.Series, bx: pd.Series, by: pd.Series) -> pd.Series:
    """Shared area of two rings."""
    import pyarrow as pa

    pack = lambda xs, ys: [pa.array([list(e[i]) for e in map(_edges, xs, ys)], pa.list_(pa.float64())) for i in range(len(EDGES))]
    return pd.Series(shared_areas(pack(ax, ay), pack(bx, by)))


@pandas_udf(ArrayType(DoubleType()))
def sc_fourier(xs: pd.Series, ys: pd.Series) -> pd.Series:
    """Fourier descriptor of a ring."""
    return pd.Series([descriptor(*_edges(x, y)[:2]) for x, y in zip(xs, ys, strict=True)], dtype="object")


@pandas_udf(DoubleType())
def sc_si(values: pd.Series) -> float:
    """Mean of the pair similarities of a group: the aggregate form of the index."""
    return float(values.mean()) if len(values) else float("nan")


class Tiles:
    """Rows (i, j) of the tiles that a box meets; dx, dy: tiles per unit."""

    def eval(self, x1: float, y1: float, x2: float, y2: float, dx: float, dy: float):
        for i in range(math.floor(x1 * dx), math.floor(x2 * dx) + 1):
            for j in range(math.floor(y1 * dy), math.floor(y2 * dy) + 1):
                yield i, j


class Edges:
    """Rows (x1, y1, x2, y2) of the edges of a ring."""

    def eval(self, xs: list, ys: list):
        for i in range(len(xs or [])):
            k = (i + 1) % len(xs)
            yield xs[i], ys[i], xs[k], ys[k]


def register(spark: SparkSession) -> None:
    """Make all functions known to SQL."""
    for name, f in {"sc_area": sc_area, "sc_intersection": sc_intersection, "sc_fourier": sc_fourier, "sc_si": sc_si}.items():
        spark.udf.register(name, f)
    spark.udtf.register("sc_tiles", udtf(Tiles, returnType="i int, j int"))
    spark.udtf.register("sc_edges", udtf(Edges, returnType="x1 double, y1 double, x2 double, y2 double"))
