"""Kernel density of a bounded sample of similarity indices, and the cut-off of a wanted top share."""

from __future__ import annotations

import math
from collections.abc import Callable
from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

_erf = np.vectorize(math.erf)

#: Density and distribution function of each kernel, over standardised distance.
KERNELS: dict[str, tuple[Callable, Callable]] = {
    "gaussian": (lambda u: np.exp(-u * u / 2) / math.sqrt(2 * math.pi), lambda u: (1 + _erf(u / math.sqrt(2))) / 2),
    "epanechnikov": (lambda u: np.where(np.abs(u) < 1, 0.75 * (1 - u * u), 0.0), lambda u: np.where(u <= -1, 0.0, np.where(u >= 1, 1.0, 0.5 + 0.75 * (u - u**3 / 3)))),
    "tophat": (lambda u: np.where(np.abs(u) <= 1, 0.5, 0.0), lambda u: np.clip((u + 1) / 2, 0, 1)),
    "logistic": (lambda u: 1 / (2 + np.exp(-np.abs(u)) + np.exp(np.abs(np.minimum(np.abs(u), 700)))), lambda u: 1 / (1 + np.exp(-np.clip(u, -700, 700)))),
}
#: The logistic kernel's standard deviation, so that bandwidths mean the same for all kernels.
SPREAD = {"gaussian": 1.0, "epanechnikov": 1 / math.sqrt(5), "tophat": 1 / math.sqrt(3), "logistic": math.pi / math.sqrt(3)}


@dataclass(frozen=True)
class Kde:
    points: np.ndarray
    kernel: str
    h: float

    def _mean(self, f: Callable, x) -> np.ndarray:
        u = (np.atleast_1d(np.asarray(x, float))[:, None] - self.points[None]) / self.h
        return f(u).mean(axis=1)

    def pdf(self, x) -> np.ndarray:
        return self._mean(KERNELS[self.kernel][0], x) / self.h

    def cdf(self, x) -> np.ndarray:
        return self._mean(KERNELS[self.kernel][1], x)

    def sf(self, x, support: tuple[float, float] = (0.0, 1.0), boundary: str = "none") -> np.ndarray:
        """Mass above x; truncate and reflect keep all mass inside the support."""
        x = np.atleast_1d(np.asarray(x, float))
        lo, hi = support
        if boundary == "truncate":
            inside = self.cdf(hi) - self.cdf(lo)
            return (self.cdf(hi) - self.cdf(np.clip(x, lo, hi))) / inside
        if boundary == "reflect":
            clipped = np.clip(x, lo, hi)
            return self.cdf(hi) - self.cdf(clipped) + self.cdf(2 * hi - clipped) - self.cdf(hi) + self.cdf(2 * lo - clipped) - self.cdf(2 * lo - hi)
        return 1 - self.cdf(x)


def bandwidth(points: np.ndarray, rule: str = "silverman") -> float:
    """Rule-of-thumb bandwidth; a small constant if all points are equal."""
    n = len(points)
    sd = float(np.std(points, ddof=1)) if n > 1 else 0.0
    if rule == "scott":
        return max(1.06 * sd * n ** (-1 / 5), 1e-4)
    iqr = float(np.subtract(*np.percentile(points, [75, 25]))) / 1.349 if n else 0.0
    spread = min(x for x in (sd, iqr) if x > 0) if max(sd, iqr) > 0 else 0.0
    return max(0.9 * spread * n ** (-1 / 5), 1e-4)


def loo_score(kde: Kde) -> float:
    """Mean logarithm of each point's density under the other points."""
    n = len(kde.points)
    if n < 2:
        return float("-inf")
    total = kde.pdf(kde.points) * n - KERNELS[kde.kernel][0](np.zeros(1))[0] / kde.h
    return float(np.log(np.maximum(total / (n - 1), 1e-12)).mean())


def kfold_score(kde: Kde, folds: int = 5) -> float:
    parts = np.arange(len(kde.points)) % folds
    scores = [np.log(np.maximum(Kde(kde.points[parts != f], kde.kernel, kde.h).pdf(kde.points[parts == f]), 1e-12)) for f in range(folds) if (parts == f).any() and (parts != f).any()]
    return float(np.concatenate(scores).mean()) if scores else float("-inf")


MULTIPLIERS = (0.25, 0.5, 0.75, 1.0, 1.5, 2.0)


def select_kde(points, kernels: tuple[str, ...] = tuple(KERNELS), multipliers: tuple[float, ...] = MULTIPLIERS, criterion: str = "loo") -> Kde:
    """The best density: by leave-one-out or k-fold likelihood over kernels and bandwidths, or a rule of thumb."""
    points = np.sort(np.asarray(points, float))
    if not len(points):
        raise ValueError("no similarity index to fit a density to")
    if criterion in ("silverman", "scott"):
        return Kde(points, kernels[0], bandwidth(points, criterion) / SPREAD[kernels[0]])
    h = bandwidth(points)
    if h <= 1e-4 or len(points) < 5:
        return Kde(points, kernels[0], max(h, 1e-4))
    score = loo_score if criterion == "loo" else kfold_score
    return max((Kde(points, k, h * m / SPREAD[k]) for k in kernels for m in multipliers), key=score)


def kde_threshold(kde: Kde, p: float, support: tuple[float, float] = (0.0, 1.0), boundary: str = "none") -> float:
    """The value above which the density holds the share p, by bisection."""
    if p <= 0 or p >= 1:
        return float("inf") if p <= 0 else float("-inf")
    wide = 40 * kde.h
    lo, hi = min(support[0], kde.points[0] - wide), max(support[1], kde.points[-1] + wide)
    for _ in range(80):
        mid = (lo + hi) / 2
        if kde.sf(mid, support, boundary)[0] > p:
            lo = mid
        else:
            hi = mid
    return float((lo + hi) / 2)


def kde_thresholds(kde: Kde, shares: tuple[float, ...], boundary: str = "none") -> dict[float, float]:
    return {p: kde_threshold(kde, p, boundary=boundary) for p in shares}


#: Rows from which an exact quantile reads a narrow band of the values instead of gathering all of them.
BAND_ROWS = 1_000_000


def exact_quantile(rows: DataFrame, column: str, q: float, band_rows: int = BAND_ROWS) -> float | None:
    """The linearly interpolated quantile. Of many rows, only those between two approximate quantiles are ordered."""
    n = rows.count()
    if n < band_rows:
        return rows.agg(F.percentile(column, F.lit(q))).head()[0]
    at = q * (n - 1)
    low, high = rows.agg(F.percentile_approx(column, [max(0.0, q - 0.002), min(1.0, q + 0.002)], 10_000)).head()[0]
    below = rows.filter(F.col(column) < F.lit(low)).count()
    skip = math.floor(at) - below
    band = rows.filter((F.col(column) >= F.lit(low)) & (F.col(column) <= F.lit(high))).select(column).orderBy(column)
    got = [r[0] for r in band.offset(skip).limit(2).collect()] if skip >= 0 else []
    if len(got) < 2 and math.floor(at) + 1 < n or not got:
        return rows.agg(F.percentile(column, F.lit(q))).head()[0]
    return got[0] + (at - math.floor(at)) * (got[-1] - got[0])


def sample_threshold(si: DataFrame, p: float, exact: bool = True) -> float:
    """Empirical quantile of the indices in si."""
    return exact_quantile(si, "si", 1 - p) if exact else si.agg(F.percentile_approx("si", 1 - p, 10_000)).head()[0]


exact_threshold = sample_threshold


def static_threshold(value: float) -> float:
    """A cut-off that does not look at the data."""
    return float(value)


def epanechnikov_terms(x: Column, point: Column, h: float) -> tuple[Column, Column]:
    """Density and distribution terms of one point, for evaluation in a plan."""
    u = (x - point) / F.lit(h)
    pdf = F.when(F.abs(u) < 1, (1 - u * u) * 0.75).otherwise(0.0) / F.lit(h)
    cdf = F.when(u <= -1, 0.0).when(u >= 1, 1.0).otherwise((u - u * u * u / 3) * 0.75 + 0.5)
    return pdf, cdf


def evaluate_kde(grid: DataFrame, sample: DataFrame, h: float) -> DataFrame:
    """x, pdf, cdf of an Epanechnikov density over a grid of x, from a bounded sample of si (broadcast)."""
    joined = grid.join(F.broadcast(sample.select("si")), how="cross")
    pdf, cdf = epanechnikov_terms(F.col("x"), F.col("si"), h)
    return joined.groupBy("x").agg(F.avg(pdf).alias("pdf"), F.avg(cdf).alias("cdf"))
