"""The eight pairwise measures of likeness of centred shapes, and their weighted sum; scalar expressions."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

NAMES = ("jaccard", "area", "curvature", "fourier", "aspect", "perimeter", "bbox", "circularity")
#: Measures by what they look at.
CATEGORIES = {"overlap": ("jaccard", "area"), "complexity": ("curvature", "fourier"), "spatial": ("aspect", "bbox"), "boundary": ("perimeter", "circularity")}
EQUAL = {name: 1 / len(NAMES) for name in NAMES}


def check_weights(weights: dict[str, float] | None) -> dict[str, float]:
    """The weights, or equal ones; they must be known, not negative and sum to one."""
    weights = dict(weights or EQUAL)
    if set(weights) - set(NAMES) or min(weights.values()) < 0 or abs(sum(weights.values()) - 1) > 1e-9:
        raise ValueError(f"weights must be of {NAMES}, not negative, and sum to 1: {weights}")
    return {k: v for k, v in weights.items() if v > 0}


def equal_weights(names: tuple[str, ...]) -> dict[str, float]:
    return {name: 1 / len(names) for name in names}


def _near(a: Column, b: Column) -> Column:
    return 1 / (1 + F.abs(a - b))


def jaccard(inter: Column, a: Column, b: Column) -> Column:
    return F.when(a + b - inter > 0, inter / (a + b - inter)).otherwise(0.0)


def area_similarity(inter: Column, a: Column, b: Column) -> Column:
    return F.when(a + b > 0, 2 * inter / (a + b)).otherwise(0.0)


def curvature_similarity(n_a: Column, n_b: Column) -> Column:
    return F.when(F.greatest(n_a, n_b) > 0, F.exp(-F.abs(n_a - n_b) / F.greatest(n_a, n_b))).otherwise(1.0)


def fourier_similarity(a: Column, b: Column) -> Column:
    return 1 / (1 + F.sqrt(F.aggregate(F.zip_with(a, b, lambda x, y: (x - y) * (x - y)), F.lit(0.0), lambda acc, x: acc + x)))


aspect_similarity = _near
circularity_similarity = _near


def perimeter_similarity(a: Column, b: Column, unit: float = 1.0) -> Column:
    return _near(a / unit, b / unit)


def bbox_similarity(ax: Column, ay: Column, bx: Column, by: Column, unit: float = 1.0) -> Column:
    return 1 / (1 + F.sqrt((ax - bx) * (ax - bx) + (ay - by) * (ay - by)) / unit)


def combined_similarity(values: dict[str, Column], weights: dict[str, float] | None = None) -> Column:
    own = check_weights(weights)
    out = F.lit(0.0)
    for name in NAMES:
        if name in own:
            out = out + F.lit(own[name]) * values[name]
    return out


def weights_map(weights: dict[str, float] | None = None) -> Column:
    """The weights as a map column, for SQL users."""
    return F.create_map(*[x for k, v in check_weights(weights).items() for x in (F.lit(k), F.lit(v))])


def overlap_bounds(a: Column, b: Column) -> tuple[Column, Column]:
    """Upper bounds of jaccard and area similarity from the two areas alone."""
    least, most = F.least(a, b), F.greatest(a, b)
    return F.when(most > 0, least / most).otherwise(0.0), F.when(a + b > 0, 2 * least / (a + b)).otherwise(0.0)
