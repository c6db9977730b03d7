"""From a wanted recall to the number of clusters to verify, by simulating the verification on a sample."""

from __future__ import annotations

import math
from dataclasses import dataclass
from statistics import NormalDist

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..sources.stages import stage
from .verify import places


@dataclass(frozen=True)
class Simulation:
    """kept: clusters in the simulated queue; high: of these, with a high index; depth: how many were checked;
    hits: high ones among them; curve: (checked, hits so far, score) at every high one."""

    kept: int
    high: int
    depth: int
    hits: int
    curve: tuple[tuple[int, int, float], ...]

    @property
    def recall(self) -> float:
        return self.hits / self.high if self.high else 0.0


def running_recall(scored: DataFrame) -> DataFrame:
    """place, hits so far and recall so far of scored rows (w, label) in order of w; for bounded samples."""
    order = Window.orderBy(F.desc("w"), "cid")
    out = scored.withColumn("place", F.row_number().over(order)).withColumn("hits", F.sum("label").over(order.rowsBetween(Window.unboundedPreceding, Window.currentRow)))
    return out.withColumn("recall", F.col("hits") / F.nullif(F.sum("label").over(Window.partitionBy()), F.lit(0.0)))


def simulate(scored: DataFrame, p: float, n: int | None = None, scope: str = "top_n") -> Simulation:
    """Verify the sample in order of w. n: length of the queue, by default the whole sample. scope: count high
    clusters in the queue only (top_n) or in the whole sample."""
    rows = [(r["place"], r["label"], r["w"]) for r in running_recall(scored).select("place", "label", "w").orderBy("place").collect()]
    kept = rows[: n or len(rows)]
    high = int(sum(x[1] for x in (kept if scope == "top_n" else rows)))
    depth = min(len(kept), math.ceil(p * len(kept) - 1e-9))
    curve, hits = [], 0
    for place, label, w in kept:
        if label:
            hits += 1
            curve.append((place, hits, w))
    return Simulation(len(kept), high, depth, sum(1 for place, _, _ in curve if place <= depth), tuple(curve))


def _clamp(x: float, total: int) -> int:
    return max(0, min(total, math.ceil(x - 1e-9)))


def budget_linear(sim: Simulation, r_d: float, total: int) -> int:
    """Wanted recall over estimated recall, times the share of high clusters, of all clusters."""
    if not sim.high or not sim.hits:
        return total
    return _clamp(r_d / sim.recall * sim.high / sim.kept * total, total)


def budget_gain_curve(sim: Simulation, r_d: float, total: int, safety: int = 0) -> int:
    """The depth at which the sample reaches the wanted recall, scaled to all clusters."""
    need = math.ceil(r_d * sim.high - 1e-9) + safety
    if not sim.high or need > len(sim.curve):
        return total
    return _clamp(next(place for place, hits, _ in sim.curve if hits >= need) / sim.kept * total, total) if need > 0 else 0


def margin(sim: Simulation, r_d: float, confidence: float) -> int:
    """High clusters of the sample to find beyond the wanted share, so that its error is on the safe side so often.

    Of `high` sampled ones the number above a cut is about normal with variance high * r_d * (1 - r_d).
    """
    if confidence <= 0.5 or not sim.high:
        return 0
    spread = NormalDist().inv_cdf(confidence) * math.sqrt(sim.high * r_d * (1 - r_d))
    return max(0, min(len(sim.curve) - math.ceil(r_d * sim.high - 1e-9), math.ceil(spread)))


def probability_cut(sim: Simulation, r_d: float) -> float:
    """The largest score cut at which the sample's recall is still the wanted one; 0 verifies all."""
    need = math.ceil(r_d * sim.high - 1e-9)
    return next((w for _, hits, w in sim.curve if hits >= need), 0.0) if sim.high else 0.0


def budget_probability_cut(sim: Simulation, r_d: float, scored_all: DataFrame) -> int:
    """Clusters whose score reaches the cut."""
    return scored_all.filter(F.col("w") >= F.lit(probability_cut(sim, r_d))).count()


def budget_oracle(scored_si: DataFrame, tau: float, r_d: float) -> int:
    """The least depth that reaches the recall if all indices were known; for evaluation only."""
    deep = places(scored_si.select("cid", "w", (F.col("si") >= F.lit(tau)).alias("high")), "w").filter("high").select("cid", F.col("place").alias("depth"))
    deep = stage(deep, "high-places")
    need = math.ceil(r_d * deep.count() - 1e-9)
    if need <= 0:
        return 0
    nth = places(deep.withColumn("up", -F.col("depth")), "up").filter(F.col("place") == need).head()
    return nth["depth"]


RULES = ("linear", "curve", "cut")
