"""The whole search: clusters, cut-off, scheduler, budget, verification."""

from __future__ import annotations

from dataclasses import dataclass, field
from functools import cached_property
from threading import Lock

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators import budget as B
from ..operators import clusters as C
from ..operators import density as D
from ..operators import features as FT
from ..operators import labelling as L
from ..operators import sampling as S
from ..operators import simindex as I
from ..operators import verify as V
from ..operators.classifier import Scheduler, score, train_scheduler
from ..operators.grid import Grid, candidate_pairs, grid_granularity, z_order
from ..sources.stages import is_small, stage


class Prepared:
    """Clusters, shapes and features of a source and a target set, each written once and shared by all searches."""

    def __init__(self, sources: DataFrame, targets: DataFrame, weights: dict[str, float] | None = None, n_features: int = 16, scaling: str = "both", min_size: int = 2, max_size: int | None = None, centered: bool = True, unit: float = 1.0, backend: str = "arrow", strategy: str | None = None, closing: str = "floor", factor: float = 1.0):
        self.sources, self.targets, self.weights, self.n_features, self.scaling = sources, targets, weights, n_features, scaling
        self.min_size, self.max_size, self.centered, self.unit, self.backend = min_size, max_size, centered, unit, backend
        self.strategy, self.closing, self.factor = strategy, closing, factor
        self.samples, self.lock = {}, Lock()

    #: What is written, and the settings of `variant` that it depends on.
    NEEDS = {"source_boxes": (), "target_boxes": (), "grid": (), "pairs": (), "members": (), "clusters": (), "total": (), "nested": (), "distinct_pairs": (), "feature_means": (), "shapes": ("centered",), "features": ("n_features", "scaling"), "all_si": ("weights", "centered"), "si_places": ("weights", "centered")}

    def variant(self, **change) -> Prepared:
        """The same clusters with other weights, centred, n_features or scaling; what does not depend on these is shared."""
        out = Prepared(self.sources, self.targets, **{k: change.get(k, getattr(self, k)) for k in ("weights", "n_features", "scaling", "min_size", "max_size", "centered", "unit", "backend", "strategy", "closing", "factor")})
        own = [k for k, v in change.items() if v != getattr(self, k)]
        if not {"weights", "centered", "n_features", "scaling"}.issuperset(own):
            raise ValueError(f"no variant of the same clusters: {own}")
        for name, needs in self.NEEDS.items():
            if not set(needs) & set(own) and (name != "distinct_pairs" or name in self.__dict__):
                out.__dict__[name] = getattr(self, name)
        return out

    @cached_property
    def source_boxes(self) -> DataFrame:
        """What joins and features need of the sources, so that geometries are made once for it."""
        return stage(FT.measured(self.sources, "sid"), "source-boxes")

    @cached_property
    def target_boxes(self) -> DataFrame:
        return stage(FT.measured(self.targets, "tid"), "target-boxes")

    @cached_property
    def grid(self) -> Grid:
        return grid_granularity(self.source_boxes, factor=self.factor)

    @cached_property
    def pairs(self) -> DataFrame:
        return stage(candidate_pairs(self.source_boxes, self.target_boxes, self.grid, self.strategy, self.closing), "pairs")

    @cached_property
    def members(self) -> DataFrame:
        return stage(C.build_clusters(self.pairs, self.min_size, self.max_size), "members")

    @cached_property
    def clusters(self) -> DataFrame:
        return stage(self.members.groupBy("cid").agg(F.count("*").alias("size")), "clusters")

    @cached_property
    def total(self) -> int:
        return self.clusters.count()

    @cached_property
    def shapes(self) -> DataFrame:
        used = self.sources.join(self.members.select("sid").distinct(), "sid", "left_semi")
        return stage(I.describe_shapes(used, centered=self.centered), "shapes")

    @cached_property
    def raw(self) -> DataFrame:
        """The features of every member pair; the search needs their means only."""
        return stage(FT.raw_features(self.members, self.sources, self.targets, C.source_stats(self.pairs), C.target_stats(self.pairs), self.grid, self.closing), "features-raw")

    @cached_property
    def feature_means(self) -> DataFrame:
        """The unscaled means of all features with the members' extremes, for any number of features and any scaling."""
        s = stage(FT.source_side(self.source_boxes, C.source_stats(self.pairs), self.grid, self.closing), "source-side")
        t = FT.target_side(self.target_boxes, C.target_stats(self.pairs), self.grid, self.closing)
        return stage(FT.pooled_means(self.members, s, t, None if is_small(s) else self.nested), "features-means")

    @cached_property
    def features(self) -> DataFrame:
        return stage(FT.scaled_means(self.feature_means, self.n_features, self.scaling), "features")

    @cached_property
    def nested(self) -> I.Nested:
        """Clusters as lists of members, those of neighbouring targets together."""
        return I.nest(self.members, self.target_boxes.select(F.col("tid").alias("cid"), z_order(F.col("mbr"), self.grid).alias("place")))

    @cached_property
    def distinct_pairs(self) -> DataFrame:
        """a and b of all member pairs, once each."""
        return stage(I.member_pairs(self.members).select("a", "b").distinct(), "distinct-pairs")

    def index_of(self, cids: DataFrame | None) -> DataFrame:
        if self.backend != "arrow":
            return I.similarity_index(self.members, self.shapes, self.weights, cids, self.backend, unit=self.unit)
        return I.similarity_index(self.members, self.shapes, self.weights, cids, unit=self.unit, layout="nested", nested=self.nested)

    def bounds_of(self, cids: DataFrame | None) -> DataFrame:
        return I.similarity_bounds(self.members, self.shapes, self.weights, cids, self.unit)

    @cached_property
    def all_si(self) -> DataFrame:
        """The index of every cluster: the exhaustive baseline and the truth of evaluations."""
        return stage(self.index_of(None), "all-si")

    @cached_property
    def si_places(self) -> DataFrame:
        """cid, si and the cluster's place by index, largest first."""
        return stage(V.places(self.all_si.select("cid", "si"), "si"), "si-places")

    def sampled(self, m: int, seed: int, roles: str) -> tuple[DataFrame, DataFrame]:
        """The indices of the drawn clusters, and their features with role and index; the same for every targeted share."""
        with self.lock:
            if (m, seed, roles) not in self.samples:
                self.samples[m, seed, roles] = self._sampled(m, seed, roles)
            return self.samples[m, seed, roles]

    def _sampled(self, m: int, seed: int, roles: str) -> tuple[DataFrame, DataFrame]:
        density_ids, label_ids = S.draw_roles(self.clusters, m, seed, roles)
        if roles == "shared":
            drawn = density_ids.withColumn("dense", F.lit(True))
        else:
            drawn = density_ids.withColumn("dense", F.lit(True)).unionByName(label_ids.withColumn("dense", F.lit(False)))
        drawn = stage(drawn.select("cid", "place", "dense"), "sample")
        known = stage(self.index_of(drawn).select("cid", "si"), "si-samples")
        # the samples' features lie in one partition from here on, so that training and simulation are small local jobs
        sampled = self.features.join(F.broadcast(drawn), "cid").join(F.broadcast(known), "cid")
        return known, stage(sampled.repartition(1), "sample-features")


@dataclass
class Plan:
    """What a search knows before it chooses a budget."""

    tau: float
    scheduler: Scheduler
    simulation: B.Simulation
    total: int
    scored: DataFrame
    known: DataFrame
    kde: D.Kde


@dataclass
class SearchResult:
    result: DataFrame
    tau: float
    scheduler: Scheduler
    simulation: B.Simulation
    budget: int
    total: int
    scored: DataFrame
    known: DataFrame
    kde: D.Kde
    settings: dict = field(default_factory=dict)

    @property
    def coverage(self) -> float:
        """Share of clusters that are verified."""
        return self.budget / self.total if self.total else 0.0


@dataclass
class SimilarClusterSearch:
    """p: wanted top share; r_d: wanted recall; m: clusters per sample; n: labels per class.

    rule: `linear` scales the estimated recall, `curve` reads the depth off the sample's gain curve, `cut` sets
    a score cut. confidence: of the curve rule, that the wanted recall is reached (0.5: no margin over the sample's
    own curve). roles: disjoint samples for the density and for the scheduler, or one shared. The verification is
    simulated on the density's sample.
    """

    p: float = 0.1
    r_d: float = 0.9
    m: int = 500
    n: int = 60
    algorithm: str = "logistic"
    rule: str = "curve"
    confidence: float = 0.9
    roles: str = "disjoint"
    kernels: tuple[str, ...] = tuple(D.KERNELS)
    criterion: str = "loo"
    boundary: str = "reflect"
    balance: str = "none"
    seed: int = 1
    prune: bool = False
    reuse: bool = True

    def plan(self, prep: Prepared) -> Plan | None:
        """All that comes before the budget: cut-off, trained scheduler, scores and simulation. None without clusters.

        The indices of both samples are computed in one job; labelling takes as long a prefix of its sample as it needs.
        """
        if not prep.total:
            return None
        known, sampled = prep.sampled(self.m, self.seed, self.roles)
        dense = sampled.filter("dense")
        kde = D.select_kde([r["si"] for r in dense.select("cid", "si").orderBy("cid").collect()], self.kernels, criterion=self.criterion)
        tau = D.kde_threshold(kde, self.p, boundary=self.boundary)
        own = sampled.filter("not dense")
        if self.roles == "shared" or own.isEmpty():
            own = sampled
        labelled = L.training_prefix(L.label_clusters(own, tau), self.n, self.seed + 1)
        scheduler = train_scheduler(labelled, self.algorithm, prep.n_features, self.balance, self.seed + 2)
        labels = L.label_clusters(dense.select("cid", "si"), tau)
        sim = B.simulate(score(scheduler, dense).join(labels, "cid").select("cid", "w", "label"), self.p)
        scored = stage(score(scheduler, prep.features), "scored")
        return Plan(tau, scheduler, sim, prep.total, scored, known, kde)

    def budget(self, plan: Plan, r_d: float | None = None, rule: str | None = None) -> int:
        """Clusters to verify for a wanted recall."""
        r_d, rule = r_d or self.r_d, rule or self.rule
        if rule == "linear":
            return B.budget_linear(plan.simulation, r_d, plan.total)
        if rule == "cut":
            return B.budget_probability_cut(plan.simulation, r_d, plan.scored)
        return B.budget_gain_curve(plan.simulation, r_d, plan.total, B.margin(plan.simulation, r_d, self.confidence))

    def run(self, prep: Prepared) -> SearchResult | None:
        """None if there are no clusters."""
        plan = self.plan(prep)
        if plan is None:
            return None
        budget = self.budget(plan)
        result = V.verify(plan.scored, budget, plan.tau, prep.index_of, plan.known if self.reuse else None, prep.bounds_of if self.prune else None)
        return SearchResult(result, plan.tau, plan.scheduler, plan.simulation, budget, plan.total, plan.scored, plan.known, plan.kde, {"p": self.p, "r_d": self.r_d, "rule": self.rule, "m": self.m, "n": self.n})
