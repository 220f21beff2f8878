"""Data model: schemas and option objects.

Points are events or microclusters: id, type, x, y, (z), t and the weight w (1 for an event, the number of
contained events for a microcluster). Time is a long in ticks of the caller's choice.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

EVENT_SCHEMA = "id bigint, type string, x double, y double, t bigint"
PAIR_SCHEMA = "src_id bigint, src_type string, src_w bigint, dst_id bigint, dst_type string, dst_w bigint"
MC_SCHEMA = "cid bigint, type string, n bigint, x double, y double, t double, ss double, tile bigint"
MEMBER_SCHEMA = "cid bigint, id bigint"

SHAPES = ("cylinder", "cone", "box")
METRICS = ("euclid", "abs", "haversine")
TIME_RULES = ("after", "from_now", "upper_only", "printed_reverse")


@dataclass(frozen=True)
class SpaceSpec:
    """The embedding space: a box of 1 to 3 spatial dimensions and time."""

    x0: float
    x1: float
    t0: float
    t1: float
    y0: float = 0.0
    y1: float = 1.0
    z0: float = 0.0
    z1: float = 1.0
    dims: int = 2

    def __post_init__(self):
        if self.dims not in (1, 2, 3):
            raise ValueError("one to three spatial dimensions")
        if any(b <= a for a, b in self.sides()):
            raise ValueError("a space needs positive lengths")

    def sides(self) -> list[tuple[float, float]]:
        space = [(self.x0, self.x1), (self.y0, self.y1), (self.z0, self.z1)][: self.dims]
        return [*space, (self.t0, self.t1)]

    @property
    def volume(self) -> float:
        return float(math.prod(b - a for a, b in self.sides()))  # whole sides may multiply beyond a long

    @classmethod
    def from_data(cls, points: DataFrame, dims: int = 2) -> SpaceSpec:
        """Bounding box of the points (one scan)."""
        names = ["x", "y", "z"][:dims] + ["t"]
        r = points.agg(*[f(c).cast("double").alias(f"{c}{i}") for c in names for i, f in ((0, F.min), (1, F.max))]).first()
        return cls(dims=dims, **r.asDict())

    def contains(self) -> Column:
        """Predicate: the point lies in the space."""
        names = ["x", "y", "z"][: self.dims] + ["t"]
        out = F.lit(True)
        for c, (a, b) in zip(names, self.sides()):
            out = out & F.col(c).between(a, b)
        return out


@dataclass(frozen=True)
class NeighbourhoodSpec:
    """Neighbourhood space of radius ``R`` and interval ``T`` after an event; see :mod:`stseq.neighbourhood`."""

    R: float
    T: float
    shape: str = "cylinder"
    metric: str = "euclid"
    time_rule: str = "after"
    delay: float = 0
    self_pairs: str = "exclude"
    edge_correction: str = "none"
    dims: int = 2

    def __post_init__(self):
        if self.R <= 0 or self.T <= 0:
            raise ValueError("R and T must be positive")
        if self.shape not in SHAPES or self.metric not in METRICS or self.time_rule not in TIME_RULES:
            raise ValueError("unknown shape, metric or time rule")
        if self.self_pairs not in ("exclude", "include") or self.edge_correction not in ("none", "clip_box", "torus"):
            raise ValueError("unknown self_pairs or edge_correction")
        if self.shape == "cone" and self.time_rule not in ("after", "from_now"):
            raise ValueError("a cone needs a time rule with two bounds")

    @property
    def bounded(self) -> bool:
        return self.time_rule in ("after", "from_now")

    @property
    def volume(self) -> float:
        if self.shape == "box":
            area = (2 * self.R) ** self.dims
        else:
            area = {1: 2 * self.R, 2: math.pi * self.R**2, 3: 4 / 3 * math.pi * self.R**3}[self.dims]
        return area * self.T / (self.dims + 1 if self.shape == "cone" else 1)


@dataclass(frozen=True)
class ClusterSpec:
    """Microclustering options; diameters bind below ``d`` or, normalised, below the combination of ``d_s`` and ``d_t``."""

    d: float | None = None
    d_s: float | None = None
    d_t: float | None = None
    K: int | None = None
    method: str = "incremental"
    normalise: str = "none"
    order_by: str = "time_id"
    assign: str = "seed"
    recheck: str = "paper"
    zero_split: str = "halve"
    nearest: str = "grid"
    tile: float | None = None
    tile_t: float | None = None
    merge_borders: bool = False
    time_unit: float = 1.0
    dims: int = 2

    def __post_init__(self):
        if self.method not in ("incremental", "grid", "duplicates", "identity"):
            raise ValueError("unknown method")
        if self.method in ("incremental", "grid") and not (self.d or (self.d_s and self.d_t)):
            raise ValueError("give d, or d_s and d_t")
        if self.normalise not in ("none", "range", "unit") or (self.normalise != "none" and not (self.d_s and self.d_t)):
            raise ValueError("normalising needs d_s and d_t")
        if self.K is not None and self.K < 2:
            raise ValueError("K is 2 at least")
        if self.order_by not in ("time_id", "time_place", "id") or self.assign not in ("seed", "centroid") or self.recheck not in ("paper", "until_fit"):
            raise ValueError("unknown order_by, assign or recheck")
        if self.zero_split not in ("halve", "seed") or self.nearest not in ("grid", "scan", "pivot"):
            raise ValueError("unknown zero_split or nearest")
        if self.tile is not None and self.normalise == "none" and self.tile < 2 * (self.d or 0):
            raise ValueError("a tile side is 2d at least")


@dataclass(frozen=True)
class MineOptions:
    theta: float = 1.0
    ratio_scope: str = "tail"
    max_length: int = 10
    allow_repeats: bool = True
    require_tail: bool = True
    min_tail_weight: int = 0
    limit_patterns: int | None = None
    top_k: int | None = None
    cycle_guard: bool = True
    strategy: str = "level"
    join: str = "grid"

    def __post_init__(self):
        if self.theta < 0 or self.max_length < 1:
            raise ValueError("theta is 0 and max_length 1 at least")
        if self.ratio_scope not in ("tail", "type") or self.strategy not in ("level", "depth") or self.join not in ("grid", "sweep", "nested"):
            raise ValueError("unknown ratio_scope, strategy or join")


def as_points(events: DataFrame) -> DataFrame:
    """Events as points of weight 1."""
    return events if "w" in events.columns else events.withColumn("w", F.lit(1).cast("long"))


def clusters_as_points(mc: DataFrame) -> DataFrame:
    """Microclusters as points weighted by their size; time is the mean, a double."""
    return mc.select(F.col("cid").alias("id"), "type", "x", "y", "t", F.col("n").alias("w"))
