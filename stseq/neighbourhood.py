"""Predicates and volumes of neighbourhood spaces, as Columns over the point structs ``src`` and ``dst``."""

from __future__ import annotations

import math

from pyspark.sql import Column
from pyspark.sql import functions as F

from stseq.model import NeighbourhoodSpec, SpaceSpec

AXES = ("x", "y", "z")


def _diff(axis: str, src: str, dst: str) -> Column:
    return F.col(f"{dst}{axis}") - F.col(f"{src}{axis}")


def squared_distance(spec: NeighbourhoodSpec, src: str, dst: str) -> Column:
    if spec.metric == "haversine":  # degrees of arc; x is longitude, y latitude
        dy, dx = F.radians(_diff("y", src, dst)), F.radians(_diff("x", src, dst))
        h = F.pow(F.sin(dy / 2), 2) + F.cos(F.radians(F.col(f"{src}y"))) * F.cos(F.radians(F.col(f"{dst}y"))) * F.pow(F.sin(dx / 2), 2)
        return F.pow(F.degrees(2 * F.asin(F.least(F.lit(1.0), F.sqrt(h)))), 2)
    if spec.metric == "abs":
        total = sum((F.abs(_diff(a, src, dst)) for a in AXES[: spec.dims]), F.lit(0))
        return total * total
    return sum((_diff(a, src, dst) * _diff(a, src, dst) for a in AXES[: spec.dims]), F.lit(0))


def within_space(spec: NeighbourhoodSpec, src: str = "src.", dst: str = "dst.") -> Column:
    if spec.shape == "box":
        out = F.lit(True)
        for a in AXES[: spec.dims]:
            out = out & (F.abs(_diff(a, src, dst)) <= spec.R)
        return out
    d2 = squared_distance(spec, src, dst)
    if spec.shape == "cone":  # the radius grows with the delay up to R
        lag = (_diff("t", src, dst) - spec.delay).cast("double")
        return d2 * F.lit(float(spec.T) ** 2) <= F.lit(float(spec.R) ** 2) * lag * lag
    return d2 <= F.lit(spec.R * spec.R)


def within_time(spec: NeighbourhoodSpec, src: str = "src.", dst: str = "dst.") -> Column:
    lag = _diff("t", src, dst)
    upper = lag <= F.lit(spec.delay + spec.T)
    if spec.time_rule == "after":
        return (lag > F.lit(spec.delay)) & upper
    if spec.time_rule == "from_now":
        return (lag >= F.lit(spec.delay)) & upper
    if spec.time_rule == "upper_only":
        return upper
    return -lag <= F.lit(spec.T)


def matches(spec: NeighbourhoodSpec, src: str = "src.", dst: str = "dst.") -> Column:
    """The target lies in the source's neighbourhood."""
    out = within_space(spec, src, dst) & within_time(spec, src, dst)
    return out & (F.col(f"{src}id") != F.col(f"{dst}id")) if spec.self_pairs == "exclude" else out


def clipped_volume(spec: NeighbourhoodSpec, space: SpaceSpec) -> Column:
    """Volume of a point's neighbourhood inside the space, for the box hull: each side is cut at the border.

    For cylinders and cones the share of the hull that is left scales the volume.
    """
    share = F.lit(1.0)
    for a, (low, high) in zip(AXES[: spec.dims], space.sides()):
        side = F.least(F.col(a) + spec.R, F.lit(high)) - F.greatest(F.col(a) - spec.R, F.lit(low))
        share = share * F.greatest(side, F.lit(0.0)) / (2 * spec.R)
    begin = F.col("t") + F.lit(spec.delay)
    stretch = F.least(begin + F.lit(spec.T), F.lit(space.t1)) - F.greatest(begin, F.lit(space.t0))
    return share * F.greatest(stretch.cast("double"), F.lit(0.0)) / float(spec.T) * spec.volume


def expected_pairs(n_src: int, n_dst: int, spec: NeighbourhoodSpec, space: SpaceSpec) -> float:
    """Pairs that independent types would have; printed and bounded before a large run."""
    return n_src * n_dst * spec.volume / space.volume if math.isfinite(space.volume) else math.inf
