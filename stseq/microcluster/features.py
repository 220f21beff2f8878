"""Additive features of microclusters and the diameter (root mean squared distance over ordered pairs of members)."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from stseq.model import ClusterSpec

AXES = ("x", "y", "z")


def diameter_cf(n: Column, ss: Column) -> Column:
    """From the count and the summed squared distance to the mean; 0 for one member."""
    return F.when(n > 1, F.sqrt(F.greatest(F.lit(0.0), 2 * ss / (n - 1)))).otherwise(0.0)


def diameter_agg(*coords: Column) -> Column:
    """The diameter as an aggregate of built-in functions: D^2 is twice the summed sample variances."""
    return F.sqrt(2 * sum((F.coalesce(F.var_samp(c), F.lit(0.0)) for c in coords), F.lit(0.0)))


def diameter_pairwise(members: DataFrame, coords: list[str], cid: str = "cid", id_col: str = "id") -> DataFrame:
    """The diameter by its definition, all pairs of members (for checks): cid, diameter."""
    a = members.select(cid, F.col(id_col).alias("_a"), *[F.col(c).alias(f"_a{c}") for c in coords])
    b = members.select(cid, F.col(id_col).alias("_b"), *[F.col(c).alias(f"_b{c}") for c in coords])
    d2 = sum(((F.col(f"_a{c}") - F.col(f"_b{c}")) * (F.col(f"_a{c}") - F.col(f"_b{c}")) for c in coords), F.lit(0.0))
    m = F.sqrt(F.count(F.lit(1)).cast("double"))
    total = a.join(b, cid).groupBy(cid).agg(F.sum(d2).alias("_t"), m.alias("_m"))
    return total.select(cid, F.when(F.col("_m") > 1, F.sqrt(F.col("_t") / (F.col("_m") * (F.col("_m") - 1)))).otherwise(0.0).alias("diameter"))


def representative(n: Column, total: Column) -> Column:
    return total / n


def scales(events: DataFrame, spec: ClusterSpec) -> tuple[list[float], float, float]:
    """Divisors of the spatial axes, of time, and the diameter bound in scaled units (one scan for ``range``)."""
    axes = AXES[: spec.dims]
    if spec.normalise == "unit":
        return [spec.d_s] * spec.dims, spec.d_t * spec.time_unit, math.sqrt(2)
    if spec.normalise == "range":
        r = events.agg(*[(F.max(a) - F.min(a)).cast("double").alias(a) for a in (*axes, "t")]).first()
        space = max([r[a] or 0.0 for a in axes]) or 1.0
        time = (r["t"] or 0.0) or 1.0
        return [(r[a] or 1.0) for a in axes], time, math.sqrt((spec.d_s / space) ** 2 + (spec.d_t * spec.time_unit / time) ** 2)
    d = spec.d if spec.d is not None else math.hypot(spec.d_s, spec.d_t)
    return [1.0] * spec.dims, spec.time_unit, d
