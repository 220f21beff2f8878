"""Clusterings that are plain aggregations: by grid cell, by equal position, and none at all."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from stseq.microcluster.features import AXES, scales
from stseq.model import ClusterSpec


def cluster_grid(events: DataFrame, spec: ClusterSpec) -> tuple[DataFrame, DataFrame]:
    """Cells of side d/sqrt(dimensions), so that no diameter is above d; one shuffle with partial aggregation."""
    axes = list(AXES[: spec.dims])
    space, time, d = scales(events, spec)
    side = d / math.sqrt(spec.dims + 1)
    scaled = {a: F.col(a) / F.lit(s) for a, s in zip([*axes, "t"], [*space, time])}
    cells = [F.floor(c / F.lit(side)).cast("long").alias(f"_c{a}") for a, c in scaled.items()]
    keyed = events.select("id", "type", *axes, "t", *cells)
    keys = ["type", *[f"_c{a}" for a in scaled]]
    cid = F.xxhash64(*keys)
    spread = sum((F.coalesce(F.var_samp(c), F.lit(0.0)) for c in scaled.values()), F.lit(0.0))
    mc = keyed.groupBy(*keys).agg(
        F.count("*").alias("n"), *[F.avg(a).alias(a) for a in axes], F.avg("t").alias("t"), (spread * (F.count("*") - 1)).alias("ss")
    ).select(cid.alias("cid"), "type", "n", *axes, "t", "ss", F.lit(0).cast("long").alias("tile"))
    return mc, keyed.select(cid.alias("cid"), "id")


def cluster_exact_duplicates(events: DataFrame, dims: int = 2) -> tuple[DataFrame, DataFrame]:
    """Events of one type at one place and time as one cluster."""
    axes = list(AXES[:dims])
    keys = ["type", *axes, "t"]
    cid = F.xxhash64(*keys)
    mc = events.groupBy(*keys).agg(F.count("*").alias("n"))
    mc = mc.select(cid.alias("cid"), "type", "n", *[F.col(a).cast("double").alias(a) for a in axes], F.col("t").cast("double").alias("t"), F.lit(0.0).alias("ss"), F.lit(0).cast("long").alias("tile"))
    return mc, events.select(cid.alias("cid"), "id")


def cluster_identity(events: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Each event its own cluster: the unreduced dataset in the index's shape."""
    axes = [a for a in AXES if a in events.columns]
    mc = events.select(F.col("id").alias("cid"), "type", F.lit(1).cast("long").alias("n"), *axes, "t", F.lit(0.0).alias("ss"), F.lit(0).cast("long").alias("tile"))
    return mc, events.select(F.col("id").alias("cid"), "id")
