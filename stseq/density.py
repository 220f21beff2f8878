"""Densities and density ratios.

For a source set S and a target type g: ratio = W * |V| / (|S| * N_g * |V_N|), where W sums the weight products
of the neighbour pairs, |S| and N_g the weights. W is an integer, so no result depends on the partitioning.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from stseq.model import NeighbourhoodSpec, SpaceSpec, as_points
from stseq.neighbourhood import clipped_volume
from stseq.neighbours import pairs_grid, torus_targets
from stseq.storage import broadcast_if_small, stored


def type_counts(points: DataFrame) -> DataFrame:
    """Weight of each type: type, N."""
    return as_points(points).groupBy("type").agg(F.sum("w").alias("N"))


def type_density(points: DataFrame, space: SpaceSpec) -> DataFrame:
    """Density of each type in the space."""
    return type_counts(points).withColumn("density", F.col("N") / F.lit(space.volume))


def local_density(pairs: DataFrame, points: DataFrame, spec: NeighbourhoodSpec) -> DataFrame:
    """Density of every target type in each source's neighbourhood, zeros included: src_id, src_type, dst_type, W, density."""
    points = as_points(points)
    types = broadcast_if_small(stored(points.select(F.col("type").alias("dst_type")).distinct(), "types"), 100_000)
    found = pairs.groupBy("src_id", "dst_type").agg(F.sum("dst_w").alias("W"))
    every = points.select(F.col("id").alias("src_id"), F.col("type").alias("src_type")).crossJoin(types)
    out = every.join(found, ["src_id", "dst_type"], "left").withColumn("W", F.coalesce("W", F.lit(0)))
    return out.select("src_id", "src_type", "dst_type", "W", (F.col("W") / F.lit(spec.volume)).alias("density"))


def link_weights(pairs: DataFrame) -> DataFrame:
    """W of each link; the partial sums stand in the join's own stage."""
    return pairs.groupBy("src_type", "dst_type").agg(F.sum(F.col("src_w") * F.col("dst_w")).alias("W"))


def ratio_of(W: Column, size: Column, N: Column, spec: NeighbourhoodSpec, space: SpaceSpec) -> Column:
    return W * F.lit(space.volume / spec.volume) / (size.cast("double") * N)


def ratio_matrix(points: DataFrame, spec: NeighbourhoodSpec, space: SpaceSpec, pairs: DataFrame | None = None, weights: DataFrame | None = None) -> DataFrame:
    """All links, those without pairs included: src_type, dst_type, W, src_n, dst_n, ratio.

    With ``edge_correction='clip_box'`` each source's density is taken over its own clipped volume, with ``'torus'``
    neighbourhoods wrap around the space.
    """
    points = as_points(points)
    counts = type_counts(points)
    every = counts.select(F.col("type").alias("src_type"), F.col("N").alias("src_n")).crossJoin(counts.select(F.col("type").alias("dst_type"), F.col("N").alias("dst_n")))
    if spec.edge_correction == "clip_box":
        if pairs is None:
            pairs = pairs_grid(points, spec, about=clipped_volume(spec, space))
        else:
            pairs = pairs.join(points.select(F.col("id").alias("src_id"), clipped_volume(spec, space).alias("src_about")), "src_id")
        mean = pairs.groupBy("src_type", "dst_type").agg(
            F.sum(F.col("src_w") * F.col("dst_w")).alias("W"), F.sum(F.col("src_w") * F.col("dst_w") / F.col("src_about")).alias("m")
        )
        out = every.join(mean, ["src_type", "dst_type"], "left")
        ratio = F.coalesce("m", F.lit(0.0)) / F.col("src_n") / (F.col("dst_n") / F.lit(space.volume))
        return out.select("src_type", "dst_type", F.coalesce("W", F.lit(0)).alias("W"), "src_n", "dst_n", ratio.alias("ratio"))
    if spec.edge_correction == "torus" and pairs is None:
        pairs = pairs_grid(points, spec, torus_targets(points, spec, space))
    if weights is None:
        weights = link_weights(pairs if pairs is not None else pairs_grid(points, spec))
    out = every.join(weights, ["src_type", "dst_type"], "left").withColumn("W", F.coalesce("W", F.lit(0)))
    return out.select("src_type", "dst_type", "W", "src_n", "dst_n", ratio_of(F.col("W"), F.col("src_n"), F.col("dst_n"), spec, space).alias("ratio"))


def density_ratio(points: DataFrame, f1: str, f2: str, spec: NeighbourhoodSpec, space: SpaceSpec) -> DataFrame:
    """Ratio of one link (one row); only its two types are joined."""
    two = as_points(points).where(F.col("type").isin(f1, f2))
    pairs = pairs_grid(two.where(F.col("type") == f1), spec, two.where(F.col("type") == f2))
    return ratio_matrix(two, spec, space, pairs).where((F.col("src_type") == f1) & (F.col("dst_type") == f2))


def mean_local_density(pairs: DataFrame, points: DataFrame, spec: NeighbourhoodSpec) -> DataFrame:
    """Weighted mean density of each target type around each source type: the numerator of the ratio."""
    size = type_counts(points).select(F.col("type").alias("src_type"), F.col("N").alias("src_n"))
    return link_weights(pairs).join(size, "src_type").withColumn("mean_density", F.col("W") / (F.col("src_n") * F.lit(spec.volume)))


def tail_ratios(tails: DataFrame, pairs: DataFrame, counts: DataFrame, spec: NeighbourhoodSpec, space: SpaceSpec) -> DataFrame:
    """Ratio of each chain's tail (seq_id, id, w) to every type that it reaches: seq_id, dst_type, W, S, ratio."""
    size = tails.groupBy("seq_id").agg(F.sum("w").alias("S"))
    reached = tails.join(pairs, F.col("id") == F.col("src_id")).groupBy("seq_id", "dst_type").agg(F.sum(F.col("w") * F.col("dst_w")).alias("W"))
    types = counts.select(F.col("type").alias("dst_type"), "N")
    out = reached.join(size, "seq_id").join(types, "dst_type")
    return out.select("seq_id", "dst_type", "W", "S", ratio_of(F.col("W"), F.col("S"), F.col("N"), spec, space).alias("ratio"))


def relation_sign(ratio: Column, eps: float = 0.0) -> Column:
    """attract above 1+eps, repel below 1-eps, else none."""
    return F.when(ratio > 1 + eps, "attract").when(ratio < 1 - eps, "repel").otherwise("none")


def ratio_vectors(matrix: DataFrame) -> DataFrame:
    """One row a source type: map of target type to ratio."""
    return matrix.groupBy("src_type").agg(F.map_from_entries(F.array_sort(F.collect_list(F.struct("dst_type", "ratio")))).alias("ratios"))
