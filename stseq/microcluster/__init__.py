"""Microclustering: weighted representatives of events of one type that lie close together."""

from __future__ import annotations

from pyspark.sql import DataFrame

from stseq.microcluster.border import merge_borders
from stseq.microcluster.grid import cluster_exact_duplicates, cluster_grid, cluster_identity
from stseq.microcluster.incremental import absorb, cluster_incremental
from stseq.microcluster.index import index_members, read_index, write_index
from stseq.model import ClusterSpec

__all__ = [
    "absorb", "cluster", "cluster_exact_duplicates", "cluster_grid", "cluster_identity", "cluster_incremental",
    "index_members", "merge_borders", "read_index", "write_index",
]


def cluster(events: DataFrame, spec: ClusterSpec) -> tuple[DataFrame, DataFrame]:
    """(microclusters, members: cid, id) by the method of ``spec``."""
    if spec.method == "grid":
        return cluster_grid(events, spec)
    if spec.method == "duplicates":
        return cluster_exact_duplicates(events, spec.dims)
    if spec.method == "identity":
        return cluster_identity(events)
    mc, members = cluster_incremental(events, spec)
    return merge_borders(mc, members, spec) if spec.merge_borders else (mc, members)
