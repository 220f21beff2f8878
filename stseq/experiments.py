"""The experiment workloads: sweeps over generated data, the gridded run, recall and accuracy beside cost."""

from __future__ import annotations

import time
from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from stseq import metrics
from stseq.density import ratio_matrix
from stseq.microcluster import cluster
from stseq.mining import mine_index, mine_instances
from stseq.model import ClusterSpec, MineOptions, NeighbourhoodSpec, SpaceSpec, clusters_as_points
from stseq.sources.planted import planted_chains, planted_events
from stseq.storage import stored

#: Settings of the generated-data experiments.
DIAMETERS = (40, 60, 80, 100)
SWEEPS = {"Ni": [100, 110, 120, 130, 140, 150, 160], "Pn": [2, 4, 6, 8, 10, 12, 14, 16, 18, 20], "Ps": [2, 3, 4, 5, 6, 7, 8, 9, 10]}
BASE = {"Ps": 5, "Pn": 10, "Ni": 100, "Nf": 20, "DSize": 1000, "TSize": 1200, "R": 10, "T": 10}
LIMITS = (20, 40, 60, 80, 100)


def generated_space(setting: dict) -> SpaceSpec:
    return SpaceSpec(x0=0, x1=setting["DSize"], y0=0, y1=setting["DSize"], t0=0, t1=setting["TSize"])


def clustering_row(events: DataFrame, spec: ClusterSpec, about: dict) -> dict:
    """Index size, compression and clustering time (ms) of one run."""
    begin = time.perf_counter()
    mc, _ = cluster(events, spec)
    size = metrics.index_size(mc)
    ms = (time.perf_counter() - begin) * 1000
    return about | {"d": spec.d, "K": spec.K, "index_size": size, "compression": metrics.compression_ratio(mc), "clustering_ms": ms}


def sweep_clustering(spark: SparkSession, parameter: str, values: list | None = None, diameters=DIAMETERS, seeds=(0,)) -> list[dict]:
    """Index size against one generator parameter, for each diameter (mean over seeds)."""
    rows = []
    for v in values or SWEEPS[parameter]:
        setting = BASE | {parameter: v}
        for d in diameters:
            runs = [clustering_row(stored(planted_events(spark, seed=s, **setting), "planted"), ClusterSpec(d=d), {parameter: v}) for s in seeds]
            rows.append(runs[0] | {k: sum(r[k] for r in runs) / len(runs) for k in ("index_size", "compression", "clustering_ms")})
    return rows


def sweep_mining(spark: SparkSession, parameter: str, values: list | None = None, diameters=DIAMETERS, theta: float = 1.0, seed: int = 0, max_length: int = 10, limit: int = 100_000) -> list[dict]:
    """Mining time, pattern count and recall of the planted chains against one parameter, by the microcluster miner."""
    rows = []
    for v in values or SWEEPS[parameter]:
        setting = BASE | {parameter: v}
        events = stored(planted_events(spark, seed=seed, **setting), "planted")
        expected = metrics.sub_chains(planted_chains(events))
        spec, space = NeighbourhoodSpec(setting["R"], setting["T"]), generated_space(setting)
        for d in diameters:
            mc, _ = cluster(events, ClusterSpec(d=d))
            points = clusters_as_points(mc)
            opts = MineOptions(theta=theta, max_length=max_length, limit_patterns=limit)
            result, ms = timed_mining(points, spec, space, opts)
            recall = metrics.recall_of(expected, result.patterns).agg(F.sum("found") / F.sum("expected")).first()[0]
            rows.append({parameter: v, "d": d, "patterns": result.patterns.count(), "mining_ms": ms, "recall": recall, "truncated": result.truncated})
    return rows


def timed_mining(points: DataFrame, spec: NeighbourhoodSpec, space: SpaceSpec, opts: MineOptions):
    begin = time.perf_counter()
    result = mine_index(points, spec, space, opts)
    return result, (time.perf_counter() - begin) * 1000


def baseline_instances(spark: SparkSession, setting: dict | None = None, theta: float = 1.0, max_length: int = 3, limit: int = 20_000, seed: int = 0) -> dict:
    """The instance miner on generated data, bounded in length and patterns (unbounded it does not end in useful time)."""
    setting = BASE | (setting or {})
    events = stored(planted_events(spark, seed=seed, **setting), "planted")
    begin = time.perf_counter()
    result = mine_instances(events, NeighbourhoodSpec(setting["R"], setting["T"]), generated_space(setting), MineOptions(theta=theta, max_length=max_length, limit_patterns=limit))
    return {"patterns": result.patterns.count(), "mining_ms": (time.perf_counter() - begin) * 1000, "truncated": result.truncated}


def size_limited(events: DataFrame, d_s: float, d_t: float, limits=LIMITS, normalise: str = "range", dims: int = 2) -> list[dict]:
    """Index size, compression and clustering time against K on gridded events."""
    return [clustering_row(events, ClusterSpec(d_s=d_s, d_t=d_t, K=k, normalise=normalise, dims=dims), {"n": events.count()}) for k in limits]


def accuracy(events: DataFrame, spec: NeighbourhoodSpec, space: SpaceSpec, clustering: ClusterSpec) -> DataFrame:
    """Relative error of every link's ratio on clusters against the events."""
    mc, _ = cluster(events, clustering)
    return metrics.ratio_error(ratio_matrix(events, spec, space), ratio_matrix(clusters_as_points(mc), spec, space))


def ablation(events: DataFrame, base: ClusterSpec, variants: dict[str, dict]) -> list[dict]:
    """Index size of each variant of the clustering options."""
    return [clustering_row(events, replace(base, **change), {"variant": name}) for name, change in {"base": {}, **variants}.items()]
