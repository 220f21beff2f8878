"""Plan checks: what a DataFrame's physical plan holds, and the estimate that bounds a join before it runs."""

from __future__ import annotations

import re

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from stseq.model import NeighbourhoodSpec, SpaceSpec, as_points
from stseq.neighbourhood import expected_pairs


def plan_text(df: DataFrame) -> str:
    return df._jdf.queryExecution().explainString(df.sparkSession._jvm.org.apache.spark.sql.execution.ExplainMode.fromString("formatted"))


def operators(df: DataFrame) -> dict[str, int]:
    """How often each physical operator stands in the plan."""
    out: dict[str, int] = {}
    for name in re.findall(r"^\(\d+\) ([A-Za-z ]+?)(?: \[| *$)", plan_text(df), re.M):
        out[name.strip()] = out.get(name.strip(), 0) + 1
    return out


def estimate_pairs(points: DataFrame, spec: NeighbourhoodSpec, space: SpaceSpec) -> DataFrame:
    """Pairs that independent types would have, by link: src_type, dst_type, expected."""
    n = as_points(points).groupBy("type").agg(F.count("*").alias("n"))
    a, b = n.select(F.col("type").alias("src_type"), F.col("n").alias("a")), n.select(F.col("type").alias("dst_type"), F.col("n").alias("b"))
    return a.crossJoin(b).select("src_type", "dst_type", (F.col("a") * F.col("b") * F.lit(spec.volume / space.volume)).alias("expected"))  # types squared


def check_size(points: DataFrame, spec: NeighbourhoodSpec, space: SpaceSpec, most: float = 1e12) -> float:
    """Expected pairs of all links; fails above ``most``, where R or T are too large for the data."""
    n = points.count()
    pairs = expected_pairs(n, n, spec, space)
    if pairs > most:
        raise ValueError(f"about {pairs:.3g} neighbour pairs expected; shrink R or T, or reduce the events first")
    return pairs


def suggest_cell(points: DataFrame, spec: NeighbourhoodSpec, fraction: float = 0.01, seed: int = 0) -> dict:
    """From a pilot sample: points to a cell of side R and T (mean, largest) scaled to the whole."""
    from stseq.neighbours import cell_columns

    cells = as_points(points).sample(fraction=fraction, seed=seed).select(*cell_columns(spec))
    r = cells.groupBy(*cells.columns).count().agg(F.avg("count").alias("mean"), F.max("count").alias("largest"), F.count("*").alias("cells")).first()
    return {k: (v or 0) / (fraction if k != "cells" else 1) for k, v in r.asDict().items()}
