"""Diameter-bounded and size-limited incremental clustering, one Arrow group for each type (and tile)."""

from __future__ import annotations

from itertools import chain

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from stseq.microcluster.features import AXES, scales
from stseq.microcluster.near_grid import clustered
from stseq.model import ClusterSpec
from stseq.storage import stored


def tile_of(spec: ClusterSpec) -> Column:
    """Tile number of a point; 0 without tiles (then a type is one group, and the result the sequential one)."""
    if spec.tile is None:
        return F.lit(0).cast("long")
    cells = [F.floor(F.col(a) / F.lit(spec.tile)) for a in AXES[: spec.dims]]
    return F.xxhash64(*cells, F.floor(F.col("t") / F.lit((spec.tile_t or spec.tile) * spec.time_unit)))


def _kernel_options(spec: ClusterSpec) -> dict:
    return {"K": spec.K, "assign": spec.assign, "recheck": spec.recheck, "zero_split": spec.zero_split, "nearest": spec.nearest}


def cluster_incremental(events: DataFrame, spec: ClusterSpec) -> tuple[DataFrame, DataFrame]:
    """(microclusters, members). Exact order of insertion holds within a group; ids never depend on the partitioning."""
    axes = list(AXES[: spec.dims])
    space, time, d = scales(events, spec)
    options = _kernel_options(spec)

    names = ["kind", "type", "tile", "local", "n", *axes, "t", "ss", "id"]

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values({"time_id": ["t", "id"], "time_place": ["t", *axes, "id"], "id": ["id"]}[spec.order_by], kind="stable")
        raw = pdf[[*axes, "t"]].to_numpy(float)
        x = raw / np.array([*space, time])
        x = x - x.mean(axis=0)
        groups = clustered(x, d, **options)
        n = np.fromiter(map(len, groups), np.int64, len(groups))
        order, first = np.fromiter(chain.from_iterable(groups), np.int64, len(x)), np.cumsum(n) - n
        del groups
        local = np.empty(len(x), np.int64)
        local[order] = np.repeat(np.arange(len(n)), n)
        mean = raw[order[first]] + np.add.reduceat(raw[order] - np.repeat(raw[order[first]], n, axis=0), first, axis=0) / n[:, None]
        # places from the cluster's first member: sums that do not lose digits
        x = x[order] - np.repeat(x[order[first]], n, axis=0)
        x = x - np.repeat(np.add.reduceat(x, first, axis=0) / n[:, None], n, axis=0)
        mc = {"kind": 0, "local": np.arange(len(n)), "n": n, "id": None, "ss": np.add.reduceat((x**2).sum(axis=1), first)}
        mc |= {a: mean[:, k] for k, a in enumerate([*axes, "t"])}
        own = {"kind": 1, "local": local, "n": None, "id": pdf["id"].to_numpy(), "ss": np.nan} | {a: np.nan for a in (*axes, "t")}
        both = pd.concat([pd.DataFrame(mc).astype({"n": "Int64", "id": "Int64"}), pd.DataFrame(own).astype({"n": "Int64", "id": "Int64"})], ignore_index=True)
        return both.assign(type=pdf["type"].iloc[0], tile=pdf["tile"].iloc[0])[names]

    # one row a cluster and one a member, so that no row grows with the data
    schema = "kind int, type string, tile bigint, local bigint, n bigint, " + ", ".join(f"{a} double" for a in axes) + ", t double, ss double, id bigint"
    grouped = events.select("id", "type", *[F.col(a).cast("double").alias(a) for a in axes], F.col("t").cast("double").alias("t"), tile_of(spec).alias("tile"))
    whole = stored(grouped.groupBy("type", "tile").applyInPandas(run, schema).withColumn("cid", F.xxhash64("type", "tile", "local")), "microclusters", "kind")
    return whole.where("kind = 0").select("cid", "type", "n", *axes, "t", "ss", "tile"), whole.where("kind = 1").select("cid", "id")


def absorb(mc: DataFrame, new_events: DataFrame, spec: ClusterSpec) -> DataFrame:
    """A ready index with new events put in: into the nearest cluster of the type (and tile) while it stays within the
    bounds, else as a new one. Members are not needed, so the work is that of the new events alone.
    """
    axes = list(AXES[: spec.dims])
    space, time, d = scales(new_events, spec)
    scale, columns, most = np.array([*space, time]), list(mc.columns), spec.K

    def run(old: pd.DataFrame, new: pd.DataFrame) -> pd.DataFrame:
        tile, kind = (old if len(old) else new)[["tile", "type"]].iloc[0]
        centre = [r for r in (old[[*axes, "t"]].to_numpy(float) / scale)]
        n, ss, cid = old["n"].tolist(), old["ss"].tolist(), old["cid"].tolist()
        for r in new.sort_values(["t", "id"], kind="stable").itertuples():
            x = np.array([getattr(r, a) for a in axes] + [r.t], float) / scale
            if centre:
                gap = np.array([((c - x) ** 2).sum() for c in centre])
                at = int(np.argmin(gap))
                grown = ss[at] + gap[at] * n[at] / (n[at] + 1)
                if np.sqrt(2 * grown / n[at]) <= d and (most is None or n[at] < most):
                    centre[at] = centre[at] + (x - centre[at]) / (n[at] + 1)
                    n[at], ss[at] = n[at] + 1, grown
                    continue
            centre.append(x)
            n.append(1)
            ss.append(0.0)
            cid.append(int(r.new_cid))
        back = np.array(centre).reshape(-1, len(scale)) * scale
        out = {"cid": cid, "type": kind, "n": n} | {a: back[:, k] for k, a in enumerate([*axes, "t"])}
        return pd.DataFrame(out | {"ss": ss, "tile": tile})[columns]

    fresh = new_events.select(
        "id", "type", *[F.col(a).cast("double").alias(a) for a in axes], F.col("t").cast("double").alias("t"),
        tile_of(spec).alias("tile"), F.xxhash64("type", F.lit("new"), "id").alias("new_cid"),
    )
    return mc.groupBy("type", "tile").cogroup(fresh.groupBy("type", "tile")).applyInPandas(run, mc.schema)
