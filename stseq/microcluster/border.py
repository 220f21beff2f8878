"""Merging clusters across tile borders: mutual nearest ones whose joint diameter stays within the bound, round by round.

Partners are clusters of one type from different tiles (or already merged ones) whose centres are at most the bound
apart. A round joins all pairs that are each other's nearest partner; rounds go on until no pair is left.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from stseq.microcluster.features import AXES, diameter_cf, scales
from stseq.model import ClusterSpec
from stseq.storage import stored


def mutual_nearest(mc: DataFrame, spec: ClusterSpec, scale: list[float], d: float) -> DataFrame:
    """One round's merges (cid, into; into < cid) among clusters with the flag ``joined``, by an equi-join on cells of side d."""
    axes = [*AXES[: spec.dims], "t"]
    names = [f"s{a}" for a in axes]
    points = mc.select("cid", "type", "tile", "joined", "n", "ss", *[(F.col(a) / F.lit(s)).alias(f"s{a}") for a, s in zip(axes, scale)])
    cell = {c: F.floor(F.col(c) / F.lit(d)).cast("long") for c in names}
    about = F.struct("cid", "tile", "joined", "n", "ss", *names)
    left = points
    for c in names:
        left = left.withColumn(f"k{c}", F.explode(F.sequence(cell[c] - 1, cell[c] + 1)))
    keys = ["type", *[f"k{c}" for c in names]]
    left = left.select(*keys, about.alias("a"))
    right = points.select("type", *[cell[c].alias(f"k{c}") for c in names], about.alias("b"))
    gap = sum(((F.col(f"a.{c}") - F.col(f"b.{c}")) * (F.col(f"a.{c}") - F.col(f"b.{c}")) for c in names), F.lit(0.0))
    n = F.col("a.n") + F.col("b.n")
    joint = F.col("a.ss") + F.col("b.ss") + gap * F.col("a.n") * F.col("b.n") / n
    fits = (gap <= d * d) & (diameter_cf(n, joint) <= d) & ((n <= spec.K) if spec.K else F.lit(True))
    apart = (F.col("a.cid") != F.col("b.cid")) & ((F.col("a.tile") != F.col("b.tile")) | F.col("a.joined") | F.col("b.joined"))
    near = left.join(right, keys).where(apart & fits).select(F.col("a.cid").alias("cid"), F.struct(gap.alias("gap"), F.col("b.cid").alias("other")).alias("to"))
    best = stored(near.groupBy("cid").agg(F.min("to").alias("to")).select("cid", F.col("to.other").alias("other")), "nearest")
    back = best.select(F.col("cid").alias("other"), F.col("other").alias("cid"))
    return best.join(back, ["cid", "other"]).where("cid < other").select(F.col("other").alias("cid"), F.col("cid").alias("into"))


def merge_borders(mc: DataFrame, members: DataFrame, spec: ClusterSpec) -> tuple[DataFrame, DataFrame]:
    axes = [*AXES[: spec.dims], "t"]
    space, time, d = scales(mc, spec)
    scale = [*space, time]
    columns, now = mc.columns, mc.withColumn("joined", F.lit(False))
    while True:
        into = stored(mutual_nearest(now, spec, scale, d), "merges")
        if not into.count():
            return now.select(*columns), members
        moved = now.join(into, "cid", "left").select(F.coalesce("into", "cid").alias("cid"), *[c for c in now.columns if c != "cid"])
        n = F.sum("n")
        mean = {a: F.sum(F.col(a) * F.col("n")) / n for a in axes}
        # the spread of the whole is that within the parts and that of their means
        between = sum((F.sum(F.pow(F.col(a) / F.lit(s), 2) * F.col("n")) - n * F.pow(mean[a] / F.lit(s), 2) for a, s in zip(axes, scale)), F.lit(0.0))
        many = F.count("*") > 1
        now = stored(moved.groupBy("cid", "type").agg(
            n.alias("n"), *[mean[a].alias(a) for a in axes], F.when(many, F.sum("ss") + F.greatest(between, F.lit(0.0))).otherwise(F.sum("ss")).alias("ss"),
            F.min("tile").alias("tile"), (many | F.bool_or("joined")).alias("joined"),
        ), "merged")
        members = stored(members.join(into, "cid", "left").select(F.coalesce("into", "cid").alias("cid"), "id"), "members")
