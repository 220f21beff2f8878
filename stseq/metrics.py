"""Cost and accuracy measures of the experiments."""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from stseq.microcluster.features import diameter_cf


def index_size(mc: DataFrame) -> int:
    return mc.count()


def compression_ratio(mc: DataFrame) -> float:
    """Events over clusters; the cluster sizes add up to the events."""
    r = mc.agg(F.sum("n"), F.count("*")).first()
    return (r[0] or 0) / r[1] if r[1] else 0.0


def timed(make: Callable[[], DataFrame]) -> tuple[DataFrame, float]:
    """Run a job into the noop sink; the result and wall milliseconds."""
    begin = time.perf_counter()
    df = make()
    df.write.format("noop").mode("overwrite").save()
    return df, (time.perf_counter() - begin) * 1000


def pattern_counts(patterns: DataFrame) -> DataFrame:
    return patterns.groupBy("length").agg(F.count("*").alias("patterns")).orderBy("length")


def sub_chains(chains: DataFrame, least: int = 2) -> DataFrame:
    """All contiguous parts of at least ``least`` types of each chain (column seq)."""
    n = F.size("seq")
    parts = chains.select("seq", F.explode(F.sequence(F.lit(1), n)).alias("i")).where(n - F.col("i") + 1 >= least)
    parts = parts.select("seq", "i", F.explode(F.sequence(F.lit(least), n - F.col("i") + 1)).alias("l"))
    return parts.select(F.slice("seq", F.col("i"), F.col("l")).alias("seq")).distinct()


def recall_of(expected: DataFrame, found: DataFrame) -> DataFrame:
    """Expected chains and whether each was found, by length: length, expected, found, recall."""
    hit = expected.select("seq").distinct().join(found.select("seq", F.lit(1).alias("hit")).distinct(), "seq", "left")
    return hit.groupBy(F.size("seq").alias("length")).agg(F.count("*").alias("expected"), F.count("hit").alias("found")).withColumn("recall", F.col("found") / F.col("expected"))


def redundancy(instance: DataFrame, reduced: DataFrame) -> DataFrame:
    """Patterns only in one of two results, in both, and their Jaccard similarity (one row)."""
    a, b = instance.select("seq").distinct().withColumn("a", F.lit(1)), reduced.select("seq").distinct().withColumn("b", F.lit(1))
    both = F.count(F.when(F.col("a").isNotNull() & F.col("b").isNotNull(), 1))
    out = a.join(b, "seq", "full").agg(F.count(F.when(F.col("b").isNull(), 1)).alias("only_first"), F.count(F.when(F.col("a").isNull(), 1)).alias("only_second"), both.alias("both"), F.count("*").alias("_n"))
    return out.withColumn("jaccard", F.when(F.col("_n") > 0, F.col("both") / F.col("_n"))).drop("_n")


def ratio_error(matrix: DataFrame, reduced: DataFrame) -> DataFrame:
    """Relative error of each link's ratio on a reduced dataset."""
    b = reduced.select("src_type", "dst_type", F.col("ratio").alias("ratio_reduced"))
    return matrix.select("src_type", "dst_type", "ratio").join(b, ["src_type", "dst_type"]).withColumn("error", F.when(F.col("ratio") > 0, F.abs(F.col("ratio_reduced") - F.col("ratio")) / F.col("ratio")))


def diameter_violations(mc: DataFrame, d: float, tolerance: float = 1e-9) -> int:
    return mc.where(diameter_cf(F.col("n"), F.col("ss")) > d + tolerance).count()


def size_histogram(mc: DataFrame) -> DataFrame:
    """Clusters by size in powers of two."""
    return mc.groupBy(F.floor(F.log2(F.col("n").cast("double"))).cast("int").alias("log2_size")).agg(F.count("*").alias("clusters"), F.sum("n").alias("events"))


def displacement(events: DataFrame, mc: DataFrame, members: DataFrame) -> DataFrame:
    """Mean spatial and temporal distance of events from their representative, by type."""
    rep = mc.select("cid", F.col("x").alias("rx"), F.col("y").alias("ry"), F.col("t").alias("rt"))
    out = members.join(rep, "cid").join(events.select("id", "type", "x", "y", "t"), "id")
    return out.groupBy("type").agg(F.avg(F.hypot(F.col("x") - F.col("rx"), F.col("y") - F.col("ry"))).alias("mean_space"), F.avg(F.abs(F.col("t") - F.col("rt"))).alias("mean_time"))


def conservation(events: DataFrame, members: DataFrame) -> DataFrame:
    """Events of each type and how many of them stand in exactly one cluster."""
    once = members.groupBy("id").agg(F.count("*").alias("times"))
    return events.select("id", "type").join(once, "id", "left").groupBy("type").agg(
        F.count("*").alias("events"), F.sum(F.when(F.coalesce("times", F.lit(0)) == 1, 1).otherwise(0)).alias("clustered_once")
    )
