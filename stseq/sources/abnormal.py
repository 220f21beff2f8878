"""Events of abnormal values: observations beyond a variable's outer quantiles."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from stseq.storage import stored


#: Accuracy of the sketch that brackets a quantile.
ACCURACY = 20_000


def thresholds(obs: DataFrame, low: float = 0.01, high: float = 0.99, method: str = "exact", by: list[str] | None = None) -> DataFrame:
    """Discrete quantiles of each variable (and group ``by``): low_q, high_q. ``approx`` is the sketch alone, for large tables.

    The exact form takes a bracket around each quantile from the sketch, counts the rows below it, and ranks only the
    distinct values inside it, so no task gathers a variable's values.
    """
    keys = ["variable", *(by or [])]
    if method == "approx":
        q = [F.percentile_approx("value", p, 100_000) for p in (low, high)]
        return obs.groupBy(*keys).agg(q[0].alias("low_q"), q[1].alias("high_q"))
    reach = 2.0 / ACCURACY
    points = [min(1.0, max(0.0, p + s)) for p in (low, high) for s in (-reach, reach)]
    known = obs.where("value is not null").groupBy(*keys).agg(F.count("*").alias("_n"), F.percentile_approx("value", points, ACCURACY).alias("_b"))
    sides = F.array(*[
        F.struct(F.lit(i).alias("side"), F.ceil(F.lit(p) * F.col("_n")).alias("place"), F.col("_b")[2 * i].alias("a"), F.col("_b")[2 * i + 1].alias("z")) for i, p in enumerate((low, high))
    ])
    known = stored(known.select(*keys, F.explode(sides).alias("_s")).select(*keys, "_s.*"), "brackets")
    # values below a bracket are one group, each value inside it another
    seen = obs.join(known, keys).where(F.col("value") <= F.col("z")).select(*keys, "side", "place", F.when(F.col("value") >= F.col("a"), F.col("value")).alias("value"))
    counted = seen.groupBy(*keys, "side", "place", "value").agg(F.count("*").alias("n"))
    run = F.sum("n").over(Window.partitionBy(*keys, "side").orderBy(F.col("value").asc_nulls_first()))
    found = counted.withColumn("_to", run).where((F.col("_to") >= F.greatest(F.col("place"), F.lit(1))) & F.col("value").isNotNull())
    return found.groupBy(*keys).agg(F.min(F.when(F.col("side") == 0, F.col("value"))).alias("low_q"), F.min(F.when(F.col("side") == 1, F.col("value"))).alias("high_q"))


def abnormal_events(obs: DataFrame, low: float = 0.01, high: float = 0.99, drop: list[tuple[str, str]] | None = None, method: str = "exact", by: list[str] | None = None) -> DataFrame:
    """Rows above the high quantile become ``High<variable>``, rows at or below the low one ``Low<variable>``."""
    keys = ["variable", *(by or [])]
    bounds = thresholds(obs, low, high, method, by)
    side = F.when(F.col("value") > F.col("high_q"), "High").when(F.col("value") <= F.col("low_q"), "Low")
    out = obs.join(bounds, keys).withColumn("side", side).where("side is not null")
    for variable, s in drop or []:
        out = out.where(~((F.col("variable") == variable) & (F.col("side") == s)))
    kind = F.concat("side", "variable")
    return out.select(F.xxhash64("row_id", "variable").alias("id"), kind.alias("type"), "x", "y", "t", "value")
