"""Gapless positions of rows in a global order, without a window over one partition."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from stseq.storage import stored


def inline_rows(spark: SparkSession, rows: list[tuple], names: list[str]) -> DataFrame:
    """A small table of longs as a local relation of the plan."""
    if not rows:
        return spark.range(0).select(*[F.col("id").alias(n) for n in names])
    values = ", ".join("(" + ", ".join(f"{int(x)}L" for x in r) + ")" for r in rows)
    return spark.sql(f"SELECT * FROM VALUES {values} AS t({', '.join(names)})")


def with_rank(df: DataFrame, order: list[str], name: str = "rank") -> tuple[DataFrame, int]:
    """Add the gapless 0-based position of each row in the order of ``order``; also return the row count.

    A range exchange sorts the rows over all tasks; each task numbers its own rows, and the counts of the
    tasks before it (one row a task reaches the driver) are added.
    """
    parts = int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    numbered = stored(df.repartitionByRange(parts, *order).sortWithinPartitions(*order).withColumn("_at", F.monotonically_increasing_id()), "ranked")
    part = F.shiftright("_at", 33)
    rows, before = [], 0
    for p, n in sorted((r["p"], r["n"]) for r in numbered.groupBy(part.alias("p")).agg(F.count("*").alias("n")).collect()):
        rows.append((p, before))
        before += n
    offsets = F.broadcast(inline_rows(df.sparkSession, rows, ["_p", "_before"]))  # a row a task
    ranked = numbered.join(offsets, part == F.col("_p")).withColumn(name, F.col("_before") + F.col("_at").bitwiseAND(F.lit((1 << 33) - 1)))
    return ranked.drop("_at", "_p", "_before"), before
