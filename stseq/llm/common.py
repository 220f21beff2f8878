"""Helpers shared by the corpus operators: shared-folder tables, ranks and connected components."""

from __future__ import annotations

import uuid
from collections.abc import Iterator
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from stseq.ranks import inline_rows, with_rank
from stseq.storage import shared_dir

__all__ = ["checked_small", "connected_components", "inline_rows", "read_table", "shared_buckets", "shared_dir", "small_batches", "stored", "with_rank"]


def stored(df: DataFrame, name: str) -> DataFrame:
    """Write ``df`` once as Parquet in the shared folder and read it back: cuts lineage, survives lost executors."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"
    with small_batches(spark):
        df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


@contextmanager
def small_batches(spark: SparkSession, rows: int = 1000) -> Iterator[None]:
    """Arrow batches of at most ``rows`` rows while a job of ours runs: whole texts would else fill tens of MB on both sides."""
    key = "spark.sql.execution.arrow.maxRecordsPerBatch"
    before = int(spark.conf.get(key))
    spark.conf.set(key, str(min(before, rows) if before > 0 else rows))
    try:
        yield
    finally:
        spark.conf.set(key, str(before))


def checked_small(df: DataFrame, name: str, rows: int = 100_000) -> DataFrame:
    """The stored table, to be broadcast only if it has at most ``rows`` rows; beyond that the join shuffles."""
    kept = stored(df, name)
    return F.broadcast(kept) if kept.count() <= rows else kept


def shared_buckets(rows: DataFrame, keys: list[str], member: str, block: int) -> DataFrame:
    """The rows (``keys``, ``member``) of buckets with two rows or more, and for each: parts (blocks of about ``block`` rows that
    its bucket is cut into) and own (its block, by a hash of the member).

    The join that leaves single rows out is on the block too, so a bucket with a third of all rows is spread like any other.
    """
    counts = rows.groupBy(*keys).agg(F.count("*").alias("n")).where("n > 1")
    counts = stored(counts.select(*keys, F.ceil(F.col("n") / F.lit(block)).cast("int").alias("parts")), "buckets")
    cut = rows.join(checked_small(counts.where("parts > 1"), "cut-buckets"), keys, "left").withColumn("parts", F.coalesce("parts", F.lit(1)))
    cut = cut.withColumn("own", F.pmod(F.xxhash64(member), F.col("parts")).cast("int"))
    return cut.join(counts.select(*keys, F.explode(F.sequence(F.lit(0), F.col("parts") - 1)).alias("own")), [*keys, "own"])


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def connected_components(edges: DataFrame, src: str = "src", dst: str = "dst", max_rounds: int = 60) -> DataFrame:
    """Smallest reachable node for every node of an undirected edge list of longs: columns node, component.

    Alternates two star operations (link larger neighbours to the smallest neighbour, then smaller ones)
    until the edge set stops changing; each round is stored in the shared folder. The least neighbours are stored
    too, so that both sides of a join come from an exchange and a node with very many edges can be split over tasks.
    """
    spark = edges.sparkSession
    now = (
        edges.where(F.col(src) != F.col(dst))
        .select(F.greatest(src, dst).alias("u"), F.least(src, dst).alias("v"))
        .distinct()
    )
    now, before = stored(now, "edges"), None
    for _ in range(max_rounds):
        digest = now.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
        if digest == before or digest[0] == 0:
            break
        before = digest
        both = now.unionByName(now.select(F.col("v").alias("u"), F.col("u").alias("v")))
        low = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        low = stored(low, "least")
        large = both.where("v > u").join(low, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v").distinct()
        large = stored(large, "large")
        down = stored(large.groupBy("u").agg(F.min("v").alias("m")), "least")
        small = (
            large.join(down, "u")
            .select(F.explode(F.array(F.struct(F.col("v").alias("a"), F.col("m").alias("b")), F.struct(F.col("u").alias("a"), F.col("m").alias("b")))).alias("e"))
            .select(F.col("e.a").alias("u"), F.col("e.b").alias("v"))
            .where("u <> v")
            .distinct()
        )
        now = stored(small, "edges")
    else:
        raise RuntimeError("connected components did not settle")
    nodes = now.groupBy(F.col("u").alias("node")).agg(F.min("v").alias("component"))
    roots = now.select(F.col("v").alias("node")).distinct().join(nodes, "node", "left_anti")
    return nodes.unionByName(roots.select("node", F.col("node").alias("component")))
