"""The microcluster index as tables: clusters partitioned by type, members apart so that the index stays narrow."""

from __future__ import annotations

import json
from dataclasses import asdict

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from stseq.model import ClusterSpec


def index_members(members: DataFrame) -> DataFrame:
    """Contained set and count of each cluster (for display): cid, members, n."""
    return members.groupBy("cid").agg(F.array_sort(F.collect_list("id")).alias("members"), F.count("*").alias("n"))


def write_index(mc: DataFrame, members: DataFrame, path: str, spec: ClusterSpec | None = None) -> None:
    mc.repartition("type").sortWithinPartitions("tile", "t").write.mode("overwrite").partitionBy("type").parquet(f"{path}/clusters")
    members.write.mode("overwrite").parquet(f"{path}/members")
    about = json.dumps(asdict(spec) if spec else {})
    mc.sparkSession.createDataFrame([(about,)], "spec string").coalesce(1).write.mode("overwrite").json(f"{path}/about")


def read_index(spark: SparkSession, path: str) -> tuple[DataFrame, DataFrame, dict]:
    """(clusters, members, options they were made with)."""
    mc = spark.read.parquet(f"{path}/clusters")
    about = json.loads(spark.read.json(f"{path}/about").first()["spec"])
    return mc.select(*[c for c in ("cid", "type", "n", "x", "y", "z", "t", "ss", "tile") if c in mc.columns]), spark.read.parquet(f"{path}/members"), about
