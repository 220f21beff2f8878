"""Tables in the folder that all executors share; they cut lineage and survive lost executors."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def shared_dir(spark: SparkSession) -> str:
    """spark.checkpoint.dir. Where it is unset a temporary folder, but only in local mode: executors of a cluster could not see it."""
    base = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not base:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
        spark.sparkContext.setCheckpointDir(tempfile.mkdtemp(prefix="stseq-shared-"))
        base = spark.sparkContext.getCheckpointDir()
    return base


def stored(df: DataFrame, name: str, *by: str) -> DataFrame:
    """Write ``df`` as Parquet (in folders of the columns ``by``) and read it back."""
    path = f"{shared_dir(df.sparkSession)}/{name}-{uuid.uuid4().hex}"
    df.write.partitionBy(*by).parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def stored_buckets(df: DataFrame, name: str, key: str) -> DataFrame:
    """Write ``df`` in buckets of ``key``, as many as shuffle partitions: joins and groupings on the key need no exchange of it."""
    spark = df.sparkSession
    n = int(spark.conf.get("spark.sql.shuffle.partitions"))
    table = f"{name}_{uuid.uuid4().hex}"
    dealt = df.repartition(n, key)  # a task has the rows of one bucket, so a bucket is one file
    dealt.write.option("path", f"{shared_dir(spark)}/{table}").bucketBy(n, key).sortBy(key).saveAsTable(table)
    return spark.table(table)


def discard(*tables: DataFrame) -> None:
    """Delete stored tables that nothing reads any more."""
    for df in tables:
        spark = df.sparkSession
        for place in {f.rsplit("/", 1)[0] for f in df.inputFiles()}:
            path = spark._jvm.org.apache.hadoop.fs.Path(place)
            path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(path, True)


def broadcast_if_small(df: DataFrame, rows: int, count: int | None = None) -> DataFrame:
    """Broadcast hint only behind a check of the row count."""
    return F.broadcast(df) if (df.count() if count is None else count) <= rows else df
