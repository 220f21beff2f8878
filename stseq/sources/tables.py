"""Adapters that turn tables into events (id, type, x, y, t); all are projections that prune the scan."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from stseq.model import SpaceSpec

HOUR = 3_600_000_000  # ticks (microseconds)
ORIGIN = "timestamp_ntz'2024-01-01 00:00:00'"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def micros(column: str, origin: str = ORIGIN):
    return F.expr(f"timestampdiff(MICROSECOND, {origin}, {column})")


def days(column: str, origin: str = "date'1992-01-01'"):
    return F.expr(f"cast(datediff(cast({column} as date), {origin}) as bigint)")


def events_from_events(spark: SparkSession, sf_dir: str) -> DataFrame:
    """User by page key over time in microseconds."""
    return table(spark, sf_dir, "events").select(
        F.col("event_id").cast("bigint").alias("id"), F.col("event_type").alias("type"), F.col("user_id").cast("bigint").alias("x"),
        F.get_json_object("props", "$.k").cast("bigint").alias("y"), micros("ts").alias("t"), "value",
    )


def events_space(events: DataFrame) -> SpaceSpec:
    """The lattice of users, 100 keys and 30 days."""
    users = events.agg(F.max("x")).first()[0] or 0
    return SpaceSpec(x0=0, x1=users + 1, y0=0, y1=100, t0=0, t1=720 * HOUR)


def events_from_events_1d(spark: SparkSession, sf_dir: str) -> DataFrame:
    return events_from_events(spark, sf_dir).drop("y")


def events_from_lineitem(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Return flag and status over parts and suppliers by ship day; the id is a hash of the row's identifying columns."""
    names = ["l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "l_shipdate", "l_extendedprice"]
    return table(spark, sf_dir, "lineitem").select(
        F.xxhash64(*names).alias("id"), F.concat("l_returnflag", "l_linestatus").alias("type"), F.col("l_partkey").cast("bigint").alias("x"),
        F.col("l_suppkey").cast("bigint").alias("y"), days("l_shipdate").alias("t"),
    )


def events_from_orders(spark: SparkSession, sf_dir: str, kind: str = "o_orderpriority") -> DataFrame:
    """Order priority (or status) on the lattice of regions and nations by day."""
    nations = table(spark, sf_dir, "nation").select(F.col("n_nationkey").alias("c_nationkey"), F.col("n_regionkey").cast("bigint").alias("x"))  # 25 rows
    customers = table(spark, sf_dir, "customer").select("c_custkey", "c_nationkey").join(F.broadcast(nations), "c_nationkey")
    orders = table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", F.col(kind).alias("type"), days("o_orderdate").alias("t"))
    return orders.join(customers, F.col("o_custkey") == F.col("c_custkey")).select(
        F.col("o_orderkey").cast("bigint").alias("id"), "type", "x", F.col("c_nationkey").cast("bigint").alias("y"), "t"
    )


def events_from_conversations(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Roles on a line of conversations, the turn as time."""
    return table(spark, sf_dir, "conversations").select(
        (F.col("conv_id") * 1000 + F.col("turn")).alias("id"), F.col("role").alias("type"), F.col("conv_id").cast("bigint").alias("x"), F.col("turn").cast("bigint").alias("t")
    )


def events_from_embeddings(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Labels at the first two components, the vector number as order."""
    return table(spark, sf_dir, "embeddings").select(
        F.col("vec_id").cast("bigint").alias("id"), F.col("label").cast("string").alias("type"), F.col("embedding")[0].cast("double").alias("x"),
        F.col("embedding")[1].cast("double").alias("y"), F.col("vec_id").cast("bigint").alias("t"),
    )


def observations_from_lineitem(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Gridded observations (variable, x, y, t, value): prices and balances on a lattice of suppliers by ship day."""
    names = ["l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "l_shipdate", "l_extendedprice"]
    orders = table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", "o_totalprice")
    customers = table(spark, sf_dir, "customer").select("c_custkey", "c_acctbal")
    wide = (
        table(spark, sf_dir, "lineitem").select(*names)
        .join(orders, F.col("l_orderkey") == F.col("o_orderkey")).join(customers, F.col("o_custkey") == F.col("c_custkey"))
        .select(
            F.xxhash64(*names).alias("row_id"), (F.col("l_suppkey") % 10 * 0.5).cast("double").alias("x"), (F.expr("l_suppkey div 10") * 0.5).cast("double").alias("y"),
            days("l_shipdate").alias("t"), F.col("l_extendedprice").cast("double").alias("Price"), F.col("o_totalprice").cast("double").alias("Order"), F.col("c_acctbal").cast("double").alias("Balance"),
        )
    )
    return wide.unpivot(["row_id", "x", "y", "t"], ["Price", "Order", "Balance"], "variable", "value")


def cleaned(events: DataFrame, space: SpaceSpec, types: list[str] | None = None) -> DataFrame:
    """Events without nulls, inside the space, of the given types."""
    out = events.where(F.col("id").isNotNull() & F.col("type").isNotNull() & F.col("t").isNotNull() & space.contains())
    return out.where(F.col("type").isin(types)) if types else out


def events_from_log(spark: SparkSession, path: str, form: str = "json") -> DataFrame:
    """Event log in JSON or CSV lines with the event columns."""
    from stseq.model import EVENT_SCHEMA

    reader = spark.read.schema(EVENT_SCHEMA)
    return reader.option("header", True).csv(path) if form == "csv" else reader.json(path)
