"""Sharding along a Hilbert curve over quantised metadata, so that files can be pruned in several dimensions.

Dimensions: language, source and size. Each is quantised to 8 bits; rows are ordered by the index of their
cell on the curve and cut into runs of equal row counts (law ``rows``) or of near equal bytes (``bytes``).
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from stseq.llm.common import checked_small, inline_rows, stored, with_rank

BITS = 8


def hilbert_index(cells: np.ndarray, bits: int = BITS) -> np.ndarray:
    """Index on the Hilbert curve of the rows of ``cells`` (n x dims, ints below 2**bits).

    Works down the bits of the transposed index: undo the excess turns, Gray-code, then interleave.
    """
    x = np.array(cells, np.int64).T.copy()
    dims = len(x)
    top = 1 << (bits - 1)
    q = top
    while q > 1:
        low = q - 1
        for i in range(dims):
            on = (x[i] & q) != 0
            swap = (x[0] ^ x[i]) & low
            x[0] = np.where(on, x[0] ^ low, x[0] ^ swap)
            if i:
                x[i] = np.where(on, x[i], x[i] ^ swap)
        q >>= 1
    for i in range(1, dims):
        x[i] ^= x[i - 1]
    turn = np.zeros(x.shape[1], np.int64)
    q = top
    while q > 1:
        turn = np.where((x[-1] & q) != 0, turn ^ (q - 1), turn)
        q >>= 1
    x ^= turn
    out = np.zeros(x.shape[1], np.int64)
    for b in range(bits - 1, -1, -1):
        for i in range(dims):
            out = (out << 1) | ((x[i] >> b) & 1)
    return out


def size_cell(size: Column, bits: int = BITS) -> Column:
    """Eight cells for each doubling of the size, so that one cell spans at most 9 percent."""
    return F.least(F.lit((1 << bits) - 1), F.floor(F.log2(size.cast("double")) * 8)).cast("int")


def with_string_cell(df: DataFrame, name: str, out: str, bits: int = BITS) -> DataFrame:
    """Add the rank of the value among the column's distinct values, spread over the cells; null is cell 0.

    The distinct values are ranked over all tasks, however many there are; their table is broadcast only if it is small.
    """
    values, n = with_rank(df.select(F.col(name).alias("_value")).where("_value is not null").distinct(), ["_value"], "_rank")
    cells = values.select("_value", F.expr(f"cast(((_rank + 1) * {1 << bits}L) div {n + 1}L as int)").alias(out))
    joined = df.join(checked_small(cells, f"cells-{out}"), F.col(name) == F.col("_value"), "left").drop("_value")
    return joined.withColumn(out, F.coalesce(out, F.lit(0)))


def with_curve(df: DataFrame, cells: list[str], bits: int = BITS, name: str = "curve") -> DataFrame:
    @F.pandas_udf("long")
    def index(*parts: pd.Series) -> pd.Series:
        return pd.Series(hilbert_index(np.stack([p.to_numpy() for p in parts], axis=1), bits))

    return df.withColumn(name, index(*cells))


def shard_documents(docs: DataFrame, shards: int = 24, law: str = "rows") -> DataFrame:
    """doc_id, size, text_crc32, law, shard, slot, grown_shard, curve for every row of ``docs``.

    Size: UTF-8 bytes of the text plus 8; a null text has no bytes. Ties on the curve go by text checksum and
    doc_id, so equal texts of one source lie together. Null language or source is cell 0. An empty table gives
    an empty result; repeated rows each get a slot.
    """
    if law not in ("rows", "bytes"):
        raise ValueError(f"unknown law {law}")
    text = F.coalesce(F.col("text"), F.lit(""))
    size = F.octet_length(text).cast("long") + 8
    tagged = docs.select("doc_id", size.alias("size"), F.crc32(text.cast("binary")).alias("text_crc32"), "lang", "source", size_cell(size).alias("c2"))
    for at, name in enumerate(("lang", "source")):
        tagged = with_string_cell(tagged, name, f"c{at}").drop(name)
    keyed = stored(with_curve(tagged, ["c0", "c1", "c2"]).drop("c0", "c1", "c2"), "curve")
    ranked, n = with_rank(keyed, ["curve", "text_crc32", "doc_id"])
    rank = F.col("rank")
    if law == "rows":
        shard = F.floor(rank * F.lit(shards) / F.lit(max(n, 1))).cast("int")
        shard = F.expr(f"cast((rank * {shards}L) div {max(n, 1)}L as int)")
        first = F.expr(f"(cast(shard as long) * {n}L + {shards - 1}L) div {shards}L")
        out = ranked.withColumn("shard", shard).withColumn("slot", rank - first)
    else:
        out = _cut_by_bytes(ranked, shards)
    return out.select(
        "doc_id", "size", "text_crc32", F.lit(law).alias("law"), "shard", F.col("slot").cast("long").alias("slot"),
        F.lit(None).cast("int").alias("grown_shard"), "curve",
    )


def _cut_by_bytes(ranked: DataFrame, shards: int, run: int = 4096) -> DataFrame:
    """Shard by the middle of each row's bytes in the running total, taken over runs of rows and then within a run."""
    from pyspark.sql import Window

    runs = ranked.withColumn("run", F.expr(f"rank div {run}L"))
    sums = runs.groupBy("run").agg(F.sum("size").alias("bytes"))
    totals, total = with_rank_sum(sums)
    inside = Window.partitionBy("run").orderBy("rank")
    placed = runs.join(totals, "run").withColumn("_mid", F.col("_before") + F.sum("size").over(inside) - F.expr("size div 2"))
    placed = placed.withColumn("shard", F.expr(f"cast(least({shards - 1}L, (_mid * {shards}L) div {max(total, 1)}L) as int)"))
    first = placed.groupBy("shard").agg(F.min("rank").alias("_first"))
    return placed.join(F.broadcast(first), "shard").withColumn("slot", F.col("rank") - F.col("_first")).drop("_mid", "_before", "_first", "run", "bytes")


def with_rank_sum(sums: DataFrame) -> tuple[DataFrame, int]:
    """Bytes before each run: sorted over all tasks, totals of tasks added from the driver (a row a task)."""

    def running(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        at = 0
        for f in frames:
            total = f["bytes"].cumsum() + at
            yield f.assign(_in=total - f["bytes"])
            at = int(total.iloc[-1]) if len(f) else at

    parts = int(sums.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    ordered = sums.repartitionByRange(parts, "run").sortWithinPartitions("run")
    ordered = stored(ordered.mapInPandas(running, "run long, bytes long, _in long").withColumn("_p", F.spark_partition_id()), "runs")
    rows, before = [], 0
    for p, n in sorted((r["_p"], r["n"]) for r in ordered.groupBy("_p").agg(F.sum("bytes").alias("n")).collect()):
        rows.append((p, before))
        before += n
    offsets = inline_rows(ordered.sparkSession, rows, ["_p", "_at"])
    return ordered.join(F.broadcast(offsets), "_p").select("run", (F.col("_in") + F.col("_at")).alias("_before")), before


def write_shards(docs: DataFrame, assigned: DataFrame, path: str) -> None:
    """Write whole rows as one folder (hilbert_shard) a shard, each in slot order (``doc_id`` must be unique)."""
    at = assigned.select("doc_id", F.col("shard").alias("hilbert_shard"), F.col("slot").alias("hilbert_slot"))
    order = ["hilbert_shard", "hilbert_slot"]
    docs.join(at, "doc_id").repartitionByRange(*order).sortWithinPartitions(*order).write.partitionBy("hilbert_shard").parquet(path)
