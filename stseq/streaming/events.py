"""Event streams: new neighbour pairs, rolling densities and microclusters kept as state.

Streams carry a timestamp ``ts`` beside the event columns (t in microseconds of ts).
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle

from stseq.microcluster.kernel import DIGITS, SLACK
from stseq.model import NeighbourhoodSpec
from stseq.neighbourhood import matches
from stseq.neighbours import _cell_axes, cell_columns, source_cells

STREAM_SCHEMA = "id bigint, type string, x bigint, y bigint, t bigint, ts timestamp"
CLUSTER_SCHEMA = "type string, tile bigint, cid bigint, n bigint, x double, y double, t double, ss double"


def read_stream(spark: SparkSession, path: str, schema: str = STREAM_SCHEMA, files: int = 2) -> DataFrame:
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files).parquet(path)


def stream_pairs(events: DataFrame, spec: NeighbourhoodSpec, late: str = "1 day") -> DataFrame:
    """Neighbour pairs as their targets arrive: a stream-stream join on cells with time bounds, so that state is dropped behind the watermark."""
    if spec.time_rule != "after" or spec.delay:
        raise ValueError("the stream join takes the time rule 'after' without delay")
    points = events.withColumn("w", F.lit(1).cast("long")).withWatermark("ts", late)
    names = ["id", "type", "x", "y", "t", "w"]
    keys = [f"c{a}" for a in _cell_axes(spec)] + ["ct"]
    src = source_cells(points, spec).select(*keys, F.struct(*names).alias("src"), F.col("ts").alias("src_ts"))
    dst = points.select(*cell_columns(spec), F.struct(*names).alias("dst"), F.col("ts").alias("dst_ts"))
    dst = dst.select(*[F.col(k).alias(f"_{k}") for k in keys], "dst", "dst_ts")
    same = F.lit(True)
    for k in keys:
        same = same & (F.col(k) == F.col(f"_{k}"))
    bounds = F.expr(f"dst_ts > src_ts AND dst_ts <= src_ts + make_dt_interval(0, 0, 0, {spec.T / 1e6:.6f})")
    joined = src.join(dst, same & bounds)
    return joined.where(matches(spec)).select(*[F.col(f"{s}.{c}").alias(f"{s}_{c}") for s in ("src", "dst") for c in ("id", "type", "w")], "dst_ts")


def stream_density(events: DataFrame, window: str = "1 day", slide: str | None = None, late: str = "1 day") -> DataFrame:
    """Events of each type in tumbling (or sliding) windows; rows behind the watermark are dropped, repeated ids count once."""
    once = events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["id"])
    span = F.window("ts", window, slide) if slide else F.window("ts", window)
    return once.groupBy(span.alias("w"), "type").agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "type", "n")


def session_counts(events: DataFrame, gap: str = "6 hours", late: str = "1 day") -> DataFrame:
    """Sessions of one user (x) and type: runs of events without a gap."""
    return events.withWatermark("ts", late).groupBy(F.session_window("ts", gap).alias("w"), "x", "type").agg(F.count("*").alias("n")).select(
        F.col("w.start").alias("start"), F.col("w.end").alias("end"), "x", "type", "n"
    )


class ClusterState(StatefulProcessor):
    """Microclusters of one (type, tile) as additive features; an event joins the nearest one while the diameter holds.

    The nearest is found over arrays of centres. A key's state ends when the watermark passes the end of its tile.
    """

    def __init__(self, d: float, time_unit: float, length: float, origin: int):
        self.d, self.unit, self.length, self.origin = d, time_unit, length, origin

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.handle = handle
        self.clusters = handle.getMapState("clusters", "cid bigint", "n bigint, x double, y double, t double, ss double")

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timerValues) -> Iterator[pd.DataFrame]:
        new = pd.concat(list(rows), ignore_index=True).sort_values(["t", "id"], kind="stable")
        known = [(k[0], tuple(v)) for k, v in self.clusters.iterator()]
        known.sort(key=lambda kv: kv[0])
        cid = [k for k, _ in known]
        size = max(16, 2 * (len(known) + len(new)))
        have = np.zeros((size, 5))  # n, x, y, t, ss
        if known:
            have[: len(known)] = [v for _, v in known]
        touched = set()
        scale = np.array([1.0, 1.0, self.unit]) * self.d
        for i, x in zip(new["id"].to_numpy(), new[["x", "y", "t"]].to_numpy(float)):
            m = len(cid)
            if m:
                gap = np.round((((have[:m, 1:4] - x) / scale) ** 2).sum(axis=1), DIGITS)
                at = int(np.argmin(gap))
                n, ss = have[at, 0], have[at, 4]
                grown = ss + gap[at] * n / (n + 1)
                if (2 * grown / n) ** 0.5 <= 1 + SLACK:
                    have[at, 1:4] += (x - have[at, 1:4]) / (n + 1)
                    have[at, 0], have[at, 4] = n + 1, grown
                    touched.add(at)
                    continue
            cid.append(int(i))
            have[m] = [1, *x, 0]
            touched.add(m)
        for at in touched:
            n, x, y, t, ss = have[at]
            self.clusters.updateValue((cid[at],), (int(n), float(x), float(y), float(t), float(ss)))
        tile_end = (np.floor(float(new["t"].iloc[-1]) / self.length) + 1) * self.length
        self.handle.registerTimer(int((self.origin + tile_end) // 1000))
        rows_at = sorted(touched)
        out = {"type": key[0], "tile": key[1], "cid": [cid[a] for a in rows_at], "n": have[rows_at, 0].astype(np.int64)}
        yield pd.DataFrame(out | {c: have[rows_at, k] for k, c in ((1, "x"), (2, "y"), (3, "t"), (4, "ss"))})

    def handleExpiredTimer(self, key, timerValues, expiredTimerInfo) -> Iterator[pd.DataFrame]:
        self.clusters.clear()
        return iter(())

    def close(self) -> None:
        pass


#: Microseconds of 2024-01-01, where a stream's t begins.
ORIGIN_MICROS = 1_704_067_200_000_000


def stream_clusters(events: DataFrame, d: float, tile: float, time_unit: float = 1.0, tile_t: float | None = None, late: str = "1 day") -> DataFrame:
    """Updated clusters of each batch (ss in units of d squared); needs the RocksDB state store (``use_rocksdb``).

    Events behind the watermark are dropped, and a tile's state with it, so state is that of the open tiles.
    """
    length = (tile_t or tile) * time_unit
    cells = F.xxhash64(F.floor(F.col("x") / tile), F.floor(F.col("y") / tile), F.floor(F.col("t") / length))
    keyed = events.withWatermark("ts", late).select("id", "type", "x", "y", "t", "ts", cells.alias("tile"))
    return keyed.groupBy("type", "tile").transformWithStateInPandas(
        statefulProcessor=ClusterState(d, time_unit, length, ORIGIN_MICROS), outputStructType=CLUSTER_SCHEMA, outputMode="Update", timeMode="EventTime"
    )


def use_rocksdb(spark: SparkSession) -> None:
    spark.conf.set("spark.sql.streaming.stateStore.providerClass", "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")


def replay(events: DataFrame, path: str, files: int = 8, parts: int = 2) -> None:
    """Write an event table (t in microseconds since 2024-01-01) as successive time slices of ``parts`` files each, for a file stream.

    A file stream reads by modification time, so the slices are written one after another; a trigger takes a slice.
    """
    stamped = events.withColumn("ts", F.timestamp_micros(F.col("t") + F.lit(ORIGIN_MICROS)))
    cuts = stamped.agg(F.percentile_approx("t", [i / files for i in range(1, files)], 10_000)).first()[0] if files > 1 else []
    edges = [None, *sorted(set(cuts or [])), None]
    for low, high in zip(edges, edges[1:]):
        part = stamped
        if low is not None:
            part = part.where(F.col("t") > low)
        if high is not None:
            part = part.where(F.col("t") <= high)
        part.repartition(parts).write.mode("append").parquet(path)


def far_row(late: str) -> str:
    """SQL of one event far behind a stream's end: its arrival moves the watermark past all others, so that open windows close."""
    return f"SELECT -1L AS id, 'end' AS type, -1L AS x, -1L AS y, 0L AS t, timestamp_micros({ORIGIN_MICROS}L) + INTERVAL 1000 DAYS + INTERVAL {late} AS ts"


def run_to_table(stream: DataFrame, folder: str, mode: str = "append", flush: str | None = None) -> DataFrame:
    """Run a stream over what there is and return its rows (in ``update`` mode every update) from Parquet files under ``folder``.

    ``flush``: SQL of a last event (see :func:`far_row`) that is put into ``folder``/in behind the others.
    """
    out = f"{folder}/out"
    if flush:
        stream.sparkSession.sql(flush).write.mode("append").parquet(f"{folder}/in")

    def keep(batch: DataFrame, number: int) -> None:
        batch.write.mode("append").parquet(out)

    q = stream.writeStream.outputMode(mode).option("checkpointLocation", f"{folder}/checkpoint").trigger(availableNow=True).foreachBatch(keep).start()
    q.awaitTermination()
    return stream.sparkSession.read.schema(stream.schema).parquet(out)
