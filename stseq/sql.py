"""SQL surface: views of events and links, and the registered functions."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from stseq.functions import register as register_functions
from stseq.model import NeighbourhoodSpec, as_points

#: The hint: by estimate the multiplied side is as small as the scan, and would be broadcast.
CELL_JOIN = """
WITH src AS (
  SELECT id, type, x, y, t, w, cx, cy, ct FROM events_st
  LATERAL VIEW explode(sequence(floor(x / {R}) - 1, floor(x / {R}) + 1)) AS cx
  LATERAL VIEW explode(sequence(floor(y / {R}) - 1, floor(y / {R}) + 1)) AS cy
  LATERAL VIEW explode(sequence(floor(t / {T}), floor(t / {T}) + 1)) AS ct
), dst AS (
  SELECT id, type, x, y, t, w, floor(x / {R}) AS cx, floor(y / {R}) AS cy, floor(t / {T}) AS ct FROM events_st
)
SELECT /*+ MERGE(b) */ a.type AS src_type, b.type AS dst_type, sum(a.w * b.w) AS W
FROM src a JOIN dst b ON a.cx = b.cx AND a.cy = b.cy AND a.ct = b.ct
WHERE b.t > a.t AND b.t <= a.t + {T} AND (b.x - a.x) * (b.x - a.x) + (b.y - a.y) * (b.y - a.y) <= {R} * {R} AND a.id <> b.id
GROUP BY a.type, b.type
"""


def register(spark: SparkSession, events: DataFrame | None = None) -> None:
    register_functions(spark)
    if events is not None:
        as_points(events).createOrReplaceTempView("events_st")


def link_weights_sql(spark: SparkSession, spec: NeighbourhoodSpec) -> DataFrame:
    """Link weights of the registered events as one SQL text (cylinder, rule 'after'); the same plan as the DataFrame form."""
    return spark.sql(CELL_JOIN.format(R=spec.R, T=spec.T))
