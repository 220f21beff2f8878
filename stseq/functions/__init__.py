"""Column functions, UDFs and UDTFs of the engine, and their SQL registration."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import DoubleType, IntegerType, LongType, StringType, StructType

from stseq.microcluster.features import diameter_agg, diameter_cf, diameter_pairwise, representative
from stseq.sequences import next_index, parse_seq, seq_append, seq_hash, seq_last, seq_prefix, seq_text

__all__ = [
    "chain_prefixes", "diameter_agg", "diameter_cf", "diameter_of", "diameter_pairwise", "mc_diameter", "neighbour_cells", "next_index", "parse_seq",
    "register", "representative", "seq_append", "seq_hash", "seq_last", "seq_prefix", "seq_text",
]


@F.pandas_udf(DoubleType())
def diameter_of(points: pd.Series) -> pd.Series:
    """Diameter of an array of coordinate arrays, by the pairwise definition (checks the additive form)."""

    def one(p) -> float:
        x = np.array([list(r) for r in p], float)
        if len(x) < 2:
            return 0.0
        d2 = ((x[:, None, :] - x[None, :, :]) ** 2).sum()
        return float(np.sqrt(d2 / (len(x) * (len(x) - 1))))

    return points.map(one)


def mc_diameter(*coords: Column) -> Column:
    """The diameter as an aggregate over a group, from built-in functions."""
    return diameter_agg(*coords)


@F.udtf(returnType=StructType().add("cx", LongType()).add("cy", LongType()).add("ct", LongType()))
class neighbour_cells:  # noqa: N801
    """Cells that a source's neighbourhood touches (the native form explodes sequences)."""

    def eval(self, x: float, y: float, t: float, R: float, T: float) -> Iterator[tuple]:
        cx, cy, ct = int(x // R), int(y // R), int(t // T)
        for i in (-1, 0, 1):
            for j in (-1, 0, 1):
                for k in (0, 1):
                    yield cx + i, cy + j, ct + k


@F.udtf(returnType=StructType().add("length", IntegerType()).add("prefix", StringType()))
class chain_prefixes:  # noqa: N801
    """Prefixes of a chain 'A -> B -> C' from two types on."""

    def eval(self, chain: str) -> Iterator[tuple]:
        parts = [p.strip() for p in (chain or "").split("->") if p.strip()]
        for n in range(2, len(parts) + 1):
            yield n, " -> ".join(parts[:n])


def register(spark: SparkSession) -> None:
    spark.udtf.register("neighbour_cells", neighbour_cells)
    spark.udtf.register("chain_prefixes", chain_prefixes)
    spark.udf.register("diameter_of", diameter_of)
