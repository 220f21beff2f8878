"""Planted patterns: the published generator, deterministic by hashing, and a form over a table's own events."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def hashed(text: Column) -> Column:
    """First 32 bits of the MD5 of a text as a number; SQL engines give the same."""
    return F.conv(F.substring(F.md5(text.cast("binary")), 1, 8), 16, 10).cast("bigint")


def _unit(*parts) -> Column:
    """Uniform in [0, 1) from the md5 of the joined parts."""
    return hashed(F.concat_ws("|", *[p if isinstance(p, Column) else F.lit(str(p)) for p in parts])) / F.lit(float(1 << 32))


def planted_events(
    spark: SparkSession, Ps: int = 5, Pn: int = 10, DSize: float = 1000, TSize: float = 1200, Nf: int = 20, Ni: int = 100, R: float = 10, T: float = 10,
    seed: int = 0, noise: float = 1.0, types_with_replacement: bool = True,
) -> DataFrame:
    """2*Ni*Ps*Pn events: id, type, x, y, t (double), pattern, step (null for noise).

    Each pattern draws its types; the first type's instances are uniform, each later one lies in the neighbourhood space of a
    drawn instance of the previous type (space reflects at the border, time is drawn up to the end). Noise is uniform.
    """
    patterns = F.floor(F.col("i") / F.lit(Ni))
    base = spark.range(Pn * Ni).withColumnRenamed("id", "i").select(patterns.alias("pattern"), (F.col("i") % Ni).alias("i"))
    if types_with_replacement:
        kind = lambda k: F.floor(_unit(seed, "type", F.col("pattern"), k) * Nf)
    else:  # the k-th type of a drawn order of all types
        def kind(k):
            order = F.array_sort(F.transform(F.sequence(F.lit(0), F.lit(Nf - 1)), lambda f: F.struct(hashed(F.concat_ws("|", F.lit(seed), F.lit("deck"), F.col("pattern").cast("string"), f.cast("string"))).alias("h"), f.alias("f"))))
            return F.element_at(order, k + 1)["f"]

    def inside(v: Column, size: float) -> Column:
        return F.when(v < 0, -v).when(v > size, 2 * size - v).otherwise(v)

    level = base.select(
        "pattern", "i", (_unit(seed, "x", F.col("pattern"), F.col("i")) * DSize).alias("x"), (_unit(seed, "y", F.col("pattern"), F.col("i")) * DSize).alias("y"),
        (_unit(seed, "t", F.col("pattern"), F.col("i")) * TSize).alias("t"),
    )
    levels = [level.select("*", F.lit(0).alias("step"), kind(0).alias("f"))]
    for k in range(1, Ps):
        key = (F.col("pattern"), F.col("i"), k)
        child = base.select("pattern", "i", F.floor(_unit(seed, "pa", *key) * Ni).cast("bigint").alias("parent"))
        up = level.select("pattern", F.col("i").alias("parent"), F.col("x").alias("px"), F.col("y").alias("py"), F.col("t").alias("pt"))
        rho, phi = F.sqrt(_unit(seed, "r", *key)) * R, _unit(seed, "phi", *key) * 6.283185307179586
        level = child.join(up, ["pattern", "parent"]).select(
            "pattern", "i", inside(F.col("px") + rho * F.cos(phi), DSize).alias("x"), inside(F.col("py") + rho * F.sin(phi), DSize).alias("y"),
            (F.col("pt") + (1 - _unit(seed, "dt", *key)) * F.least(F.lit(float(T)), F.lit(float(TSize)) - F.col("pt"))).alias("t"),
        )
        levels.append(level.select("*", F.lit(k).alias("step"), kind(k).alias("f")))
    rows = reduce(DataFrame.unionByName, levels).select(
        (F.col("step") * (Pn * Ni) + F.col("pattern") * Ni + F.col("i")).cast("bigint").alias("id"), F.format_string("f%02d", F.col("f").cast("int")).alias("type"), "x", "y", "t",
        F.col("pattern").cast("int").alias("pattern"), F.col("step").cast("int").alias("step"),
    )
    n = int(round(noise * Ni * Ps * Pn))
    extra = spark.range(n).select(
        (F.col("id") + F.lit(Ni * Ps * Pn)).alias("id"), F.format_string("f%02d", F.floor(_unit(seed, "nf", F.col("id")) * Nf).cast("int")).alias("type"),
        (_unit(seed, "nx", F.col("id")) * DSize).alias("x"), (_unit(seed, "ny", F.col("id")) * DSize).alias("y"), (_unit(seed, "nt", F.col("id")) * TSize).alias("t"),
        F.lit(None).cast("int").alias("pattern"), F.lit(None).cast("int").alias("step"),
    )
    return rows.unionByName(extra)


def planted_on_rows(rows: DataFrame, n: int, Ps: int = 5, Pn: int = 10, DSize: float = 1000, TSize: float = 1200, Nf: int = 20, R: float = 10, T: float = 10, seed: int = 0) -> DataFrame:
    """The generator on a table: ``rows`` (row, t; row gapless from 0, ``n`` in all) are the instances, dealt to the patterns in turn.

    An instance begins at its row's time, at a hashed place, and is followed as in :func:`planted_events`; each row also gives Ps
    events of noise. 2*n*Ps events: id, type, x, y, t (double), pattern, step (null for noise).
    """
    base = rows.select((F.col("row") % Pn).alias("pattern"), F.expr(f"row div {Pn}").alias("i"), "row", F.col("t").cast("double").alias("t"))
    place = (F.col("pattern"), F.col("i"))
    level = base.select("pattern", "i", "row", (_unit(seed, "x", *place) * DSize).alias("x"), (_unit(seed, "y", *place) * DSize).alias("y"), "t")
    kind = lambda k: F.floor(_unit(seed, "type", F.col("pattern"), k) * Nf)

    def inside(v: Column, size: float) -> Column:
        return F.when(v < 0, -v).when(v > size, 2 * size - v).otherwise(v)

    levels = [level.select("*", F.lit(0).alias("step"), kind(0).alias("f"))]
    for k in range(1, Ps):
        key = (F.col("pattern"), F.col("i"), k)
        many = F.expr(f"({n} - pattern + {Pn - 1}) div {Pn}")  # instances of the pattern
        child = base.select("pattern", "i", "row", F.floor(_unit(seed, "pa", *key) * many).cast("bigint").alias("parent"))
        up = level.select("pattern", F.col("i").alias("parent"), F.col("x").alias("px"), F.col("y").alias("py"), F.col("t").alias("pt"))
        rho, phi = F.sqrt(_unit(seed, "r", *key)) * R, _unit(seed, "phi", *key) * 6.283185307179586
        level = child.join(up.hint("merge"), ["pattern", "parent"]).select(
            "pattern", "i", "row", inside(F.col("px") + rho * F.cos(phi), DSize).alias("x"), inside(F.col("py") + rho * F.sin(phi), DSize).alias("y"),
            (F.col("pt") + (1 - _unit(seed, "dt", *key)) * F.least(F.lit(float(T)), F.lit(float(TSize)) - F.col("pt"))).alias("t"),
        )
        levels.append(level.select("*", F.lit(k).alias("step"), kind(k).alias("f")))
    planted = reduce(DataFrame.unionByName, levels).select(
        (F.col("step") * n + F.col("row")).cast("bigint").alias("id"), F.format_string("f%02d", F.col("f").cast("int")).alias("type"), "x", "y", "t",
        F.col("pattern").cast("int").alias("pattern"), F.col("step").cast("int").alias("step"),
    )
    at = rows.select("row", F.explode(F.sequence(F.lit(0), F.lit(Ps - 1))).alias("k")).select((F.col("row") + F.col("k") * n).cast("bigint").alias("i"))
    noise = at.select(
        (F.col("i") + F.lit(n * Ps)).alias("id"), F.format_string("f%02d", F.floor(_unit(seed, "nf", F.col("i")) * Nf).cast("int")).alias("type"),
        (_unit(seed, "nx", F.col("i")) * DSize).alias("x"), (_unit(seed, "ny", F.col("i")) * DSize).alias("y"), (_unit(seed, "nt", F.col("i")) * TSize).alias("t"),
        F.lit(None).cast("int").alias("pattern"), F.lit(None).cast("int").alias("step"),
    )
    return planted.unionByName(noise)


def planted_chains(events: DataFrame) -> DataFrame:
    """The chain of types of each pattern."""
    steps = events.where("pattern is not null").select("pattern", "step", "type").distinct()
    return steps.groupBy("pattern").agg(F.transform(F.array_sort(F.collect_list(F.struct("step", "type"))), lambda s: s["type"]).alias("seq"))


PLANT_ID = 1_000_000_000


def planted_from_events(events: DataFrame, modulus: int = 50, length: int = 4, chains: int = 1, cell: int = 1, span: int = 7, lag_unit: int = 1_000_000, lags: int = 86_400) -> DataFrame:
    """A table's events and ``chains`` planted chains of ``length`` types; ids of events are gapless from 0.

    Roots are the events whose id is a multiple of ``modulus``. Each row of a later step takes a hashed row of the step before, and
    lies up to ``span`` cells off in both axes and up to ``lags`` time units later.
    """
    roots = events.where(F.col("id") % modulus == 0).select(F.expr(f"id div {modulus}").alias("i"), "x", "y", "t")
    return with_planted(events, roots, length, chains, cell, span, lag_unit, lags)


def with_planted(events: DataFrame, roots: DataFrame, length: int = 4, chains: int = 1, cell: float = 1, span: int = 7, lag_unit: int = 1_000_000, lags: int = 86_400) -> DataFrame:
    """Events and the chains planted on ``roots`` (i, x, y, t; i gapless from 0)."""
    out = events.select("id", "type", "x", "y", "t")
    n = roots.count()
    if not n:
        return out
    for c in range(chains):
        name, mark = ("P", "") if c == 0 else (f"Q{c}_", f"c{c}:")
        level = roots
        for j in range(1, length + 1):
            if j > 1:
                key = lambda what: hashed(F.concat(F.lit(f"{mark}{what}{j}|"), F.col("i").cast("string")))  # noqa: B023, E731
                up = level.select(F.col("i").alias("p"), F.col("x").alias("px"), F.col("y").alias("py"), F.col("t").alias("pt"))
                level = roots.select("i", (key("pa") % n).alias("p")).join(up, "p").select(
                    "i", (F.col("px") + (key("dx") % (2 * span + 1) - span) * F.lit(cell)).alias("x"), (F.col("py") + (key("dy") % (2 * span + 1) - span) * F.lit(cell)).alias("y"),
                    (F.col("pt") + 1 + (key("dt") % lags) * F.lit(lag_unit)).alias("t"),
                )
            out = out.unionByName(level.select((F.lit(PLANT_ID * (1 + j + 100 * c)) + F.col("i")).alias("id"), F.lit(f"{name}{j}").alias("type"), "x", "y", "t"))
    return out
