"""The neighbourhood join: all (source, target) pairs where the target lies in the source's neighbourhood.

``pairs_grid`` is the engine's way: an equi-join on space-time cells of side R and T with the exact test as
residual condition. ``pairs_sweep`` slides a time window through spatial tiles, ``pairs_nested_loop`` tests all
pairs of blocks within reach, ``pair_weights_cells`` counts whole cells at once.
"""

from __future__ import annotations


import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from stseq.model import PAIR_SCHEMA, NeighbourhoodSpec, SpaceSpec, as_points
from stseq.neighbourhood import AXES, matches

_PAIR = ("src_id", "src_type", "src_w", "dst_id", "dst_type", "dst_w")


def _points(df: DataFrame, spec: NeighbourhoodSpec) -> DataFrame:
    return as_points(df).select("id", "type", *AXES[: spec.dims], "t", "w")


def _pair_columns() -> list[Column]:
    return [F.col(f"{side}.{c}").alias(f"{side}_{c}") for side in ("src", "dst") for c in ("id", "type", "w")]


def _packed(df: DataFrame, name: str) -> DataFrame:
    return df.select(F.struct("*").alias(name))


#: Width of a block of the nested loop, in radii.
BLOCK_RADII = 16


def pairs_nested_loop(events: DataFrame, spec: NeighbourhoodSpec, targets: DataFrame | None = None) -> DataFrame:
    """Block nested loop: all pairs of a block of sources and a block of targets are tested.

    With two time bounds a block is a slice of time and of one axis, and two blocks that no neighbourhood spans are left out; a time
    rule without a lower bound tests every pair.
    """
    points, others = _points(events, spec), _points(targets if targets is not None else events, spec)
    if not spec.bounded:
        return _packed(points, "src").crossJoin(_packed(others, "dst")).where(matches(spec)).select(*_pair_columns())
    axis, side = _cell_axes(spec)[0], BLOCK_RADII * spec.R
    begin = F.col("t") + F.lit(spec.delay)
    src = points.withColumn("ba", F.explode(F.sequence(_cell(F.col(axis) - spec.R, side), _cell(F.col(axis) + spec.R, side))))
    src = src.withColumn("bt", F.explode(F.sequence(_cell(begin, spec.T), _cell(begin + F.lit(spec.T), spec.T))))
    src = src.select("ba", "bt", F.struct(*points.columns).alias("src"))
    dst = others.select(_cell(F.col(axis), side).alias("ba"), _cell(F.col("t"), spec.T).alias("bt"), F.struct(*others.columns).alias("dst"))
    return src.join(dst.hint("merge"), ["ba", "bt"]).where(matches(spec)).select(*_pair_columns())


def _cell(value: Column, side: float) -> Column:
    return F.floor(value / F.lit(side)).cast("long")


def _cell_axes(spec: NeighbourhoodSpec) -> list[str]:
    # degrees of longitude shrink towards the poles, so only latitude is cut into cells there
    return ["y"] if spec.metric == "haversine" else list(AXES[: spec.dims])


def cell_columns(spec: NeighbourhoodSpec, prefix: str = "", cell_r: float | None = None) -> list[Column]:
    """Cell numbers of a point as a target."""
    side = cell_r or spec.R
    return [*(_cell(F.col(prefix + a), side).alias(f"c{a}") for a in _cell_axes(spec)), _cell(F.col(prefix + "t"), spec.T).alias("ct")]


def source_cells(df: DataFrame, spec: NeighbourhoodSpec, double: bool = False) -> DataFrame:
    """Source copies, one for each cell that may hold a target: 3 (with ``double`` cells of two radii: 2) to each spatial axis and 2 in time."""
    out = df
    for a in _cell_axes(spec):
        c = _cell(F.col(a), spec.R)
        low, high = (F.shiftright(c - 1, 1), F.shiftright(c + 1, 1)) if double else (c - 1, c + 1)
        out = out.withColumn(f"c{a}", F.explode(F.sequence(low, high)))
    c = _cell(F.col("t") + F.lit(spec.delay), spec.T)
    return out.withColumn("ct", F.explode(F.sequence(c, c + 1)))


#: Targets that are broadcast (their number is checked); more are joined by a shuffle of both sides.
BROADCAST_TARGETS = 200_000
#: Mean number of targets in an occupied cell below which cells of two radii cost less than copies of the sources.
SPARSE = 4.0


def _sparse(targets: DataFrame, spec: NeighbourhoodSpec) -> bool:
    """Whether occupied cells hold few targets on the average (one pass over them); no result depends on it."""
    cells = targets.select(F.xxhash64(*cell_columns(spec)).alias("cell"))
    rows, cells = cells.agg(F.count("*"), F.approx_count_distinct("cell")).first()
    return rows < SPARSE * cells


def pairs_grid(events: DataFrame, spec: NeighbourhoodSpec, targets: DataFrame | None = None, broadcast_targets: int = BROADCAST_TARGETS, about: Column | None = None) -> DataFrame:
    """Equi-join on cells, then the exact test. Needs a time rule with two bounds.

    The sources are the multiplied side, so they are never the broadcast one: few targets are sent to all tasks
    and the sources stay where they are, else both sides are dealt by cell (and hot cells split by AQE). The count stops
    above the bound; ``broadcast_targets=0`` skips it. Where both sides are dealt and targets lie far apart, cells have two
    radii, for fewer copies. ``about`` is a function of the source that its pairs carry as ``src_about``.
    """
    if not spec.bounded:
        raise ValueError(f"time rule {spec.time_rule} has no lower bound; use pairs_nested_loop")
    keys = [f"c{a}" for a in _cell_axes(spec)] + ["ct"]
    points = _points(events, spec)
    dst = _points(targets, spec) if targets is not None else points
    few = broadcast_targets > 0 and dst.select("id").limit(broadcast_targets + 1).count() <= broadcast_targets
    double = broadcast_targets > 0 and not few and _sparse(dst, spec)
    more = [] if about is None else [about.alias("src_about")]
    src = source_cells(points, spec, double).select(*keys, F.struct(*points.columns, *more).alias("src"))
    cells = [*(F.shiftright(F.col(k), 1).alias(k) if double and k != "ct" else k for k in keys), "dst"]
    dst = dst.select(*cell_columns(spec), F.struct(*dst.columns).alias("dst")).select(*cells)
    joined = src.join(F.broadcast(dst), keys) if few else src.join(dst.hint("merge"), keys)
    return joined.where(matches(spec)).select(*_pair_columns(), *(["src.src_about"] if more else []))


def torus_targets(points: DataFrame, spec: NeighbourhoodSpec, space: SpaceSpec) -> DataFrame:
    """The points and their copies beyond the borders of a space that wraps around, as far as neighbourhoods reach."""
    out = _points(points, spec)
    reach = [(a, low, high, spec.R, spec.R) for a, (low, high) in zip(AXES[: spec.dims], space.sides())]
    reach.append(("t", space.t0, space.t1, 0, spec.delay + spec.T))
    for a, low, high, before, after in reach:
        length = F.lit(high - low).cast(out.schema[a].dataType)
        copies = F.array(F.col(a) - length, F.col(a), F.col(a) + length)
        out = out.withColumn(a, F.explode(copies)).where((F.col(a) >= F.lit(low - before)) & (F.col(a) <= F.lit(high + after)))
    return out


def pairs_sweep(events: DataFrame, spec: NeighbourhoodSpec, tile: float | None = None, targets: DataFrame | None = None, slice_t: float | None = None) -> DataFrame:
    """Plane sweep: in each spatial tile and time slice, a window of length T slides over the targets sorted by time.

    Sources are copied into every tile and slice that their neighbourhood touches, so no pair crosses tasks.
    """
    if not spec.bounded or spec.metric == "haversine" or spec.shape == "cone":
        raise ValueError("the sweep takes cylinders and boxes in flat space, and a time rule with two bounds")
    side, length = tile or 8 * spec.R, slice_t or 16 * spec.T
    axes = AXES[: spec.dims]
    src = _points(events, spec)
    keys = []
    for a in axes:
        src = src.withColumn(f"c{a}", F.explode(F.sequence(_cell(F.col(a) - spec.R, side), _cell(F.col(a) + spec.R, side))))
        keys.append(f"c{a}")
    begin = F.col("t") + F.lit(spec.delay)
    src = src.withColumn("ct", F.explode(F.sequence(_cell(begin, length), _cell(begin + F.lit(spec.T), length))))
    keys.append("ct")
    dst = _points(targets if targets is not None else events, spec)
    dst = dst.select("*", *[_cell(F.col(a), side).alias(f"c{a}") for a in axes], _cell(F.col("t"), length).alias("ct"))
    both = src.withColumn("role", F.lit(0)).unionByName(dst.withColumn("role", F.lit(1)))

    def sweep(pdf: pd.DataFrame) -> pd.DataFrame:
        s, d = pdf[pdf["role"] == 0], pdf[pdf["role"] == 1].sort_values("t", kind="stable")
        if s.empty or d.empty:
            return pd.DataFrame(columns=list(_PAIR))
        when, t = d["t"].to_numpy(), s["t"].to_numpy()
        lo = np.searchsorted(when, t + spec.delay, "left" if spec.time_rule == "from_now" else "right")
        hi = np.searchsorted(when, t + spec.delay + spec.T, "right")
        n = np.maximum(hi - lo, 0)
        out = []
        at = 0
        while at < len(n):  # so many pairs at once that they stay within memory
            to = at + max(1, int(np.searchsorted(np.cumsum(n[at:]), 2_000_000)))
            i = np.repeat(np.arange(at, min(to, len(n))), n[at:to])
            j = np.arange(len(i)) - np.repeat(np.cumsum(n[at:to]) - n[at:to], n[at:to]) + lo[i]
            gaps = [np.abs(d[a].to_numpy()[j] - s[a].to_numpy()[i]) for a in axes]
            if spec.shape == "box":
                ok = np.all([g <= spec.R for g in gaps], axis=0)
            elif spec.metric == "abs":
                ok = sum(gaps) <= spec.R
            else:
                ok = sum(g * g for g in gaps) <= spec.R * spec.R
            if spec.self_pairs == "exclude":
                ok &= s["id"].to_numpy()[i] != d["id"].to_numpy()[j]
            i, j = i[ok], j[ok]
            out.append(pd.DataFrame({f"{p}_{c}": f[c].to_numpy()[k] for p, f, k in (("src", s, i), ("dst", d, j)) for c in ("id", "type", "w")}))
            at = to
        return pd.concat(out, ignore_index=True)[list(_PAIR)]

    return both.groupBy(*keys).applyInPandas(sweep, PAIR_SCHEMA)


def pairs_window(events: DataFrame, spec: NeighbourhoodSpec, tile: float | None = None) -> DataFrame:
    """The sweep with DataFrame functions alone: a range window over time in each tile collects the targets (integer time)."""
    if spec.time_rule != "after" or spec.metric == "haversine":
        raise ValueError("the window sweep takes the time rule 'after' in flat space")
    from pyspark.sql import Window

    side = tile or 4 * spec.R
    points = _points(events, spec)
    axes = AXES[: spec.dims]
    copies = points
    for a in axes:  # halo copies serve as targets of the tiles around
        copies = copies.withColumn(f"c{a}", F.explode(F.sequence(_cell(F.col(a) - spec.R, side), _cell(F.col(a) + spec.R, side))))
    home = F.lit(True)
    for a in axes:
        home = home & (F.col(f"c{a}") == _cell(F.col(a), side))
    order = Window.partitionBy(*[f"c{a}" for a in axes]).orderBy("t").rangeBetween(1 + int(spec.delay), int(spec.delay + spec.T))
    seen = copies.withColumn("later", F.collect_list(F.struct(*points.columns)).over(order)).where(home)
    flat = seen.select(F.struct(*points.columns).alias("src"), F.explode("later").alias("dst"))
    return flat.where(matches(spec)).select(*_pair_columns())


def pair_weights_cells(events: DataFrame, spec: NeighbourhoodSpec, subdivide: int = 2) -> DataFrame:
    """W of each link (src_type, dst_type, W) from cell counts: cells wholly inside count at once, border cells point by point."""
    if not spec.bounded or spec.shape == "cone" or spec.metric != "euclid":
        raise ValueError("cell counts take cylinders and boxes, Euclidean distance and two time bounds")
    side, step = spec.R / subdivide, spec.T / subdivide
    axes = AXES[: spec.dims]
    points = _points(events, spec)
    target = points.select("*", *[_cell(F.col(a), side).alias(f"c{a}") for a in axes], _cell(F.col("t"), step).alias("ct"))
    keys = [f"c{a}" for a in axes] + ["ct"]
    counts = target.groupBy(*keys, F.col("type").alias("dst_type")).agg(F.sum("w").alias("cell_w"))
    src = points
    for a in axes:
        src = src.withColumn(f"c{a}", F.explode(F.sequence(_cell(F.col(a) - spec.R, side), _cell(F.col(a) + spec.R, side))))
    begin = F.col("t") + F.lit(spec.delay)
    src = src.withColumn("ct", F.explode(F.sequence(_cell(begin, step), _cell(begin + F.lit(spec.T), step))))

    def far(a: str) -> Column:
        low = F.col(f"c{a}") * F.lit(side)
        return F.greatest(F.abs(F.col(a) - low), F.abs(F.col(a) - low - F.lit(side)))

    def near(a: str) -> Column:
        low = F.col(f"c{a}") * F.lit(side)
        return F.greatest(low - F.col(a), F.col(a) - low - F.lit(side), F.lit(0.0))

    if spec.shape == "box":
        inside, touches = F.lit(True), F.lit(True)
        for a in axes:
            inside, touches = inside & (far(a) <= spec.R), touches & (near(a) <= spec.R)
    else:
        inside = sum((far(a) * far(a) for a in axes), F.lit(0.0)) <= spec.R**2
        touches = sum((near(a) * near(a) for a in axes), F.lit(0.0)) <= spec.R**2
    low = F.col("ct") * F.lit(step)
    inside = inside & (low > begin) & (low + F.lit(step) <= begin + F.lit(spec.T))
    src = src.withColumn("_in", inside).where(touches)
    whole = src.where("_in").groupBy(*keys, "type").agg(F.sum("w").alias("src_w")).join(counts.hint("merge"), keys)
    whole = whole.groupBy(F.col("type").alias("src_type"), "dst_type").agg(F.sum(F.col("src_w") * F.col("cell_w")).alias("W"))
    border = src.where("not _in").select(*keys, F.struct(*points.columns).alias("src")).join(target.select(*keys, F.struct(*points.columns).alias("dst")).hint("merge"), keys)
    border = border.where(matches(spec)).groupBy(F.col("src.type").alias("src_type"), F.col("dst.type").alias("dst_type")).agg(F.sum(F.col("src.w") * F.col("dst.w")).alias("W"))
    return whole.unionByName(border).groupBy("src_type", "dst_type").agg(F.sum("W").alias("W"))


def neighbours_of(tail: DataFrame, pairs: DataFrame) -> DataFrame:
    """Pairs whose source is in ``tail`` (column id)."""
    return pairs.join(tail.select(F.col("id").alias("src_id")).distinct(), "src_id", "left_semi")


def neighbour_lists(pairs: DataFrame) -> DataFrame:
    """One row a source with its neighbours' ids; for display of small data."""
    return pairs.groupBy("src_id", "src_type").agg(F.array_sort(F.collect_set("dst_id")).alias("neighbours"))


def covered_instances(pairs: DataFrame, members: DataFrame) -> DataFrame:
    """Instances contained in the clusters of each source cluster's neighbourhood: src_id, id."""
    return pairs.select("src_id", F.col("dst_id").alias("cid")).join(members, "cid").select("src_id", "id").distinct()


def count_candidates(events: DataFrame, spec: NeighbourhoodSpec) -> DataFrame:
    """Join work: candidate pairs that share a cell of one radius and pairs that pass (one row)."""
    keys = [f"c{a}" for a in _cell_axes(spec)] + ["ct"]
    points = _points(events, spec)
    s = source_cells(points, spec).groupBy(*keys).agg(F.count("*").alias("s"))
    d = points.select(*cell_columns(spec)).groupBy(*keys).agg(F.count("*").alias("d"))
    tested = s.join(d, keys).agg(F.coalesce(F.sum(F.col("s") * F.col("d")), F.lit(0)).alias("candidates"))
    kept = pairs_grid(events, spec).agg(F.count("*").alias("pairs"))
    return tested.crossJoin(kept)  # one row each


