"""Chains of event types and their index."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from stseq.density import ratio_matrix, tail_ratios, type_counts
from stseq.model import NeighbourhoodSpec, SpaceSpec, as_points
from stseq.neighbours import pairs_grid
from stseq.ranks import with_rank
from stseq.storage import stored

ARROW = " -> "


def seq_append(seq: Column, f: Column) -> Column:
    return F.concat(seq, F.array(f))


def seq_prefix(seq: Column) -> Column:
    return F.slice(seq, F.lit(1), F.size(seq) - 1)


def seq_last(seq: Column) -> Column:
    return F.element_at(seq, -1)


def seq_text(seq: Column) -> Column:
    return F.array_join(seq, ARROW)


def parse_seq(text: Column) -> Column:
    """'A -> B' to its array."""
    return F.transform(F.split(text, "->"), lambda p: F.trim(p))


def seq_hash(seq: Column) -> Column:
    """Identity of a chain, the same in every run and partitioning."""
    return F.xxhash64(F.array_join(seq, "\x1f"))


def next_index(previous: Column, ratio: Column) -> Column:
    """Minimum of the prefix's index (null for a single type: nothing yet) and the last link's ratio."""
    return F.least(F.coalesce(previous, ratio), ratio)


def significant(patterns: DataFrame, theta: float) -> DataFrame:
    return patterns.where(F.col("seq_index") >= theta)


def tail_set(points: DataFrame, chain: list[str], spec: NeighbourhoodSpec, pairs: DataFrame | None = None) -> DataFrame:
    """Points of the last type that continue some occurrence of the chain: id, w."""
    points = as_points(points)
    tail = points.where(F.col("type") == chain[0]).select("id", "w")
    for before, f in zip(chain, chain[1:]):
        if pairs is None:
            src = points.where(F.col("type") == before).join(tail.select("id"), "id", "left_semi")
            step = pairs_grid(src, spec, points.where(F.col("type") == f))
        else:
            step = pairs.where(F.col("dst_type") == f).join(tail.select(F.col("id").alias("src_id")), "src_id", "left_semi")
        tail = step.select(F.col("dst_id").alias("id"), F.col("dst_w").alias("w")).distinct()
    return tail


def sequence_index(points: DataFrame, chain: list[str], spec: NeighbourhoodSpec, space: SpaceSpec, scope: str = "tail", pairs: DataFrame | None = None) -> DataFrame:
    """Ratio of each link of one given chain and the index up to it: position, src_type, dst_type, ratio, seq_index."""
    points = as_points(points)
    pairs = pairs if pairs is not None else pairs_grid(points, spec)
    counts = type_counts(points)
    links = None
    if scope == "type":
        matrix = ratio_matrix(points, spec, space, pairs)
    for k, (before, f) in enumerate(zip(chain, chain[1:])):
        if scope == "type":
            one = matrix.where((F.col("src_type") == before) & (F.col("dst_type") == f)).select("ratio")
        else:
            tail = tail_set(points, chain[: k + 1], spec, pairs).select(F.lit(k).cast("long").alias("seq_id"), "id", "w")
            one = tail_ratios(tail, pairs, counts, spec, space).where(F.col("dst_type") == f).select("ratio")
        one = one.select(F.lit(k + 1).alias("position"), F.lit(before).alias("src_type"), F.lit(f).alias("dst_type"), "ratio")
        links = one if links is None else links.unionByName(one)
    so_far = links.select(F.col("position").alias("upto"), F.col("ratio").alias("r"))
    low = links.join(so_far, F.col("upto") <= F.col("position")).groupBy("position").agg(F.min("r").alias("seq_index"))  # a row a link
    return links.join(low, "position").select("position", "src_type", "dst_type", "ratio", "seq_index")


def contains_chain(outer: Column, inner: Column) -> Column:
    """``inner`` stands in ``outer`` as a contiguous part."""
    return F.concat(F.lit("\x1f"), F.array_join(outer, "\x1f"), F.lit("\x1f")).contains(F.concat(F.lit("\x1f"), F.array_join(inner, "\x1f"), F.lit("\x1f")))


def maximal(patterns: DataFrame) -> DataFrame:
    """Patterns that are no contiguous part of a longer pattern: every pattern's parts are exploded, then anti-joined."""
    n = F.size("seq")
    starts = F.sequence(F.lit(1), n)
    parts = (
        patterns.select("seq", F.explode(starts).alias("i")).select("seq", "i", F.explode(F.sequence(F.lit(1), n - F.col("i") + 1)).alias("l"))
        .where(F.col("l") < n).select(F.slice("seq", F.col("i"), F.col("l")).alias("part")).distinct()
    )
    return patterns.join(parts, F.col("seq") == F.col("part"), "left_anti")


def top_k_patterns(patterns: DataFrame, k: int, min_length: int = 2) -> DataFrame:
    """The k strongest chains; ties go to the shorter, then the lexically first."""
    return patterns.where(F.size("seq") >= min_length).orderBy(F.desc("seq_index"), F.size("seq"), seq_text(F.col("seq"))).limit(k)


def simulate_threshold(points: DataFrame, spec: NeighbourhoodSpec, space: SpaceSpec, runs: int = 20, q: float = 0.95, seed: int = 0, what: str = "max") -> DataFrame:
    """Ratios that chance gives: type labels are shuffled over the points ``runs`` times; per run the largest ratio, and their quantile.

    The neighbour pairs do not depend on labels and are taken once. Labels go by rank of a hash, so a run is
    the same in any partitioning; the ranks come from one sort over all tasks: run, max_ratio, threshold.
    """
    points = as_points(points)
    pairs = stored(pairs_grid(points, spec).select("src_id", "dst_id", "src_w", "dst_w"), "pairs")
    slots, n = with_rank(points.select("id", "w"), ["id"], "slot")
    codes, _ = with_rank(points.select("type").distinct(), ["type"], "code")
    each = points.select("id", "type").join(F.broadcast(points.sparkSession.range(runs).select(F.col("id").alias("run"))))  # runs rows
    cards, _ = with_rank(each.select("run", "type", "id", F.unhex(F.md5(F.concat_ws("|", F.lit(str(seed)), F.col("run").cast("string"), F.col("id").cast("string")).cast("binary"))).alias("_h")), ["run", "_h", "id"], "card")
    cards = cards.join(codes, "type", "left").select("run", (F.col("card") - F.col("run") * F.lit(n)).alias("slot"), F.col("code").cast("int").alias("code"))
    # a row a point, with its labels of all runs: a pair meets its two rows once, not once a run; no side is small, whatever its estimate
    hand = cards.groupBy("slot").agg(F.transform(F.array_sort(F.collect_list(F.struct("run", "code"))), lambda c: c["code"]).alias("labels"))
    label = stored(slots.hint("merge").join(hand, "slot").select("id", "w", "labels"), "labels")
    src = label.select(F.col("id").alias("src_id"), F.col("labels").alias("src_labels")).hint("merge")
    dst = label.select(F.col("id").alias("dst_id"), F.col("labels").alias("dst_labels")).hint("merge")
    both = pairs.join(src, "src_id").join(dst, "dst_id").select((F.col("src_w") * F.col("dst_w")).alias("w"), F.posexplode(F.arrays_zip("src_labels", "dst_labels")).alias("run", "link"))
    W = both.groupBy("run", F.col("link.src_labels").alias("src_type"), F.col("link.dst_labels").alias("dst_type")).agg(F.sum("w").alias("W"))
    N = label.select("w", F.posexplode("labels").alias("run", "type")).groupBy("run", "type").agg(F.sum("w").alias("N"))
    out = W.join(N.select("run", F.col("type").alias("src_type"), F.col("N").alias("src_n")), ["run", "src_type"]).join(
        N.select("run", F.col("type").alias("dst_type"), F.col("N").alias("dst_n")), ["run", "dst_type"]
    )
    ratio = F.col("W") * F.lit(space.volume / spec.volume) / (F.col("src_n").cast("double") * F.col("dst_n"))
    best = out.groupBy("run").agg(F.max(ratio).alias("max_ratio"))
    return best.crossJoin(best.agg(F.percentile("max_ratio", q).alias("threshold")))  # a row a run
