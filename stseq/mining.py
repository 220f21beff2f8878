"""Search for all significant chains, over events or over microclusters; all chains of one length at a time.

State between levels: a table of chains (seq_id, seq, index, last type) and one of tails (seq_id, id, w). A level joins
tails with the stored pairs, scores (chain, next type) by one aggregation, keeps what reaches the threshold
and forms the next tails as distinct targets. The driver sees one count a level.
"""

from __future__ import annotations

from dataclasses import dataclass, field, replace
from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from stseq.density import ratio_matrix, ratio_of, type_counts
from stseq.model import ClusterSpec, MineOptions, NeighbourhoodSpec, SpaceSpec, as_points, clusters_as_points
from stseq.neighbours import pairs_grid, pairs_nested_loop, pairs_sweep
from stseq.sequences import next_index, seq_append, seq_hash, seq_last, seq_text
from stseq.storage import broadcast_if_small, stored, stored_buckets

#: Rows of a counted table that may be broadcast.
SMALL = 100_000
PATTERN_SCHEMA = "seq array<string>, length int, seq_index double, last_ratio double, tail_weight bigint"


@dataclass
class MiningResult:
    patterns: DataFrame
    pairs: DataFrame
    levels: list[dict] = field(default_factory=list)
    #: Why the search ended: "complete" (no chain survives), "max_length" (longer ones may exist) or "limit_patterns".
    ended: str = "complete"

    @property
    def truncated(self) -> bool:
        return self.ended == "limit_patterns"


def neighbour_pairs(points: DataFrame, spec: NeighbourhoodSpec, how: str = "grid") -> DataFrame:
    return {"grid": pairs_grid, "sweep": pairs_sweep, "nested": pairs_nested_loop}[how](points, spec)


def seed(points: DataFrame) -> tuple[DataFrame, DataFrame]:
    """1-chains and their tails: every type with all its points."""
    points = as_points(points)
    chains = points.select("type").distinct().select(F.array("type").alias("seq")).select(
        seq_hash(F.col("seq")).alias("seq_id"), "seq", F.lit(None).cast("double").alias("seq_index")
    )
    tails = points.select(seq_hash(F.array("type")).alias("seq_id"), "id", "w")
    return chains, tails


def expand_level(chains: DataFrame, tails: DataFrame, pairs: DataFrame, counts: DataFrame, spec: NeighbourhoodSpec, space: SpaceSpec, opts: MineOptions, links: DataFrame | None = None) -> tuple[DataFrame, DataFrame]:
    """Chains one type longer that reach the threshold (with last_ratio and their parent), and the touched pairs (parent, dst)."""
    size = tails.groupBy("seq_id").agg(F.sum("w").alias("S"))
    touched = tails.join(pairs.select("src_id", "dst_id", "dst_type", "dst_w"), F.col("id") == F.col("src_id")).select("seq_id", "w", "dst_id", "dst_type", "dst_w")
    if opts.ratio_scope == "tail":
        scored = touched.groupBy("seq_id", "dst_type").agg(F.sum(F.col("w") * F.col("dst_w")).alias("W"))
        scored = scored.join(size, "seq_id").join(counts, F.col("dst_type") == F.col("type"))
        scored = scored.withColumn("ratio", ratio_of(F.col("W"), F.col("S"), F.col("N"), spec, space)).select("seq_id", "dst_type", "ratio").join(chains, "seq_id")
    else:
        strong = links.select(F.col("src_type").alias("last"), "dst_type", "ratio")
        scored = chains.withColumn("last", seq_last(F.col("seq"))).join(strong, "last").drop("last")
    if not opts.allow_repeats:
        scored = scored.where(~F.array_contains("seq", F.col("dst_type")))
    longer = scored.select(
        F.col("seq_id").alias("parent"), "dst_type", seq_append(F.col("seq"), F.col("dst_type")).alias("seq"),
        next_index(F.col("seq_index"), F.col("ratio")).alias("seq_index"), F.col("ratio").alias("last_ratio"),
    ).where(F.col("seq_index") >= opts.theta)
    return longer.withColumn("seq_id", seq_hash(F.col("seq"))), touched


def mine_index(points: DataFrame, spec: NeighbourhoodSpec, space: SpaceSpec, opts: MineOptions = MineOptions(), pairs: DataFrame | None = None) -> MiningResult:
    """All significant chains of length 2 and more over weighted points (events, or a microcluster index).

    Stops without survivors, at ``max_length``, or above ``limit_patterns`` chains (None: no such limit); the result's
    ``ended`` says which. Pairs are stored in buckets of their source, so a level moves tails, not pairs. For time
    rules that let an event follow itself in a cycle, ``cycle_guard`` drops a chain whose tail is the same set
    as its prefix's tail one period before.
    """
    points = as_points(points)
    if opts.strategy == "depth":
        return mine_depth_first(points, spec, space, opts)
    pairs = stored_buckets(pairs if pairs is not None else neighbour_pairs(points, spec, opts.join), "pairs", "src_id")
    counts = broadcast_if_small(stored(type_counts(points), "counts"), SMALL)
    links = ratio_matrix(points, spec, space, pairs).where(F.col("ratio") >= opts.theta) if opts.ratio_scope == "type" else None
    chains, tails = seed(points)
    result = MiningResult(patterns=points.sparkSession.createDataFrame([], PATTERN_SCHEMA), pairs=pairs)
    found, total, theta = [], 0, opts.theta
    guard: DataFrame | None = None
    for length in range(2, opts.max_length + 1):
        longer, touched = expand_level(chains, tails, pairs, counts, spec, space, replace(opts, theta=theta), links)
        longer = stored(longer, f"chains-{length}")
        n = longer.count()
        if not n:
            break
        if opts.limit_patterns is not None and total + n > opts.limit_patterns:
            result.ended = "limit_patterns"
            break
        kept = broadcast_if_small(longer.select(F.col("parent").alias("seq_id"), "dst_type", F.col("seq_id").alias("child")), SMALL, n)
        tails = touched.join(kept, ["seq_id", "dst_type"]).select(F.col("child").alias("seq_id"), F.col("dst_id").alias("id"), F.col("dst_w").alias("w")).distinct()
        tails = stored(tails, f"tails-{length}")
        size = tails.groupBy("seq_id").agg(F.sum("w").alias("tail_weight"), F.count("*").alias("m"), F.expr("bit_xor(xxhash64(id))").alias("mark"))
        alive = longer.join(size, "seq_id", "left")
        if opts.require_tail or opts.min_tail_weight:
            alive = alive.where(F.coalesce("tail_weight", F.lit(0)) >= max(opts.min_tail_weight, 1 if opts.require_tail else 0))
        alive = stored(alive, f"alive-{length}")
        rows = alive.count()
        if not rows:
            break
        found.append(alive.select("seq", F.size("seq").alias("length"), "seq_index", "last_ratio", F.coalesce("tail_weight", F.lit(0)).alias("tail_weight")))
        total += rows
        result.levels.append({"length": length, "chains": rows})
        chains = alive.select("seq_id", "seq", "seq_index")
        if opts.top_k and total >= opts.top_k:
            # an index never grows with the chain, so what is below the k-th strongest cannot lead to a better one
            strongest = reduce(DataFrame.unionByName, found).orderBy(F.desc("seq_index")).limit(opts.top_k)
            theta = max(theta, strongest.agg(F.min("seq_index")).first()[0])
            chains = chains.where(F.col("seq_index") >= theta)
        if opts.cycle_guard and spec.time_rule != "after":
            # a tail seen before in an ancestor that ends in the same type repeats for ever
            seen = alive.select("seq_id", "parent", seq_last(F.col("seq")).alias("last"), "m", "mark")
            old = guard.join(seen.select("seq_id", "parent").withColumnRenamed("parent", "anc").withColumnRenamed("seq_id", "now"), F.col("of") == F.col("anc")) if guard is not None else None
            if old is not None:
                hist = stored(old.select(F.col("now").alias("of"), F.col("g_last"), F.col("g_m"), F.col("g_mark")), f"guard-{length}")
                loops = seen.join(hist, (F.col("seq_id") == F.col("of")) & (F.col("last") == F.col("g_last")) & (F.col("m") == F.col("g_m")) & (F.col("mark") == F.col("g_mark"))).select("seq_id").distinct()
                chains = chains.join(loops, "seq_id", "left_anti")
            own = seen.select(F.col("seq_id").alias("of"), F.col("last").alias("g_last"), F.col("m").alias("g_m"), F.col("mark").alias("g_mark"))
            guard = own if old is None else hist.unionByName(own)
        tails = tails.join(chains.select("seq_id"), "seq_id", "left_semi")
    else:
        result.ended = "max_length" if found or opts.max_length < 2 else "complete"
    if found:
        result.patterns = reduce(DataFrame.unionByName, found).where(F.col("seq_index") >= theta)
    return result


def mine_depth_first(points: DataFrame, spec: NeighbourhoodSpec, space: SpaceSpec, opts: MineOptions) -> MiningResult:
    """The same chains in depth-first order, pair lists on the driver; for tests on small data."""
    points = as_points(points)
    pairs = stored(neighbour_pairs(points, spec, opts.join), "pairs")
    weight = {r["id"]: (r["type"], r["w"]) for r in points.select("id", "type", "w").collect()}
    after: dict = {}
    for r in pairs.select("src_id", "dst_id").collect():
        after.setdefault(r["src_id"], []).append(r["dst_id"])
    N: dict = {}
    for f, w in weight.values():
        N[f] = N.get(f, 0) + w
    out = []

    def expand(seq, index, tail):
        if len(seq) >= opts.max_length:
            return
        size = sum(weight[i][1] for i in tail)
        for f in sorted(N):
            if f in seq and not opts.allow_repeats:
                continue
            reached = [(i, j) for i in tail for j in after.get(i, ()) if weight[j][0] == f]
            W = sum(weight[i][1] * weight[j][1] for i, j in reached)
            ratio = W * (space.volume / spec.volume) / (float(size) * N[f])
            low = ratio if index is None else min(index, ratio)
            new = {j for _, j in reached}
            if low >= opts.theta and (new or not opts.require_tail):
                out.append((seq + [f], len(seq) + 1, low, ratio, sum(weight[j][1] for j in new)))
                if opts.limit_patterns is None or len(out) <= opts.limit_patterns:
                    expand(seq + [f], low, new)

    for f in sorted(N):
        expand([f], None, {i for i, (g, _) in weight.items() if g == f})
    spark = points.sparkSession
    cut = opts.limit_patterns is not None and len(out) > opts.limit_patterns
    longest = max((row[1] for row in out), default=0)
    return MiningResult(spark.createDataFrame(out, PATTERN_SCHEMA), pairs, ended="limit_patterns" if cut else "max_length" if longest >= opts.max_length else "complete")


def mine_instances(events: DataFrame, spec: NeighbourhoodSpec, space: SpaceSpec, opts: MineOptions = MineOptions()) -> MiningResult:
    """The instance miner: the search on the events themselves (the baseline)."""
    return mine_index(as_points(events.drop("w")), spec, space, opts)


def mine_microclusters(events: DataFrame, clustering: ClusterSpec, spec: NeighbourhoodSpec, space: SpaceSpec, opts: MineOptions = MineOptions()) -> MiningResult:
    """The microcluster miner: reduce the events to weighted representatives, then search on these."""
    from stseq.microcluster import cluster

    mc, _ = cluster(events, clustering)
    return mine_index(clusters_as_points(mc), spec, space, opts)


def mine_top_k(points: DataFrame, spec: NeighbourhoodSpec, space: SpaceSpec, k: int, opts: MineOptions = MineOptions()) -> MiningResult:
    """The ``k`` strongest chains of index ``theta`` or more, and those that tie with the last; weaker ones are not extended."""
    return mine_index(points, spec, space, replace(opts, top_k=k))


def pattern_table(patterns: DataFrame) -> DataFrame:
    """Patterns with the chain as text, rounded for comparison."""
    return patterns.select(
        seq_text(F.col("seq")).alias("pattern"), "length", F.round("seq_index", 6).alias("seq_index"), F.round("last_ratio", 6).alias("last_ratio"), "tail_weight"
    )
