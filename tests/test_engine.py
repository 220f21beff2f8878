"""The engine against brute force, worked examples, published index sizes and its own invariants."""

import glob
import itertools
import math
import os
import random
import time
from dataclasses import replace

import numpy as np
import pytest
from pyspark.sql import functions as F

from stseq import density, experiments, metrics, mining, neighbours, plans, sequences, sql
from stseq.functions import diameter_of, mc_diameter, register
from stseq.microcluster import absorb, cluster, index_members, read_index, write_index
from stseq.microcluster.features import diameter_cf, diameter_pairwise
from stseq.microcluster.kernel import Clusters, cluster_points, split
from stseq.microcluster.near_grid import GridClusters
from stseq.model import ClusterSpec, MineOptions, NeighbourhoodSpec, SpaceSpec, as_points, clusters_as_points
from stseq.neighbourhood import clipped_volume
from stseq.sources import tables
from stseq.sources.planted import planted_chains, planted_events

MINI = [
    (1, "A", 10, 10, 0), (2, "A", 50, 50, 0), (11, "B", 11, 10, 2), (12, "B", 11, 11, 2), (13, "B", 7, 8, 3), (14, "B", 7, 7, 3),
    (15, "B", 51, 50, 2), (16, "B", 51, 51, 2), (17, "B", 48, 48, 4), (18, "B", 48, 47, 4),
]
MINI_SPACE = SpaceSpec(x0=0, x1=100, y0=0, y1=100, t0=0, t1=10)
MINI_SPEC = NeighbourhoodSpec(R=5, T=5)
SCHEMA = "id bigint, type string, x double, y double, t bigint"


@pytest.fixture(scope="module")
def mini(spark):
    return spark.createDataFrame([(i, f, float(x), float(y), t) for i, f, x, y, t in MINI], SCHEMA)


def cloud(n, seed, types="ABC", size=60, time=80):
    rng = random.Random(seed)
    return [(i, rng.choice(types), float(rng.randint(0, size)), float(rng.randint(0, size)), rng.randint(0, time)) for i in range(n)]


@pytest.fixture(scope="module")
def events(spark):
    return spark.createDataFrame(cloud(400, 1), SCHEMA)


def brute(rows, spec):
    out = set()
    for a, b in itertools.product(rows, rows):
        dx, dy, lag = b[2] - a[2], b[3] - a[3], b[4] - a[4] - spec.delay
        late = {"after": 0 < lag <= spec.T, "from_now": 0 <= lag <= spec.T, "upper_only": lag <= spec.T, "printed_reverse": a[4] - b[4] <= spec.T}[spec.time_rule]
        if spec.shape == "box":
            near = abs(dx) <= spec.R and abs(dy) <= spec.R
        elif spec.shape == "cone":
            near = (dx * dx + dy * dy) * spec.T**2 <= spec.R**2 * lag * lag
        elif spec.metric == "abs":
            near = abs(dx) + abs(dy) <= spec.R
        else:
            near = dx * dx + dy * dy <= spec.R**2
        if late and near and a[0] != b[0]:
            out.add((a[0], b[0]))
    return out


def ids(pairs):
    return sorted((r["src_id"], r["dst_id"]) for r in pairs.select("src_id", "dst_id").collect())


@pytest.mark.parametrize("change", [{}, {"shape": "box"}, {"shape": "cone"}, {"metric": "abs"}, {"time_rule": "from_now"}, {"delay": 3}])
def test_joins_agree(events, change):
    spec = replace(NeighbourhoodSpec(R=7, T=9), **change)
    want = sorted(brute(cloud(400, 1), spec))
    assert ids(neighbours.pairs_grid(events, spec)) == want
    if spec.shape != "cone":
        assert ids(neighbours.pairs_sweep(events, spec, tile=20, slice_t=25)) == want
    if spec.time_rule == "after":
        assert ids(neighbours.pairs_window(events, spec, tile=15)) == want


def test_unbounded_rules(events):
    for rule in ("upper_only", "printed_reverse"):
        spec = NeighbourhoodSpec(R=7, T=9, time_rule=rule)
        assert ids(neighbours.pairs_nested_loop(events, spec)) == sorted(brute(cloud(400, 1), spec))
        with pytest.raises(ValueError):
            neighbours.pairs_grid(events, spec)


def test_cell_counts_and_work(events):
    spec = NeighbourhoodSpec(R=7, T=9)
    pairs = neighbours.pairs_grid(events, spec)
    want = sorted(tuple(r) for r in density.link_weights(pairs).collect())
    for k in (1, 2, 3):
        assert sorted(tuple(r) for r in neighbours.pair_weights_cells(events, spec, k).collect()) == want
    work = neighbours.count_candidates(events, spec).first()
    assert work["pairs"] == pairs.count() <= work["candidates"]
    assert neighbours.neighbours_of(events.where("id < 10").select("id"), pairs).count() == pairs.where("src_id < 10").count()
    lists = {r["src_id"]: r["neighbours"] for r in neighbours.neighbour_lists(pairs).collect()}
    assert sum(map(len, lists.values())) == pairs.count()


def test_haversine(spark):
    rng = random.Random(4)
    rows = [(i, "A", rng.uniform(-20, 20), rng.uniform(40, 70), rng.randint(0, 50)) for i in range(200)]
    df = spark.createDataFrame(rows, SCHEMA)
    spec = NeighbourhoodSpec(R=2, T=10, metric="haversine")

    def arc(a, b):
        p, q = map(math.radians, (a[3], b[3]))
        h = math.sin((q - p) / 2) ** 2 + math.cos(p) * math.cos(q) * math.sin(math.radians(b[2] - a[2]) / 2) ** 2
        return math.degrees(2 * math.asin(math.sqrt(h)))

    want = sorted((a[0], b[0]) for a in rows for b in rows if 0 < b[4] - a[4] <= 10 and arc(a, b) <= 2)
    assert ids(neighbours.pairs_grid(df, spec)) == want and want


def test_volumes_and_options(events):
    assert NeighbourhoodSpec(R=2, T=3).volume == pytest.approx(math.pi * 12)
    assert NeighbourhoodSpec(R=2, T=3, shape="cone").volume == pytest.approx(math.pi * 4)
    assert NeighbourhoodSpec(R=2, T=3, shape="box").volume == 48
    assert NeighbourhoodSpec(R=2, T=3, dims=1).volume == 12
    assert NeighbourhoodSpec(R=2, T=3, dims=3).volume == pytest.approx(4 / 3 * math.pi * 24)
    assert SpaceSpec.from_data(events).dims == 2 and MINI_SPACE.volume == 100_000
    for bad in (lambda: NeighbourhoodSpec(R=0, T=1), lambda: NeighbourhoodSpec(R=1, T=1, shape="cone", time_rule="upper_only"), lambda: ClusterSpec(), lambda: ClusterSpec(d=1, K=1), lambda: MineOptions(theta=-1), lambda: SpaceSpec(0, 0, 0, 1)):
        with pytest.raises(ValueError):
            bad()


def test_mini_example(spark, mini):
    mc, members = cluster(mini, ClusterSpec(d=2))
    sets = {tuple(r["members"]): r["n"] for r in index_members(members).collect()}
    assert sets == {(1,): 1, (2,): 1, (11, 12): 2, (13, 14): 2, (15, 16): 2, (17, 18): 2}
    assert metrics.compression_ratio(mc) == pytest.approx(10 / 6)
    points = clusters_as_points(mc)
    pairs = neighbours.pairs_grid(points, MINI_SPEC)
    a1 = members.where("id = 1").first()["cid"]
    covered = neighbours.covered_instances(pairs, members).where(F.col("src_id") == a1)
    assert sorted(r["id"] for r in covered.collect()) == [11, 12, 13, 14]
    assert sequences.tail_set(points, ["A", "B"], MINI_SPEC).count() == 4
    for data in (mini, points):
        r = density.density_ratio(data, "A", "B", MINI_SPEC, MINI_SPACE).first()
        assert r["W"] == 8 and r["ratio"] == pytest.approx(127.323954)
        assert density.density_ratio(data, "B", "A", MINI_SPEC, MINI_SPACE).first()["ratio"] == 0


def test_chain_example_and_order_of_search(spark):
    rows, n = [], 0
    for k in range(3):
        for step, f in enumerate("ABCD"):
            rows.append((n, f, 20.0 + 25 * k + step, 30.0 + step, step * 2))
            n += 1
    df = spark.createDataFrame(rows, SCHEMA)
    space = SpaceSpec(x0=0, x1=100, y0=0, y1=100, t0=0, t1=10)
    spec = NeighbourhoodSpec(R=2, T=2)
    found = mining.pattern_table(mining.mine_instances(df, spec, space, MineOptions(theta=1)).patterns).collect()
    assert {r["pattern"] for r in found} == {"A -> B", "B -> C", "C -> D", "A -> B -> C", "B -> C -> D", "A -> B -> C -> D"}
    steps = sequences.sequence_index(df, list("ABCD"), spec, space).orderBy("position").collect()
    assert [s["seq_index"] for s in steps] == list(itertools.accumulate((s["ratio"] for s in steps), min))


@pytest.mark.parametrize("change", [{}, {"allow_repeats": False}, {"max_length": 3}, {"theta": 1.02}])
def test_level_equals_depth_first(events, change):
    opts = replace(MineOptions(theta=1.0, max_length=4), **change)
    spec, space = NeighbourhoodSpec(R=6, T=8), SpaceSpec(x0=0, x1=61, y0=0, y1=61, t0=0, t1=81)
    one = mining.mine_index(events, spec, space, opts).patterns
    two = mining.mine_index(events, spec, space, replace(opts, strategy="depth")).patterns
    key = lambda df: sorted((r["pattern"], r["seq_index"], r["tail_weight"]) for r in mining.pattern_table(df).collect())
    assert key(one) == key(two) and key(one)
    # prefix-closed, and the index never grows
    index = {tuple(r["seq"]): r["seq_index"] for r in one.collect()}
    assert all(len(s) == 2 or index[s[:-1]] >= v for s, v in index.items())


def test_type_scope_cycles_and_limits(events):
    spec, space = NeighbourhoodSpec(R=6, T=8), SpaceSpec(x0=0, x1=61, y0=0, y1=61, t0=0, t1=81)
    result = mining.mine_index(events, spec, space, MineOptions(theta=0.9, ratio_scope="type", max_length=3))
    strong = {(r["src_type"], r["dst_type"]) for r in density.ratio_matrix(events, spec, space).where("ratio >= 0.9").collect()}
    for r in result.patterns.collect():
        assert all(link in strong for link in zip(r["seq"], r["seq"][1:]))
    cut = mining.mine_index(events, spec, space, MineOptions(theta=0.1, limit_patterns=5))
    assert cut.truncated
    now = mining.mine_index(events, NeighbourhoodSpec(R=6, T=8, time_rule="from_now"), space, MineOptions(theta=0.5, max_length=4))
    assert now.patterns.count() > 0


def test_identity_bridge_and_weights(events):
    spec, space = NeighbourhoodSpec(R=6, T=8), SpaceSpec(x0=0, x1=61, y0=0, y1=61, t0=0, t1=81)
    opts = MineOptions(theta=1.0, max_length=3)
    key = lambda df: sorted(tuple(r) for r in mining.pattern_table(df).collect())
    want = key(mining.mine_instances(events, spec, space, opts).patterns)
    for method in ("identity", "duplicates"):
        assert key(mining.mine_microclusters(events, ClusterSpec(method=method), spec, space, opts).patterns) == want
    assert key(mining.mine_instances(events, spec, space, replace(opts, join="sweep")).patterns) == want


def pairwise(x):
    m = len(x)
    return math.sqrt(sum(((a - b) ** 2).sum() for a in x for b in x) / (m * (m - 1))) if m > 1 else 0.0


def reference_clusters(x, d, K=None):
    """Plain insertion with pairwise diameters."""
    groups = []
    for i in range(len(x)):
        if not groups:
            groups.append([i])
            continue
        at = min(range(len(groups)), key=lambda g: (((x[groups[g]].mean(axis=0) - x[i]) ** 2).sum()))
        groups[at].append(i)

        def cut(g):
            own = groups[g]
            left, right = split(x[own])
            groups[g] = [own[k] for k in left]
            groups.append([own[k] for k in right])
            return g, len(groups) - 1

        if K and len(groups[at]) > K:
            for piece in cut(at):
                if pairwise(x[groups[piece]]) > d:
                    cut(piece)
        elif pairwise(x[groups[at]]) > d:
            cut(at)
    return groups


def test_kernel():
    rng = np.random.default_rng(0)
    for K in (None, 6):
        x = rng.random((150, 3)) * 10
        want = sorted(map(sorted, reference_clusters(x, 3.0, K)))
        for nearest in ("scan", "pivot"):
            assert sorted(map(sorted, cluster_points(x, 3.0, K=K, nearest=nearest))) == want
    fit = cluster_points(rng.random((300, 3)) * 10, 2.0, recheck="until_fit", assign="centroid")
    assert sorted(i for g in fit for i in g) == list(range(300))
    same = cluster_points(np.zeros((50, 3)), 1.0, K=8)
    assert max(map(len, same)) <= 8
    assert [len(g) for g in cluster_points(np.zeros((9, 3)), 1.0, K=8)] == [5, 4]
    wide = np.array([[0.0]] * 100 + [[6.0], [9.0]])
    assert pairwise(wide) == pytest.approx(1.5077, abs=1e-3) and pairwise(wide[100:]) == pytest.approx(3.0)
    c = Clusters(rng.random((40, 2)), 0.5)
    for g in range(len(c.run())):
        assert c._diameter(g) == pytest.approx(pairwise(c.p[c.members[g]]), abs=1e-9)


def test_grid_search_gives_the_same_clusters():
    rng = np.random.default_rng(3)
    for k, (n, size, d, K) in enumerate([(300, 12, 5, None), (400, 40, 5, 10), (300, 200, 2, None), (200, 3, 2, 4), (250, 30, 20, 2)]):
        x = rng.integers(0, size, (n, 2 + k % 2)).astype(float) if k < 4 else rng.random((n, 3)) * size
        for recheck in ("paper", "until_fit"):
            assert GridClusters(x, d, K=K, recheck=recheck).run() == Clusters(x - x.mean(axis=0), d, K=K, recheck=recheck).run()


def test_grid_search_is_exact_far_from_the_mean():
    x = np.random.default_rng(4).integers(0, 6, (300, 3)).astype(float)
    apart = x + np.array([1e5, 0, 0])
    near = GridClusters(x, 2.0, K=10).run()
    both = GridClusters(np.concatenate([x, apart]), 2.0, K=10)
    assert both.fits and len(both.run()) >= len(near)
    assert GridClusters(apart, 2.0, K=10).run() == near


def test_grid_search_does_not_scan_all_centres():
    x = np.random.default_rng(5).random((60_000, 3)) * 600
    begin = time.process_time()
    assert sum(map(len, GridClusters(x, 5.0).run())) == len(x)
    assert time.process_time() - begin < 30  # 60000 scans of all centres: more than twice that


class _Counted(dict):
    asked = 0

    def get(self, key):
        _Counted.asked += 1
        return super().get(key)


@pytest.mark.parametrize("shuffled", [False, True])
def test_grid_search_asks_few_cells(shuffled):
    rng = np.random.default_rng(5)
    p = rng.uniform(0, 1, (6000, 3)) * [300, 5, 40]
    p = p if shuffled else p[np.argsort(p[:, 2])]
    grid = GridClusters(p, 1.0, K=10)
    grid.cells = [_Counted() for _ in grid.cells]
    _Counted.asked = 0
    assert grid.run() == Clusters(p, 1.0, K=10).run()
    assert _Counted.asked < (45 if shuffled else 30) * len(p)


def test_grid_search_adds_a_far_event_without_a_split():
    p = np.array([[10.0 * (i % 50), 10.0 * (i // 50), i / 100] for i in range(2000)])
    grid = GridClusters(p, 1.0)
    grid._split = None
    assert grid.run() == [[i] for i in range(2000)] == Clusters(p, 1.0).run()


def test_cluster_tables(spark, events, tmp_path):
    spec = ClusterSpec(d=12, K=7, recheck="until_fit")
    mc, members = cluster(events, spec)
    assert metrics.diameter_violations(mc, 12) == 0 and mc.agg(F.max("n")).first()[0] <= 7
    assert all(r["events"] == r["clustered_once"] for r in metrics.conservation(events, members).collect())
    placed = members.join(events, "id")
    one = {r["cid"]: r["diameter"] for r in diameter_pairwise(placed, ["x", "y", "t"]).collect()}
    for r in mc.select("cid", diameter_cf(F.col("n"), F.col("ss")).alias("d")).collect():
        assert r["d"] == pytest.approx(one[r["cid"]], abs=1e-6)
    agg = placed.groupBy("cid").agg(mc_diameter(F.col("x"), F.col("y"), F.col("t")).alias("d"), diameter_of(F.collect_list(F.array("x", "y", F.col("t").cast("double")))).alias("p"))
    assert all(r["d"] == pytest.approx(r["p"], abs=1e-6) for r in placed.groupBy("cid").agg(mc_diameter(F.col("x"), F.col("y"), F.col("t")).alias("d"), F.collect_list(F.array("x", "y", F.col("t").cast("double"))).alias("a")).select("d", diameter_of("a").alias("p")).collect()) and agg is not None
    write_index(mc, members, str(tmp_path / "index"), spec)
    back, mem, about = read_index(spark, str(tmp_path / "index"))
    assert back.count() == mc.count() and mem.count() == 400 and about["K"] == 7
    more = spark.createDataFrame([(1000 + i, f, x, y, t) for i, f, x, y, t in cloud(60, 9)], SCHEMA)
    grown = absorb(mc, more, spec)
    assert grown.agg(F.sum("n")).first()[0] == 460 and metrics.diameter_violations(grown, 12) == 0
    assert metrics.size_histogram(mc).agg(F.sum("events")).first()[0] == 400
    assert metrics.displacement(events, mc, members).count() == 3


def test_tiles_and_border_merge(events):
    whole, _ = cluster(events, ClusterSpec(d=10))
    tiled = ClusterSpec(d=10, tile=20)
    parts, mem = cluster(events, tiled)
    merged, mem2 = cluster(events, replace(tiled, merge_borders=True))
    assert merged.count() <= parts.count() and whole.count() <= parts.count() * 1.1
    assert merged.agg(F.sum("n")).first()[0] == 400 == mem2.count()
    assert metrics.diameter_violations(merged.join(parts, "cid", "left_anti"), 10) == 0


def test_scaling_invariance(spark, events):
    spec, space = NeighbourhoodSpec(R=6, T=8), SpaceSpec(x0=0, x1=61, y0=0, y1=61, t0=0, t1=81)
    big = events.select("id", "type", (F.col("x") * 4).alias("x"), (F.col("y") * 4).alias("y"), (F.col("t") * 4).alias("t"))
    bspec, bspace = NeighbourhoodSpec(R=24, T=32), SpaceSpec(x0=0, x1=244, y0=0, y1=244, t0=0, t1=324)
    a = {tuple(r[:3]): r["ratio"] for r in density.ratio_matrix(events, spec, space).collect()}
    b = {tuple(r[:3]): r["ratio"] for r in density.ratio_matrix(big, bspec, bspace).collect()}
    assert a.keys() == b.keys() and all(a[k] == pytest.approx(b[k]) for k in a)
    # swapping the types and turning time around leaves the weights
    back = events.withColumn("t", -F.col("t"))
    c = {(r["dst_type"], r["src_type"]): r["W"] for r in density.ratio_matrix(back, spec, space).collect()}
    assert c == {k[:2]: k[2] for k in a}


def test_independent_types_and_edges(spark):
    df = spark.createDataFrame(cloud(3000, 3, size=100, time=100), SCHEMA)
    spec, space = NeighbourhoodSpec(R=10, T=10), SpaceSpec(x0=-0.5, x1=100.5, y0=-0.5, y1=100.5, t0=-0.5, t1=100.5)
    plain = [r["ratio"] for r in density.ratio_matrix(df, spec, space).collect()]
    fixed = [r["ratio"] for r in density.ratio_matrix(df, replace(spec, edge_correction="clip_box"), space).where("ratio > 0").collect()]
    wrapped = [r["ratio"] for r in density.ratio_matrix(df.withColumn("t", F.col("t").cast("double")), replace(spec, edge_correction="torus"), space).collect()]
    assert abs(np.mean(wrapped) - 1) < 0.03
    assert np.mean(plain) < 1 and abs(np.mean(fixed) - 1) < abs(np.mean(plain) - 1)
    assert df.select(clipped_volume(spec, space).alias("v")).agg(F.max("v")).first()[0] <= spec.volume * (1 + 1e-9)


def test_published_index_sizes(spark):
    """Generated data of 10000 events: index sizes for d = 40, 60, 80, 100 as published (7246, 6502, 5489, 4451), within 3 percent."""
    events = planted_events(spark, seed=1).cache()
    assert events.count() == 10_000
    for d, want in ((40, 7246), (60, 6502), (80, 5489), (100, 4451)):
        mc, _ = cluster(events, ClusterSpec(d=d))
        assert abs(mc.count() / want - 1) < 0.03
    chains = planted_chains(events)
    assert chains.count() == 10 and chains.where("size(seq) = 5").count() == 10
    expected = metrics.sub_chains(chains)
    spec, space = NeighbourhoodSpec(R=10, T=10), experiments.generated_space(experiments.BASE)
    mc, _ = cluster(events, ClusterSpec(d=40))
    result = mining.mine_index(clusters_as_points(mc), spec, space, MineOptions(theta=1, max_length=5))
    recall = {r["length"]: r["recall"] for r in metrics.recall_of(expected, result.patterns).collect()}
    assert recall[2] > 0.9 and recall[5] >= 0.6
    matrix = density.ratio_matrix(events, spec, space)
    error = metrics.ratio_error(matrix, density.ratio_matrix(clusters_as_points(mc), spec, space))
    assert error.count() > 0


def test_generator_forms(spark):
    from stseq.sources.datasource import register as register_source

    small = planted_events(spark, Ps=3, Pn=2, Ni=20, types_with_replacement=False)
    assert small.count() == 240 and small.select("id").distinct().count() == 240
    assert all(len(set(r["seq"])) == 3 for r in planted_chains(small).collect())
    register_source(spark)
    df = spark.read.format("planted").option("Ps", 3).option("Pn", 2).option("Ni", 20).load()
    assert df.count() == 240 and df.select("id").distinct().count() == 240
    rows = experiments.sweep_clustering(spark, "Pn", [2], (40, 100))
    assert rows[0]["index_size"] > rows[1]["index_size"]
    mined = experiments.sweep_mining(spark, "Pn", [2], (40,), max_length=3)
    assert mined[0]["patterns"] > 0
    assert experiments.baseline_instances(spark, {"Pn": 2}, max_length=2)["patterns"] > 0
    assert [r["variant"] for r in experiments.ablation(small, ClusterSpec(d=40), {"centroid": {"assign": "centroid"}})] == ["base", "centroid"]
    assert experiments.accuracy(small, NeighbourhoodSpec(10, 10), experiments.generated_space(experiments.BASE), ClusterSpec(d=40)).count() >= 0


def test_patterns_helpers(spark):
    df = spark.createDataFrame([(["A", "B"], 5.0), (["B", "C"], 4.0), (["A", "B", "C"], 4.0), (["C", "A"], 9.0)], "seq array<string>, seq_index double")
    assert sorted(r["seq"] for r in sequences.maximal(df).collect()) == [["A", "B", "C"], ["C", "A"]]
    assert [r["seq"] for r in sequences.top_k_patterns(df, 2).collect()] == [["C", "A"], ["A", "B"]]
    r = df.limit(1).select(sequences.seq_text(F.col("seq")).alias("t"), sequences.seq_last(F.col("seq")).alias("l"), sequences.seq_prefix(F.col("seq")).alias("p")).first()
    assert tuple(r) == ("A -> B", "B", ["A"])
    assert spark.range(1).select(sequences.parse_seq(F.lit("A -> B->C"))).first()[0] == ["A", "B", "C"]
    assert sequences.significant(df, 5).count() == 2
    red = metrics.redundancy(df, df.limit(2)).first()
    assert (red["only_first"], red["both"]) == (2, 2)


def test_simulated_threshold(spark, events):
    spec, space = NeighbourhoodSpec(R=6, T=8), SpaceSpec(x0=0, x1=61, y0=0, y1=61, t0=0, t1=81)
    a = sequences.simulate_threshold(events, spec, space, runs=5).orderBy("run").collect()
    b = sequences.simulate_threshold(events.repartition(7), spec, space, runs=5).orderBy("run").collect()
    assert len(a) == 5 and [r["max_ratio"] for r in a] == pytest.approx([r["max_ratio"] for r in b]) and a[0]["threshold"] > 0.8


def test_simulated_labels_are_not_broadcast(events):
    spec, space = NeighbourhoodSpec(R=6, T=8), SpaceSpec(x0=0, x1=61, y0=0, y1=61, t0=0, t1=81)
    assert plans.operators(sequences.simulate_threshold(events, spec, space, runs=2)).get("SortMergeJoin", 0) >= 2


def test_sql_surface_and_plans(spark, events):
    spec = NeighbourhoodSpec(R=7, T=9)
    sql.register(spark, events)
    register(spark)
    want = sorted(tuple(r) for r in density.link_weights(neighbours.pairs_grid(events, spec)).collect())
    assert sorted(tuple(r) for r in sql.link_weights_sql(spark, spec).collect()) == want
    assert spark.sql("SELECT * FROM chain_prefixes('A -> B -> C')").count() == 2
    assert spark.sql("SELECT * FROM neighbour_cells(10.0D, 10.0D, 3.0D, 5.0D, 5.0D)").count() == 18
    ops = plans.operators(density.link_weights(neighbours.pairs_grid(events, spec)))
    assert not any("Cartesian" in k or "NestedLoop" in k for k in ops)
    space = SpaceSpec.from_data(events)
    assert plans.estimate_pairs(events, spec, space).count() == 9
    with pytest.raises(ValueError):
        plans.check_size(events, spec, space, most=10)
    assert plans.suggest_cell(events, spec, 1.0)["cells"] > 0


def test_sql_surface_broadcasts_no_points(spark, events):
    sql.register(spark, events)
    ops = plans.operators(sql.link_weights_sql(spark, NeighbourhoodSpec(R=7, T=9)))
    assert "SortMergeJoin" in ops and "BroadcastHashJoin" not in ops


def test_nested_loop_leaves_out_blocks_without_reach(events):
    spec = NeighbourhoodSpec(R=1, T=9, delay=2)
    pairs = neighbours.pairs_nested_loop(events, spec)
    assert ids(pairs) == ids(neighbours.pairs_grid(events, spec)) and pairs.count()
    assert not any("Cartesian" in k or "NestedLoop" in k for k in plans.operators(pairs))


@pytest.mark.parametrize("spec", [NeighbourhoodSpec(R=3, T=9), NeighbourhoodSpec(R=3, T=9, delay=2, shape="box"), NeighbourhoodSpec(R=3, T=9, dims=1)])
def test_cells_of_two_radii_give_the_same_pairs(events, spec, monkeypatch):
    monkeypatch.setattr(neighbours, "_sparse", lambda *a: False)
    moved = events.withColumn("x", F.col("x") - 31)
    want = ids(neighbours.pairs_grid(moved, spec, broadcast_targets=1))
    monkeypatch.setattr(neighbours, "_sparse", lambda *a: True)
    assert ids(neighbours.pairs_grid(moved, spec, broadcast_targets=1)) == want == ids(neighbours.pairs_nested_loop(moved, spec))
    assert neighbours.source_cells(moved, spec, True).count() == 2 * 2**spec.dims * moved.count()


def test_sparse_targets_get_cells_of_two_radii(events):
    assert neighbours._sparse(as_points(events), NeighbourhoodSpec(R=1, T=1)) and not neighbours._sparse(as_points(events), NeighbourhoodSpec(R=60, T=80))


def test_edge_correction_joins_no_volumes_to_pairs(events):
    spec = NeighbourhoodSpec(R=7, T=9, edge_correction="clip_box")
    carried, joined = density.ratio_matrix(events, spec, WIDE_SPACE), density.ratio_matrix(events, spec, WIDE_SPACE, neighbours.pairs_grid(events, spec))
    joins = [sum(n for k, n in plans.operators(m).items() if k.endswith("Join")) for m in (carried, joined)]
    assert joins[0] == joins[1] - 1
    key = lambda m: sorted((r["src_type"], r["dst_type"], r["W"], round(r["ratio"] / 1e9, 6)) for r in m.collect())
    assert key(carried) == key(joined)


def test_cell_counts_broadcast_no_points(events):
    ops = plans.operators(neighbours.pair_weights_cells(events, NeighbourhoodSpec(R=7, T=9)))
    assert ops["SortMergeJoin"] == 2 and "BroadcastHashJoin" not in ops


WIDE_SPACE = SpaceSpec(x0=0, x1=90_000, y0=0, y1=100, t0=0, t1=2_592_000_000_000)  # 2.3e19, above a long


def test_type_density_in_a_volume_above_a_long(events):
    got = {r["type"]: r["density"] * WIDE_SPACE.volume for r in density.type_density(events, WIDE_SPACE).collect()}
    assert got == pytest.approx({r["type"]: r["count"] for r in events.groupBy("type").count().collect()})


def test_edge_correction_in_a_volume_above_a_long(events):
    matrix = density.ratio_matrix(events, NeighbourhoodSpec(R=7, T=9, edge_correction="clip_box"), WIDE_SPACE).collect()
    assert len(matrix) == 9 and all(r["ratio"] > 0 for r in matrix)


def test_weighted_density_in_a_volume_above_a_long(events):
    mc, _ = cluster(events, ClusterSpec(d=10, method="grid"))
    got = {r["type"]: r["N"] for r in density.type_density(clusters_as_points(mc), WIDE_SPACE).collect()}
    assert got == {r["type"]: r["count"] for r in events.groupBy("type").count().collect()}


def test_generator_source_serves_every_customer(spark, sf):
    from stseq.queries_methods import generator_source

    assert generator_source(spark, sf).agg(F.sum("events")).first()[0] == tables.table(spark, sf, "customer").count()


def test_mini_clusters_hold_every_customer(spark, sf):
    from stseq.queries_clusters import mini_clusters

    assert mini_clusters(spark, sf).agg(F.sum("n")).first()[0] == tables.table(spark, sf, "customer").count()


def test_generator_base_plants_on_every_customer(spark, sf):
    from stseq.queries_clusters import generator_base

    n, rows = tables.table(spark, sf, "customer").count(), generator_base(spark, sf)
    assert (rows.count(), rows.select("id").distinct().count(), rows.agg(F.max("id")).first()[0]) == (10 * n, 10 * n, 10 * n - 1)


def test_adapters_handle_bad_rows(spark, sf, tmp_path):
    rows = [(1, "A", 1.0, 1.0, 1), (2, None, 1.0, 1.0, 1), (3, "A", 1e9, 1.0, 1), (None, "A", 1.0, 1.0, 1), (4, "B", 1.0, 1.0, None)]
    df = spark.createDataFrame(rows, SCHEMA)
    assert [r["id"] for r in tables.cleaned(df, MINI_SPACE).collect()] == [1]
    df.where("id = 1").write.json(str(tmp_path / "j"))
    df.where("id = 1").write.option("header", True).csv(str(tmp_path / "c"))
    assert tables.events_from_log(spark, str(tmp_path / "j")).count() == tables.events_from_log(spark, str(tmp_path / "c"), "csv").count() == 1
    empty = df.limit(0)
    assert density.ratio_matrix(empty, MINI_SPEC, MINI_SPACE).count() == 0
    assert mining.mine_instances(empty, MINI_SPEC, MINI_SPACE).patterns.count() == 0
    assert as_points(df).columns[-1] == "w"


def test_streams(spark, events, tmp_path):
    from stseq.streaming import events as s

    hour = tables.HOUR
    timed = events.select("id", "type", F.col("x").cast("bigint").alias("x"), F.col("y").cast("bigint").alias("y"), (F.col("t") * hour).alias("t"))
    s.replay(timed, str(tmp_path / "in"), 4)
    spec = NeighbourhoodSpec(R=7, T=9 * hour)
    got = s.run_to_table(s.stream_pairs(s.read_stream(spark, str(tmp_path / "in")), spec, "1 hour"), str(tmp_path / "p"))
    assert ids(got) == ids(neighbours.pairs_grid(timed, spec))
    sessions = s.run_to_table(s.session_counts(s.read_stream(spark, str(tmp_path / "in")), "2 hours", "1 hour"), str(tmp_path / "s"))
    assert sessions.count() > 0


def rounded(rows):
    plain = lambda v: round(float(v), 5) if isinstance(v, (int, float)) and not isinstance(v, bool) else str(v)
    return sorted((tuple(plain(v) for v in r) for r in rows), key=str)


@pytest.mark.parametrize("name", [
    "mc_embeddings", "mc_embeddings_limited", "mc_conversations", "mc_absorbed", "mc_incremental_dk", "mc_incremental_tiled", "mini_clusters", "mini_mining",
    "pairs_haversine", "ratio_matrix_torus", "simulate_threshold", "abnormal_thresholds", "mine_top_k", "index_roundtrip", "stream_late",
])
def test_queries_equal_their_sql(spark, sf, name):
    import duckdb

    import __spark_entry__

    con = duckdb.connect()
    for path in glob.glob(f"{sf}/*.parquet"):
        con.execute(f"CREATE VIEW {os.path.basename(path)[:-8]} AS SELECT * FROM '{path}'")
    got = __spark_entry__.queries()[name](spark, sf)
    want = con.execute(__spark_entry__.oracle_sql()[name])
    names = [d[0] for d in want.description]
    assert sorted(names) == sorted(got.columns)
    assert rounded(got.select(*[f"`{n}`" for n in names]).collect()) == rounded(want.fetchall())


def test_border_merge_against_brute_force(events):
    """Rounds of mutual-nearest merges of the clusters of tiles, computed again from the members."""
    spec = ClusterSpec(d=10, tile=20)
    at = {r["id"]: (r["type"], np.array([r["x"], r["y"], r["t"]], float)) for r in events.collect()}
    mc, members = cluster(events, spec)
    tile = {r["cid"]: r["tile"] for r in mc.collect()}
    groups = {}
    for r in members.collect():
        groups.setdefault(r["cid"], []).append(r["id"])
    state = {c: (tile[c], False, ids) for c, ids in groups.items()}
    while True:
        centre = {c: np.mean([at[i][1] for i in ids], axis=0) for c, (_, _, ids) in state.items()}
        best = {}
        for a, (ta, ja, ia) in state.items():
            for b, (tb, jb, ib) in state.items():
                if a == b or at[ia[0]][0] != at[ib[0]][0] or not (ta != tb or ja or jb):
                    continue
                gap = ((centre[a] - centre[b]) ** 2).sum()
                if gap <= 100 and pairwise(np.array([at[i][1] for i in ia + ib])) <= 10:
                    best[a] = min(best.get(a, (np.inf, 0)), (gap, b))
        pairs = [(a, b) for a, (_, b) in best.items() if a < b and best.get(b, (0, None))[1] == a]
        if not pairs:
            break
        for a, b in pairs:
            state[a] = (state[a][0], True, state[a][2] + state.pop(b)[2])
    _, merged = cluster(events, replace(spec, merge_borders=True))
    got = {}
    for r in merged.collect():
        got.setdefault(r["cid"], set()).add(r["id"])
    assert sorted(map(sorted, got.values())) == sorted(sorted(ids) for _, _, ids in state.values())


def test_bucketed_pairs_stay_where_they_are(spark, events):
    from stseq.storage import stored_buckets

    spec = NeighbourhoodSpec(R=6, T=8)
    pairs = stored_buckets(neighbours.pairs_grid(events, spec), "pairs", "src_id")
    step = events.select("id").hint("merge").join(pairs, F.col("id") == F.col("src_id"))
    assert plans.plan_text(step).count("hashpartitioning(src_id") == 0 and step.count() == pairs.count()


def test_why_a_search_ends(events):
    spec, space = NeighbourhoodSpec(R=6, T=8), SpaceSpec(x0=0, x1=61, y0=0, y1=61, t0=0, t1=81)
    for opts, why in ((MineOptions(theta=0.1, max_length=2), "max_length"), (MineOptions(theta=99.0), "complete"), (MineOptions(theta=0.1, limit_patterns=5), "limit_patterns")):
        assert mining.mine_index(events, spec, space, opts).ended == why


def test_entry_contract(spark):
    import __spark_entry__ as e

    q, o = e.queries(), e.oracle_sql()
    assert set(o) <= set(q) and len(o) >= 50
    assert e.entry(spark).count() > 0


def test_whole_chains_of_the_planted_input(spark):
    from stseq.queries import queries

    sf, found = "/root/testdata/sf0.01", queries()
    patterns = {k: {r["pattern"] for r in found[k](spark, sf).collect()} for k in ("mine_instances_tail", "mine_instances_type_whole", "mine_grid_mc_whole", "miner_difference_whole")}
    assert "P1 -> P2 -> P3 -> P4" in patterns["mine_instances_type_whole"]
    assert patterns["miner_difference_whole"] == patterns["mine_instances_tail"] - patterns["mine_grid_mc_whole"]
