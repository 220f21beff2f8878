"""Registered queries of the join variants, measures, functions, sinks and streams that have no query elsewhere, and their SQL."""

from __future__ import annotations

import uuid
from collections.abc import Callable
from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from stseq import density, metrics, mining, neighbours, plans, queries as core, sequences, sql
from stseq.functions import diameter_of, mc_diameter, register
from stseq.microcluster import cluster, index_members, read_index, write_index
from stseq.model import ClusterSpec, MineOptions, NeighbourhoodSpec, SpaceSpec, clusters_as_points
from stseq.ranks import with_rank
from stseq.sources import datasource, tables
from stseq.storage import shared_dir, stored

HOUR, DAY = core.HOUR, core.DAY
CITY = replace(core.F1, metric="abs")
ARC = NeighbourhoodSpec(R=0.1, T=50, metric="haversine")
SELF = replace(core.F5, time_rule="from_now", self_pairs="include")
REVERSE = replace(core.F5, time_rule="printed_reverse")
WIDE_GRID = ClusterSpec(d=20, method="grid", time_unit=HOUR)
Query = Callable[[SparkSession, str], DataFrame]


def place(spark: SparkSession, name: str) -> str:
    return f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"


def torus_ratios(spark: SparkSession, sf: str) -> DataFrame:
    """Links with neighbourhoods that wrap around the lattice of users, keys and days."""
    return core.links(density.ratio_matrix(core.f1(spark, sf), replace(core.F1, edge_correction="torus"), core.events_volume(spark, sf)))


def one_link(spark: SparkSession, sf: str) -> DataFrame:
    out = density.density_ratio(core.f2(spark, sf), "P1", "P2", core.F1, core.events_volume(spark, sf))
    return core.links(out)


def mean_local_density(spark: SparkSession, sf: str) -> DataFrame:
    events = core.f1(spark, sf)
    out = density.mean_local_density(neighbours.pairs_grid(events, core.F1), events, core.F1)
    return out.select("src_type", "dst_type", F.col("W").cast("bigint").alias("W"), F.round(F.col("mean_density") * 1e15, 6).alias("density_e15"))


def neighbours_of_tail(spark: SparkSession, sf: str) -> DataFrame:
    """What follows the tail of P1 -> P2: neighbours by type."""
    events = stored(core.f2(spark, sf), "events")
    tail = sequences.tail_set(events, ["P1", "P2"], core.F1)
    return neighbours.neighbours_of(tail, neighbours.pairs_grid(events, core.F1)).groupBy("dst_type").agg(F.count("*").alias("pairs"), F.countDistinct("src_id").alias("sources"))


def neighbour_lists(spark: SparkSession, sf: str) -> DataFrame:
    lists = neighbours.neighbour_lists(neighbours.pairs_grid(tables.events_from_embeddings(spark, sf), core.F6))
    return lists.select("src_id", "src_type", F.array_join(F.col("neighbours").cast("array<string>"), ",").alias("neighbours"))


def ratio_vectors(spark: SparkSession, sf: str) -> DataFrame:
    vectors = density.ratio_vectors(core.conversation_ratios(spark, sf))
    return vectors.select("src_type", F.map_keys("ratios")[0].alias("first_type"), F.size("ratios").alias("links"), F.round(F.aggregate(F.map_values("ratios"), F.lit(0.0), lambda a, x: a + x), 6).alias("total"))


def join_work(spark: SparkSession, sf: str) -> DataFrame:
    """Pairs that share a cell and pairs that are neighbours."""
    return neighbours.count_candidates(core.f1(spark, sf), core.F1)


def expected_pairs(spark: SparkSession, sf: str) -> DataFrame:
    return plans.estimate_pairs(core.f1(spark, sf), core.F1, core.events_volume(spark, sf)).select("src_type", "dst_type", F.round("expected", 6).alias("expected"))


def depth_first(spark: SparkSession, sf: str) -> DataFrame:
    """The search in the published order, on conversations at threshold 1."""
    points = tables.events_from_conversations(spark, sf)
    space = SpaceSpec(x0=0, x1=float(points.agg(F.max("x")).first()[0] + 1), t0=0, t1=8, dims=1)
    return mining.pattern_table(mining.mine_instances(points, core.F5, space, MineOptions(theta=1.0, max_length=4, strategy="depth")).patterns)


def _mine(opts: MineOptions) -> Callable[[SparkSession, str], mining.MiningResult]:
    return lambda spark, sf: mining.mine_instances(core.f2(spark, sf), core.F1, core.events_volume(spark, sf), opts)


def heavy_tails(spark: SparkSession, sf: str) -> DataFrame:
    return mining.pattern_table(_mine(MineOptions(theta=3.0, max_length=3, min_tail_weight=150))(spark, sf).patterns)


def top_chains(spark: SparkSession, sf: str) -> DataFrame:
    """The four strongest chains of all, by raising the threshold while the search runs."""
    return mining.pattern_table(_mine(MineOptions(theta=2.0, max_length=3, top_k=4))(spark, sf).patterns)


def pattern_counts(spark: SparkSession, sf: str) -> DataFrame:
    return metrics.pattern_counts(_mine(MineOptions(theta=2.0, max_length=4))(spark, sf).patterns)


def redundancy(spark: SparkSession, sf: str) -> DataFrame:
    """Chains at threshold 2 on events and on clusters of cells of 10: only here, only there, in both."""
    events = _mine(MineOptions(theta=2.0, max_length=3))(spark, sf).patterns
    mc, _ = cluster(core.f2(spark, sf), WIDE_GRID)
    reduced = mining.mine_index(clusters_as_points(mc), core.F1_MC, core.events_volume(spark, sf), MineOptions(theta=2.0, max_length=3)).patterns
    return metrics.redundancy(events, reduced).withColumn("jaccard", F.round("jaccard", 6))


def ratio_error(spark: SparkSession, sf: str) -> DataFrame:
    """Relative error of each link on grid clusters against the events."""
    space = core.events_volume(spark, sf)
    mc, _ = cluster(core.f2(spark, sf), WIDE_GRID)
    out = metrics.ratio_error(density.ratio_matrix(core.f2(spark, sf), core.F1, space), density.ratio_matrix(clusters_as_points(mc), core.F1_MC, space))
    return out.select("src_type", "dst_type", F.round("ratio", 6).alias("ratio"), F.round("ratio_reduced", 6).alias("ratio_reduced"), F.round("error", 6).alias("error"))


def displacement(spark: SparkSession, sf: str) -> DataFrame:
    events = core.f1(spark, sf)
    mc, members = cluster(events, WIDE_GRID)
    out = metrics.displacement(events, mc, members)
    return out.select("type", F.round("mean_space", 6).alias("mean_space"), F.round(F.col("mean_time") / HOUR, 6).alias("mean_hours"))


def size_histogram(spark: SparkSession, sf: str) -> DataFrame:
    return metrics.size_histogram(cluster(core.f1(spark, sf), WIDE_GRID)[0])


def wide_clusters(spark: SparkSession, sf: str) -> DataFrame:
    """Clusters of cells of side 20 that are wider than 8: the violations of a bound they were not made for."""
    mc, _ = cluster(core.f1(spark, sf), WIDE_GRID)
    return spark.createDataFrame([(metrics.diameter_violations(mc, 8.0),)], "violations bigint")


def diameter_functions(spark: SparkSession, sf: str) -> DataFrame:
    """The diameter of a label's vectors by the Arrow function (all pairs) and by the aggregate of built-in functions."""
    points = tables.events_from_embeddings(spark, sf)
    return points.groupBy("type").agg(
        F.round(diameter_of(F.collect_list(F.array("x", "y"))), 6).alias("pairwise"), F.round(mc_diameter(F.col("x"), F.col("y")), 6).alias("additive"),
    )


def chain_prefixes(spark: SparkSession, sf: str) -> DataFrame:
    """The table function over the found chains, from SQL."""
    register(spark)
    view = f"chains_{uuid.uuid4().hex}"
    mining.pattern_table(_mine(MineOptions(theta=core.THETA, max_length=4))(spark, sf).patterns).createOrReplaceTempView(view)
    return spark.sql(f"SELECT c.pattern, p.length, p.prefix FROM {view} c, LATERAL chain_prefixes(c.pattern) p")


def touched_cells(spark: SparkSession, sf: str) -> DataFrame:
    """Source copies to a cell by the table function, for the sign-ups: the cells with more than three."""
    register(spark)
    view = f"points_{uuid.uuid4().hex}"
    core.f1(spark, sf).where("type = 'signup'").createOrReplaceTempView(view)
    cells = spark.sql(f"SELECT c.cx, c.cy, c.ct FROM {view} e, LATERAL neighbour_cells(CAST(e.x AS DOUBLE), CAST(e.y AS DOUBLE), CAST(e.t AS DOUBLE), 10D, CAST({DAY} AS DOUBLE)) c")
    return cells.groupBy("cx", "cy", "ct").agg(F.count("*").alias("sources")).where("sources > 3")


def sql_surface(spark: SparkSession, sf: str) -> DataFrame:
    sql.register(spark, core.f1(spark, sf))
    return sql.link_weights_sql(spark, core.F1).select("src_type", "dst_type", F.col("W").cast("bigint").alias("pairs"))


def index_roundtrip(spark: SparkSession, sf: str) -> DataFrame:
    """Grid clusters written as an index and read back, with the events that each holds."""
    spec = ClusterSpec(d=10, method="grid", time_unit=HOUR)
    mc, members = cluster(core.f1(spark, sf), spec)
    path = place(spark, "index")
    write_index(mc, members, path, spec)
    clusters, held, _ = read_index(spark, path)
    both = clusters.join(index_members(held).withColumnRenamed("n", "held"), "cid")
    return both.select("type", "n", "held", F.array_min("members").alias("first"), F.round("x", 6).alias("x"), F.round("y", 6).alias("y"))


def log_roundtrip(spark: SparkSession, sf: str) -> DataFrame:
    """Events written as JSON lines and as CSV, read back as logs."""
    path = place(spark, "log")
    events = core.f1(spark, sf).select("id", "type", F.col("x").cast("double").alias("x"), F.col("y").cast("double").alias("y"), "t")
    events.write.json(f"{path}/json")
    events.write.option("header", True).csv(f"{path}/csv")
    logs = [tables.events_from_log(spark, f"{path}/{form}", form) for form in ("json", "csv")]
    return logs[0].unionByName(logs[1]).groupBy("id", "type", "x", "y", "t").agg(F.count("*").alias("logs"))


def generator_source(spark: SparkSession, sf: str) -> DataFrame:
    """The generator as a Python data source, an event for every customer: events by market segment, and whether all lie in the space."""
    datasource.register(spark)
    customers, n = with_rank(tables.table(spark, sf, "customer").select("c_custkey", "c_mktsegment"), ["c_custkey"], "row")
    made = spark.read.format("planted").option("Pn", 4).option("Ni", n // 40 + 1).load()  # 40 * Ni events, gapless from 0
    rows = customers.select("c_mktsegment", F.col("row").alias("id")).join(made, "id")
    inside = F.col("x").between(0, 1000) & F.col("y").between(0, 1000) & F.col("t").between(0, 1200) & F.col("type").rlike("^f[01][0-9]$")
    return rows.groupBy(F.col("c_mktsegment").alias("segment")).agg(F.count("*").alias("events"), F.countDistinct("id").alias("ids"), F.count(F.when(~inside, 1)).alias("outside"))


def daily_rollup(spark: SparkSession, sf: str) -> DataFrame:
    day = F.expr(f"cast(t div {DAY} as bigint)")
    return core.f1(spark, sf).withColumn("day", day).rollup("type", "day").agg(F.count("*").alias("n"), F.max("x").alias("largest_x"))


def grouping_sets(spark: SparkSession, sf: str) -> DataFrame:
    day = F.expr(f"cast(t div {DAY} as bigint)")
    events = core.f1(spark, sf).withColumn("day", day)
    return events.groupingSets([[F.col("type")], [F.col("day")], []], "type", "day").agg(F.count("*").alias("n"), F.grouping_id().cast("bigint").alias("level"))


def approximate_users(spark: SparkSession, sf: str) -> DataFrame:
    """Whether the sketch of distinct users is within five percent of the count."""
    out = core.f1(spark, sf).groupBy("type").agg(F.approx_count_distinct("x", 0.01).alias("about"), F.countDistinct("x").alias("users"))
    return out.select("type", "users", (F.abs(F.col("about") - F.col("users")) <= 0.05 * F.col("users")).alias("close"))


def set_operations(spark: SparkSession, sf: str) -> DataFrame:
    """Users by what they did: both click and purchase, click but no error, any of sign-up and view."""
    def who(kind: str) -> DataFrame:
        return core.f1(spark, sf).where((F.col("type") == kind) & (F.col("y") < 20)).select("x").distinct()

    both, only, some = who("click").intersect(who("purchase")), who("click").subtract(who("error")), who("signup").unionByName(who("view")).distinct()
    return both.withColumn("what", F.lit("both")).unionByName(only.withColumn("what", F.lit("only"))).unionByName(some.withColumn("what", F.lit("some")))


def sessions(spark: SparkSession, sf: str) -> DataFrame:
    from stseq.streaming import events as s

    folder = place(spark, "sessions")
    s.replay(core.f1(spark, sf).select("id", "type", "x", "y", "t"), f"{folder}/in", 1)
    out = s.run_to_table(s.session_counts(s.read_stream(spark, f"{folder}/in"), "6 hours", "40 days"), folder, "append", flush=s.far_row("40 days"))
    return out.where("x >= 0").select("x", "type", "n", F.date_format("start", "yyyy-MM-dd HH:mm:ss").alias("start"))


def sliding_counts(spark: SparkSession, sf: str) -> DataFrame:
    from stseq.streaming import events as s

    folder = place(spark, "sliding")
    s.replay(core.f1(spark, sf).select("id", "type", "x", "y", "t"), f"{folder}/in")
    out = s.run_to_table(s.stream_density(s.read_stream(spark, f"{folder}/in"), "2 days", "1 day", "3 days"), folder, "update")
    return out.groupBy("start", "type").agg(F.max("n").alias("n")).select(F.date_format("start", "yyyy-MM-dd").alias("start"), "type", "n")


def late_counts(spark: SparkSession, sf: str) -> DataFrame:
    """A stream whose last slice (the first ten days) lies behind the watermark of the slice before: it is dropped."""
    from stseq.streaming import events as s

    folder = place(spark, "late")
    events = core.f1(spark, sf).select("id", "type", "x", "y", "t")
    s.replay(events.where(F.col("t") >= 10 * DAY), f"{folder}/in", 2)  # late rows are told by the watermark of two batches before
    s.replay(events.where(F.col("t") < 10 * DAY), f"{folder}/in", 1)
    out = s.run_to_table(s.stream_density(s.read_stream(spark, f"{folder}/in"), late="5 days"), folder, "update")
    return out.groupBy("start", "type").agg(F.max("n").alias("n")).select(F.date_format("start", "yyyy-MM-dd").alias("day"), "type", "n")


def queries() -> dict[str, Query]:
    return {
        "pairs_city_block": core._pairs(CITY),
        "pairs_haversine": core._pairs(ARC, tables.events_from_embeddings),
        "pairs_reverse": core._pairs(REVERSE, tables.events_from_conversations, neighbours.pairs_nested_loop),
        "pairs_with_self": core._pairs(SELF, tables.events_from_conversations),
        "ratio_matrix_torus": torus_ratios, "density_ratio": one_link, "mean_local_density": mean_local_density, "neighbours_of_tail": neighbours_of_tail,
        "neighbour_lists": neighbour_lists, "ratio_vectors": ratio_vectors, "join_work": join_work, "expected_pairs": expected_pairs,
        "mine_depth_first": depth_first, "mine_heavy_tails": heavy_tails, "mine_top_k": top_chains, "pattern_counts": pattern_counts,
        "redundancy": redundancy, "ratio_error": ratio_error, "displacement": displacement, "size_histogram": size_histogram, "diameter_violations": wide_clusters,
        "diameter_functions": diameter_functions, "chain_prefixes": chain_prefixes, "touched_cells": touched_cells, "sql_surface": sql_surface,
        "index_roundtrip": index_roundtrip, "log_roundtrip": log_roundtrip, "generator_source": generator_source,
        "daily_rollup": daily_rollup, "grouping_sets": grouping_sets, "approximate_users": approximate_users, "set_operations": set_operations,
        "stream_sessions": sessions, "stream_sliding": sliding_counts, "stream_late": late_counts,
    }


def oracle_sql() -> dict[str, str]:
    f1, f2, f5, f6 = core.SQL_F1, core.sql_f2(), core.SQL_F5, core.SQL_F6
    volume = core.F1_VOLUME

    def counted(ev: str, on: str) -> str:
        return f"WITH {ev} SELECT a.type AS src_type, b.type AS dst_type, count(*) AS pairs FROM ev a JOIN ev b ON {on} GROUP BY ALL"

    arc = "degrees(2 * asin(least(1.0::DOUBLE, sqrt(pow(sin(radians(b.y - a.y) / 2), 2) + cos(radians(a.y)) * cos(radians(b.y)) * pow(sin(radians(b.x - a.x) / 2), 2)))))"
    span = 720 * HOUR
    torus = f"""WITH {f1}, u AS (SELECT max(user_id) + 1 AS m FROM events), n AS (SELECT type, count(*) AS c FROM ev GROUP BY type),
 im AS (SELECT id, type, x + i * m AS x, y + j * 100 AS y, t + k * {span} AS t FROM ev, u, (VALUES (-1), (0), (1)) p(i), (VALUES (-1), (0), (1)) q(j), (VALUES (-1), (0), (1)) r(k)
  WHERE x + i * m BETWEEN -10 AND m + 10 AND y + j * 100 BETWEEN -10 AND 110 AND t + k * {span} BETWEEN 0 AND {span + DAY}),
 wt AS (SELECT a.type AS src_type, b.type AS dst_type, count(*) AS W FROM ev a JOIN im b ON a.id <> b.id AND b.t > a.t AND b.t <= a.t + {DAY} AND (b.x - a.x) * (b.x - a.x) + (b.y - a.y) * (b.y - a.y) <= 100 GROUP BY ALL)
SELECT s.type AS src_type, d.type AS dst_type, coalesce(W, 0) AS W, s.c AS src_n, d.c AS dst_n, round(coalesce(W, 0) * ({volume} / {core.F1.volume!r}::DOUBLE) / (s.c::DOUBLE * d.c), 6) AS ratio
FROM n s CROSS JOIN n d LEFT JOIN wt ON wt.src_type = s.type AND wt.dst_type = d.type"""
    tail2 = f"WITH {f2}, {core.sql_pairs(core.F1)}, t2 AS (SELECT DISTINCT dst_id AS id FROM pairs WHERE src_type = 'P1' AND dst_type = 'P2')"
    cells = f"""c AS (SELECT *, floor(x / 10.0) AS cx, floor(y / 10.0) AS cy, floor(t / {float(DAY)!r}::DOUBLE) AS ct FROM ev)"""
    mined3 = core.sql_mine(f2, core.F1, volume, 2.0, 3)
    grid = core.sql_grid(f2, 20)
    on_grid = f"{grid.replace('ev AS (SELECT id, type, x, y, t, w FROM base', 'evs AS (SELECT id, type, x, y, t, w FROM base').replace('FROM ev)', 'FROM evs)')}, ev AS (SELECT row_number() OVER () AS id, type, x, y, t, n AS w FROM mc)"
    mined_grid = core.sql_mine(on_grid, core.F1_MC, volume, 2.0, 3)
    grid1 = core.sql_grid(f1, 20)
    spread = f"coalesce(var_samp(x) + var_samp(y) + var_samp(t / {float(HOUR)!r}::DOUBLE), 0)"
    day = f"d AS (SELECT *, t // {DAY} AS day FROM ev)"
    user = "SELECT DISTINCT x FROM ev WHERE y < 20 AND type"
    return {
        "pairs_city_block": counted(f1, f"b.t > a.t AND b.t <= a.t + {DAY} AND abs(b.x - a.x) + abs(b.y - a.y) <= 10 AND a.id <> b.id"),
        "pairs_haversine": counted(f6, f"b.t > a.t AND b.t <= a.t + 50 AND {arc} <= 0.1 AND a.id <> b.id"),
        "pairs_reverse": counted(f5, "a.t - b.t <= 2 AND (b.x - a.x) * (b.x - a.x) <= 0.25 AND a.id <> b.id"),
        "pairs_with_self": counted(f5, "b.t >= a.t AND b.t <= a.t + 2 AND a.x = b.x"),
        "ratio_matrix_torus": torus,
        "density_ratio": f"SELECT * FROM ({core.sql_ratio(f2, core.F1, volume)}) WHERE src_type = 'P1' AND dst_type = 'P2'",
        "mean_local_density": f"WITH {f1}, {core.sql_pairs(core.F1)}, n AS (SELECT type, count(*) AS c FROM ev GROUP BY type) SELECT src_type, dst_type, count(*) AS W, round(count(*) / (any_value(c) * {core.F1.volume!r}::DOUBLE) * 1e15, 6) AS density_e15 FROM pairs JOIN n ON n.type = src_type GROUP BY src_type, dst_type",
        "neighbours_of_tail": f"{tail2} SELECT dst_type, count(*) AS pairs, count(DISTINCT src_id) AS sources FROM pairs WHERE src_id IN (SELECT id FROM t2) GROUP BY dst_type",
        "neighbour_lists": f"WITH {f6}, {core.sql_pairs(core.F6)} SELECT src_id, src_type, string_agg(dst_id::VARCHAR, ',' ORDER BY dst_id) AS neighbours FROM pairs GROUP BY src_id, src_type",
        "ratio_vectors": f"SELECT src_type, min(dst_type) AS first_type, count(*) AS links, round(sum(ratio), 6) AS total FROM ({core.sql_ratio(f5, core.F5, '((SELECT max(x) + 1 FROM ev) * 8.0::DOUBLE)').replace('round(coalesce(W, 0)', '(coalesce(W, 0)').replace(', 6) AS ratio', ') AS ratio')}) GROUP BY src_type",
        "join_work": f"WITH {f1}, {cells}, {core.sql_pairs(core.F1)} SELECT (SELECT count(*) FROM c a JOIN c b ON b.cx BETWEEN a.cx - 1 AND a.cx + 1 AND b.cy BETWEEN a.cy - 1 AND a.cy + 1 AND b.ct BETWEEN a.ct AND a.ct + 1) AS candidates, (SELECT count(*) FROM pairs) AS pairs",
        "expected_pairs": f"WITH {f1}, n AS (SELECT type, count(*) AS c FROM ev GROUP BY type) SELECT s.type AS src_type, d.type AS dst_type, round(s.c * d.c * ({core.F1.volume!r}::DOUBLE / {volume}), 6) AS expected FROM n s CROSS JOIN n d",
        "mine_depth_first": core.sql_mine(f5, core.F5, "((SELECT max(x) + 1 FROM ev) * 8.0::DOUBLE)", 1.0, 4),
        "mine_heavy_tails": _heavy(f2, volume),
        "mine_top_k": f"WITH m AS ({mined3}) SELECT * FROM m WHERE seq_index >= (SELECT min(seq_index) FROM (SELECT seq_index FROM m ORDER BY seq_index DESC LIMIT 4))",
        "pattern_counts": f"SELECT length, count(*) AS patterns FROM ({core.sql_mine(f2, core.F1, volume, 2.0, 4)}) GROUP BY length",
        "redundancy": f"WITH a AS (SELECT pattern FROM ({mined3})), b AS (SELECT pattern FROM ({mined_grid})) SELECT count(*) FILTER (b.pattern IS NULL) AS only_first, count(*) FILTER (a.pattern IS NULL) AS only_second, count(*) FILTER (a.pattern = b.pattern) AS \"both\", round(count(*) FILTER (a.pattern = b.pattern) / count(*)::DOUBLE, 6) AS jaccard FROM a FULL JOIN b ON a.pattern = b.pattern",
        "ratio_error": f"SELECT a.src_type, a.dst_type, round(a.ratio, 6) AS ratio, round(b.ratio, 6) AS ratio_reduced, CASE WHEN a.ratio > 0 THEN round(abs(b.ratio - a.ratio) / a.ratio, 6) END AS error FROM ({_exact(core.sql_ratio(f2, core.F1, volume))}) a JOIN ({_exact(core.sql_ratio(on_grid, core.F1_MC, volume))}) b USING (src_type, dst_type)",
        "displacement": f"WITH {grid1} SELECT type, round(avg(sqrt(pow(c.x - mc.x, 2) + pow(c.y - mc.y, 2))), 6) AS mean_space, round(avg(abs(c.t - mc.t)) / {float(HOUR)!r}::DOUBLE, 6) AS mean_hours FROM cells c JOIN mc USING (type, cx, cy, ct) GROUP BY type",
        "size_histogram": f"WITH {grid1} SELECT floor(log2(n))::INTEGER AS log2_size, count(*) AS clusters, sum(n)::BIGINT AS events FROM mc GROUP BY 1",
        "diameter_violations": f"WITH {grid1}, w AS (SELECT sqrt(2 * {spread}) AS d FROM cells GROUP BY type, cx, cy, ct) SELECT count(*) AS violations FROM w WHERE d > 8 + 1e-9",
        "diameter_functions": f"WITH {f6}, p AS (SELECT a.type, sqrt(sum(pow(a.x - b.x, 2) + pow(a.y - b.y, 2)) / (any_value(n.c) * (any_value(n.c) - 1))) AS d FROM ev a JOIN ev b ON a.type = b.type JOIN (SELECT type, count(*) AS c FROM ev GROUP BY type) n ON n.type = a.type GROUP BY a.type) SELECT type, round(d, 6) AS pairwise, round(d, 6) AS additive FROM p",
        "chain_prefixes": f"WITH m AS ({core.sql_mine(f2, core.F1, volume)}) SELECT pattern, k::INTEGER AS length, array_to_string(string_split(pattern, ' -> ')[:k], ' -> ') AS prefix FROM m, range(2, 5) r(k) WHERE k <= m.length",
        "touched_cells": f"WITH {f1}, {cells} SELECT (cx + i)::BIGINT AS cx, (cy + j)::BIGINT AS cy, (ct + k)::BIGINT AS ct, count(*) AS sources FROM c, (VALUES (-1), (0), (1)) a(i), (VALUES (-1), (0), (1)) b(j), (VALUES (0), (1)) d(k) WHERE type = 'signup' GROUP BY 1, 2, 3 HAVING count(*) > 3",
        "sql_surface": core.sql_counts(f1, core.F1),
        "index_roundtrip": f"WITH {core.sql_grid(f1)} SELECT mc.type, mc.n, count(*) AS held, min(c.id) AS first, round(any_value(mc.x), 6) AS x, round(any_value(mc.y), 6) AS y FROM mc JOIN cells c USING (type, cx, cy, ct) GROUP BY type, cx, cy, ct, mc.n",
        "log_roundtrip": f"WITH {f1} SELECT id, type, x::DOUBLE AS x, y::DOUBLE AS y, t, 2 AS logs FROM ev",
        "generator_source": "SELECT c_mktsegment AS segment, count(*) AS events, count(*) AS ids, 0 AS outside FROM customer GROUP BY c_mktsegment",
        "daily_rollup": f"WITH {f1}, {day} SELECT type, day, count(*) AS n, max(x) AS largest_x FROM d GROUP BY ROLLUP (type, day)",
        "grouping_sets": f"WITH {f1}, {day} SELECT type, day, count(*) AS n, grouping_id(type, day) AS level FROM d GROUP BY GROUPING SETS ((type), (day), ())",
        "approximate_users": f"WITH {f1} SELECT type, count(DISTINCT x) AS users, true AS close FROM ev GROUP BY type",
        "set_operations": f"WITH {f1} SELECT x, 'both' AS what FROM ({user} = 'click' INTERSECT {user} = 'purchase') UNION ALL SELECT x, 'only' FROM ({user} = 'click' EXCEPT {user} = 'error') UNION ALL SELECT x, 'some' FROM ({user} = 'signup' UNION {user} = 'view')",
        "stream_sessions": f"""WITH {f1}, g AS (SELECT *, CASE WHEN t - lag(t) OVER w < {6 * HOUR} THEN 0 ELSE 1 END AS fresh FROM ev WINDOW w AS (PARTITION BY x, type ORDER BY t)),
 s AS (SELECT *, sum(fresh) OVER (PARTITION BY x, type ORDER BY t ROWS UNBOUNDED PRECEDING) AS k FROM g)
SELECT x, type, count(*) AS n, strftime(TIMESTAMP '2024-01-01' + to_microseconds(min(t)), '%Y-%m-%d %H:%M:%S') AS start FROM s GROUP BY x, type, k""",
        "stream_sliding": f"WITH {f1}, w AS (SELECT type, t // {DAY} - k AS d FROM ev, (VALUES (0), (1)) v(k)) SELECT strftime(TIMESTAMP '2024-01-01' + to_days(d::INTEGER), '%Y-%m-%d') AS start, type, count(*) AS n FROM w GROUP BY d, type",
        "stream_late": f"WITH {f1} SELECT strftime(TIMESTAMP '2024-01-01' + to_microseconds(t), '%Y-%m-%d') AS day, type, count(*) AS n FROM ev WHERE t >= {10 * DAY} GROUP BY ALL",
        "simulate_threshold": _simulated(f1, volume),
    }


def _exact(query: str) -> str:
    """The ratios without rounding."""
    return query.replace("round(coalesce(W, 0)", "(coalesce(W, 0)").replace(", 6) AS ratio", ") AS ratio")


def _heavy(ev: str, volume: str, least: int = 150) -> str:
    """The unrolled search where chains with a light tail are not extended."""
    query = core.sql_mine(ev, core.F1, volume, 3.0, 3)
    # tails of length 2 that are too light end their chain
    query = query.replace(" FROM t2 t JOIN pairs p", f" FROM (SELECT * FROM t2 WHERE pat IN (SELECT pat FROM t2 GROUP BY pat HAVING sum(w) >= {least})) t JOIN pairs p")
    return f"SELECT * FROM ({query}) WHERE tail_weight >= {least}"


def _simulated(ev: str, volume: str, runs: int = 20, q: float = 0.95) -> str:
    """Labels dealt by the rank of an md5, as in the Spark form; the quantile interpolates."""
    factor = f"({volume} / {core.F1.volume!r}::DOUBLE)"
    return f"""WITH {ev}, {core.sql_pairs(core.F1)}, slots AS (SELECT id, row_number() OVER (ORDER BY id) AS slot FROM ev),
 cards AS (SELECT r.run, e.type, row_number() OVER (PARTITION BY r.run ORDER BY md5(concat_ws('|', '0', r.run::VARCHAR, e.id::VARCHAR)), e.id) AS slot FROM ev e, range({runs}) r(run)),
 label AS (SELECT run, id, type FROM slots JOIN cards USING (slot)), n AS (SELECT run, type, count(*) AS c FROM label GROUP BY ALL),
 w AS (SELECT s.run, s.type AS a, d.type AS b, count(*) AS W FROM pairs p JOIN label s ON s.id = p.src_id JOIN label d ON d.id = p.dst_id AND d.run = s.run GROUP BY ALL),
 best AS (SELECT w.run, max(W * {factor} / (x.c::DOUBLE * y.c)) AS m FROM w JOIN n x ON x.run = w.run AND x.type = w.a JOIN n y ON y.run = w.run AND y.type = w.b GROUP BY w.run)
SELECT run, round(m, 9) AS max_ratio, round((SELECT quantile_cont(m, {q}) FROM best), 9) AS threshold FROM best"""
