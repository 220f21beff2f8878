"""Registered queries over the given tables, and the same in DuckDB SQL."""

from __future__ import annotations

import math
import uuid
from collections.abc import Callable
from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from stseq import density, metrics, mining, neighbours, sequences
from stseq.microcluster import cluster
from stseq.microcluster.features import diameter_cf, diameter_pairwise
from stseq.model import ClusterSpec, MineOptions, NeighbourhoodSpec, SpaceSpec, as_points, clusters_as_points
from stseq.ranks import with_rank
from stseq.sources import abnormal, tables
from stseq.sources.planted import planted_from_events, with_planted
from stseq.storage import stored

HOUR = tables.HOUR
DAY = 24 * HOUR
F1 = NeighbourhoodSpec(R=10, T=DAY)
F1_MC = NeighbourhoodSpec(R=10.0001, T=DAY)
F1_LINE = NeighbourhoodSpec(R=10, T=HOUR, dims=1)
F3 = NeighbourhoodSpec(R=1.0, T=30)
F5 = NeighbourhoodSpec(R=0.5, T=2, dims=1)
F6 = NeighbourhoodSpec(R=0.1, T=50)
F7 = NeighbourhoodSpec(R=10, T=30)
F8 = NeighbourhoodSpec(R=1, T=1)
F3_MC = ClusterSpec(d_s=2.5, d_t=30, K=20, normalise="range", order_by="time_place")
GRID = ClusterSpec(d=10, method="grid", time_unit=HOUR)
THETA = 5.0
Query = Callable[[SparkSession, str], DataFrame]


# ---- fixtures -------------------------------------------------------------------------------------------------

def f1(spark: SparkSession, sf: str) -> DataFrame:
    return tables.events_from_events(spark, sf)


def f2(spark: SparkSession, sf: str) -> DataFrame:
    return planted_from_events(f1(spark, sf))


def f3(spark: SparkSession, sf: str) -> DataFrame:
    return abnormal.abnormal_events(tables.observations_from_lineitem(spark, sf), drop=[("Balance", "Low")])


def f4(spark: SparkSession, sf: str) -> DataFrame:
    """The abnormal events and a three-step chain planted on the high prices of every tenth day (whole cells and days)."""
    base = abnormal.abnormal_events(tables.observations_from_lineitem(spark, sf), drop=[("Balance", "Low")])
    roots, _ = with_rank(base.where("type = 'HighPrice' and t % 10 = 0").select("t", "x", "y", "value"), ["t", "x", "y", "value"], "i")
    return with_planted(base.select("id", "type", "x", "y", "t"), roots.select("i", "x", "y", "t"), length=3, cell=0.5, span=1, lag_unit=1, lags=29)


def events_volume(spark: SparkSession, sf: str) -> SpaceSpec:
    return tables.events_space(f1(spark, sf))


def lattice_space(points: DataFrame, pad: float = 1.0) -> SpaceSpec:
    """From 0 (or the least value) to the largest value and one step more."""
    r = points.agg(F.max("x"), F.max("y"), F.min("t"), F.max("t")).first()
    return SpaceSpec(x0=0, x1=float(r[0]) + pad, y0=0, y1=float(r[1]) + pad, t0=float(r[2]), t1=float(r[3]) + 1)


def links(matrix: DataFrame) -> DataFrame:
    return matrix.select("src_type", "dst_type", F.col("W").cast("bigint").alias("W"), "src_n", "dst_n", F.round("ratio", 6).alias("ratio"))


def pair_counts(pairs: DataFrame) -> DataFrame:
    return pairs.groupBy("src_type", "dst_type").agg(F.count("*").alias("pairs"))


# ---- SQL building blocks ---------------------------------------------------------------------------------------

SQL_F1 = """ev AS (SELECT event_id AS id, event_type AS type, user_id AS x, CAST(json_extract_string(props, '$.k') AS BIGINT) AS y,
 date_diff('microsecond', TIMESTAMP '2024-01-01', ts) AS t, 1 AS w, value FROM events)"""
SQL_F5 = "ev AS (SELECT conv_id * 1000 + turn AS id, role AS type, conv_id AS x, 0 AS y, turn AS t, 1 AS w FROM conversations)"
SQL_F6 = "ev AS (SELECT vec_id AS id, CAST(label AS VARCHAR) AS type, CAST(embedding[1] AS DOUBLE) AS x, CAST(embedding[2] AS DOUBLE) AS y, vec_id AS t, 1 AS w FROM embeddings)"
SQL_F7 = "ev AS (SELECT row_number() OVER () AS id, l_returnflag || l_linestatus AS type, l_partkey AS x, l_suppkey AS y, date_diff('day', DATE '1992-01-01', CAST(l_shipdate AS DATE)) AS t, 1 AS w FROM lineitem)"
SQL_F8 = """ev AS (SELECT o_orderkey AS id, o_orderpriority AS type, n_regionkey AS x, c_nationkey AS y, date_diff('day', DATE '1992-01-01', CAST(o_orderdate AS DATE)) AS t, 1 AS w
 FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey)"""
SQL_OBS = """obs AS (SELECT l_orderkey, l_partkey, l_suppkey, l_linenumber, l_shipdate, (l_suppkey % 10) * 0.5::DOUBLE AS x, (l_suppkey // 10) * 0.5::DOUBLE AS y,
 date_diff('day', DATE '1992-01-01', CAST(l_shipdate AS DATE)) AS t, v.variable, v.value
 FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey,
 LATERAL (VALUES ('Price', CAST(l_extendedprice AS DOUBLE)), ('Order', CAST(o_totalprice AS DOUBLE)), ('Balance', CAST(c_acctbal AS DOUBLE))) AS v(variable, value)),
 bounds AS (SELECT variable, quantile_disc(value, 0.01) AS low_q, quantile_disc(value, 0.99) AS high_q FROM obs GROUP BY variable)"""
SQL_F3 = SQL_OBS + """, ev AS (SELECT row_number() OVER () AS id, CASE WHEN value > high_q THEN 'High' ELSE 'Low' END || variable AS type, x, y, t, 1 AS w
 FROM obs JOIN bounds USING (variable) WHERE value > high_q OR (value <= low_q AND variable <> 'Balance'))"""


def _h(what: str, j: int) -> str:
    return f"('0x' || substr(md5('{what}{j}|' || CAST(i AS VARCHAR)), 1, 8))::BIGINT"


def sql_f4() -> str:
    """The abnormal events as ``ev`` and the chain P1 -> P2 -> P3 on the high prices of every tenth day."""
    out = SQL_OBS + """, base AS (SELECT row_number() OVER () AS id, CASE WHEN value > high_q THEN 'High' ELSE 'Low' END || variable AS type, x, y, t, value
 FROM obs JOIN bounds USING (variable) WHERE value > high_q OR (value <= low_q AND variable <> 'Balance')),
 p1 AS (SELECT row_number() OVER (ORDER BY t, x, y, value) - 1 AS i, x, y, t FROM base WHERE type = 'HighPrice' AND t % 10 = 0)"""
    for j in (2, 3):
        h = {k: _h(k, j).replace("CAST(i", "CAST(c.i") for k in ("pa", "dx", "dy", "dt")}
        out += f""", p{j} AS (SELECT c.i, p.x + ({h['dx']} % 3 - 1) * 0.5::DOUBLE AS x, p.y + ({h['dy']} % 3 - 1) * 0.5::DOUBLE AS y, p.t + 1 + {h['dt']} % 29 AS t
 FROM p1 c JOIN p{j - 1} p ON p.i = {h['pa']} % (SELECT count(*) FROM p1))"""
    parts = " UNION ALL ".join(f"SELECT {1_000_000_000 * (1 + j)} + i, 'P{j}', x, y, t, 1 FROM p{j}" for j in (1, 2, 3))
    return out + f", ev AS (SELECT id, type, x, y, t, 1 AS w FROM base UNION ALL {parts})"


def sql_f2(length: int = 4, modulus: int = 50) -> str:
    out = SQL_F1.replace("ev AS", "base AS") + f", p1 AS (SELECT id // {modulus} AS i, x, y, t FROM base WHERE id % {modulus} = 0)"
    for j in range(2, length + 1):
        out += f""", p{j} AS (SELECT c.i, p.x + {_h('dx', j).replace('CAST(i', 'CAST(c.i')} % 15 - 7 AS x, p.y + {_h('dy', j).replace('CAST(i', 'CAST(c.i')} % 15 - 7 AS y,
 p.t + 1 + ({_h('dt', j).replace('CAST(i', 'CAST(c.i')} % 86400) * 1000000 AS t
 FROM p1 c JOIN p{j - 1} p ON p.i = {_h('pa', j).replace('CAST(i', 'CAST(c.i')} % (SELECT count(*) FROM p1))"""
    parts = " UNION ALL ".join(f"SELECT {1_000_000_000 * (1 + j)} + i, 'P{j}', x, y, t, 1 FROM p{j}" for j in range(1, length + 1))
    return out + f", ev AS (SELECT id, type, x, y, t, w FROM base UNION ALL {parts})"


def sql_match(spec: NeighbourhoodSpec, a: str = "a", b: str = "b") -> str:
    dist = f"({b}.x - {a}.x) * ({b}.x - {a}.x)" + (f" + ({b}.y - {a}.y) * ({b}.y - {a}.y)" if spec.dims > 1 else "")
    lag = f"({b}.t - {a}.t)"
    if spec.shape == "box":
        space = f"abs({b}.x - {a}.x) <= {spec.R} AND abs({b}.y - {a}.y) <= {spec.R}"
    elif spec.shape == "cone":
        space = f"({dist}) * {float(spec.T) ** 2!r}::DOUBLE <= {float(spec.R) ** 2!r}::DOUBLE * CAST({lag} - {spec.delay} AS DOUBLE) * CAST({lag} - {spec.delay} AS DOUBLE)"
    else:
        space = f"{dist} <= {spec.R * spec.R!r}::DOUBLE"
    lower = {"after": f"{b}.t > {a}.t + {spec.delay} AND ", "from_now": f"{b}.t >= {a}.t + {spec.delay} AND "}.get(spec.time_rule, "")
    return f"{lower}{b}.t <= {a}.t + {spec.delay + spec.T} AND {space} AND {a}.id <> {b}.id"


def sql_pairs(spec: NeighbourhoodSpec) -> str:
    return f"pairs AS (SELECT a.id AS src_id, a.type AS src_type, a.w AS src_w, b.id AS dst_id, b.type AS dst_type, b.w AS dst_w FROM ev a JOIN ev b ON {sql_match(spec)})"


def sql_counts(ev: str, spec: NeighbourhoodSpec) -> str:
    return f"WITH {ev}, {sql_pairs(spec)} SELECT src_type, dst_type, count(*) AS pairs FROM pairs GROUP BY ALL"


F1_VOLUME = f"((SELECT max(user_id) + 1 FROM events) * 100.0::DOUBLE * {720 * HOUR}::DOUBLE)"


def sql_ratio(ev: str, spec: NeighbourhoodSpec, volume: str) -> str:
    return f"""WITH {ev}, {sql_pairs(spec)}, n AS (SELECT type, sum(w)::BIGINT AS c FROM ev GROUP BY type),
 wt AS (SELECT src_type, dst_type, sum(src_w * dst_w)::BIGINT AS W FROM pairs GROUP BY ALL)
SELECT s.type AS src_type, d.type AS dst_type, coalesce(W, 0) AS W, s.c AS src_n, d.c AS dst_n,
 round(coalesce(W, 0) * ({volume} / {spec.volume!r}::DOUBLE) / (s.c::DOUBLE * d.c), 6) AS ratio
FROM n s CROSS JOIN n d LEFT JOIN wt ON wt.src_type = s.type AND wt.dst_type = d.type"""


LATTICE = "((SELECT max(x) + 1 FROM ev) * (SELECT (max(y) + 1)::DOUBLE FROM ev) * (SELECT (max(t) + 1 - min(t))::DOUBLE FROM ev))"


def sql_mine(ev: str, spec: NeighbourhoodSpec, volume: str, theta: float = THETA, length: int = 4, scope: str = "tail") -> str:
    """All significant chains up to ``length``, one block of CTEs for each length."""
    factor = f"({volume} / {spec.volume!r}::DOUBLE)"
    out = f"WITH {ev}, {sql_pairs(spec)}, n AS (SELECT type, sum(w)::BIGINT AS c FROM ev GROUP BY type), t1 AS (SELECT type AS pat, NULL::DOUBLE AS idx, type AS last, id, w FROM ev)"
    if scope == "type":
        out += f""", lk AS (SELECT p.src_type, p.dst_type, sum(src_w * dst_w) * {factor} / (any_value(s.c)::DOUBLE * any_value(d.c)) AS ratio
 FROM pairs p JOIN n s ON s.type = p.src_type JOIN n d ON d.type = p.dst_type GROUP BY p.src_type, p.dst_type)"""
    for k in range(2, length + 1):
        t = f"t{k - 1}"
        if scope == "type":
            score = f"SELECT DISTINCT t.pat, t.idx, lk.dst_type, lk.ratio FROM {t} t JOIN lk ON lk.src_type = t.last"
        else:
            score = f"""SELECT t.pat, any_value(t.idx) AS idx, p.dst_type, sum(t.w * p.dst_w) * {factor} / (any_value(s.total)::DOUBLE * any_value(n.c)) AS ratio
 FROM {t} t JOIN pairs p ON p.src_id = t.id JOIN (SELECT pat, sum(w) AS total FROM {t} GROUP BY pat) s ON s.pat = t.pat JOIN n ON n.type = p.dst_type GROUP BY t.pat, p.dst_type"""
        out += f""", s{k} AS (SELECT pat, dst_type, ratio, least(coalesce(idx, ratio), ratio) AS idx FROM ({score}) WHERE least(coalesce(idx, ratio), ratio) >= {theta}),
 t{k} AS (SELECT DISTINCT s.pat || ' -> ' || s.dst_type AS pat, s.idx, s.dst_type AS last, p.dst_id AS id, p.dst_w AS w
 FROM s{k} s JOIN {t} t ON t.pat = s.pat JOIN pairs p ON p.src_id = t.id AND p.dst_type = s.dst_type),
 r{k} AS (SELECT s.pat || ' -> ' || s.dst_type AS pattern, {k} AS length, round(s.idx, 6) AS seq_index, round(s.ratio, 6) AS last_ratio, x.tail_weight
 FROM s{k} s JOIN (SELECT pat, sum(w)::BIGINT AS tail_weight FROM t{k} GROUP BY pat) x ON x.pat = s.pat || ' -> ' || s.dst_type)"""
    return out + " " + " UNION ALL ".join(f"SELECT * FROM r{k}" for k in range(2, length + 1))


SIDE = 10 / math.sqrt(3)


def sql_grid(ev: str, d: float = 10, name: str = "mc", with_ev: bool = True) -> str:
    side = d / math.sqrt(3)
    cell = f"floor(x / {side!r}::DOUBLE) AS cx, floor(y / {side!r}::DOUBLE) AS cy, floor((t / {float(HOUR)!r}::DOUBLE) / {side!r}::DOUBLE) AS ct"
    return f"{ev}, cells AS (SELECT *, {cell} FROM ev), {name} AS (SELECT type, cx, cy, ct, count(*) AS n, avg(x) AS x, avg(y) AS y, avg(t::DOUBLE) AS t FROM cells GROUP BY type, cx, cy, ct)"


def grid_mc(spark: SparkSession, sf: str, events: Callable = f1) -> tuple[DataFrame, DataFrame]:
    return cluster(events(spark, sf), GRID)


# ---- queries -------------------------------------------------------------------------------------------------

#: The clustering that scales: space-time tiles of 100 hours, users and keys, merged across their borders.
TILED = ClusterSpec(d=5, time_unit=HOUR, tile=100, merge_borders=True)


def _mine_mc(clustering: ClusterSpec) -> Query:
    def run(spark: SparkSession, sf: str) -> DataFrame:
        result = mining.mine_microclusters(f2(spark, sf), clustering, F1_MC, events_volume(spark, sf), MineOptions(theta=THETA, max_length=4))
        return mining.pattern_table(result.patterns)

    return run


def flagship(spark: SparkSession, sf: str) -> DataFrame:
    """Microcluster miner on the planted events: incremental clusters in tiles, then all significant chains."""
    return _mine_mc(TILED)(spark, sf)


def _pairs(spec: NeighbourhoodSpec, source: Callable = f1, how: Callable = neighbours.pairs_grid) -> Query:
    return lambda spark, sf: pair_counts(how(source(spark, sf), spec))


def _ratios(source: Callable, spec: NeighbourhoodSpec, space: Callable | None = None) -> Query:
    def run(spark: SparkSession, sf: str) -> DataFrame:
        points = source(spark, sf)
        return links(density.ratio_matrix(points, spec, space(spark, sf) if space else lattice_space(points)))

    return run


def conversation_ratios(spark: SparkSession, sf: str) -> DataFrame:
    points = tables.events_from_conversations(spark, sf)
    n = points.agg(F.max("x")).first()[0] + 1
    return density.ratio_matrix(points, F5, SpaceSpec(x0=0, x1=float(n), t0=0, t1=8, dims=1))


def embedding_ratios(spark: SparkSession, sf: str) -> DataFrame:
    points = tables.events_from_embeddings(spark, sf)
    n = points.agg(F.max("t")).first()[0] + 1
    return links(density.ratio_matrix(points, F6, SpaceSpec(x0=-1, x1=1, y0=-1, y1=1, t0=0, t1=float(n))))


def local_density(spark: SparkSession, sf: str) -> DataFrame:
    events = f1(spark, sf)
    out = density.local_density(neighbours.pairs_grid(events, F1), events, F1)
    return out.select("src_id", "src_type", "dst_type", F.col("W").cast("bigint").alias("W"), F.round(F.col("density") * 1e15, 3).alias("density_e15"))


def sequence_index_chain4(spark: SparkSession, sf: str) -> DataFrame:
    out = sequences.sequence_index(f2(spark, sf), ["P1", "P2", "P3", "P4"], F1, events_volume(spark, sf))
    return out.select("position", "src_type", "dst_type", F.round("ratio", 6).alias("ratio"), F.round("seq_index", 6).alias("seq_index"))


def tail_set_chain4(spark: SparkSession, sf: str) -> DataFrame:
    return sequences.tail_set(f2(spark, sf), ["P1", "P2", "P3", "P4"], F1).select("id")


def _mine(opts: MineOptions, join: str = "grid") -> Query:
    return lambda spark, sf: mining.pattern_table(mining.mine_instances(f2(spark, sf), F1, events_volume(spark, sf), opts).patterns)


def _mine_grid_mc(opts: MineOptions) -> Query:
    def run(spark: SparkSession, sf: str) -> DataFrame:
        mc, _ = grid_mc(spark, sf, f2)
        return mining.pattern_table(mining.mine_index(clusters_as_points(mc), F1_MC, events_volume(spark, sf), opts).patterns)

    return run


def identity_bridge(spark: SparkSession, sf: str) -> DataFrame:
    spec = ClusterSpec(method="identity")
    return mining.pattern_table(mining.mine_microclusters(f2(spark, sf), spec, F1, events_volume(spark, sf), MineOptions(theta=THETA, max_length=4)).patterns)


def grid_microclusters(spark: SparkSession, sf: str) -> DataFrame:
    mc, _ = grid_mc(spark, sf)
    return mc.select("type", "n", F.round("x", 6).alias("x"), F.round("y", 6).alias("y"), F.round(F.col("t") / HOUR, 6).alias("t_hours"))


def grid_mc_members(spark: SparkSession, sf: str) -> DataFrame:
    _, members = grid_mc(spark, sf)
    sizes = members.groupBy("cid").agg(F.count("*").alias("n"), F.min("id").alias("first"))
    return members.join(sizes, "cid").select("id", "n", "first")


def grid_mc_diameter(spark: SparkSession, sf: str) -> DataFrame:
    """Diameters above zero at d=20, additive form; the oracle takes all pairs of members."""
    mc, members = cluster(f1(spark, sf), ClusterSpec(d=20, method="grid", time_unit=HOUR))
    first = members.groupBy("cid").agg(F.min("id").alias("first"))
    return mc.where("n > 1").join(first, "cid").select("first", "n", F.round(diameter_cf(F.col("n"), F.col("ss")), 6).alias("diameter"))


def grid_mc_diameter_pairwise(spark: SparkSession, sf: str) -> DataFrame:
    _, members = cluster(f1(spark, sf), ClusterSpec(d=20, method="grid", time_unit=HOUR))
    placed = members.join(f1(spark, sf).select("id", "x", "y", (F.col("t") / HOUR).alias("t")), "id")
    first = members.groupBy("cid").agg(F.min("id").alias("first"), F.count("*").alias("n")).where("n > 1")
    return diameter_pairwise(placed, ["x", "y", "t"]).join(first, "cid").select("first", "n", F.round("diameter", 6).alias("diameter"))


def grid_mc_compression(spark: SparkSession, sf: str) -> DataFrame:
    parts = None
    for d in (5, 10, 20):
        mc, _ = cluster(f1(spark, sf), ClusterSpec(d=d, method="grid", time_unit=HOUR))
        row = mc.agg(F.count("*").alias("index_size"), F.round(F.sum("n") / F.count("*"), 6).alias("compression")).select(F.lit(d).alias("d"), "index_size", "compression")
        parts = row if parts is None else parts.unionByName(row)
    return parts


def duplicate_clusters(spark: SparkSession, sf: str) -> DataFrame:
    mc, _ = cluster(tables.events_from_orders(spark, sf), ClusterSpec(method="duplicates"))
    return mc.select("type", "x", "y", "t", "n")


def cluster_neighbours(spark: SparkSession, sf: str) -> DataFrame:
    mc, members = grid_mc(spark, sf)
    first = members.groupBy("cid").agg(F.min("id").alias("first"))
    pairs = neighbours.pairs_grid(clusters_as_points(mc), F1_MC)
    a, b = first.select(F.col("cid").alias("src_id"), F.col("first").alias("src_first")), first.select(F.col("cid").alias("dst_id"), F.col("first").alias("dst_first"))
    return pairs.join(a, "src_id").join(b, "dst_id").select("src_first", "dst_first", "src_w", "dst_w")


def covered_instances(spark: SparkSession, sf: str) -> DataFrame:
    mc, members = grid_mc(spark, sf)
    first = members.groupBy("cid").agg(F.min("id").alias("first")).select(F.col("cid").alias("src_id"), "first")
    covered = neighbours.covered_instances(neighbours.pairs_grid(clusters_as_points(mc), F1_MC), members)
    return covered.groupBy("src_id").agg(F.count("*").alias("covered")).join(first, "src_id").select(F.col("first").alias("src_first"), "covered")


def weighted_density(spark: SparkSession, sf: str) -> DataFrame:
    mc, _ = grid_mc(spark, sf, f2)
    out = density.type_density(clusters_as_points(mc), events_volume(spark, sf))
    return out.select("type", "N", F.round(F.col("density") * 1e15, 6).alias("density_e15"))


def ratio_matrix_grid_mc(spark: SparkSession, sf: str) -> DataFrame:
    mc, _ = grid_mc(spark, sf, f2)
    return links(density.ratio_matrix(clusters_as_points(mc), F1_MC, events_volume(spark, sf)))


def mc_conservation(spark: SparkSession, sf: str) -> DataFrame:
    events = f1(spark, sf)
    _, members = cluster(events, ClusterSpec(d=20, K=10, time_unit=HOUR))
    return metrics.conservation(events, members)


def mc_bounds(spark: SparkSession, sf: str) -> DataFrame:
    """Clusters above the size limit or (split until they fit) above the diameter: none."""
    mc, _ = cluster(f1(spark, sf), ClusterSpec(d=20, K=10, recheck="until_fit", time_unit=HOUR))
    bad = (F.col("n") > 10) | (diameter_cf(F.col("n"), F.col("ss")) > 20 + 1e-9)
    return mc.groupBy("type").agg(F.sum("n").alias("events"), F.sum(F.when(bad, 1).otherwise(0)).alias("violations"))


def _incremental(spec: ClusterSpec, source: Callable = f1) -> Query:
    def run(spark: SparkSession, sf: str) -> DataFrame:
        mc, _ = cluster(source(spark, sf), spec)
        unit = F.lit(float(spec.time_unit))
        return mc.select("type", "n", F.round("x", 6).alias("x"), F.round("y", 6).alias("y"), F.round(F.col("t") / unit, 6).alias("t"), F.round("ss", 6).alias("ss"))

    return run


def mc_index_sweep(spark: SparkSession, sf: str) -> DataFrame:
    """Index size and compression of gridded abnormal events against the size limit K."""
    events = stored(f3(spark, sf), "abnormal")
    rows = []
    for k in (20, 40, 60, 80, 100):
        mc, _ = cluster(events, replace(F3_MC, K=k))
        r = mc.agg(F.count("*"), F.sum("n")).first()
        rows.append((k, r[0], (r[1] or 0) / max(r[0], 1)))
    return spark.createDataFrame(rows, "K int, index_size bigint, compression double")


def abnormal_thresholds(spark: SparkSession, sf: str) -> DataFrame:
    return abnormal.thresholds(tables.observations_from_lineitem(spark, sf)).select("variable", "low_q", "high_q")


def abnormal_events(spark: SparkSession, sf: str) -> DataFrame:
    return f3(spark, sf).select("type", "x", "y", "t", "value")


def mine_abnormal_planted(spark: SparkSession, sf: str) -> DataFrame:
    """Chains of abnormal events at threshold 1, which independent ones do not reach: the planted ones of lengths 2, 2 and 3 must be among them."""
    points = stored(f4(spark, sf), "abnormal")
    found = mining.mine_instances(points, F3, lattice_space(points), MineOptions(theta=1.0, max_length=4)).patterns
    return mining.pattern_table(found)


def planted_recall(spark: SparkSession, sf: str) -> DataFrame:
    found = mining.mine_instances(f2(spark, sf), F1, events_volume(spark, sf), MineOptions(theta=THETA, max_length=4)).patterns
    planted = spark.createDataFrame([(["P1", "P2", "P3", "P4"],)], "seq array<string>")
    return metrics.recall_of(metrics.sub_chains(planted), found).select("length", "expected", "found", "recall")


def maximal_patterns(spark: SparkSession, sf: str) -> DataFrame:
    found = mining.mine_instances(f2(spark, sf), F1, events_volume(spark, sf), MineOptions(theta=THETA, max_length=4)).patterns
    return mining.pattern_table(sequences.maximal(found))


def top_k_patterns(spark: SparkSession, sf: str) -> DataFrame:
    found = mining.mine_instances(f2(spark, sf), F1, events_volume(spark, sf), MineOptions(theta=THETA, max_length=4)).patterns
    return mining.pattern_table(sequences.top_k_patterns(found, 5))


def _miner_difference(opts: MineOptions) -> Query:
    """Chains that the search on events finds and the search on grid clusters does not."""
    return lambda spark, sf: _mine(opts)(spark, sf).select("pattern").exceptAll(_mine_grid_mc(opts)(spark, sf).select("pattern"))


def simulate_threshold(spark: SparkSession, sf: str) -> DataFrame:
    out = sequences.simulate_threshold(f1(spark, sf), F1, events_volume(spark, sf), runs=20)
    return out.select("run", F.round("max_ratio", 9).alias("max_ratio"), F.round("threshold", 9).alias("threshold"))


def asof_previous_cause(spark: SparkSession, sf: str) -> DataFrame:
    """For each purchase the user's last click at or before it."""
    events = f1(spark, sf).where(F.col("type").isin("click", "purchase"))
    order = Window.partitionBy("x").orderBy("t", F.when(F.col("type") == "click", 0).otherwise(1))
    last = F.last(F.when(F.col("type") == "click", F.col("t")), ignorenulls=True).over(order)
    return events.withColumn("cause_t", last).where("type = 'purchase'").select("id", "cause_t")


def type_gap_stats(spark: SparkSession, sf: str) -> DataFrame:
    """Time between successive events of one user."""
    order = Window.partitionBy("x").orderBy("t", "id")
    gaps = f1(spark, sf).withColumn("gap", F.col("t") - F.lag("t").over(order)).where("gap is not null")
    return gaps.groupBy("type").agg(F.count("*").alias("gaps"), F.min("gap").alias("least"), F.max("gap").alias("most"), F.round(F.avg("gap"), 3).alias("mean"))


def rolling_counts(spark: SparkSession, sf: str) -> DataFrame:
    """For each event how many the user had in the day before it."""
    span = Window.partitionBy("x").orderBy("t").rangeBetween(-DAY, 0)
    return f1(spark, sf).select("id", F.count("*").over(span).alias("day_count"))


def hourly_cube(spark: SparkSession, sf: str) -> DataFrame:
    day = F.expr(f"cast(t div {DAY} as bigint)")
    return f1(spark, sf).withColumn("day", day).cube("type", "day").agg(F.count("*").alias("n"), F.countDistinct("x").alias("users"))


def rank_links(spark: SparkSession, sf: str) -> DataFrame:
    matrix = density.ratio_matrix(f1(spark, sf), F1, events_volume(spark, sf))
    order = Window.partitionBy("src_type").orderBy(F.desc("W"), "dst_type")
    return matrix.select("src_type", "dst_type", F.col("W").cast("bigint").alias("W"), F.rank().over(Window.partitionBy("src_type").orderBy(F.desc("W"))).alias("rank"), F.row_number().over(order).alias("place"), F.ntile(2).over(order).alias("half"))


def relation_sign(spark: SparkSession, sf: str) -> DataFrame:
    return conversation_ratios(spark, sf).select("src_type", "dst_type", density.relation_sign(F.col("ratio"), 0.05).alias("relation"))


def edge_corrected(spark: SparkSession, sf: str) -> DataFrame:
    out = density.ratio_matrix(f1(spark, sf), replace(F1, edge_correction="clip_box"), events_volume(spark, sf))
    return out.select("src_type", "dst_type", F.col("W").cast("bigint").alias("W"), F.round("ratio", 6).alias("ratio"))


def stream_pairs(spark: SparkSession, sf: str) -> DataFrame:
    from stseq.storage import shared_dir
    from stseq.streaming import events as s

    folder = f"{shared_dir(spark)}/stream-{uuid.uuid4().hex}"
    s.replay(f1(spark, sf).select("id", "type", "x", "y", "t"), f"{folder}/in")
    spec = NeighbourhoodSpec(R=10, T=6 * HOUR)
    return pair_counts(s.run_to_table(s.stream_pairs(s.read_stream(spark, f"{folder}/in"), spec, "3 days"), folder))


def stream_density(spark: SparkSession, sf: str) -> DataFrame:
    from stseq.storage import shared_dir
    from stseq.streaming import events as s

    folder = f"{shared_dir(spark)}/density-{uuid.uuid4().hex}"
    s.replay(f1(spark, sf).select("id", "type", "x", "y", "t"), f"{folder}/in")
    out = s.run_to_table(s.stream_density(s.read_stream(spark, f"{folder}/in"), late="3 days"), folder, "update")
    # the last update of a window is its whole count
    return out.groupBy("start", "type").agg(F.max("n").alias("n")).select(F.date_format("start", "yyyy-MM-dd").alias("day"), "type", "n")


def stream_clusters(spark: SparkSession, sf: str) -> DataFrame:
    """Final state of the clusters kept by the stream."""
    from stseq.storage import shared_dir
    from stseq.streaming import events as s

    before = spark.conf.get("spark.sql.streaming.stateStore.providerClass", None)
    folder = f"{shared_dir(spark)}/clusters-{uuid.uuid4().hex}"
    s.replay(f1(spark, sf).select("id", "type", "x", "y", "t"), f"{folder}/in", 2)
    s.use_rocksdb(spark)
    try:
        out = s.run_to_table(s.stream_clusters(s.read_stream(spark, f"{folder}/in"), 20.0, 500.0, HOUR), folder, "update")
    finally:
        if before:
            spark.conf.set("spark.sql.streaming.stateStore.providerClass", before)
    return out.groupBy("type", "tile", "cid").agg(F.max_by("ss", "n").alias("ss"), F.max("n").alias("n")).select("type", "n", F.round("ss", 4).alias("ss"))


def queries() -> dict[str, Query]:
    from stseq import queries_clusters, queries_methods

    after_or_now = replace(F8, time_rule="from_now")
    return queries_clusters.queries() | queries_methods.queries() | {
        "flagship": flagship,
        "space_volume": lambda s, d: s.createDataFrame([(SpaceSpec.from_data(f1(s, d)).volume / DAY,)], "volume double").select(F.round("volume", 3).alias("volume_days")),
        "type_density": lambda s, d: density.type_density(f1(s, d), events_volume(s, d)).select("type", "N", F.round(F.col("density") * 1e15, 6).alias("density_e15")),
        "pairs_nested_count": _pairs(F1, how=neighbours.pairs_nested_loop),
        "pairs_grid_count": _pairs(F1),
        "pairs_sweep_count": _pairs(F1, how=neighbours.pairs_sweep),
        "pairs_window_count": _pairs(replace(F1, T=6 * HOUR), how=lambda e, n: neighbours.pairs_window(e, n, tile=60)),
        "pair_weights_cells": lambda s, d: neighbours.pair_weights_cells(f1(s, d), F1).select("src_type", "dst_type", F.col("W").cast("bigint").alias("pairs")),
        "pairs_cone": _pairs(replace(F1, shape="cone")),
        "pairs_box": _pairs(replace(F1, shape="box")),
        "pairs_1d": _pairs(F1_LINE, tables.events_from_events_1d),
        "pairs_from_now": _pairs(after_or_now, tables.events_from_orders),
        "pairs_delayed": _pairs(replace(F3, delay=7), f3),
        "pairs_upper_only": _pairs(replace(F5, time_rule="upper_only"), tables.events_from_conversations, neighbours.pairs_nested_loop),
        "local_density": local_density,
        "ratio_matrix_events": _ratios(f1, F1, events_volume),
        "ratio_matrix_lineitem": _ratios(tables.events_from_lineitem, F7),
        "ratio_matrix_orders": _ratios(tables.events_from_orders, F8),
        "ratio_matrix_planted": _ratios(f2, F1, events_volume),
        "ratio_matrix_abnormal": _ratios(f3, F3),
        "ratio_matrix_conversations": lambda s, d: links(conversation_ratios(s, d)),
        "ratio_matrix_embeddings": embedding_ratios,
        "ratio_matrix_edge_corrected": edge_corrected,
        "relation_sign": relation_sign,
        "sequence_index_chain4": sequence_index_chain4,
        "tail_set_chain4": tail_set_chain4,
        "mine_instances_tail": _mine(MineOptions(theta=THETA, max_length=4)),
        "mine_instances_type": _mine(MineOptions(theta=THETA, max_length=3, ratio_scope="type")),
        "mine_instances_type_whole": _mine(MineOptions(theta=THETA, ratio_scope="type")),
        "mine_instances_sweep": _mine(MineOptions(theta=THETA, max_length=4, join="sweep")),
        "grid_microclusters": grid_microclusters,
        "grid_mc_members": grid_mc_members,
        "grid_mc_diameter": grid_mc_diameter,
        "grid_mc_diameter_pairwise": grid_mc_diameter_pairwise,
        "grid_mc_compression": grid_mc_compression,
        "duplicate_clusters": duplicate_clusters,
        "cluster_neighbours": cluster_neighbours,
        "covered_instances": covered_instances,
        "weighted_density": weighted_density,
        "ratio_matrix_grid_mc": ratio_matrix_grid_mc,
        "mine_grid_mc": _mine_grid_mc(MineOptions(theta=THETA, max_length=3)),
        "mine_grid_mc_whole": _mine_grid_mc(MineOptions(theta=THETA)),
        "identity_bridge": identity_bridge,
        "mc_conservation": mc_conservation,
        "mc_bounds": mc_bounds,
        "mc_incremental_d": _incremental(ClusterSpec(d=20, time_unit=HOUR)),
        "mc_incremental_dk": _incremental(F3_MC, f3),
        "mc_incremental_tiled": _incremental(ClusterSpec(d=20, time_unit=HOUR, tile=200, merge_borders=True)),
        "mc_index_sweep": mc_index_sweep,
        "mine_microclusters": _mine_mc(ClusterSpec(d=5, time_unit=HOUR)),
        "mine_abnormal_planted": mine_abnormal_planted,
        "abnormal_thresholds": abnormal_thresholds,
        "abnormal_events": abnormal_events,
        "event_projection_events": lambda s, d: f1(s, d),
        "event_projection_lineitem": lambda s, d: tables.events_from_lineitem(s, d).drop("id"),
        "event_projection_orders": lambda s, d: tables.events_from_orders(s, d),
        "event_projection_conversations": lambda s, d: tables.events_from_conversations(s, d),
        "event_projection_embeddings": lambda s, d: tables.events_from_embeddings(s, d),
        "simulate_threshold": simulate_threshold,
        "planted_events": lambda s, d: f2(s, d),
        "planted_recall": planted_recall,
        "maximal_patterns": maximal_patterns,
        "top_k_patterns": top_k_patterns,
        "miner_difference": _miner_difference(MineOptions(theta=THETA, max_length=3)),
        "miner_difference_whole": _miner_difference(MineOptions(theta=THETA)),
        "asof_previous_cause": asof_previous_cause,
        "type_gap_stats": type_gap_stats,
        "rolling_counts": rolling_counts,
        "hourly_cube": hourly_cube,
        "rank_links": rank_links,
        "stream_pairs": stream_pairs,
        "stream_density": stream_density,
        "stream_clusters": stream_clusters,
    }


def oracle_sql() -> dict[str, str]:
    from stseq import queries_clusters, queries_methods

    f2_sql = sql_f2()
    counts = sql_counts(SQL_F1, F1)
    mined = sql_mine(f2_sql, F1, F1_VOLUME)
    grid = sql_grid(SQL_F1)
    grid2 = sql_grid(f2_sql)
    mc_ev = ", evmc AS (SELECT row_number() OVER () AS id, type, x, y, t, n AS w FROM mc)"
    first = "fm AS (SELECT type, cx, cy, ct, min(id) AS first FROM cells GROUP BY ALL)"
    mc_first = f"WITH {grid}, {first}, q AS (SELECT mc.*, fm.first AS id, n AS w FROM mc JOIN fm USING (type, cx, cy, ct))"
    on_mc = sql_match(F1_MC)
    grid_mine = sql_mine(f"{grid2.replace('ev AS (SELECT id, type, x, y, t, w FROM base', 'evs AS (SELECT id, type, x, y, t, w FROM base').replace('FROM ev)', 'FROM evs)')}, ev AS (SELECT row_number() OVER () AS id, type, x, y, t, n AS w FROM mc)", F1_MC, F1_VOLUME, length=3)
    grid_ratio = sql_ratio(f"{grid2.replace('ev AS (SELECT id, type, x, y, t, w FROM base', 'evs AS (SELECT id, type, x, y, t, w FROM base').replace('FROM ev)', 'FROM evs)')}, ev AS (SELECT row_number() OVER () AS id, type, x, y, t, n AS w FROM mc)", F1_MC, F1_VOLUME)
    conv_volume = "((SELECT max(x) + 1 FROM ev) * 8.0::DOUBLE)"
    dup = f"WITH {SQL_F8} SELECT type, x::DOUBLE AS x, y::DOUBLE AS y, t::DOUBLE AS t, count(*) AS n FROM ev GROUP BY type, x, y, t"
    pairwise = f"""WITH {sql_grid(SQL_F1, 20)}, {first}, big AS (SELECT * FROM (SELECT *, count(*) OVER (PARTITION BY type, cx, cy, ct) AS n FROM cells) WHERE n > 1)
SELECT min(a.id) AS first, any_value(a.n) AS n, round(sqrt(sum((a.x - b.x) ** 2 + (a.y - b.y) ** 2 + ((a.t - b.t) / {float(HOUR)!r}::DOUBLE) ** 2) / (any_value(a.n) * (any_value(a.n) - 1))), 6) AS diameter
FROM big a JOIN big b USING (type, cx, cy, ct) GROUP BY type, cx, cy, ct"""
    clip = f"""WITH {SQL_F1}, {sql_pairs(F1)}, n AS (SELECT type, count(*) AS c FROM ev GROUP BY type), u AS (SELECT max(user_id) + 1 AS m FROM events),
 v AS (SELECT id, (least(x + 10, m) - greatest(x - 10, 0)) / 20.0::DOUBLE * ((least(y + 10, 100) - greatest(y - 10, 0)) / 20.0::DOUBLE)
 * ((least(t + {DAY}, {720 * HOUR}) - t)::DOUBLE / {float(DAY)!r}::DOUBLE) * {F1.volume!r}::DOUBLE AS vol FROM ev, u),
 wt AS (SELECT src_type, dst_type, count(*) AS W, sum(1 / vol) AS m FROM pairs JOIN v ON v.id = src_id GROUP BY ALL)
SELECT s.type AS src_type, d.type AS dst_type, coalesce(W, 0) AS W, round(coalesce(m, 0) / s.c / (d.c / {F1_VOLUME}), 6) AS ratio FROM n s CROSS JOIN n d LEFT JOIN wt ON wt.src_type = s.type AND wt.dst_type = d.type"""
    chain = f"""WITH {f2_sql}, {sql_pairs(F1)}, n AS (SELECT type, count(*) AS c FROM ev GROUP BY type), t1 AS (SELECT id, w FROM ev WHERE type = 'P1')"""
    for k in (2, 3, 4):
        chain += f""", t{k} AS (SELECT DISTINCT dst_id AS id, dst_w AS w FROM pairs JOIN t{k - 1} ON src_id = id WHERE dst_type = 'P{k}'),
 l{k} AS (SELECT {k - 1} AS position, 'P{k - 1}' AS src_type, 'P{k}' AS dst_type, count(*) * ({F1_VOLUME} / {F1.volume!r}::DOUBLE) / ((SELECT count(*) FROM t{k - 1})::DOUBLE * (SELECT c FROM n WHERE type = 'P{k}')) AS ratio FROM pairs JOIN t{k - 1} ON src_id = id WHERE dst_type = 'P{k}')"""
    chain_links = chain + " SELECT position, src_type, dst_type, round(ratio, 6) AS ratio, round(min(ratio) OVER (ORDER BY position), 6) AS seq_index FROM (SELECT * FROM l2 UNION ALL SELECT * FROM l3 UNION ALL SELECT * FROM l4)"
    return queries_clusters.oracle_sql() | queries_methods.oracle_sql() | {
        "space_volume": f"WITH {SQL_F1} SELECT round((max(x) - min(x))::DOUBLE * (max(y) - min(y)) * (max(t) - min(t)) / {float(DAY)!r}::DOUBLE, 3) AS volume_days FROM ev",
        "type_density": f"WITH {SQL_F1} SELECT type, count(*) AS N, round(count(*) / {F1_VOLUME} * 1e15, 6) AS density_e15 FROM ev GROUP BY type",
        "pairs_nested_count": counts, "pairs_grid_count": counts, "pairs_sweep_count": counts, "pair_weights_cells": counts,
        "pairs_window_count": sql_counts(SQL_F1, replace(F1, T=6 * HOUR)),
        "pairs_cone": sql_counts(SQL_F1, replace(F1, shape="cone")),
        "pairs_box": sql_counts(SQL_F1, replace(F1, shape="box")),
        "pairs_1d": sql_counts(SQL_F1, F1_LINE),
        "pairs_from_now": sql_counts(SQL_F8, replace(F8, time_rule="from_now")),
        "pairs_delayed": sql_counts(SQL_F3, replace(F3, delay=7)),
        "pairs_upper_only": sql_counts(SQL_F5, replace(F5, time_rule="upper_only")),
        "local_density": f"""WITH {SQL_F1}, {sql_pairs(F1)}, k AS (SELECT DISTINCT type FROM ev), p AS (SELECT src_id, dst_type, count(*) AS W FROM pairs GROUP BY ALL)
SELECT e.id AS src_id, e.type AS src_type, k.type AS dst_type, coalesce(p.W, 0) AS W, round(coalesce(p.W, 0) / {F1.volume!r}::DOUBLE * 1e15, 3) AS density_e15 FROM ev e CROSS JOIN k LEFT JOIN p ON p.src_id = e.id AND p.dst_type = k.type""",
        "ratio_matrix_events": sql_ratio(SQL_F1, F1, F1_VOLUME),
        "ratio_matrix_lineitem": sql_ratio(SQL_F7, F7, LATTICE),
        "ratio_matrix_orders": sql_ratio(SQL_F8, F8, LATTICE),
        "ratio_matrix_planted": sql_ratio(f2_sql, F1, F1_VOLUME),
        "ratio_matrix_abnormal": sql_ratio(SQL_F3, F3, LATTICE),
        "ratio_matrix_conversations": sql_ratio(SQL_F5, F5, conv_volume),
        "ratio_matrix_embeddings": sql_ratio(SQL_F6, F6, "(4.0::DOUBLE * (SELECT max(t) + 1 FROM ev))"),
        "ratio_matrix_edge_corrected": clip,
        "relation_sign": f"SELECT src_type, dst_type, CASE WHEN ratio > 1.05 THEN 'attract' WHEN ratio < 0.95 THEN 'repel' ELSE 'none' END AS relation FROM ({sql_ratio(SQL_F5, F5, conv_volume)})",
        "sequence_index_chain4": chain_links,
        "tail_set_chain4": chain + " SELECT id FROM t4",
        "mine_instances_tail": mined, "mine_instances_sweep": mined, "identity_bridge": mined,
        "mine_instances_type": sql_mine(f2_sql, F1, F1_VOLUME, length=3, scope="type"),
        "grid_microclusters": f"WITH {grid} SELECT type, n, round(x, 6) AS x, round(y, 6) AS y, round(t / {float(HOUR)!r}::DOUBLE, 6) AS t_hours FROM mc",
        "grid_mc_members": f"WITH {grid} SELECT id, count(*) OVER w AS n, min(id) OVER w AS first FROM cells WINDOW w AS (PARTITION BY type, cx, cy, ct)",
        "grid_mc_diameter": pairwise, "grid_mc_diameter_pairwise": pairwise,
        "grid_mc_compression": " UNION ALL ".join(f"(WITH {sql_grid(SQL_F1, d)} SELECT {d} AS d, count(*) AS index_size, round(sum(n) / count(*), 6) AS compression FROM mc)" for d in (5, 10, 20)),
        "duplicate_clusters": dup,
        "cluster_neighbours": f"{mc_first} SELECT a.id AS src_first, b.id AS dst_first, a.w AS src_w, b.w AS dst_w FROM q a JOIN q b ON {on_mc}",
        "covered_instances": f"{mc_first} SELECT a.id AS src_first, sum(b.n)::BIGINT AS covered FROM q a JOIN q b ON {on_mc} GROUP BY a.id",
        "weighted_density": f"WITH {grid2} SELECT type, sum(n)::BIGINT AS N, round(sum(n) / {F1_VOLUME} * 1e15, 6) AS density_e15 FROM mc GROUP BY type",
        "ratio_matrix_grid_mc": grid_ratio,
        "mine_grid_mc": grid_mine,
        "mc_conservation": f"WITH {SQL_F1} SELECT type, count(*) AS events, count(*) AS clustered_once FROM ev GROUP BY type",
        "mc_bounds": f"WITH {SQL_F1} SELECT type, count(*) AS events, 0 AS violations FROM ev GROUP BY type",
        "abnormal_thresholds": f"WITH {SQL_OBS} SELECT * FROM bounds",
        "abnormal_events": f"WITH {SQL_OBS} SELECT CASE WHEN value > high_q THEN 'High' ELSE 'Low' END || variable AS type, x, y, t, value FROM obs JOIN bounds USING (variable) WHERE value > high_q OR (value <= low_q AND variable <> 'Balance')",
        "event_projection_events": f"WITH {SQL_F1} SELECT id, type, x, y, t, value FROM ev",
        "event_projection_lineitem": f"WITH {SQL_F7} SELECT type, x, y, t FROM ev",
        "event_projection_orders": f"WITH {SQL_F8} SELECT id, type, x, y, t FROM ev",
        "event_projection_conversations": f"WITH {SQL_F5} SELECT id, type, x, t FROM ev",
        "event_projection_embeddings": f"WITH {SQL_F6} SELECT id, type, x, y, t FROM ev",
        "planted_events": f"WITH {f2_sql} SELECT id, type, x, y, t FROM ev",
        "planted_recall": f"SELECT length, max(5 - length) AS expected, count(*) AS found, count(*) / max(5 - length)::DOUBLE AS recall FROM ({mined}) WHERE pattern IN ('P1 -> P2', 'P2 -> P3', 'P3 -> P4', 'P1 -> P2 -> P3', 'P2 -> P3 -> P4', 'P1 -> P2 -> P3 -> P4') GROUP BY length",
        "maximal_patterns": f"WITH m AS ({mined}) SELECT * FROM m WHERE NOT EXISTS (SELECT 1 FROM m o WHERE o.length > m.length AND contains(' -> ' || o.pattern || ' -> ', ' -> ' || m.pattern || ' -> '))",
        "top_k_patterns": f"SELECT * FROM ({mined}) ORDER BY seq_index DESC, length, pattern LIMIT 5",
        "miner_difference": f"SELECT pattern FROM ({sql_mine(f2_sql, F1, F1_VOLUME, length=3)}) EXCEPT ALL SELECT pattern FROM ({grid_mine})",
        "asof_previous_cause": f"WITH {SQL_F1} SELECT p.id, c.t AS cause_t FROM (SELECT * FROM ev WHERE type = 'purchase') p ASOF LEFT JOIN (SELECT * FROM ev WHERE type = 'click') c ON p.x = c.x AND p.t >= c.t",
        "type_gap_stats": f"WITH {SQL_F1}, g AS (SELECT type, t - lag(t) OVER (PARTITION BY x ORDER BY t, id) AS gap FROM ev) SELECT type, count(*) AS gaps, min(gap) AS least, max(gap) AS most, round(avg(gap), 3) AS mean FROM g WHERE gap IS NOT NULL GROUP BY type",
        "rolling_counts": f"WITH {SQL_F1} SELECT id, count(*) OVER (PARTITION BY x ORDER BY t RANGE BETWEEN {DAY} PRECEDING AND CURRENT ROW) AS day_count FROM ev",
        "hourly_cube": f"WITH {SQL_F1}, d AS (SELECT *, t // {DAY} AS day FROM ev) SELECT type, day, count(*) AS n, count(DISTINCT x) AS users FROM d GROUP BY CUBE (type, day)",
        "rank_links": f"SELECT src_type, dst_type, W, rank() OVER (PARTITION BY src_type ORDER BY W DESC) AS rank, row_number() OVER v AS place, ntile(2) OVER v AS half FROM ({sql_ratio(SQL_F1, F1, F1_VOLUME)}) WINDOW v AS (PARTITION BY src_type ORDER BY W DESC, dst_type)",
        "stream_pairs": sql_counts(SQL_F1, NeighbourhoodSpec(R=10, T=6 * HOUR)),
        "stream_density": f"WITH {SQL_F1} SELECT strftime(TIMESTAMP '2024-01-01' + to_microseconds(t), '%Y-%m-%d') AS day, type, count(*) AS n FROM ev GROUP BY ALL",
    }
