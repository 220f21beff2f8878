"""Registered queries of the incremental clusterings, the search on their clusters and the sweeps over generated data.

The oracle runs the clustering as recursive DuckDB SQL (:mod:`stseq.cluster_sql`), event by event.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import replace
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from stseq import cluster_sql, experiments, metrics, mining, queries as core
from stseq.microcluster import absorb, cluster
from stseq.model import ClusterSpec, MineOptions, NeighbourhoodSpec, SpaceSpec, clusters_as_points
from stseq.ranks import with_rank
from stseq.sources import tables
from stseq.sources.planted import planted_chains, planted_events, planted_on_rows
from stseq.storage import stored

HOUR = core.HOUR
#: Embeddings: number 100 of the order counts as one unit of place.
EMB = ClusterSpec(d=0.3, time_unit=100.0)
EMB_K = ClusterSpec(d=0.5, K=4, time_unit=100.0)
EMB_N = NeighbourhoodSpec(R=0.2, T=100)
CONV = ClusterSpec(d=10, K=5, dims=1)
MINI = (("A", 10, 10, 0), ("A", 50, 50, 0), ("B", 11, 10, 2), ("B", 11, 11, 2), ("B", 7, 8, 3), ("B", 7, 7, 3), ("B", 51, 50, 2), ("B", 51, 51, 2), ("B", 48, 48, 4), ("B", 48, 47, 4))
MINI_N, MINI_SPACE = NeighbourhoodSpec(R=5, T=5), SpaceSpec(x0=0, x1=100, y0=0, y1=100, t0=0, t1=10)
Query = Callable[[SparkSession, str], DataFrame]


def mini(spark: SparkSession) -> DataFrame:
    """The example of two groups of A, each with two clusters of B behind it."""
    return spark.createDataFrame([(i + 1, f, float(x), float(y), t) for i, (f, x, y, t) in enumerate(MINI)], "id bigint, type string, x double, y double, t bigint")


def embeddings(spark: SparkSession, sf: str) -> DataFrame:
    return tables.events_from_embeddings(spark, sf)


def embedding_space(points: DataFrame) -> SpaceSpec:
    return SpaceSpec(x0=-1, x1=1, y0=-1, y1=1, t0=0, t1=float(points.agg(F.max("t")).first()[0] + 1))


def conversation_clusters(spark: SparkSession, sf: str) -> DataFrame:
    mc, _ = cluster(tables.events_from_conversations(spark, sf), CONV)
    return mc.select("type", "n", F.round("x", 6).alias("x"), F.round("t", 6).alias("t"), F.round("ss", 6).alias("ss"))


def limit_comparison(spark: SparkSession, sf: str) -> DataFrame:
    """Index size and compression by the diameter alone and with size limits, side by side."""
    rows = []
    for k in (None, 8, 4, 2):
        mc, _ = cluster(embeddings(spark, sf), replace(EMB_K, K=k))
        rows.append(mc.select(F.lit(k or 0).alias("K"), "n").groupBy("K").agg(F.count("*").alias("index_size"), F.max("n").alias("largest"), F.round(F.sum("n") / F.count("*"), 6).alias("compression")))
    return reduce(DataFrame.unionByName, rows)


def search_work(spark: SparkSession, sf: str) -> DataFrame:
    """The triangle inequality gives the same clusters as the scan of all centres: clusters of each that the other lacks."""
    scan, pivot = (core._incremental(replace(EMB, nearest=n), embeddings)(spark, sf) for n in ("scan", "pivot"))
    return scan.exceptAll(pivot).agg(F.count("*").alias("only_scan")).crossJoin(pivot.exceptAll(scan).agg(F.count("*").alias("only_pivot"))).crossJoin(scan.agg(F.count("*").alias("clusters")))


def absorbed(spark: SparkSession, sf: str) -> DataFrame:
    """All events put into an empty index one after another, without splits."""
    events = embeddings(spark, sf)
    mc, _ = cluster(events, EMB)
    out = absorb(mc.where("n < 0"), events, EMB)
    return out.select("type", "n", F.round("x", 6).alias("x"), F.round("y", 6).alias("y"), F.round(F.col("t") / 100.0, 6).alias("t"), F.round("ss", 6).alias("ss"))


def mine_embedding_clusters(spark: SparkSession, sf: str) -> DataFrame:
    """The search on clusters at the published threshold 1."""
    events = embeddings(spark, sf)
    found = mining.mine_microclusters(events, EMB, EMB_N, embedding_space(events), MineOptions(theta=1.0, max_length=3))
    return mining.pattern_table(found.patterns)


def mine_abnormal_clusters(spark: SparkSession, sf: str) -> DataFrame:
    """The published run on gridded events: size-limited clusters of abnormal events and a planted chain, threshold 1."""
    points = stored(core.f4(spark, sf), "abnormal")
    mc, _ = cluster(points, replace(core.F3_MC, d_s=1.0, d_t=5))
    return mining.pattern_table(mining.mine_index(clusters_as_points(mc), core.F3, core.lattice_space(points), MineOptions(theta=1.0, max_length=3)).patterns)


def customers(spark: SparkSession, sf: str) -> DataFrame:
    """Market segments over nations and thousands of the balance, a time step for every thousand customers."""
    return tables.table(spark, sf, "customer").select(
        F.col("c_custkey").cast("bigint").alias("id"), F.col("c_mktsegment").alias("type"), F.col("c_nationkey").cast("double").alias("x"),
        (F.col("c_acctbal").cast("double") / 1000).alias("y"), F.expr("cast(c_custkey div 1000 as bigint)").alias("t"),
    )


def mini_clusters(spark: SparkSession, sf: str) -> DataFrame:
    """The clustering of the example, diameter 2, on the customers."""
    return core._incremental(ClusterSpec(d=2), customers)(spark, sf).select("type", "n", "x", "y", "t")


def mini_mining(spark: SparkSession, sf: str) -> DataFrame:
    """Ratios of the example on events and on its clusters: equal."""
    on_events = mining.mine_instances(mini(spark), MINI_N, MINI_SPACE, MineOptions(theta=1.0)).patterns
    on_clusters = mining.mine_microclusters(mini(spark), ClusterSpec(d=2), MINI_N, MINI_SPACE, MineOptions(theta=1.0)).patterns
    return mining.pattern_table(on_events).withColumn("level", F.lit("events")).unionByName(mining.pattern_table(on_clusters).withColumn("level", F.lit("clusters")))


# ---- sweeps over generated data -------------------------------------------------------------------------------

def generated(spark: SparkSession, parameter: str, seed: int = 0) -> DataFrame:
    """Events of all settings of a sweep: one table with the column ``value``, types and places apart."""
    parts = [planted_events(spark, seed=seed, **(experiments.BASE | {parameter: v})).withColumn("value", F.lit(v)) for v in experiments.SWEEPS[parameter]]
    return reduce(DataFrame.unionByName, parts)


def generated_clusters(spark: SparkSession, parameter: str) -> DataFrame:
    """Clusters of all settings and diameters in one job: value, d, type, x, y, t, n. Coordinates go by the diameter, which becomes 1."""
    events = generated(spark, parameter).select("value", F.explode(F.array(*[F.lit(d) for d in experiments.DIAMETERS])).alias("d"), "id", "type", "x", "y", "t")
    one = events.select(
        (F.col("id") * 1000 + F.col("d")).alias("id"), F.concat_ws("|", F.col("value").cast("string"), F.col("d").cast("string"), "type").alias("type"),
        *[(F.col(a) / F.col("d")).alias(a) for a in ("x", "y", "t")],
    )
    mc, _ = cluster(one.repartition("type"), ClusterSpec(d=1.0))
    part = F.split("type", r"\|")
    return mc.select(
        part[0].cast("int").alias("value"), part[1].cast("int").alias("d"), part[2].alias("type"), "n", "cid",
        *[(F.col(a) * part[1].cast("int")).alias(a) for a in ("x", "y", "t")],
    )


def _index_sizes(parameter: str) -> Query:
    """Index size and compression of the published generator, all values and diameters."""

    def run(spark: SparkSession, sf: str) -> DataFrame:
        mc = generated_clusters(spark, parameter)
        return mc.groupBy(F.col("value").alias(parameter), "d").agg(F.sum("n").alias("events"), F.count("*").alias("index_size"), F.round(F.sum("n") / F.count("*"), 6).alias("compression"))

    return run


def _pattern_sweep(parameter: str, max_length: int = 10) -> Query:
    """Chains found at threshold 1 on the clusters of every setting, and the share of planted chains found.

    All settings are searched in one job: types carry the setting, and places are moved apart by more than R.
    """

    def run(spark: SparkSession, sf: str) -> DataFrame:
        mc = stored(generated_clusters(spark, parameter), "generated")
        name = F.concat_ws("|", F.col("value").cast("string"), F.col("d").cast("string"), "type")
        points = mc.select(
            F.col("cid").alias("id"), name.alias("type"), (F.col("x") + (F.col("value") * 1000 + F.col("d")) * 3000.0).alias("x"), "y", "t", F.col("n").alias("w"),
        )
        spec = NeighbourhoodSpec(R=experiments.BASE["R"], T=experiments.BASE["T"])
        found = mining.mine_index(points, spec, experiments.generated_space(experiments.BASE), MineOptions(theta=1.0, max_length=max_length))
        first = F.split(F.col("seq")[0], r"\|")
        got = stored(found.patterns.select(first[0].cast("int").alias("value"), first[1].cast("int").alias("d"), F.transform("seq", lambda f: F.element_at(F.split(f, r"\|"), -1)).alias("seq")), "patterns")
        planted = reduce(DataFrame.unionByName, [
            metrics.sub_chains(planted_chains(planted_events(spark, **(experiments.BASE | {parameter: v})))).withColumn("value", F.lit(v)) for v in experiments.SWEEPS[parameter]
        ])
        wanted = planted.crossJoin(spark.createDataFrame([(d,) for d in experiments.DIAMETERS], "d int"))  # four rows
        hit = wanted.join(got.withColumn("hit", F.lit(1)), ["value", "d", "seq"], "left").groupBy("value", "d").agg(F.count("*").alias("expected"), F.count("hit").alias("found"))
        count = got.groupBy("value", "d").agg(F.count("*").alias("patterns"), F.max(F.size("seq")).alias("longest"))
        return hit.join(count, ["value", "d"], "left").select(F.col("value").alias(parameter), "d", F.coalesce("patterns", F.lit(0)).alias("patterns"), "longest", "expected", "found")

    return run


def generator_base(spark: SparkSession, sf: str) -> DataFrame:
    """The generator at the published base setting, with the customers as instances; the balance gives the time."""
    table = tables.table(spark, sf, "customer").select("c_custkey", ((F.col("c_acctbal").cast("double") + 1000) / 11000 * 1200).alias("t"))
    rows, n = with_rank(table, ["c_custkey"], "row")
    out = planted_on_rows(rows, n)
    return out.select("id", "type", F.round("x", 6).alias("x"), F.round("y", 6).alias("y"), F.round("t", 6).alias("t"), "pattern", "step")


def generated_instances(spark: SparkSession, sf: str) -> DataFrame:
    """The instance miner on the base setting at threshold 1, up to three types: chains by length, which multiply with each step."""
    spec = NeighbourhoodSpec(R=experiments.BASE["R"], T=experiments.BASE["T"])
    events = planted_events(spark).select("id", "type", "x", "y", "t")
    return metrics.pattern_counts(mining.mine_instances(events, spec, experiments.generated_space(experiments.BASE), MineOptions(theta=1.0, max_length=3)).patterns)


def generated_base_clusters(spark: SparkSession, sf: str) -> DataFrame:
    """Clusters of the base setting at the diameter 60, by type and size."""
    mc, _ = cluster(planted_events(spark), ClusterSpec(d=60))
    return mc.groupBy("type", "n").agg(F.count("*").alias("clusters"))


# ---- SQL -------------------------------------------------------------------------------------------------------

def sql_points(ev: str, d: float | str, unit: float = 1.0, group: str = "type", order: str = "t, id", source: str = "ev", dims: int = 2, scale: tuple = ("1", "1", None)) -> str:
    """CTE pts of the clustering: group, place and time over the bound, order of insertion."""
    by = f"{d}::DOUBLE" if not isinstance(d, str) else f"({d})"
    time = scale[2] or f"{float(unit)!r}::DOUBLE"
    y = f"e.y / {scale[1]}::DOUBLE / {by}" if dims > 1 else "0.0::DOUBLE"
    order = ", ".join(f"e.{c.strip()}" for c in order.split(","))
    return f"{ev}, pts AS (SELECT {group} AS g, e.type, e.id, e.x / {scale[0]}::DOUBLE / {by} AS x, {y} AS y, e.t / {time} / {by} AS t, row_number() OVER (PARTITION BY {group} ORDER BY {order}) AS o FROM {source} e)"


def sql_spread(keys: str) -> str:
    return f"coalesce(var_samp({keys}), 0)"


def sql_clusters(points: str, unit: float, d2: str, limit: int | None = None, source: str = "ev", how: Callable = cluster_sql.clustering, dims: int = 2, extra: str = "") -> str:
    body = how("pts", limit) if how is cluster_sql.clustering else how("pts")
    y = "round(avg(e.y), 6) AS y, " if dims > 1 else ""
    return f"""WITH RECURSIVE {points}, {body}{extra}
SELECT e.type, count(*) AS n, round(avg(e.x), 6) AS x, {y}round(avg(e.t) / {float(unit)!r}::DOUBLE, 6) AS t,
 round((coalesce(var_samp(p.x), 0) + coalesce(var_samp(p.y), 0) + coalesce(var_samp(p.t), 0)) * (count(*) - 1) * {d2}, 6) AS ss
FROM cl JOIN {source} e ON e.id = cl.id JOIN pts p ON p.id = cl.id GROUP BY cl.g, cl.c, e.type"""


def sql_tiled(points: str, limit: int | None = None, source: str = "ev") -> str:
    """CTEs up to mcx (type, n, x, y, t, ss): clusters of tiles, merged across borders."""
    return f"""{points}, {cluster_sql.clustering('pts', limit)},
 tiles AS (SELECT cl.g || '#' || cl.c AS g, any_value(p.type) AS type, cl.g AS tile, count(*) AS n, avg(p.x) AS x, avg(p.y) AS y, avg(p.t) AS t,
  (coalesce(var_samp(p.x), 0) + coalesce(var_samp(p.y), 0) + coalesce(var_samp(p.t), 0)) * (count(*) - 1) AS ss FROM cl JOIN pts p ON p.id = cl.id GROUP BY cl.g, cl.c),
 {cluster_sql.merging('tiles')},
 mcx AS (SELECT any_value(e.type) AS type, count(*) AS n, avg(e.x) AS x, avg(e.y) AS y, avg(e.t) AS t,
  (coalesce(var_samp(p.x), 0) + coalesce(var_samp(p.y), 0) + coalesce(var_samp(p.t), 0)) * (count(*) - 1) AS ss
  FROM merged m JOIN cl ON cl.g || '#' || cl.c = m.g JOIN {source} e ON e.id = cl.id JOIN pts p ON p.id = cl.id GROUP BY m.root)"""


def sql_mine_clusters(clusters: str, spec: NeighbourhoodSpec, volume: str, theta: float, length: int) -> str:
    """The search over mcx (type, n, x, y, t)."""
    ev = f"{clusters}, ev AS (SELECT row_number() OVER () AS id, type, x, y, t, n AS w FROM mcx)"
    return core.sql_mine(ev, spec, volume, theta, length).replace("WITH ", "WITH RECURSIVE ", 1)


def sql_untiled(points: str, limit: int | None = None, source: str = "evs") -> str:
    return f"""{points}, {cluster_sql.clustering('pts', limit)},
 mcx AS (SELECT any_value(e.type) AS type, count(*) AS n, avg(e.x) AS x, avg(e.y) AS y, avg(e.t) AS t FROM cl JOIN {source} e ON e.id = cl.id GROUP BY cl.g, cl.c)"""


def _renamed(ev: str) -> str:
    """A fixture's CTE ``ev`` under the name ``evs``."""
    at = ev.rindex("ev AS (")
    return ev[:at] + "evs AS (" + ev[at + 7 :]


def tile_group(side: float) -> str:
    return f"concat_ws('/', e.type, floor(e.x / {side}), floor(e.y / {side}), floor(e.t / {float(side * HOUR)!r}::DOUBLE))"


def sql_unit(what: str, *keys: str) -> str:
    """The generator's uniform number of a key (seed 0)."""
    return f"(('0x' || substr(md5(concat_ws('|', '0', '{what}', {', '.join(keys)})), 1, 8))::BIGINT / 4294967296.0::DOUBLE)"


def sql_generator() -> str:
    """CTE gen: the published base setting."""
    b = experiments.BASE
    out = f"""base AS (SELECT i // {b['Ni']} AS pattern, i % {b['Ni']} AS i FROM range({b['Pn'] * b['Ni']}) r(i)),
 l0 AS (SELECT pattern, i, {sql_unit('x', 'pattern', 'i')} * 1000 AS x, {sql_unit('y', 'pattern', 'i')} * 1000 AS y, {sql_unit('t', 'pattern', 'i')} * 1200 AS t FROM base)"""
    for k in range(1, b["Ps"]):
        key = ("c.pattern", "c.i", f"'{k}'")
        rho, phi = f"sqrt({sql_unit('r', *key)}) * 10", f"{sql_unit('phi', *key)} * 6.283185307179586::DOUBLE"
        out += f""", m{k} AS (SELECT c.pattern, c.i, p.x + {rho} * cos({phi}) AS x, p.y + {rho} * sin({phi}) AS y, p.t + (1 - {sql_unit('dt', *key)}) * least(10.0::DOUBLE, 1200.0::DOUBLE - p.t) AS t
  FROM base c JOIN l{k - 1} p ON p.pattern = c.pattern AND p.i = floor({sql_unit('pa', *key)} * {b['Ni']})::BIGINT),
 l{k} AS (SELECT pattern, i, CASE WHEN x < 0 THEN -x WHEN x > 1000 THEN 2000 - x ELSE x END AS x, CASE WHEN y < 0 THEN -y WHEN y > 1000 THEN 2000 - y ELSE y END AS y, t FROM m{k})"""
    rows = " UNION ALL ".join(
        f"SELECT {k * b['Pn'] * b['Ni']} + pattern * {b['Ni']} + i AS id, printf('f%02d', floor({sql_unit('type', 'pattern', repr(str(k)))} * 20)::INTEGER) AS type, x, y, t, pattern, {k} AS step FROM l{k}"
        for k in range(b["Ps"])
    )
    n = b["Ni"] * b["Ps"] * b["Pn"]
    noise = f"SELECT i + {n}, printf('f%02d', floor({sql_unit('nf', 'i')} * 20)::INTEGER), {sql_unit('nx', 'i')} * 1000, {sql_unit('ny', 'i')} * 1000, {sql_unit('nt', 'i')} * 1200, NULL, NULL FROM range({n}) r(i)"
    return out + f", gen AS ({rows} UNION ALL {noise}), ev AS (SELECT *, 1 AS w FROM gen)"


def sql_generator_on_customers() -> str:
    """CTE gen: the base setting with the customers, in order of their keys, as instances."""
    b = experiments.BASE
    out = f"""base AS (SELECT row, row % {b['Pn']} AS pattern, row // {b['Pn']} AS i, t, (n - row % {b['Pn']} + {b['Pn'] - 1}) // {b['Pn']} AS many, n
  FROM (SELECT row_number() OVER (ORDER BY c_custkey) - 1 AS row, count(*) OVER () AS n, (c_acctbal::DOUBLE + 1000) / 11000 * 1200 AS t FROM customer)),
 l0 AS (SELECT n, row, pattern, i, {sql_unit('x', 'pattern', 'i')} * 1000 AS x, {sql_unit('y', 'pattern', 'i')} * 1000 AS y, t FROM base)"""
    for k in range(1, b["Ps"]):
        key = ("c.pattern", "c.i", f"'{k}'")
        rho, phi = f"sqrt({sql_unit('r', *key)}) * 10", f"{sql_unit('phi', *key)} * 6.283185307179586::DOUBLE"
        out += f""", m{k} AS (SELECT c.n, c.row, c.pattern, c.i, p.x + {rho} * cos({phi}) AS x, p.y + {rho} * sin({phi}) AS y, p.t + (1 - {sql_unit('dt', *key)}) * least(10.0::DOUBLE, 1200.0::DOUBLE - p.t) AS t
  FROM base c JOIN l{k - 1} p ON p.pattern = c.pattern AND p.i = floor({sql_unit('pa', *key)} * c.many)::BIGINT),
 l{k} AS (SELECT n, row, pattern, i, CASE WHEN x < 0 THEN -x WHEN x > 1000 THEN 2000 - x ELSE x END AS x, CASE WHEN y < 0 THEN -y WHEN y > 1000 THEN 2000 - y ELSE y END AS y, t FROM m{k})"""
    rows = " UNION ALL ".join(f"SELECT {k} * n + row AS id, printf('f%02d', floor({sql_unit('type', 'pattern', repr(str(k)))} * 20)::INTEGER) AS type, x, y, t, pattern, {k} AS step FROM l{k}" for k in range(b["Ps"]))
    noise = f"SELECT i + n * {b['Ps']}, printf('f%02d', floor({sql_unit('nf', 'i')} * 20)::INTEGER), {sql_unit('nx', 'i')} * 1000, {sql_unit('ny', 'i')} * 1000, {sql_unit('nt', 'i')} * 1200, NULL, NULL FROM (SELECT n, row + k * n AS i FROM base, range({b['Ps']}) r(k))"
    return out + f", gen AS ({rows} UNION ALL {noise}), ev AS (SELECT *, 1 AS w FROM gen)"


def queries() -> dict[str, Query]:
    return {
        "mc_embeddings": core._incremental(EMB, embeddings),
        "mc_embeddings_limited": core._incremental(EMB_K, embeddings),
        "mc_conversations": conversation_clusters,
        "mc_limit_comparison": limit_comparison,
        "mc_search_work": search_work,
        "mc_absorbed": absorbed,
        "mine_embedding_clusters": mine_embedding_clusters,
        "mine_abnormal_clusters": mine_abnormal_clusters,
        "mini_clusters": mini_clusters,
        "mini_mining": mini_mining,
        "generator_base": generator_base,
        "generated_base_clusters": generated_base_clusters,
        "generated_instances": generated_instances,
        "generated_index_Ni": _index_sizes("Ni"),
        "generated_index_Pn": _index_sizes("Pn"),
        "generated_index_Ps": _index_sizes("Ps"),
        "generated_patterns_Ni": _pattern_sweep("Ni"),
        "generated_patterns_Pn": _pattern_sweep("Pn"),
        "generated_patterns_Ps": _pattern_sweep("Ps"),
    }


def oracle_sql() -> dict[str, str]:
    emb = sql_points(core.SQL_F6, 0.3, 100.0)
    emb_k = sql_points(core.SQL_F6, 0.5, 100.0)
    f3 = core.SQL_F3 + """, sc AS (SELECT coalesce(nullif((max(x) - min(x))::DOUBLE, 0), 1) AS sx, coalesce(nullif((max(y) - min(y))::DOUBLE, 0), 1) AS sy, coalesce(nullif((max(t) - min(t))::DOUBLE, 0), 1) AS st FROM ev)"""
    bound = "(SELECT sqrt(pow(2.5 / greatest(sx, sy), 2) + pow(30 / st, 2)) FROM sc)"
    scale = ("(SELECT sx FROM sc)", "(SELECT sy FROM sc)", "(SELECT st FROM sc)")
    f3_points = sql_points(f3, bound, order="t, x, y, id", scale=scale)
    limits = " UNION ALL ".join(
        f"(WITH RECURSIVE {f3_points}, {cluster_sql.clustering('pts', k)} SELECT {k} AS K, count(*) AS index_size, sum(n) / count(*) AS compression FROM (SELECT count(*) AS n FROM cl GROUP BY g, c))" for k in (20, 40, 60, 80, 100)
    )
    emb_limits = " UNION ALL ".join(
        f"(WITH RECURSIVE {emb_k}, {cluster_sql.clustering('pts', k)} SELECT {k or 0} AS K, count(*) AS index_size, max(n) AS largest, round(sum(n) / count(*), 6) AS compression FROM (SELECT count(*) AS n FROM cl GROUP BY g, c))" for k in (None, 8, 4, 2)
    )
    f2 = _renamed(core.sql_f2())
    f4 = _renamed(core.sql_f4()) + ", sc AS (SELECT coalesce(nullif((max(x) - min(x))::DOUBLE, 0), 1) AS sx, coalesce(nullif((max(y) - min(y))::DOUBLE, 0), 1) AS sy, coalesce(nullif((max(t) - min(t))::DOUBLE, 0), 1) AS st FROM evs)"
    f4_bound = "(SELECT sqrt(pow(1.0 / greatest(sx, sy), 2) + pow(5 / st, 2)) FROM sc)"
    f4_volume = "((SELECT max(x) + 1 FROM evs) * (SELECT (max(y) + 1)::DOUBLE FROM evs) * (SELECT (max(t) + 1 - min(t))::DOUBLE FROM evs))"
    mini_ev = "ev AS (SELECT id, type, x::DOUBLE AS x, y::DOUBLE AS y, t, 1 AS w FROM (VALUES " + ", ".join(f"({i + 1}, '{f}', {x}, {y}, {t})" for i, (f, x, y, t) in enumerate(MINI)) + ") v(id, type, x, y, t))"
    customer_ev = "ev AS (SELECT c_custkey AS id, c_mktsegment AS type, c_nationkey::DOUBLE AS x, c_acctbal::DOUBLE / 1000 AS y, c_custkey // 1000 AS t, 1 AS w FROM customer)"
    mini_on_clusters = sql_mine_clusters(sql_untiled(sql_points(_renamed(mini_ev), 2, source="evs")), MINI_N, "100000.0::DOUBLE", 1.0, 4)
    return {
        "mc_incremental_d": sql_clusters(sql_points(core.SQL_F1, 20, HOUR), HOUR, "400.0"),
        "mc_incremental_dk": sql_clusters(f3_points, 1.0, f"pow({bound}, 2)", 20),
        "mc_incremental_tiled": f"WITH RECURSIVE {sql_tiled(sql_points(core.SQL_F1, 20, HOUR, tile_group(200)))} SELECT type, n, round(x, 6) AS x, round(y, 6) AS y, round(t / {float(HOUR)!r}::DOUBLE, 6) AS t, round(ss * 400, 6) AS ss FROM mcx",
        "mc_index_sweep": limits,
        "flagship": sql_mine_clusters(sql_tiled(sql_points(f2, 5, HOUR, tile_group(100), source="evs"), source="evs"), core.F1_MC, core.F1_VOLUME, core.THETA, 4),
        "mine_microclusters": sql_mine_clusters(sql_untiled(sql_points(f2, 5, HOUR, source="evs")), core.F1_MC, core.F1_VOLUME, core.THETA, 4),
        "mine_abnormal_planted": core.sql_mine(core.sql_f4(), core.F3, core.LATTICE, 1.0, 4),
        "stream_clusters": f"""WITH RECURSIVE {sql_points(core.SQL_F1, 20, HOUR, "concat_ws('/', e.type, floor(e.x / 500), floor(e.y / 500), floor(e.t / " + f"{float(500 * HOUR)!r}::DOUBLE))")}, {cluster_sql.absorbing('pts')}
SELECT any_value(p.type) AS type, count(*) AS n, round((coalesce(var_samp(p.x), 0) + coalesce(var_samp(p.y), 0) + coalesce(var_samp(p.t), 0)) * (count(*) - 1), 4) AS ss FROM cl JOIN pts p ON p.id = cl.id GROUP BY cl.g, cl.c""",
        "mc_embeddings": sql_clusters(emb, 100.0, repr(0.3 * 0.3)),
        "mc_embeddings_limited": sql_clusters(emb_k, 100.0, "0.25", 4),
        "mc_conversations": sql_clusters(sql_points(core.SQL_F5, 10, dims=1), 1.0, "100.0", 5, dims=1),
        "mc_limit_comparison": emb_limits,
        "mc_search_work": f"WITH RECURSIVE {emb}, {cluster_sql.clustering('pts')} SELECT 0 AS only_scan, 0 AS only_pivot, count(DISTINCT (g, c)) AS clusters FROM cl",
        "mc_absorbed": sql_clusters(emb, 100.0, repr(0.3 * 0.3), how=cluster_sql.absorbing),
        "mine_embedding_clusters": sql_mine_clusters(sql_untiled(sql_points(_renamed(core.SQL_F6), 0.3, 100.0, source="evs")), EMB_N, "(4.0::DOUBLE * (SELECT max(t) + 1 FROM evs))", 1.0, 3),
        "mine_abnormal_clusters": sql_mine_clusters(sql_untiled(sql_points(f4, f4_bound, order="t, x, y, id", scale=scale, source="evs"), 20), core.F3, f4_volume, 1.0, 3),
        "mini_clusters": f"SELECT type, n, x, y, t FROM ({sql_clusters(sql_points(customer_ev, 2), 1.0, '4.0')})",
        "mini_mining": f"SELECT *, 'events' AS level FROM ({core.sql_mine(mini_ev, MINI_N, '100000.0::DOUBLE', 1.0, 4)}) UNION ALL SELECT *, 'clusters' AS level FROM ({mini_on_clusters})",
        "generated_instances": f"SELECT length, count(*) AS patterns FROM ({core.sql_mine(sql_generator(), NeighbourhoodSpec(R=10, T=10), '1200000000.0::DOUBLE', 1.0, 3)}) GROUP BY length",
        "generator_base": f"WITH {sql_generator_on_customers()} SELECT id, type, round(x, 6) AS x, round(y, 6) AS y, round(t, 6) AS t, pattern, step FROM ev",
        "generated_base_clusters": f"WITH RECURSIVE {sql_points(sql_generator(), 60)}, {cluster_sql.clustering('pts')} SELECT g AS type, n, count(*) AS clusters FROM (SELECT g, c, count(*) AS n FROM cl GROUP BY g, c) GROUP BY g, n",
    }


