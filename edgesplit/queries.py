"""Queries of the engine's methods, baselines, measures, jobs and operators, with their DuckDB twins."""

from __future__ import annotations

from collections.abc import Callable
from functools import partial

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import workloads
from .functions import scoring
from .functions import sql as sql_functions
from .functions.hashing import portable, portable_sql
from .operators import cluster_map, clustering, degrees, jobs, metrics, placement, stateless
from .plans.api import METHODS, partition
from .plans.storage import fresh_path, materialise, prepare
from .sources import builders
from .sources.builders import PAGE_LINK_SQL, graph_sql, table
from .streaming import live

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}


def _add(name: str, query: Query, oracle: str | None = None) -> None:
    QUERIES[name] = query
    if oracle:
        ORACLES[name] = oracle


def _graph(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return builders.graph(prepare(spark), sf_dir, name)


def _g(name: str) -> str:
    """CTEs g (edges) and d (degrees) of a graph."""
    return f"g AS ({graph_sql(name, 'duck')}), d AS (SELECT v, count(*) AS d FROM (SELECT src AS v FROM g UNION ALL SELECT dst FROM g) t GROUP BY v)"


# ---- graphs and degrees --------------------------------------------------------------------------

for _name in builders.GRAPHS:
    _add(f"graph_{_name}", partial(_graph, name=_name), graph_sql(_name, "duck"))
_add("graph_page_link", partial(_graph, name="page_link"), PAGE_LINK_SQL)
_add("graph_embed_knn", partial(_graph, name="embed_knn"))
_add("degrees", lambda s, d: degrees.compute(_graph(s, d, "doc_token")), f"WITH {_g('doc_token')} SELECT v, d FROM d")
_add("degree_histogram", lambda s, d: degrees.compute(_graph(s, d, "order_supp")).groupBy("d").agg(F.count("*").alias("n")), f"WITH {_g('order_supp')} SELECT d, count(*) AS n FROM d GROUP BY d")
_add("top_hubs", lambda s, d: degrees.compute(_graph(s, d, "order_supp")).orderBy(F.desc("d"), "v").limit(20), f"WITH {_g('order_supp')} SELECT v, d FROM d ORDER BY d DESC, v LIMIT 20")

# ---- stateless methods ---------------------------------------------------------------------------

_FIRST = "(a.d < b.d OR (a.d = b.d AND src <= dst))"


def _p_sql(method: str, k: int) -> str:
    """SQL expression of a stateless partition over columns src and dst."""
    edge = stateless.edge_hash_sql()
    if method == "hash_edge":
        return f"{edge} % {k}"
    if method == "hash_src":
        return f"{portable_sql('src')} % {k}"
    if method == "grid":
        _, n = stateless.grid_shape(k)
        a, b = f"({portable_sql('src')} % {k})", f"({portable_sql('dst')} % {k})"
        return f"CASE WHEN {edge} % 2 = 0 THEN ({a} // {n}) * {n} + {b} % {n} ELSE ({b} // {n}) * {n} + {a} % {n} END"
    sets = stateless.DIFFERENCE_SETS[k]
    own = lambda x: "[" + ", ".join(f"({d} + {portable_sql(x)} % {k}) % {k}" for d in sets) + "]"
    return f"(SELECT s[CAST({edge} % len(s) + 1 AS INTEGER)] FROM (SELECT list_sort(list_intersect({own('src')}, {own('dst')})) AS s))"


def _assigned_sql(method: str, graph: str, k: int) -> str:
    """CTEs up to ``a`` (src, dst, p)."""
    if method == "dbh":
        p = portable_sql(f"CASE WHEN {_FIRST} THEN src ELSE dst END")
        return f"{_g(graph)}, a AS (SELECT src, dst, CAST({p} % {k} AS INTEGER) AS p FROM g JOIN d AS a ON a.v = src JOIN d AS b ON b.v = dst)"
    return f"{_g(graph)}, a AS (SELECT src, dst, CAST({_p_sql(method, k)} AS INTEGER) AS p FROM g)"


def _stateless(spark: SparkSession, sf_dir: str, method: str, graph: str, k: int) -> DataFrame:
    edges = _graph(spark, sf_dir, graph)
    if method == "dbh":
        return stateless.dbh(edges, degrees.compute(edges), k)
    return {"grid": stateless.grid, "hash_edge": stateless.hash_edge, "hash_src": stateless.hash_src, "pds": stateless.difference_sets}[method](edges, k)


for _method, _graph_name, _k in (("dbh", "order_part", 32), ("grid", "cust_part", 12), ("pds", "cust_part", 13), ("hash_edge", "cust_part", 8), ("hash_src", "cust_part", 8)):
    _add(f"{_method}_assign", partial(_stateless, method=_method, graph=_graph_name, k=_k), f"WITH {_assigned_sql(_method, _graph_name, _k)} SELECT src, dst, p FROM a")
_RF_SQL = "SELECT CAST(count(*) AS BIGINT) AS replicas, CAST(count(DISTINCT v) AS BIGINT) AS vertices, round(count(*)::DOUBLE / count(DISTINCT v), 6) AS rf FROM (SELECT DISTINCT v, p FROM (SELECT src AS v, p FROM a UNION ALL SELECT dst, p FROM a) t) t"
_add("dbh_loads", lambda s, d: metrics.loads(_stateless(s, d, "dbh", "cust_part", 32)), f"WITH {_assigned_sql('dbh', 'cust_part', 32)} SELECT p, count(*) AS n FROM a GROUP BY p")
_add(
    "dbh_rf", lambda s, d: metrics.replication_factor(_stateless(s, d, "dbh", "cust_part", 32)).select("replicas", "vertices", F.round("rf", 6).alias("rf")), f"WITH {_assigned_sql('dbh', 'cust_part', 32)} {_RF_SQL}"
)
_add(
    "dbh_alpha", lambda s, d: metrics.imbalance(_stateless(s, d, "dbh", "cust_part", 32), 32).select("edges", "max_load", F.round("alpha", 6).alias("alpha")),
    f"WITH {_assigned_sql('dbh', 'cust_part', 32)} SELECT CAST(sum(n) AS BIGINT) AS edges, max(n) AS max_load, round(max(n) * 32.0::DOUBLE / sum(n), 6) AS alpha FROM (SELECT count(*) AS n FROM a GROUP BY p) t",
)
_add(
    "sync_messages", lambda s, d: metrics.sync_messages(_stateless(s, d, "grid", "cust_part", 12)),
    f"WITH {_assigned_sql('grid', 'cust_part', 12)} SELECT CAST(sum(r - 1) AS BIGINT) AS messages FROM (SELECT v, count(DISTINCT p) AS r FROM (SELECT src AS v, p FROM a UNION ALL SELECT dst, p FROM a) t GROUP BY v) t",
)
_STATELESS_RF = " UNION ALL ".join(
    f"SELECT '{m}' AS method, {k} AS k, round((SELECT count(*) FROM (SELECT src AS v, p FROM a_{m}_{k} UNION SELECT dst, p FROM a_{m}_{k}) t)::DOUBLE / (SELECT count(*) FROM d), 6) AS rf, "
    f"round((SELECT max(n) FROM (SELECT count(*) AS n FROM a_{m}_{k} GROUP BY p) t) * {k}.0::DOUBLE / (SELECT count(*) FROM g), 6) AS alpha"
    for m in ("dbh", "grid", "hash_edge", "hash_src") for k in (4, 16)
)
_STATELESS_PARTS = ", ".join(f"a_{m}_{k} AS (" + _assigned_sql(m, "cust_part", k).split(", a AS (", 1)[1] for m in ("dbh", "grid", "hash_edge", "hash_src") for k in (4, 16))
_add("rf_stateless", lambda s, d: workloads.stateless_rf(_graph(s, d, "cust_part"), ("dbh", "grid", "hash_edge", "hash_src"), (4, 16)), f"WITH {_g('cust_part')}, {_STATELESS_PARTS} {_STATELESS_RF}")
_add(
    "load_statistics", lambda s, d: metrics.load_statistics(_stateless(s, d, "hash_src", "cust_part", 8)),
    f"WITH {_assigned_sql('hash_src', 'cust_part', 8)}, l AS (SELECT p, count(*) AS n FROM a GROUP BY p) SELECT round(avg(n), 6) AS mean, round(stddev_samp(n), 6) AS sd, round(quantile_cont(n, 0.5), 6) AS median, "
    "round(quantile_cont(n, 0.9), 6) AS p90, round(regr_slope(n, p), 6) AS slope FROM l",
)
_add("rf_sketch", lambda s, d: metrics.replication_factor_estimate(_stateless(s, d, "dbh", "cust_part", 32), 32))
_add(
    "partition_profile", lambda s, d: jobs.partition_profile(_stateless(s, d, "hash_edge", "cust_part", 8)),
    f"WITH {_assigned_sql('hash_edge', 'cust_part', 8)}, c AS (SELECT DISTINCT v, p FROM (SELECT src AS v, p FROM a UNION ALL SELECT dst, p FROM a) t), r AS (SELECT v, count(*) AS r FROM c GROUP BY v), "
    "x AS (SELECT c.p, count(*) AS vertices, sum(CASE WHEN r > 1 THEN 1 ELSE 0 END) AS mirrors FROM c JOIN r USING (v) GROUP BY c.p), e AS (SELECT p, count(*) AS edges FROM a GROUP BY p) "
    "SELECT p, CAST(sum(edges) AS BIGINT) AS edges, CAST(sum(vertices) AS BIGINT) AS vertices, CAST(sum(mirrors) AS BIGINT) AS mirrors FROM e JOIN x USING (p) GROUP BY ROLLUP (p)",
)

# ---- phase 2 over known clusters: nations --------------------------------------------------------

_K, _CAP_ALPHA = 4, 1.05
_NATION = "nation_planted"


def _nation_clusters(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    """Edges, and clusters by nation: customers by their own, parts by their place in a block of 25."""
    edges = _graph(spark, sf_dir, _NATION)
    nations = table(spark, sf_dir, "customer").select((F.col("c_custkey") * 8 + 3).alias("v"), F.col("c_nationkey").cast("long").alias("n"))
    known = degrees.compute(edges).join(nations, "v", "left")
    return edges, known.select("v", F.coalesce("n", F.floor(F.col("v") / 8).cast("long") % 25).alias("c"), "d")


def _nation_plan(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    edges, clusters = _nation_clusters(spark, sf_dir)
    mapped = cluster_map.assign(clustering.volumes(clusters), _K)
    return edges, placement.enrich(edges, placement.vertex_plan(clusters, mapped))


_CL = f"{_g(_NATION)}, cl AS (SELECT d.v, coalesce(CAST(c_nationkey AS BIGINT), (d.v // 8) % 25) AS c, d.d FROM d LEFT JOIN customer ON d.v = c_custkey * 8 + 3), vols AS (SELECT c, CAST(sum(d) AS BIGINT) AS vol FROM cl GROUP BY c)"
_LEAST = "CASE WHEN l0 <= l1 AND l0 <= l2 AND l0 <= l3 THEN 0 WHEN l1 <= l2 AND l1 <= l3 THEN 1 WHEN l2 <= l3 THEN 2 ELSE 3 END"
_LPT = (
    f"{_CL}, j AS (SELECT c, vol, row_number() OVER (ORDER BY vol DESC, c) AS i FROM vols), "
    "run(i, c, vol, p, l0, l1, l2, l3) AS (SELECT CAST(0 AS BIGINT), CAST(-1 AS BIGINT), CAST(0 AS BIGINT), -1, CAST(0 AS BIGINT), CAST(0 AS BIGINT), CAST(0 AS BIGINT), CAST(0 AS BIGINT) "
    f"UNION ALL SELECT j.i, j.c, j.vol, {_LEAST}, " + ", ".join(f"l{p} + CASE WHEN ({_LEAST}) = {p} THEN j.vol ELSE 0 END" for p in range(_K)) + " FROM run JOIN j ON j.i = run.i + 1), "
    "m AS (SELECT c, vol, p FROM run WHERE i > 0)"
)
_PLAN = (
    f"{_LPT}, pl AS (SELECT v, d, cl.c, vol, p FROM cl JOIN m ON m.c = cl.c), "
    "e AS (SELECT src, dst, a.d AS d_u, b.d AS d_v, a.vol AS vol_u, b.vol AS vol_v, a.p AS p_u, b.p AS p_v FROM g JOIN pl AS a ON a.v = src JOIN pl AS b ON b.v = dst)"
)
_add("volumes_nation", lambda s, d: clustering.volumes(_nation_clusters(s, d)[1]), f"WITH {_CL} SELECT c, vol FROM vols")
_add("lpt_nation", lambda s, d: cluster_map.assign(clustering.volumes(_nation_clusters(s, d)[1]), _K), f"WITH RECURSIVE {_LPT} SELECT c, vol, p FROM m")
_add(
    "lpt_hist_loads", lambda s, d: cluster_map.by_histogram(clustering.volumes(_nation_clusters(s, d)[1]), _K).groupBy("p").agg(F.sum("vol").alias("vol")), f"WITH RECURSIVE {_LPT} SELECT p, CAST(sum(vol) AS BIGINT) AS vol FROM m GROUP BY p"
)
_add(
    "makespan_ratio", lambda s, d: cluster_map.makespan_ratio(cluster_map.assign(clustering.volumes(_nation_clusters(s, d)[1]), _K), _K).select("max_volume", F.round("ratio", 6).alias("ratio")),
    f"WITH RECURSIVE {_LPT}, x AS (SELECT sum(vol) AS s, max(vol) AS m FROM m GROUP BY p) SELECT CAST(max(s) AS BIGINT) AS max_volume, round(max(s) / greatest(sum(s)::DOUBLE / {_K}, max(m)::DOUBLE), 6) AS ratio FROM x",
)
_add(
    "prepartition_nation", lambda s, d: _nation_plan(s, d)[1].where("p_u = p_v").select("src", "dst", F.col("p_u").alias("p")), f"WITH RECURSIVE {_PLAN} SELECT src, dst, p_u AS p FROM e WHERE p_u = p_v"
)
_add(
    "stage_mix_nation", lambda s, d: metrics.stage_mix(_nation_plan(s, d)[1].select(F.when(F.col("p_u") == F.col("p_v"), "prepartition").otherwise("scored").alias("stage"))).select("stage", "n", F.round("share", 6).alias("share")),
    f"WITH RECURSIVE {_PLAN}, x AS (SELECT CASE WHEN p_u = p_v THEN 'prepartition' ELSE 'scored' END AS stage FROM e) SELECT stage, count(*) AS n, round(count(*)::DOUBLE / sum(count(*)) OVER (), 6) AS share FROM x GROUP BY stage",
)


def _one_batch(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = materialise(_nation_plan(spark, sf_dir)[1], "nation-plan")
    own = rows.where("p_u = p_v").select("src", "dst", F.col("p_u").alias("p"))
    return placement.choose_of_two(placement.with_sets(rows.where("p_u <> p_v"), placement.replica_sets(own)))


_REP = (
    f"{_PLAN}, rp AS (SELECT DISTINCT v, p FROM (SELECT src AS v, p_u AS p FROM e WHERE p_u = p_v UNION ALL SELECT dst, p_u FROM e WHERE p_u = p_v) t), "
    "f AS (SELECT e.*, r1.v IS NOT NULL AS uu, r2.v IS NOT NULL AS vu, r3.v IS NOT NULL AS uv, r4.v IS NOT NULL AS vv FROM e LEFT JOIN rp r1 ON r1.v = src AND r1.p = p_u LEFT JOIN rp r2 ON r2.v = dst AND r2.p = p_u "
    "LEFT JOIN rp r3 ON r3.v = src AND r3.p = p_v LEFT JOIN rp r4 ON r4.v = dst AND r4.p = p_v WHERE p_u <> p_v), "
    "sc AS (SELECT *, CASE WHEN uu THEN 2 - d_u::DOUBLE / (d_u + d_v) ELSE 0 END + CASE WHEN vu THEN 2 - d_v::DOUBLE / (d_u + d_v) ELSE 0 END + vol_u::DOUBLE / (vol_u + vol_v) AS score_u, "
    "CASE WHEN uv THEN 2 - d_u::DOUBLE / (d_u + d_v) ELSE 0 END + CASE WHEN vv THEN 2 - d_v::DOUBLE / (d_u + d_v) ELSE 0 END + vol_v::DOUBLE / (vol_u + vol_v) AS score_v FROM f)"
)
_add(
    "pair_score_nation", lambda s, d: _one_batch(s, d).select("src", "dst", F.round("score_u", 6).alias("score_u"), F.round("score_v", 6).alias("score_v")),
    f"WITH RECURSIVE {_REP} SELECT src, dst, round(score_u, 6) AS score_u, round(score_v, 6) AS score_v FROM sc",
)
_add(
    "two_candidate_one_batch", lambda s, d: _one_batch(s, d).select("src", "dst", "p"),
    f"WITH RECURSIVE {_REP} SELECT src, dst, CASE WHEN score_u >= score_v - 1e-12 THEN p_u ELSE p_v END AS p FROM sc",
)


def _capped(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Step 2 under the hard cap, in (src, dst) order: own edges that fit."""
    rows = _nation_plan(spark, sf_dir)[1].where("p_u = p_v").withColumn("p", F.col("p_u"))
    rows = materialise(degrees.with_position(rows.select("src", "dst", "p"), ("src", "dst")), "own")
    loads = placement.Loads(_K, rows.count() // 5)
    return placement.admit(rows, loads)[0].select("src", "dst", "p")


_add(
    "admission_capped", _capped,
    f"WITH RECURSIVE {_PLAN}, o AS (SELECT src, dst, p_u AS p, row_number() OVER (PARTITION BY p_u ORDER BY src, dst) AS r, count(*) OVER () AS n FROM e WHERE p_u = p_v) SELECT src, dst, p FROM o WHERE r <= n // 5",
)

# ---- phase 1: one bulk round ---------------------------------------------------------------------


def _round(spark: SparkSession, sf_dir: str, graph: str) -> DataFrame:
    edges = degrees.with_position(_graph(spark, sf_dir, graph), ("src", "dst"))
    known = materialise(degrees.compute(edges), "degrees")
    return clustering.one_round(edges, clustering.singletons(known), 200).select("v", "c", "d")


def _round_sql(graph: str, cap: int = 200) -> str:
    return (
        f"WITH {_g(graph)}, s AS (SELECT row_number() OVER (ORDER BY src, dst) - 1 AS pos, src, dst, a.d AS du, b.d AS dv FROM g JOIN d a ON a.v = src JOIN d b ON b.v = dst WHERE a.d <= {cap} AND b.d <= {cap}), "
        # Singletons have residual volume zero, so the first end always moves.
        f"mv AS (SELECT pos, src AS v, du AS d, src AS source, dst AS target, dv AS room FROM s WHERE dv + du <= {cap}), "
        "best AS (SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY v ORDER BY room DESC, pos) AS r FROM mv) t WHERE r = 1), "
        "roles AS (SELECT c, arg_min(role, pos) AS role FROM (SELECT source AS c, 0 AS role, pos * 2 AS pos FROM best UNION ALL SELECT target, 1, pos * 2 + 1 FROM best) t GROUP BY c), "
        "kept AS (SELECT best.*, sum(d) OVER (PARTITION BY target ORDER BY pos, v ROWS UNBOUNDED PRECEDING) AS arrived FROM best JOIN roles a ON a.c = source AND a.role = 0 JOIN roles b ON b.c = target AND b.role = 1) "
        f"SELECT d.v, coalesce(k.target, d.v) AS c, d.d FROM d LEFT JOIN (SELECT v, target FROM kept WHERE room + arrived <= {cap}) k ON k.v = d.v"
    )


for _name in ("cust_order", _NATION):
    _add(f"cluster_round_{_name}", partial(_round, graph=_name), _round_sql(_name))



def _second_round(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One round from clusters by nation, whose residual volumes differ, so that the rule of the smaller residual decides."""
    edges, clusters = _nation_clusters(spark, sf_dir)
    edges = materialise(degrees.with_position(edges, ("src", "dst")), "edges")
    # Each nation's customers and parts apart: 50 clusters that still have to meet.
    clusters = materialise(clusters.select("v", (F.col("c") * 2 + F.col("v") % 8 % 2 + F.lit(1000)).alias("c"), "d"), "clusters")
    moves = clustering.propose(edges, clusters, None)
    return moves.select("v", "source", "target", "pos")


_add(
    "cluster_proposals_residual", _second_round,
    f"WITH {_CL}, c2 AS (SELECT v, c * 2 + v % 8 % 2 + 1000 AS c, d FROM cl), w AS (SELECT c, CAST(sum(d) AS BIGINT) AS vol FROM c2 GROUP BY c), "
    "s AS (SELECT row_number() OVER (ORDER BY src, dst) - 1 AS pos, src, dst, a.d AS du, b.d AS dv, a.c AS cu, b.c AS cv, x.vol AS vu, y.vol AS vv FROM g JOIN c2 a ON a.v = src JOIN c2 b ON b.v = dst JOIN w x ON x.c = a.c JOIN w y ON y.c = b.c), "
    "mv AS (SELECT pos, CASE WHEN vu - du <= vv - dv THEN src ELSE dst END AS v, CASE WHEN vu - du <= vv - dv THEN cu ELSE cv END AS source, CASE WHEN vu - du <= vv - dv THEN cv ELSE cu END AS target, "
    "CASE WHEN vu - du <= vv - dv THEN vv ELSE vu END AS room FROM s WHERE cu <> cv) "
    "SELECT v, source, target, pos FROM (SELECT *, row_number() OVER (PARTITION BY v ORDER BY room DESC, pos) AS r FROM mv) t WHERE r = 1",
)

# ---- certificates: every method covers every edge once and keeps the cap -------------------------

_CERTIFIED = [m for m in METHODS if m not in ("dbh", "grid", "pds", "hash_edge", "hash_src")]


def _certificates(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = workloads.sweep(_graph(spark, sf_dir, _NATION), [workloads.setting(m, 8) for m in _CERTIFIED])
    bound = F.least(F.col("k").cast("double"), 2 * F.col("edges") / F.col("vertices"))
    return rows.select("method", "edges", "vertices", (F.col("max_load") <= F.col("cap")).alias("balanced"), "covered", ((F.col("rf") >= 1) & (F.col("rf") <= bound)).alias("rf_in_bounds"))


_add(
    "certificates_sequential", _certificates,
    f"WITH {_g(_NATION)} SELECT m AS method, (SELECT count(*) FROM g) AS edges, (SELECT count(*) FROM d) AS vertices, true AS balanced, true AS covered, true AS rf_in_bounds FROM (SELECT unnest({_CERTIFIED}) AS m) t",
)


def _certificate(spark: SparkSession, sf_dir: str, method: str, engine: str, graph: str = _NATION, k: int = 8) -> DataFrame:
    edges = materialise(_graph(spark, sf_dir, graph), "graph")
    done = partition(edges, k, method=method, engine=engine, batches=2)
    cover = metrics.check_exact_cover(edges, done.assignment)
    return metrics.imbalance(done.assignment, k).crossJoin(cover).select("edges", (F.col("max_load") <= done.cap).alias("balanced"), ((F.col("missing") == 0) & (F.col("extra") == 0)).alias("covered"))


for _method, _engine in (("cluster_guided", "bulk"), ("cluster_guided", "shards"), ("cluster_guided_full", "bulk"), ("cluster_guided_full", "shards"), ("hdrf", "bulk"), ("hdrf", "shards"), ("greedy", "shards")):
    _add(f"certificate_{_method}_{_engine}", partial(_certificate, method=_method, engine=_engine), f"WITH {_g(_NATION)} SELECT count(*) AS edges, true AS balanced, true AS covered FROM g")


def _invariants(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Clusters of the bulk engine: volumes add up, and one above the cap has a single member."""
    edges = materialise(degrees.with_position(_graph(spark, sf_dir, "order_supp")), "stream")
    n = edges.count()
    cap = degrees.volume_cap(n, 8, 1.05, 0.05)
    clusters = clustering.stream_cluster(edges, materialise(degrees.compute(edges), "degrees"), cap, n, batches=2)
    per = clusters.groupBy("c").agg(F.sum("d").alias("vol"), F.count("*").alias("m"))
    return per.agg(F.sum("vol").alias("volume"), F.sum("m").alias("vertices"), (F.max(F.when(F.col("m") > 1, F.col("vol"))) <= cap).alias("bounded"))


_add("cluster_invariants", _invariants, f"WITH {_g('order_supp')} SELECT CAST(sum(d) AS BIGINT) AS volume, count(*) AS vertices, true AS bounded FROM d")


def _hdrf_batch(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All edges scored against a frozen state: replicas and loads of a hash of every edge whose hash is even."""
    edges = _graph(spark, sf_dir, "part_supp")
    known = degrees.compute(edges)
    first = stateless.hash_edge(edges, 4).where(portable(F.col("src")) % 2 == 0)
    loads = placement.Loads(4, 10**9)
    loads.add(first)
    d_u, d_v = (known.select(F.col("v").alias(x), F.col("d").alias(n)) for x, n in (("src", "d_u"), ("dst", "d_v")))
    rest = edges.where(portable(F.col("src")) % 2 == 1).join(d_u, "src").join(d_v, "dst")
    return placement.choose_of_all(placement.with_sets(rest, placement.replica_sets(first)), 4, loads, 1.1, 1.0).select("src", "dst", "p")


_add(
    "hdrf_one_batch", _hdrf_batch,
    f"WITH {_g('part_supp')}, a AS (SELECT src, dst, {stateless.edge_hash_sql()} % 4 AS p FROM g WHERE {portable_sql('src')} % 2 = 0), "
    "rp AS (SELECT DISTINCT v, p FROM (SELECT src AS v, p FROM a UNION ALL SELECT dst, p FROM a) t), ld AS (SELECT i AS p, (SELECT count(*) FROM a WHERE a.p = i) AS n FROM range(4) r(i)), "
    f"x AS (SELECT src, dst, ld.p, round(CASE WHEN r1.v IS NOT NULL THEN 2 - a.d::DOUBLE / (a.d + b.d) ELSE 0 END + CASE WHEN r2.v IS NOT NULL THEN 2 - b.d::DOUBLE / (a.d + b.d) ELSE 0 END "
    "+ 1.1::DOUBLE * ((SELECT max(n) FROM ld) - n) / (1.0::DOUBLE + (SELECT max(n) FROM ld) - (SELECT min(n) FROM ld)), 9) AS s "
    f"FROM g JOIN d a ON a.v = src JOIN d b ON b.v = dst CROSS JOIN ld LEFT JOIN rp r1 ON r1.v = src AND r1.p = ld.p LEFT JOIN rp r2 ON r2.v = dst AND r2.p = ld.p WHERE {portable_sql('src')} % 2 = 1) "
    "SELECT src, dst, CAST(p AS INTEGER) AS p FROM (SELECT *, row_number() OVER (PARTITION BY src, dst ORDER BY s DESC, p) AS r FROM x) t WHERE r = 1",
)

# ---- jobs ----------------------------------------------------------------------------------------


def _pagerank(spark: SparkSession, sf_dir: str) -> DataFrame:
    done = _stateless(spark, sf_dir, "hash_edge", "cust_order", 8)
    return jobs.pagerank(done, 3, k=8).select("v", F.round(F.col("rank") + 1e-9, 6).alias("rank"))


_STEP = "{n} AS (SELECT o.v, 0.15 + 0.85 * coalesce(sum(r.rank / x.d), 0) AS rank FROM d o LEFT JOIN arcs ON arcs.dst = o.v LEFT JOIN {p} r ON r.v = arcs.src LEFT JOIN d x ON x.v = arcs.src GROUP BY o.v)"
_add(
    "pagerank_3", _pagerank,
    f"WITH {_g('cust_order')}, arcs AS (SELECT src, dst FROM g UNION ALL SELECT dst, src FROM g), r0 AS (SELECT v, 1.0::DOUBLE AS rank FROM d), "
    + ", ".join(_STEP.format(n=f"r{i + 1}", p=f"r{i}") for i in range(3)) + " SELECT v, round(rank + 1e-9, 6) AS rank FROM r3",
)
_add(
    "cc_labels", lambda s, d: jobs.connected_components(_graph(s, d, "cust_order"), "src", "dst").select(F.col("node").alias("v"), F.col("root").alias("label")),
    # The graph is a forest of stars around customers.
    f"WITH {_g('cust_order')}, h AS (SELECT src, least(src, min(dst)) AS label FROM g GROUP BY src) SELECT src AS v, label FROM h UNION ALL SELECT dst, label FROM g JOIN h USING (src)",
)


def _neighbours(spark: SparkSession, sf_dir: str) -> DataFrame:
    vectors = table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("v"), F.col("embedding").cast("array<double>").alias("x"))
    return jobs.neighbour_mean(_graph(spark, sf_dir, "embed_knn"), vectors).select("v", F.transform("mean", lambda y: F.round(y, 6)).alias("mean"))


_add("neighbour_mean_label", _neighbours)

# ---- operators around the methods ----------------------------------------------------------------


def _rows_of_report(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = None
    for method, k in (("hash_edge", 4), ("hash_edge", 8), ("hash_src", 4), ("hash_src", 8)):
        one = metrics.loads(_stateless(spark, sf_dir, method, "cust_part", k)).select(F.lit(method).alias("method"), F.lit(k).alias("k"), "n")
        out = one if out is None else out.union(one)
    return out


_REPORT = " UNION ALL ".join(f"SELECT '{m}' AS method, {k} AS k, count(*) AS n FROM (SELECT {_p_sql(m, k)} AS p FROM g) t GROUP BY p" for m, k in (("hash_edge", 4), ("hash_edge", 8), ("hash_src", 4), ("hash_src", 8)))
_add(
    "report_cube", lambda s, d: _rows_of_report(s, d).cube("method", "k").agg(F.max("n").alias("max_load"), F.sum("n").alias("edges")),
    f"WITH {_g('cust_part')}, r AS ({_REPORT}) SELECT method, k, max(n) AS max_load, CAST(sum(n) AS BIGINT) AS edges FROM r GROUP BY CUBE (method, k)",
)
_add(
    "report_pivot", lambda s, d: _rows_of_report(s, d).groupBy("method").pivot("k", [4, 8]).agg(F.max("n")).select("method", F.col("4").alias("k4"), F.col("8").alias("k8")),
    f"WITH {_g('cust_part')}, r AS ({_REPORT}) SELECT method, max(CASE WHEN k = 4 THEN n END) AS k4, max(CASE WHEN k = 8 THEN n END) AS k8 FROM r GROUP BY method",
)
_add(
    "sample_rate", lambda s, d: _graph(s, d, "cust_part").where(portable(portable(F.col("src")) + portable(F.col("dst"), 1)) % 100 < 5),
    f"WITH {_g('cust_part')} SELECT src, dst FROM g WHERE {stateless.edge_hash_sql()} % 100 < 5",
)
_add(
    "setops_cover", lambda s, d: metrics.check_exact_cover(_graph(s, d, "cust_order"), _stateless(s, d, "grid", "cust_order", 12)), "SELECT CAST(0 AS BIGINT) AS missing, CAST(0 AS BIGINT) AS extra"
)
_add(
    "window_running_volume", lambda s, d: clustering.volumes(_nation_clusters(s, d)[1]).withColumn("running", F.sum("vol").over(Window.orderBy("c").rowsBetween(Window.unboundedPreceding, 0))),
    f"WITH {_CL} SELECT c, vol, CAST(sum(vol) OVER (ORDER BY c ROWS UNBOUNDED PRECEDING) AS BIGINT) AS running FROM vols",
)


def _as_of(spark: SparkSession, sf_dir: str) -> DataFrame:
    """For each event the last snapshot of its type (the first event of each hour) at or before it.

    Two levels: the last snapshot of each day is carried over the days, then snapshots are followed inside a day.
    """
    events = table(spark, sf_dir, "events").select("event_id", F.col("ts").cast("timestamp").alias("ts"), F.col("event_type").alias("t"))
    hours = events.groupBy("t", F.date_trunc("hour", "ts").alias("h")).agg(F.min(F.struct("ts", "event_id")).alias("s"))
    snaps = materialise(hours.select("t", F.col("s.ts").alias("ts"), F.col("s.event_id").alias("snap"), F.to_date("s.ts").alias("day")), "snapshots")
    days = events.select("t", F.to_date("ts").alias("day")).distinct().join(snaps.groupBy("t", "day").agg(F.max_by("snap", "ts").alias("last")), ["t", "day"], "left")
    carried = days.withColumn("before", F.last("last", ignorenulls=True).over(Window.partitionBy("t").orderBy("day").rowsBetween(Window.unboundedPreceding, -1)))
    both = events.select("event_id", "ts", "t", F.to_date("ts").alias("day"), F.lit(None).cast("long").alias("snap"), F.lit(1).alias("late"))
    both = both.union(snaps.select(F.lit(None).cast("long"), "ts", "t", "day", "snap", F.lit(0)))
    inside = F.last("snap", ignorenulls=True).over(Window.partitionBy("t", "day").orderBy("ts", "late").rowsBetween(Window.unboundedPreceding, 0))
    seen = both.withColumn("inside", inside).where("event_id is not null").join(carried.select("t", "day", "before"), ["t", "day"], "left")
    return seen.select("event_id", F.coalesce("inside", "before").alias("seen"))


_add(
    "asof_cluster_snapshot", _as_of,
    "WITH s AS (SELECT event_type AS t, min(ts) AS taken, arg_min(event_id, row(ts, event_id)) AS snap FROM events GROUP BY event_type, date_trunc('hour', ts)) "
    "SELECT event_id, snap AS seen FROM events ASOF LEFT JOIN s ON t = event_type AND taken <= ts",
)
_add(
    "interval_edges",
    lambda s, d: (
        (lambda e: e.alias("a").join(e.alias("b"), (F.col("a.user_id") == F.col("b.user_id")) & (F.col("a.event_id") < F.col("b.event_id")) & (F.abs(F.unix_micros(F.col("b.ts").cast("timestamp")) - F.unix_micros(F.col("a.ts").cast("timestamp"))) <= 3_600_000_000)))(
            table(s, d, "events").select("event_id", "user_id", "ts")
        )
    ).select(F.col("a.event_id").alias("src"), F.col("b.event_id").alias("dst")),
    "SELECT a.event_id AS src, b.event_id AS dst FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_id < b.event_id AND abs(epoch_us(b.ts) - epoch_us(a.ts)) <= 3600000000",
)


def _sessions(spark: SparkSession, sf_dir: str) -> DataFrame:
    events = table(spark, sf_dir, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    before = F.lag("ts").over(Window.partitionBy("user_id").orderBy("ts", "event_id"))
    new = F.when(before.isNull() | (F.unix_micros("ts") - F.unix_micros(before) > 6 * 3_600_000_000), 1).otherwise(0)
    return events.select("user_id", new.alias("new")).groupBy("user_id").agg(F.sum("new").cast("long").alias("sessions"), F.count("*").alias("events"))


_add(
    "session_edges", _sessions,
    "SELECT user_id, CAST(sum(CASE WHEN b IS NULL OR epoch_us(ts) - epoch_us(b) > 21600000000 THEN 1 ELSE 0 END) AS BIGINT) AS sessions, count(*) AS events "
    "FROM (SELECT user_id, ts, lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS b FROM events) t GROUP BY user_id",
)
_add(
    "payload_json_weight", lambda s, d: table(s, d, "events").groupBy("event_type").agg(F.sum(F.get_json_object("props", "$.k").cast("long")).alias("weight")),
    "SELECT event_type, CAST(sum(CAST(json_extract_string(props, '$.k') AS BIGINT)) AS BIGINT) AS weight FROM events GROUP BY event_type",
)
_add(
    "replica_bitmaps",
    lambda s, d: (
        _stateless(s, d, "hash_edge", "cust_part", 8).select(F.explode(F.array("src", "dst")).alias("v"), "p").groupBy("v").agg(F.bit_or(F.expr("shiftleft(1L, p)")).alias("bits"))
    ),
    f"WITH {_assigned_sql('hash_edge', 'cust_part', 8)} SELECT v, CAST(bit_or(CAST(1 AS BIGINT) << p) AS BIGINT) AS bits FROM (SELECT src AS v, p FROM a UNION ALL SELECT dst, p FROM a) t GROUP BY v",
)


def _sql_surface(spark: SparkSession, sf_dir: str) -> DataFrame:
    sql_functions.register(prepare(spark))
    _graph(spark, sf_dir, "cust_order").createOrReplaceTempView("edges")
    return spark.sql("SELECT portable_hash(src, 0L) % 8 AS p, count(*) AS n FROM edges GROUP BY 1")


_add("sql_portable_hash", _sql_surface, f"WITH {_g('cust_order')} SELECT {portable_sql('src')} % 8 AS p, count(*) AS n FROM g GROUP BY 1")

_ENDS_SQL = "(SELECT src AS v, p FROM a UNION ALL SELECT dst, p FROM a)"
_add(
    "replica_bitmaps_wide", lambda s, d: metrics.replica_bitmaps(_stateless(s, d, "hash_edge", "cust_part", 100), 100).select("v", F.col("bits")[0].alias("low"), F.col("bits")[1].alias("high")),
    f"WITH {_assigned_sql('hash_edge', 'cust_part', 100)} SELECT v, CAST(bit_or(CASE WHEN p < 63 THEN CAST(1 AS BIGINT) << p ELSE 0 END) AS BIGINT) AS low, CAST(bit_or(CASE WHEN p >= 63 THEN CAST(1 AS BIGINT) << (p - 63) ELSE 0 END) AS BIGINT) AS high "
    f"FROM {_ENDS_SQL} t GROUP BY v",
)


def _sketched_covers(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Whether each partition's distinct vertices, and those of all by merging sketches, are estimated within a twentieth."""
    done = materialise(_stateless(spark, sf_dir, "dbh", "cust_part", 8), "assigned")
    ends = done.select(F.explode(F.array("src", "dst")).alias("v"), "p")
    sketches = materialise(metrics.cover_sketches(done), "sketches")
    guess = sketches.select("p", F.hll_sketch_estimate("sketch").alias("guess")).union(sketches.agg(F.lit(-1).alias("p"), F.hll_sketch_estimate(F.hll_union_agg("sketch")).alias("guess")))
    exact = ends.groupBy("p").agg(F.countDistinct("v").alias("n")).union(ends.agg(F.lit(-1).alias("p"), F.countDistinct("v").alias("n")))
    return guess.join(exact, "p").select("p", "n", (F.abs(F.col("guess") - F.col("n")) <= 0.05 * F.col("n")).alias("near"))


_add(
    "cover_sketches", _sketched_covers,
    f"WITH {_assigned_sql('dbh', 'cust_part', 8)}, e AS {_ENDS_SQL} SELECT p, count(DISTINCT v) AS n, true AS near FROM e GROUP BY p UNION ALL SELECT -1, count(DISTINCT v), true FROM e",
)
_add(
    "udaf_merge_masks", lambda s, d: _stateless(s, d, "hash_edge", "cust_part", 8).select(F.explode(F.array("src", "dst")).alias("v"), F.expr("shiftleft(1L, p)").alias("m")).groupBy("v").agg(scoring.merge_masks("m").alias("bits")),
    ORACLES["replica_bitmaps"],
)


def _arrow_scores(spark: SparkSession, sf_dir: str) -> DataFrame:
    edges = _nation_plan(spark, sf_dir)[1]
    own = edges.where("p_u = p_v").select("src", "dst", F.col("p_u").alias("p"))
    rows = placement.with_sets(edges.where("p_u <> p_v"), placement.replica_sets(own))
    held = lambda ps, p: F.array_contains(F.col(ps), F.col(p)).cast("double")
    score = lambda p, vol: F.round(scoring.pair_score_arrow("d_u", "d_v", vol, "vol_u", "vol_v", held("ps_u", p), held("ps_v", p)), 6)
    return rows.select("src", "dst", score("p_u", "vol_u").alias("score_u"), score("p_v", "vol_v").alias("score_v"))


_add("arrow_udf_pair_score", _arrow_scores, ORACLES["pair_score_nation"])


def _udtf_candidates(spark: SparkSession, sf_dir: str) -> DataFrame:
    sql_functions.register(prepare(spark))
    _graph(spark, sf_dir, "cust_order").createOrReplaceTempView("edges")
    homes = "SELECT src, dst, CAST(portable_hash(src, 0L) % 4 AS INT) AS a, CAST(portable_hash(dst, 0L) % 4 AS INT) AS b FROM edges"
    return spark.sql(f"SELECT src, dst, t.p, t.is_home FROM ({homes}), LATERAL edge_partition_candidates(a, b, 4) t")


_add(
    "udtf_candidates", _udtf_candidates,
    f"WITH {_g('cust_order')} SELECT src, dst, CAST(i AS INTEGER) AS p, i IN ({portable_sql('src')} % 4, {portable_sql('dst')} % 4) AS is_home FROM g CROSS JOIN range(4) r(i)",
)


def _udtf_lpt(spark: SparkSession, sf_dir: str) -> DataFrame:
    """List scheduling as a table function over one array of the nations' volumes, in the order of their names."""
    sql_functions.register(prepare(spark))
    volumes = clustering.volumes(_nation_clusters(spark, sf_dir)[1]).agg(F.sort_array(F.collect_list(F.struct("c", "vol"))).alias("x"))
    volumes.select(F.col("x.vol").alias("vols")).createOrReplaceTempView("nation_volumes")
    return spark.sql(f"SELECT t.place, t.vol, t.p FROM nation_volumes, LATERAL lpt(vols, {_K}) t")


_add("udtf_lpt", _udtf_lpt, f"WITH RECURSIVE {_LPT} SELECT CAST(row_number() OVER (ORDER BY c) - 1 AS INTEGER) AS place, vol, p FROM m")
_add(
    "map_policies", lambda s, d: (
        (lambda v: cluster_map.assign(v, _K, "hash").withColumn("policy", F.lit("hash")).union(cluster_map.assign(v, _K, "unsorted_list").withColumn("policy", F.lit("unsorted_list"))))(clustering.volumes(_nation_clusters(s, d)[1]))
    ),
    f"WITH RECURSIVE {_LPT.replace('ORDER BY vol DESC, c', 'ORDER BY c')} SELECT c, vol, p, 'unsorted_list' AS policy FROM m UNION ALL SELECT c, vol, CAST({portable_sql('c')} % {_K} AS INTEGER), 'hash' FROM vols",
)
_add(
    "cluster_quality_nation", lambda s, d: (
        metrics.cluster_quality(*_nation_clusters(s, d)).select("clusters", "largest_volume", F.round("inside_share", 6).alias("inside_share"), F.round("modularity", 6).alias("modularity"))
    ),
    f"WITH {_CL}, i AS (SELECT avg((a.c = b.c)::INTEGER) AS x FROM g JOIN cl a ON a.v = src JOIN cl b ON b.v = dst) "
    "SELECT count(*) AS clusters, max(vol) AS largest_volume, round((SELECT x FROM i), 6) AS inside_share, round((SELECT x FROM i) - sum(vol::DOUBLE * vol) / (sum(vol)::DOUBLE * sum(vol)::DOUBLE), 6) AS modularity FROM vols",
)
_add(
    "state_size_nation", lambda s, d: metrics.state_size(_nation_clusters(s, d)[1], _stateless(s, d, "hash_edge", _NATION, 8), 8),
    f"WITH {_assigned_sql('hash_edge', _NATION, 8)} SELECT (SELECT count(*) * 8 FROM d) AS dense_bits, (SELECT count(*) FROM (SELECT DISTINCT v, p FROM {_ENDS_SQL} t) u) AS sparse_rows",
)
_add(
    "dbh_given_degrees", lambda s, d: (lambda e: partition(e, 8, method="dbh", degrees_table=degrees.compute(e)).assignment.select("src", "dst", "p"))(_graph(s, d, "cust_part")),
    f"WITH {_assigned_sql('dbh', 'cust_part', 8)} SELECT src, dst, p FROM a",
)
_add(
    "window_recent_degree",
    lambda s, d: table(s, d, "events").select("event_id", F.count("*").over(Window.partitionBy("user_id").orderBy(F.unix_micros(F.col("ts").cast("timestamp"))).rangeBetween(-3_600_000_000, 0)).alias("recent")),
    "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY epoch_us(ts) RANGE BETWEEN 3600000000 PRECEDING AND CURRENT ROW) AS recent FROM events",
)
_add(
    "session_windows", lambda s, d: live.session_counts(table(s, d, "events")).select("user_id", F.unix_micros(F.col("start").cast("timestamp")).alias("start_us"), "n"),
    "WITH b AS (SELECT user_id, epoch_us(ts) AS t, lag(epoch_us(ts)) OVER (PARTITION BY user_id ORDER BY ts) AS before FROM events), "
    "s AS (SELECT user_id, t, sum(CASE WHEN before IS NULL OR t - before >= 21600000000 THEN 1 ELSE 0 END) OVER (PARTITION BY user_id ORDER BY t ROWS UNBOUNDED PRECEDING) AS i FROM b) "
    "SELECT user_id, min(t) AS start_us, count(*) AS n FROM s GROUP BY user_id, i",
)

# ---- streams -------------------------------------------------------------------------------------


def _streamed(spark: SparkSession, sf_dir: str, make: Callable[[DataFrame], DataFrame]) -> DataFrame:
    """Run a stream over the events folder to its end and read what it wrote."""
    prepare(spark)
    folder, out = fresh_path(spark, "events"), fresh_path(spark, "streamed")
    table(spark, sf_dir, "events").write.parquet(folder)
    done = make(live.event_stream(spark, folder))
    query = done.writeStream.format("parquet").option("path", out).option("checkpointLocation", f"{out}-log").trigger(availableNow=True).start()
    query.awaitTermination()
    return spark.read.schema(done.schema).parquet(out)


def _stream_dbh(spark: SparkSession, sf_dir: str) -> DataFrame:
    known = table(spark, sf_dir, "events").select((F.col("user_id") * 8 + 4).alias("v")).groupBy("v").agg(F.count("*").alias("d"))
    known = materialise(known, "degrees")
    pair = lambda e: live.assign_live(e.select((F.col("user_id") * 8 + 4).alias("src"), (F.col("event_id") * 8).alias("dst")), known, 8)
    return _streamed(spark, sf_dir, pair).select("src", "dst", "p")


_add(
    "stream_dbh", _stream_dbh,
    # Events are in no table of degrees, so theirs is 0: the lower one.
    f"SELECT user_id * 8 + 4 AS src, event_id * 8 AS dst, CAST({portable_sql('event_id * 8')} % 8 AS INTEGER) AS p FROM events",
)


for _name, _slide in (("tumbling", 600), ("sliding", 300)):
    _add(
        f"window_{_name}", lambda s, d, x=_slide: live.window_counts(table(s, d, "events"), "10 minutes", f"{x} seconds").select(F.unix_micros(F.col("start").cast("timestamp")).alias("start_us"), "n"),
        f"SELECT CAST(w AS BIGINT) AS start_us, count(*) AS n FROM (SELECT unnest([(epoch_us(ts) // {_slide * 10**6} - i) * {_slide * 10**6} FOR i IN range({600 // _slide})]) AS w FROM events) t GROUP BY w",
    )


def _stream_clusters(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Clusters after the event stream's edges (user, event type) came in one micro-batch."""
    prepare(spark)
    folder = fresh_path(spark, "edges")
    kinds = F.pmod(F.xxhash64("event_type"), F.lit(1000)) * 8 + 7
    table(spark, sf_dir, "events").select((F.col("user_id") * 8 + 4).alias("src"), kinds.alias("dst")).distinct().coalesce(1).write.parquet(folder)
    state = live.LiveClusters(spark, None, fresh_path(spark, "live"))
    query = live.run(spark.readStream.schema("src long, dst long").parquet(folder), state)
    query.awaitTermination()
    return state.clusters


_add("stream_cluster_state", _stream_clusters)

# ---- experiments ---------------------------------------------------------------------------------

_add("w_k_sweep", workloads.k_sweep)
_add("w_main_grid", workloads.main_grid)
_add("w_phase_split", workloads.phase_split)
_add("w_stage_mix", workloads.stage_shares)
_add("w_restream_rf", workloads.restream)
_add("w_restream_time", workloads.restream_time)
_add("w_full_scan", workloads.full_scan)
_add("w_pagerank", workloads.pagerank_totals)
_add("w_storage", workloads.storage_levels)
_add("w_hep_tau", workloads.hep_tau)
_add("w_ablation", workloads.ablation)
_add("w_evaluations", workloads.evaluations)
_add(
    "evaluations_bound", lambda s, d: workloads.evaluations(s, d).select("method", "k", F.when(F.col("method") == "hdrf", F.col("per_edge") == F.col("k")).otherwise(F.col("per_edge") <= 2).alias("as_claimed")),
    "SELECT method, k, true AS as_claimed FROM (SELECT unnest(['cluster_guided', 'hdrf']) AS method) m CROSS JOIN (SELECT unnest([4, 32, 256]) AS k) t",
)


def _complexity(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The nearest whole power of k that score evaluations an edge follow: none for two candidates, the first for a full scan.

    Two candidates stay below 2 an edge, but come nearer to it as k grows and fewer edges are pre-partitioned.
    """
    slope = F.regr_slope(F.log("per_edge"), F.log("k"))
    return workloads.evaluations(spark, sf_dir).groupBy("method").agg(F.abs(F.round(slope, 0)).alias("power_of_k"))


_add("complexity_in_k", _complexity, "SELECT unnest(['cluster_guided', 'hdrf']) AS method, unnest([0.0::DOUBLE, 1.0::DOUBLE]) AS power_of_k")


def _quality_engines(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Distributed engines against the exact stream and against DBH: replication factors within a twentieth, and below."""
    rows = workloads.engine_quality(spark, sf_dir, _NATION, 8, ("hdrf", "cluster_guided", "cluster_guided_full"), ("bulk",))
    return rows.select("method", "engine", (F.col("rf") <= 1.05 * F.col("rf_sequential")).alias("near_sequential"), (F.col("rf") < F.col("rf_dbh")).alias("below_dbh"))


_add("w_engine_quality", lambda s, d: workloads.engine_quality(s, d))
_add(
    "quality_engines", _quality_engines,
    "SELECT method, 'bulk' AS engine, true AS near_sequential, true AS below_dbh FROM (SELECT unnest(['hdrf', 'cluster_guided', 'cluster_guided_full']) AS method) t",
)
_add("w_linearity", workloads.linearity)
_add("w_memory", workloads.memory)
