"""The experiments, on graphs derived from the given tables.

Quality experiments run many settings over one graph.  Each setting is a sequential run by
definition, so a setting is one task and all settings run side by side; time experiments call
``partition`` itself.
"""

from __future__ import annotations

import time
from collections.abc import Iterator
from functools import partial, reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .operators import degrees, jobs, metrics
from .operators import sequential as seq
from .operators import stateless
from .plans.api import GUIDED, partition, run_stored, run_stream, spooled
from .plans.storage import materialise, prepare, session_value, temporary
from .sources import builders

_DEFAULTS = dict(
    passes=1, migration="residual", degree_mode="exact", schedule="lpt", terms="replica,cluster", warm_start=True, bounded=True, factor=0.25, try_second=False, seed=0, lam=1.1, eps=1.0, tau=10.0, cache=2, expansion=0.1,
    min_buffer=10, latency_factor=40.0, alpha=1.05,
)
#: With it on, a union of tables of one partition has one partition too, and settings would wait for each other.
_ONE_EACH = "spark.sql.unionOutputPartitioning"
_RESULT = "setting int, method string, variant string, k int, edges long, vertices long, rf double, max_load long, cap long, covered boolean, scored long, prepartitioned long, clusters long, seconds double, memory_mb double"


def setting(method: str, k: int, variant: str = "", **changes) -> dict:
    unknown = set(changes) - set(_DEFAULTS)
    if unknown:
        raise ValueError(f"unknown options {sorted(unknown)}")
    return {"method": method, "k": k, "variant": variant} | _DEFAULTS | changes


def sweep(edges: DataFrame, settings: list[dict]) -> DataFrame:
    """A row of measures for each setting."""
    spark = prepare(edges.sparkSession)

    def run(batches: Iterator[pa.RecordBatch], i: int) -> Iterator[pa.RecordBatch]:
        s = settings[i]
        _reset_peak()
        stream = spooled(batches)
        if not stream.m:
            return
        m, k = stream.m, s["k"]
        cap = degrees.hard_cap(m, k, s["alpha"])
        options = s | {"limit": degrees.volume_cap(m, k, s["alpha"], s["factor"]) if s["bounded"] else None, "terms": tuple(s["terms"].split(","))}
        begin = time.perf_counter()
        stream, parts, names = run_stream(stream, k, cap, s["method"], options)
        seconds = time.perf_counter() - begin
        replicas = sum(x.bit_count() for x in (parts.mask if s["warm_start"] else _masks(stream, parts)))
        load = np.bincount(parts.p, minlength=k)
        values = [
            i, s["method"], s["variant"], k, m, stream.n, replicas / stream.n, int(load.max()), cap, bool((parts.p >= 0).all()), parts.scored, int((parts.stage == 0).sum()) if s["method"] in GUIDED else 0,
            len(np.unique(names)) if names is not None else 0, seconds, _peak_mb(),
        ]
        kinds = (pa.int32(), pa.string(), pa.string(), pa.int32(), pa.int64(), pa.int64(), pa.float64(), pa.int64(), pa.int64(), pa.bool_(), pa.int64(), pa.int64(), pa.int64(), pa.float64(), pa.float64())
        yield pa.RecordBatch.from_arrays([pa.array([v], t) for v, t in zip(values, kinds, strict=True)], names=[x.split()[0] for x in _RESULT.split(", ")])

    # A setting is a task that reads the stored edges itself and adds up their positions: no copies of them go through a shuffle.
    with temporary():
        rows = degrees.with_position(edges.select("src", "dst")).select("pos", "src", "dst").coalesce(1)
        each = [rows.mapInArrow(partial(run, i=i), _RESULT) for i in range(len(settings))]
        with session_value(spark, _ONE_EACH, "false"):
            return materialise(reduce(DataFrame.union, each).drop("setting"), "sweep", keep=True)


def _reset_peak() -> None:
    """From now on the process's peak of resident memory counts anew (where the system can do that)."""
    try:
        with open("/proc/self/clear_refs", "w") as f:
            f.write("5")
    except OSError:
        pass


def _peak_mb() -> float | None:
    """Most resident MB of this process since ``_reset_peak``, interpreter and libraries included; null where the system does not tell."""
    try:
        with open("/proc/self/status") as f:
            return next((int(line.split()[1]) / 1024 for line in f if line.startswith("VmHWM:")), None)
    except OSError:
        return None


def _masks(stream: seq.Stream, parts: seq.Partitions) -> list[int]:
    """Replica masks of the result alone (the ablation without warm start forgets those of its first step)."""
    masks = [0] * stream.n
    for at, us, vs in stream.chunks():
        for u, v, p in zip(us.tolist(), vs.tolist(), parts.p[at : at + len(us)].tolist(), strict=True):
            masks[u] |= 1 << p
            masks[v] |= 1 << p
    return masks


def stateless_rf(edges: DataFrame, methods: tuple[str, ...], ks: tuple[int, ...]) -> DataFrame:
    """``method, k, rf, alpha`` of stateless methods."""
    known = degrees.compute(edges)
    out = None
    for method in methods:
        for k in ks:
            done = stateless.dbh(edges, known, k) if method == "dbh" else {"grid": stateless.grid, "hash_edge": stateless.hash_edge, "hash_src": stateless.hash_src, "pds": stateless.difference_sets}[method](edges, k)
            one = metrics.replication_factor(done).crossJoin(metrics.imbalance(done, k)).select(F.lit(method).alias("method"), F.lit(k).alias("k"), F.round("rf", 6).alias("rf"), F.round("alpha", 6).alias("alpha"))
            out = one if out is None else out.union(one)
    return out


def k_sweep(spark: SparkSession, sf_dir: str, graph: str = "cust_part", ks: tuple[int, ...] = (4, 8, 16, 32, 64, 128, 256)) -> DataFrame:
    """Quality against k of the guided method, HDRF and DBH."""
    edges = materialise(builders.graph(spark, sf_dir, graph), "graph")
    rows = sweep(edges, [setting(m, k) for m in ("cluster_guided", "hdrf") for k in ks]).select("method", "k", F.round("rf", 6).alias("rf"), F.round(F.col("max_load") * F.col("k") / F.col("edges"), 6).alias("alpha"))
    return rows.union(stateless_rf(edges, ("dbh",), ks))


MAIN_METHODS = ("cluster_guided", "hdrf", "adwise", "sne", "ne", "dne", "multilevel", "hep")
MAIN_GRAPHS = ("cust_part", "order_part", "order_supp", "nation_planted", "doc_token", "doc_line", "cust_order")
HEP_TAUS = (100, 10, 1)


def main_grid(spark: SparkSession, sf_dir: str, graphs: tuple[str, ...] = MAIN_GRAPHS, ks: tuple[int, ...] = (4, 32, 128, 256), methods: tuple[str, ...] = MAIN_METHODS, repeats: int = 3) -> DataFrame:
    """Graphs x methods x k: quality, mean and sd of seconds, and peak memory over repeated runs.

    The hybrid runs with each of its thresholds (``variant``).  Memory is the worker's, so it is null for DBH, which is no single task.
    """
    out = None
    for name in graphs:
        edges = materialise(builders.graph(spark, sf_dir, name), "graph")
        variants = [(m, str(t), {"tau": float(t)}) for m in methods if m == "hep" for t in HEP_TAUS] + [(m, "", {}) for m in methods if m != "hep"]
        runs = sweep(edges, [setting(m, k, x, **o) for _ in range(repeats) for m, x, o in variants for k in ks])
        measured = F.round(F.max("rf"), 6).alias("rf"), F.round(F.max(F.col("max_load") * F.col("k") / F.col("edges")), 6).alias("alpha")
        rows = runs.groupBy("method", "variant", "k").agg(*measured, F.avg("seconds").alias("seconds"), F.stddev_samp("seconds").alias("sd_s"), F.count("*").alias("runs"), F.max("memory_mb").alias("memory_mb"))
        rows = rows.unionByName(_timed_dbh(edges, ks, repeats), allowMissingColumns=True).select(F.lit(name).alias("graph"), "*")
        out = rows if out is None else out.union(rows)
    return out


def _timed_dbh(edges: DataFrame, ks: tuple[int, ...], repeats: int) -> DataFrame:
    """``method, variant, k, rf, alpha, seconds, sd_s, runs`` of DBH; its degree pass counts."""
    seconds = []
    for k in ks:
        for _ in range(repeats):
            timer = metrics.Timer()
            with temporary(), timer.phase("run"):
                materialise(stateless.dbh(edges, degrees.compute(edges), k), "hashed")
            seconds.append((k, timer.seconds["run"]))
    times = edges.sparkSession.createDataFrame(seconds, "k int, s double").groupBy("k").agg(F.avg("s").alias("seconds"), F.stddev_samp("s").alias("sd_s"), F.count("*").alias("runs"))
    return stateless_rf(edges, ("dbh",), ks).join(times, "k").select("method", F.lit("").alias("variant"), "k", "rf", "alpha", "seconds", "sd_s", "runs")


def phase_split(spark: SparkSession, sf_dir: str, graph: str = "cust_part", k: int = 32, engine: str = "bulk", batches: int = 2) -> DataFrame:
    """``phase, seconds, share`` of degree pass, clustering and partitioning."""
    done = partition(builders.graph(spark, sf_dir, graph), k, engine=engine, batches=batches)
    rows = [(n, s) for n, s in done.seconds.items() if n != "load"]
    total = sum(s for _, s in rows) or 1.0
    return spark.createDataFrame([(n, s, s / total) for n, s in rows], "phase string, seconds double, share double")


def stage_shares(spark: SparkSession, sf_dir: str, k: int = 32, graphs: tuple[str, ...] = ("cust_part", "order_part", "nation_planted", "doc_line", "cust_order")) -> DataFrame:
    """Share of pre-partitioned edges by graph."""
    out = None
    for name in graphs:
        rows = sweep(builders.graph(spark, sf_dir, name), [setting("cluster_guided", k)]).select(F.lit(name).alias("graph"), "k", F.round(F.col("prepartitioned") / F.col("edges"), 6).alias("prepartitioned_share"))
        out = rows if out is None else out.union(rows)
    return out


def restream(spark: SparkSession, sf_dir: str, graph: str = "cust_part", k: int = 32, passes: tuple[int, ...] = (1, 2, 4, 8)) -> DataFrame:
    """Replication factor by clustering passes, and over that of one pass."""
    rows = sweep(builders.graph(spark, sf_dir, graph), [setting("cluster_guided", k, str(r), passes=r) for r in passes])
    base = F.max(F.when(F.col("variant") == "1", F.col("rf"))).over(Window.partitionBy())
    return rows.select(F.col("variant").cast("int").alias("passes"), F.round("rf", 6).alias("rf"), F.round(F.col("rf") / base, 6).alias("ratio"))


def restream_time(spark: SparkSession, sf_dir: str, graph: str = "cust_part", k: int = 32, passes: tuple[int, ...] = (1, 2, 4, 8)) -> DataFrame:
    """Seconds by clustering passes."""
    edges = materialise(builders.graph(spark, sf_dir, graph), "graph")
    rows = []
    for r in passes:
        with temporary():
            done = partition(edges, k, engine="sequential", passes=r)
            rows.append((r, done.seconds["partitioning"]))
    return spark.createDataFrame([(r, s, s / rows[0][1]) for r, s in rows], "passes int, seconds double, ratio double")


def full_scan(spark: SparkSession, sf_dir: str, graphs: tuple[str, ...] = ("cust_part", "order_part", "order_supp", "doc_line"), ks: tuple[int, ...] = (4, 32, 128, 256)) -> DataFrame:
    """Full-scan variant over the two-candidate method: quality, score evaluations and a setting's own seconds."""
    rows = None
    for name in graphs:
        own = sweep(builders.graph(spark, sf_dir, name), [setting(m, k) for m in GUIDED for k in ks]).withColumn("graph", F.lit(name))
        rows = own if rows is None else rows.union(own)
    pick = lambda m, c: F.max(F.when(F.col("method") == m, F.col(c)))
    wide = rows.groupBy("graph", "k").agg(*[pick(m, c).alias(f"{c}_{n}") for m, n in zip(GUIDED, ("two", "all"), strict=True) for c in ("rf", "scored", "seconds")])
    return wide.select("graph", "k", F.round("rf_two", 6).alias("rf_two"), F.round("rf_all", 6).alias("rf_all"), F.round(F.col("rf_all") / F.col("rf_two"), 6).alias("rf_ratio"), "scored_two", "scored_all", "seconds_two", "seconds_all", (F.col("seconds_all") / F.col("seconds_two")).alias("seconds_ratio"))


PAGERANK_METHODS = ("cluster_guided", "cluster_guided_full", "hdrf", "dbh", "sne", "hep")


def pagerank_totals(spark: SparkSession, sf_dir: str, graphs: tuple[str, ...] = ("cust_part", "order_supp"), k: int = 32, iterations: int = 10, methods: tuple[str, ...] = PAGERANK_METHODS) -> DataFrame:
    """Replication factor, messages of an iteration, seconds of partitioning, of PageRank and of both; 100 iterations as published take ten times as long."""
    rows = []
    for name in graphs:
        edges = materialise(builders.graph(spark, sf_dir, name), "graph")
        for method in methods:
            with temporary():
                done = partition(edges, k, method=method, engine="sequential", tau=1.0)
                timer = metrics.Timer()
                with timer.phase("job"):
                    jobs.pagerank(done.assignment, iterations, k=k).agg(F.sum("rank")).collect()
                one = metrics.replication_factor(done.assignment).first()
            split = done.seconds["partitioning"]
            rows.append((name, method, one["rf"], one["replicas"] - one["vertices"], split, timer.seconds["job"], split + timer.seconds["job"]))
    return spark.createDataFrame(rows, "graph string, method string, rf double, messages long, partition_s double, pagerank_s double, total_s double")


def storage_levels(spark: SparkSession, sf_dir: str, graph: str = "cust_part", k: int = 32) -> DataFrame:
    """Seconds of the sequential engine whose every pass reads the edges again: from a cache, from executor disks, from plain and from compressed files.

    Storing the edges does not count.  ``passes`` is how often they were read.
    """
    from pyspark import StorageLevel

    prepare(spark)
    # The first run of a session starts Python workers: it is not one of those compared.
    run_stored(spark.createDataFrame([(0, 1, 2)], "pos long, src long, dst long").coalesce(1), 1, 2).collect()
    rows = []
    # One task streams the edges, so a stored table is one piece and keeps its order.
    with temporary(), session_value(spark, "spark.sql.files.maxPartitionBytes", str(1 << 40)), session_value(spark, "spark.sql.files.openCostInBytes", str(1 << 40)):
        stream = degrees.with_position(builders.graph(spark, sf_dir, graph))
        stream = materialise(stream.select("pos", "src", "dst").coalesce(1).sortWithinPartitions("pos"), "stored", options={"compression": "none"})
        edges = stream.count()
        for name, level in (("cache", StorageLevel.MEMORY_AND_DISK), ("disk", StorageLevel.DISK_ONLY), ("files", None), ("files_zstd", None)):
            stored = materialise(stream, "stored-zstd", options={"compression": "zstd"}) if name == "files_zstd" else stream
            if level is not None:
                stored = stored.persist(level)
                stored.count()
            timer = metrics.Timer()
            with temporary():
                with timer.phase("run"):
                    done = materialise(run_stored(stored, edges, k), "assignment")
                first = done.select("passes").first()
            if level is not None:
                stored.unpersist(blocking=True)
            rows.append((name, timer.seconds["run"], first[0] if first else 0))
    return spark.createDataFrame([(n, s, s / rows[0][1], r) for n, s, r in rows], "storage string, seconds double, ratio double, passes int")


def hep_tau(spark: SparkSession, sf_dir: str, graph: str = "order_supp", k: int = 32) -> DataFrame:
    """The hybrid by its threshold."""
    rows = sweep(builders.graph(spark, sf_dir, graph), [setting("hep", k, str(t), tau=float(t)) for t in (100, 10, 1)])
    return rows.select(F.col("variant").cast("int").alias("tau"), F.round("rf", 6).alias("rf"), "scored")


def ablation(spark: SparkSession, sf_dir: str, graph: str = "nation_planted", k: int = 16) -> DataFrame:
    """Each part of the design taken away in turn."""
    changes = {
        "default": {}, "unbounded": {"bounded": False}, "partial_degrees": {"degree_mode": "partial"}, "whole_volume": {"migration": "volume"}, "cold_start": {"warm_start": False}, "replica_only": {"terms": "replica"},
        "cluster_only": {"terms": "cluster"}, "hash_schedule": {"schedule": "hash"}, "round_robin": {"schedule": "round_robin"}, "unsorted_list": {"schedule": "unsorted_list"}, "second_try": {"try_second": True},
        "cap_x1": {"factor": 1.0}, "cap_x0.5": {"factor": 0.5}, "cap_x0.1": {"factor": 0.1},
    }
    rows = sweep(builders.graph(spark, sf_dir, graph), [setting("cluster_guided", k, n, **c) for n, c in changes.items()])
    return rows.select("variant", F.round("rf", 6).alias("rf"), "prepartitioned", "clusters", (F.col("max_load") <= F.col("cap")).alias("balanced"))


def evaluations(spark: SparkSession, sf_dir: str, graph: str = "cust_part", ks: tuple[int, ...] = (4, 32, 256)) -> DataFrame:
    """Score evaluations an edge: flat in k for two candidates, k for a full scan."""
    rows = sweep(builders.graph(spark, sf_dir, graph), [setting(m, k) for m in ("cluster_guided", "hdrf") for k in ks])
    return rows.select("method", "k", F.round(F.col("scored") / F.col("edges"), 6).alias("per_edge"))


def engine_quality(spark: SparkSession, sf_dir: str, graph: str = "nation_planted", k: int = 8, methods: tuple[str, ...] = ("hdrf", "cluster_guided", "cluster_guided_full"), engines: tuple[str, ...] = ("bulk", "shards")) -> DataFrame:
    """``method, engine, rf, alpha, rf_sequential, rf_dbh, seconds``: what distributed engines lose against the exact stream."""
    edges = materialise(builders.graph(spark, sf_dir, graph), "graph")
    factor = lambda done: metrics.replication_factor(done.assignment).first()["rf"]
    plain, rows = factor(partition(edges, k, method="dbh")), []
    for method in methods:
        exact = factor(partition(edges, k, method=method, engine="sequential"))
        for engine in engines:
            done = partition(edges, k, method=method, engine=engine)
            rows.append((method, engine, factor(done), metrics.imbalance(done.assignment, k).first()["alpha"], exact, plain, sum(done.seconds.values())))
    return spark.createDataFrame(rows, "method string, engine string, rf double, alpha double, rf_sequential double, rf_dbh double, seconds double")


def linearity(spark: SparkSession, sf_dir: str, graph: str = "cust_part", ks: tuple[int, ...] = (4, 32, 256), shares: tuple[float, ...] = (0.25, 0.5, 1.0), repeats: int = 3) -> DataFrame:
    """Mean and sd of a setting's seconds over growing parts of a graph, and the power of the edges that they follow."""
    whole, rows = materialise(builders.graph(spark, sf_dir, graph), "graph"), None
    for share in shares:
        part = whole.where(F.pmod(F.xxhash64("src", "dst"), F.lit(1000)) < int(1000 * share))
        own = sweep(part, [setting(m, k, str(i)) for m in ("cluster_guided", "hdrf") for k in ks for i in range(repeats)]).select("method", "k", "edges", "seconds")
        rows = own if rows is None else rows.union(own)
    rows = materialise(rows, "linearity")
    slope = rows.groupBy("method", "k").agg(F.regr_slope(F.log("seconds"), F.log("edges")).alias("power"))
    return rows.groupBy("method", "k", "edges").agg(F.avg("seconds").alias("mean_s"), F.stddev_samp("seconds").alias("sd_s"), F.count("*").alias("runs")).join(slope, ["method", "k"])


def memory(spark: SparkSession, sf_dir: str, graph: str = "cust_part", ks: tuple[int, ...] = (4, 32, 256)) -> DataFrame:
    """``k, edges, dense_bits, sparse_rows, bits_an_edge``: the state of the guided method, which grows with vertices and k and not with edges."""
    edges, rows = materialise(builders.graph(spark, sf_dir, graph), "graph"), []
    n = edges.count()
    for k in ks:
        with temporary():
            done = partition(edges, k, engine="sequential")
            one = metrics.state_size(done.clusters, done.assignment, k).first()
        rows.append((k, n, one["dense_bits"], one["sparse_rows"], one["dense_bits"] / n if n else None))
    return spark.createDataFrame(rows, "k int, edges long, dense_bits long, sparse_rows long, bits_an_edge double")
