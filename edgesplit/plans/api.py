"""``partition``: every method and engine behind one call."""

from __future__ import annotations

import os
import tempfile
from collections.abc import Iterator
from dataclasses import dataclass, field
from typing import IO

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..operators import cluster_map as cm
from ..operators import clustering, degrees, metrics, placement, sequential, stateless
from ..sources.edge_list import write_assignment
from .storage import materialise, prepare, temporary

STATELESS = ("dbh", "grid", "pds", "hash_edge", "hash_src")
SEQUENTIAL = ("greedy", "hdrf", "adwise", "ne", "sne", "dne", "hep", "multilevel", "label_prop")
GUIDED = ("cluster_guided", "cluster_guided_full")
METHODS = (*GUIDED, *STATELESS, *SEQUENTIAL)
ENGINES = ("bulk", "sequential", "shards")
_BULK = (*GUIDED, "hdrf")
_SHARDS = (*GUIDED, "hdrf", "greedy")


@dataclass
class PartitionResult:
    """Assignment ``src, dst, pos, p, stage`` and what led to it."""

    assignment: DataFrame
    k: int
    alpha: float
    method: str
    engine: str
    cap: int
    edges: int
    passes: int
    seconds: dict[str, float]
    clusters: DataFrame | None = None
    cluster_map: DataFrame | None = None
    scored: int | None = None
    extra: dict = field(default_factory=dict)

    @property
    def loads(self) -> DataFrame:
        return metrics.loads(self.assignment)

    @property
    def replicas(self) -> DataFrame:
        return self.assignment.select(F.explode(F.array("src", "dst")).alias("v"), "p").distinct()

    def report(self, graph: str = "") -> DataFrame:
        """``metric, value, k, method, engine, graph``."""
        spark = self.assignment.sparkSession
        own = [("passes", float(self.passes)), ("cap", float(self.cap)), *((f"seconds_{n}", s) for n, s in self.seconds.items())]
        if self.scored is not None:
            own.append(("score_evaluations", float(self.scored)))
        rows = metrics.evaluate(self.assignment, self.k, self.alpha).union(spark.createDataFrame(own, "metric string, value double"))
        return rows.select("metric", "value", F.lit(self.k).alias("k"), F.lit(self.method).alias("method"), F.lit(self.engine).alias("engine"), F.lit(graph).alias("graph"))

    def save(self, path: str) -> None:
        manifest = {r["metric"]: r["value"] for r in self.report().select("metric", "value").collect()}
        write_assignment(self.assignment, path, manifest | {"method": self.method, "engine": self.engine, "k": self.k})


def partition(
    edges: DataFrame, k: int, alpha: float = 1.05, method: str = "cluster_guided", engine: str = "bulk", passes: int = 1, batches: int = 4, volume_cap: int | None = None, cap_factor: float = 0.25,
    bounded: bool = True, migration: str = "residual", degree_mode: str = "exact", schedule: str = "lpt", terms: tuple[str, ...] = ("replica", "cluster"), warm_start: bool = True, try_second: bool = False,
    degrees_table: DataFrame | None = None, clusters: DataFrame | None = None, seed: int = 0, lam: float = 1.1, eps: float = 1.0, tau: float = 10.0, cache: int = 2, expansion: float = 0.1,
    min_buffer: int = 10, latency_factor: float = 40.0, order_by: tuple[str, ...] | None = None, subrounds: int = 1, min_moved: float = 0.0, first_batch: int = 256, growth: float = 0.5, shard_edges: int = 100_000,
) -> PartitionResult:
    """Split distinct edges ``src, dst`` into k partitions.

    Stateless methods are expressions and ignore ``engine``.  In-memory and buffered baselines know
    the sequential engine only, where one task holds the graph, as their own systems do; it has to be
    asked for.  An option that the engine does not know raises.  ``first_batch`` is the number of edges
    in the bulk engine's first batch, ``growth`` how much each next one may be larger than all before it
    (only where a method scores all partitions; others take ``batches`` even ones).  ``shard_edges`` is
    about how many edges the shards engine gives to one fold.
    """
    prepare(edges.sparkSession)
    if method not in METHODS:
        raise ValueError(f"unknown method {method!r}; one of {METHODS}")
    if engine not in ENGINES:
        raise ValueError(f"unknown engine {engine!r}; one of {ENGINES}")
    if not set(terms) <= {"replica", "cluster"} or not terms:
        raise ValueError("terms are replica, cluster or both")
    _check_options(method, engine, degree_mode, clusters is not None, degrees_table is not None)
    degrees.hard_cap(1, k, alpha)
    timer = metrics.Timer()
    with timer.phase("load"):
        with temporary():
            stream = edges if "pos" in edges.columns else degrees.with_position(edges.select("src", "dst"), order_by)
            stream = materialise(stream, "stream", keep=True)
        total = stream.count()
    cap = degrees.hard_cap(total, k, alpha)
    engine = "stateless" if method in STATELESS else engine
    out = PartitionResult(stream, k, alpha, method, engine, cap, total, 1, timer.seconds)
    if method in STATELESS:
        with timer.phase("partitioning"):
            _stateless(out, stream, k, method, seed, degrees_table)
        return out
    limit = (volume_cap or degrees.volume_cap(total, k, alpha, cap_factor)) if bounded else None
    if limit is not None and limit < 1:
        raise ValueError("the volume cap must be at least 1")
    options = dict(limit=limit, passes=passes, migration=migration, degree_mode=degree_mode, schedule=schedule, terms=terms, warm_start=warm_start, try_second=try_second, seed=seed, lam=lam, eps=eps, tau=tau, cache=cache, expansion=expansion, min_buffer=min_buffer, latency_factor=latency_factor, first_batch=first_batch, growth=growth, shard_edges=shard_edges)
    if engine == "sequential":
        with timer.phase("partitioning"):
            _sequential(out, stream, options)
        return out
    with timer.phase("degrees"):
        known = degrees.check_known(stream, degrees_table) if degrees_table is not None else materialise(degrees.compute(stream), "degrees")
    if method in GUIDED:
        with timer.phase("clustering"):
            out.clusters = clusters if clusters is not None else clustering.stream_cluster(stream, known, limit, total, passes, batches, migration, subrounds, min_moved)
        out.passes = (degrees_table is None) + (passes if clusters is None else 0) + 2
    with timer.phase("partitioning"):
        _bulk(out, stream, known, engine, batches, options)
    return out


def _check_options(method: str, engine: str, degree_mode: str, own_clusters: bool, own_degrees: bool) -> None:
    """Raise where an engine cannot do what it is asked for."""
    if method in STATELESS:
        return
    known = {"bulk": _BULK, "shards": _SHARDS, "sequential": METHODS}[engine]
    if method not in known:
        raise ValueError(f"{method} has no {engine} engine; ask for engine='sequential', which holds the graph in one task")
    if degree_mode not in ("exact", "partial"):
        raise ValueError("degree_mode is exact or partial")
    if degree_mode == "partial" and engine != "sequential":
        raise ValueError("partial degrees are counted edge by edge: engine='sequential' only")
    if engine == "sequential" and (own_clusters or own_degrees):
        raise ValueError("the sequential engine counts degrees and clusters itself; given ones need engine='bulk' or 'shards'")


def _stateless(out: PartitionResult, stream: DataFrame, k: int, method: str, seed: int, known: DataFrame | None) -> None:
    if method == "dbh":
        known = degrees.check_known(stream, known) if known is not None else degrees.compute(stream)
        done, out.passes = stateless.dbh(stream, known, k, seed), 2
    else:
        done = {"grid": stateless.grid, "pds": stateless.difference_sets, "hash_edge": stateless.hash_edge, "hash_src": stateless.hash_src}[method](stream, k, seed)
    out.assignment = materialise(done.withColumn("stage", F.lit("hashed")), "assignment")


def _bulk(out: PartitionResult, stream: DataFrame, known: DataFrame, engine: str, batches: int, o: dict) -> None:
    k, loads = out.k, placement.Loads(out.k, out.cap)
    parts: list[DataFrame] = []
    sets = None
    if out.method in GUIDED:
        out.cluster_map = materialise(cm.assign(clustering.volumes(out.clusters), k, o["schedule"]), "cluster-map")
        plan = materialise(placement.vertex_plan(out.clusters, out.cluster_map), "vertex-plan")
        rows = materialise(placement.enrich(stream, plan), "enriched")
        own, refused = placement.admit(rows.where("p_u = p_v").withColumn("p", F.col("p_u")), loads)
        own = own.withColumn("stage", F.lit("prepartition"))
        loads.add(own)
        parts = [own, *(placement.overflow(refused, loads, o["seed"]) if refused is not None else [])]
        rest = rows.where("p_u <> p_v")
        if o["warm_start"]:
            first = parts[0].select("src", "dst", "p")
            for x in parts[1:]:
                first = first.unionByName(x.select("src", "dst", "p"))
            sets = materialise(placement.replica_sets(first), "replicas")
    else:
        d_u, d_v = (known.select(F.col("v").alias(x), F.col("d").alias(n)) for x, n in (("src", "d_u"), ("dst", "d_v")))
        rest = materialise(stream.join(d_u, "src").join(d_v, "dst").withColumns({"p_u": F.lit(0), "p_v": F.lit(0)}), "enriched")
    if engine == "shards":
        parts += _shards(out, rest, sets, loads, o)
    else:
        two = out.method == "cluster_guided"
        choose = (lambda b, _now, _n: placement.choose_of_two(b, o["terms"])) if two else (lambda b, now, n: placement.choose_of_all(b, k, now, o["lam"], o["eps"], n))
        rounds = placement.even_batches(out.edges, batches) if two else placement.growing_batches(out.edges, o["first_batch"], o["growth"])
        parts += placement.place_stream(rest, sets, loads, rounds, choose, o["seed"], o["try_second"], spread=not two)
        out.scored = rest.count() * (2 if two else k)
    columns = ["pos", "src", "dst", "p", "stage"]
    done = parts[0].select(columns)
    for x in parts[1:]:
        done = done.unionByName(x.select(columns))
    out.assignment = materialise(done, "assignment")


def _shards(out: PartitionResult, rest: DataFrame, sets: DataFrame | None, loads: placement.Loads, o: dict) -> list[DataFrame]:
    """Each shard of edges is folded alone, with its share of every partition's free places; what finds none overflows.

    An edge's shard is that of its end of lower degree: such a vertex's edges meet, and only hubs are spread.
    """
    k, method = out.k, out.method
    spark = rest.sparkSession
    shards = max(1, -(-out.edges // o["shard_edges"]))
    rows = placement.with_sets(rest, sets if sets is not None else spark.createDataFrame([], "v long, ps array<int>"))
    rows = rows.withColumn("__shard", F.pmod(F.xxhash64(F.when((F.col("d_u") < F.col("d_v")) | ((F.col("d_u") == F.col("d_v")) & (F.col("src") <= F.col("dst"))), F.col("src")).otherwise(F.col("dst"))), F.lit(shards)).cast("int"))
    sizes = {r["__shard"]: r["n"] for r in rows.groupBy("__shard").agg(F.count("*").alias("n")).collect()}
    whole, free = max(1, sum(sizes.values())), loads.free()
    kept = [(n, t) for n, t in rest.dtypes]

    def fold(table: pa.Table) -> pa.Table:
        table = table.sort_by("pos")
        stream = sequential.Stream(table.column("src").to_numpy(), table.column("dst").to_numpy())
        share = sizes[table.column("__shard")[0].as_py()] / whole
        quota = [int(x * share) for x in free]
        own = sequential.Partitions(stream, k, max(quota, default=0), o["seed"])
        own.load = [own.cap - x for x in quota]
        for x, d, c in ((stream.u, "d_u", "ps_u"), (stream.v, "d_v", "ps_v")):
            for i, n, ps in zip(x.tolist(), table.column(d).to_pylist(), table.column(c).to_pylist(), strict=True):
                own.degree[i] = n
                own.mask[i] = sum(1 << p for p in ps) | own.mask[i]
        p = _fold_two(stream, own, table, o) if method == "cluster_guided" else _fold_all(stream, own, method, o)
        return table.select([n for n, _ in kept]).append_column("p", pa.array(p.astype(np.int32)))

    schema = ", ".join(f"{n} {t}" for n, t in kept) + ", p int"
    chosen = materialise(rows.groupBy("__shard").applyInArrow(fold, schema), "shards")
    good = chosen.where("p >= 0").withColumn("stage", F.lit("scored"))
    loads.add(good)
    out.scored = sum(sizes.values()) * (2 if method == "cluster_guided" else k)
    refused = chosen.where("p < 0")
    return [good, *(placement.overflow(refused, loads, o["seed"]) if refused.limit(1).count() else [])]


def _fold_two(stream: sequential.Stream, own: sequential.Partitions, table: pa.Table, o: dict) -> np.ndarray:
    out = np.full(stream.m, -1, np.int32)
    p, q, a, b = (table.column(c).to_pylist() for c in ("p_u", "p_v", "vol_u", "vol_v"))
    for e, (u, v) in enumerate(zip(stream.u.tolist(), stream.v.tolist(), strict=True)):
        first = sequential.first_of_two(own.mask[u], own.mask[v], own.degree[u], own.degree[v], a[e], b[e], p[e], q[e], o["terms"])
        best, second = (p[e], q[e]) if first else (q[e], p[e])
        for x in (best, second) if o["try_second"] else (best,):
            if own.load[x] < own.cap:
                own.put(e, u, v, x, 1)
                out[e] = x
                break
    return out


def _fold_all(stream: sequential.Stream, own: sequential.Partitions, method: str, o: dict) -> np.ndarray:
    room = sum(own.cap - x for x in own.load)
    if room < stream.m:  # the last ones overflow
        head = sequential.Stream(stream.ids[stream.u[:room]], stream.ids[stream.v[:room]])
        if not room:
            return np.full(stream.m, -1, np.int32)
        back = np.searchsorted(stream.ids, head.ids).tolist()
        part = sequential.Partitions(head, own.k, own.cap)
        part.load, part.mask, part.degree = list(own.load), [own.mask[i] for i in back], [own.degree[i] for i in back]
        done = _fold_all(head, part, method, o)
        return np.concatenate((done, np.full(stream.m - room, -1, np.int32)))
    if method == "greedy":
        sequential.greedy(stream, own)
    else:
        sequential.hdrf(stream, own, o["lam"], o["eps"])
    return own.p


def run_sequential(src: np.ndarray, dst: np.ndarray, k: int, cap: int, method: str, o: dict) -> tuple[sequential.Stream, sequential.Partitions, np.ndarray | None]:
    """One method over arrays in stream order."""
    return run_stream(sequential.Stream(src, dst), k, cap, method, o)


def pieces(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[np.ndarray, ...]]:
    """Arrow batches ``pos, src, dst`` as arrays of about a million edges."""

    def columns(held: list[pa.RecordBatch]) -> tuple[np.ndarray, ...]:
        table = pa.Table.from_batches(held)
        return tuple(table.column(c).to_numpy() for c in ("pos", "src", "dst"))

    held: list[pa.RecordBatch] = []
    for b in batches:
        held.append(b)
        if sum(x.num_rows for x in held) >= 1 << 20:
            yield columns(held)
            held = []
    if any(x.num_rows for x in held):
        yield columns(held)


def spooled(batches: Iterator[pa.RecordBatch]) -> sequential.SpooledStream:
    """The stream of Arrow batches ``pos, src, dst``."""
    return sequential.SpooledStream(pieces(batches))


def run_stream(stream: sequential.Stream, k: int, cap: int, method: str, o: dict) -> tuple[sequential.Stream, sequential.Partitions, np.ndarray | None]:
    """One method over a stream."""
    parts = sequential.Partitions(stream, k, cap, o["seed"], try_second=o["try_second"])
    names = None
    if method in GUIDED:
        names, volumes = sequential.cluster(stream, o["limit"], o["passes"], o["migration"], o["degree_mode"])
        home = sequential.map_clusters(names, volumes, k, o["schedule"], o["seed"])
        sequential.guided(stream, parts, names, volumes, home, o["terms"], o["warm_start"], (o["lam"], o["eps"]) if method == "cluster_guided_full" else None)
    elif method == "hdrf":
        sequential.hdrf(stream, parts, o["lam"], o["eps"], o["degree_mode"])
    elif method == "greedy":
        sequential.greedy(stream, parts)
    elif method == "adwise":
        sequential.adwise(stream, parts, o["lam"], o["min_buffer"], o["latency_factor"])
    elif method == "ne":
        sequential.expand(stream, parts)
    elif method == "sne":
        sequential.expand_stream(stream, parts, o["cache"])
    elif method == "dne":
        sequential.expand_together(stream, parts, o["expansion"], o["seed"])
    elif method == "hep":
        sequential.hybrid(stream, parts, o["tau"], o["lam"], o["eps"])
    elif method == "multilevel":
        sequential.multilevel(stream, parts, o["seed"])
    else:
        sequential.label_propagation(stream, parts, seed=o["seed"])
    return stream, parts, names


def run_stored(stored: DataFrame, edges: int, k: int, alpha: float = 1.05, cap_factor: float = 0.25, passes: int = 1) -> DataFrame:
    """``pos, p, stage, passes`` of the guided method, whose every pass reads the stored edges again.

    ``stored`` has one partition ``pos, src, dst`` in order.  No edge is spooled or kept: the task's input is the stored
    table once for degrees, once for each clustering pass and twice to place edges.
    """
    prepare(stored.sparkSession)
    cap, limit = degrees.hard_cap(edges, k, alpha), degrees.volume_cap(edges, k, alpha, cap_factor)
    options = dict(limit=limit, passes=passes, migration="residual", degree_mode="exact", schedule="lpt", terms=("replica", "cluster"), warm_start=True, try_second=False, seed=0, lam=1.1, eps=1.0)

    def fold(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        graph = sequential.PassedStream(pieces(batches))
        if not graph.m:
            return
        graph, done, _ = run_stream(graph, k, cap, "cluster_guided", options)
        stages = np.array(sequential.STAGES)
        for at in range(0, graph.m, 50_000):
            p, stage = done.p[at : at + 50_000], done.stage[at : at + 50_000]
            arrays = [pa.array(np.arange(at, at + len(p))), pa.array(p.astype(np.int32)), pa.array(stages[stage]), pa.array(np.full(len(p), graph.passes, np.int32))]
            yield pa.RecordBatch.from_arrays(arrays, names=["pos", "p", "stage", "passes"])

    again = stored.select("pos", "src", "dst")
    for _ in range(passes + 2):
        again = again.union(stored.select("pos", "src", "dst"))
    return again.coalesce(1).mapInArrow(fold, "pos long, p int, stage string, passes int")


def _sequential(out: PartitionResult, stream: DataFrame, o: dict) -> None:
    k, cap, method = out.k, out.cap, out.method

    def fold(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        with tempfile.TemporaryFile(prefix="positions-") as places:
            graph = spooled(_numbered(batches, places))
            if not graph.m:
                return
            graph, done, names = run_stream(graph, k, cap, method, o)
            stages, c = np.array(sequential.STAGES), graph.ids[names] if names is not None else None
            for at, u, v in graph.chunks(50_000):
                n, own = len(u), slice(at, at + len(u))
                pos = np.frombuffer(os.pread(places.fileno(), 8 * n, 8 * at), np.int64)
                arrays = [pa.array(pos), pa.array(graph.ids[u]), pa.array(graph.ids[v]), pa.array(done.p[own].astype(np.int32)), pa.array(stages[done.stage[own]]), pa.array(np.full(n, done.scored))]
                arrays += [pa.array(c[x]) if c is not None else pa.nulls(n, pa.int64()) for x in (u, v)]
                yield pa.RecordBatch.from_arrays(arrays, names=["pos", "src", "dst", "p", "stage", "scored", "c_u", "c_v"])

    # The stream is folded in order by one task: that is what this engine means.  Given positions may have gaps.
    ordered = stream.select("pos", "src", "dst").coalesce(1).sortWithinPartitions("pos")
    done = materialise(ordered.mapInArrow(fold, "pos long, src long, dst long, p int, stage string, scored long, c_u long, c_v long"), "assignment")
    out.assignment = done.select("pos", "src", "dst", "p", "stage")
    first = done.select("scored").first()
    out.scored = first[0] if first else 0
    if method in GUIDED:
        ends = done.select(F.col("src").alias("v"), F.col("c_u").alias("c")).union(done.select(F.col("dst").alias("v"), F.col("c_v").alias("c")))
        out.clusters = ends.groupBy("v").agg(F.first("c").alias("c"), F.count("*").alias("d"))
        out.passes = 1 + o["passes"] + 2


def _numbered(batches: Iterator[pa.RecordBatch], places: IO[bytes]) -> Iterator[pa.RecordBatch]:
    """Batches in order with gapless positions; their own go to a file."""
    total = 0
    for b in batches:
        if b.num_rows:
            os.pwrite(places.fileno(), np.ascontiguousarray(b.column("pos").to_numpy()), 8 * total)
            yield pa.RecordBatch.from_arrays([pa.array(np.arange(total, total + b.num_rows)), b.column("src"), b.column("dst")], names=["pos", "src", "dst"])
            total += b.num_rows


def admission_rank(rows: DataFrame) -> DataFrame:
    """Place of each row among those of its target, in stream order."""
    return rows.withColumn("place", F.row_number().over(Window.partitionBy("p").orderBy("pos")))
