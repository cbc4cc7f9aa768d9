"""The bulk and shard engines, sources, measures and jobs on Spark."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from edgesplit.functions.hashing import portable, portable_numpy
from edgesplit import workloads
from edgesplit.operators import cluster_map, clustering, degrees, jobs, metrics
from edgesplit.operators import sequential as seq
from edgesplit.operators.components import connected_components
from edgesplit.plans import storage
from edgesplit.plans.api import partition, run_sequential, run_stored
from edgesplit.queries import QUERIES
from edgesplit.sources import builders, edge_list
from edgesplit.sources.builders import graph

from .conftest import SF

TRIANGLES = [(0, 1, 2), (1, 2, 3), (2, 1, 3), (3, 4, 5), (4, 5, 6), (5, 4, 6), (6, 3, 4)]


def frame(spark, rows):
    return spark.createDataFrame(rows, "pos long, src long, dst long")


def test_portable_hash_agrees(spark):
    ids = [0, 1, 8, 2**31 - 1, 2**40 + 3, 12345678901]
    got = [r[0] for r in spark.createDataFrame([(x,) for x in ids], "v long").select(portable(F.col("v"), 3)).collect()]
    assert got == portable_numpy(np.array(ids), 3).tolist()


@pytest.mark.parametrize("cap", [8, 5])
def test_batches_of_one_edge_are_the_stream(spark, cap):
    edges = frame(spark, TRIANGLES)
    got = clustering.stream_cluster(edges, degrees.compute(edges), cap, 7, batches=7)
    stream = seq.Stream(np.array([e[1] for e in TRIANGLES]), np.array([e[2] for e in TRIANGLES]))
    names, _ = seq.cluster(stream, cap)
    want = dict(zip(stream.ids.tolist(), stream.ids[names].tolist(), strict=True))
    assert {r["v"]: r["c"] for r in got.collect()} == want


def test_bulk_two_triangles(spark):
    done = partition(frame(spark, TRIANGLES), 2, 1.2, batches=7, volume_cap=8)
    rows = {(r["src"], r["dst"]): (r["p"], r["stage"]) for r in done.assignment.collect()}
    assert rows[3, 4] == (0, "scored") and {rows[1, 2][0], rows[2, 3][0], rows[1, 3][0]} == {0} and done.scored == 2
    report = {r["metric"]: r["value"] for r in done.report("toy").collect()}
    assert report["replication_factor"] == pytest.approx(7 / 6) and report["measured_alpha"] == pytest.approx(8 / 7)


def test_bulk_overflow_under_a_tight_cap(spark):
    rows = [(i, a, b) for i, (a, b) in enumerate((a, b) for a in range(5) for b in range(a + 1, 5))]
    done = partition(frame(spark, rows), 2, 1.0, batches=2, volume_cap=100)
    assert sorted(r["n"] for r in done.loads.collect()) == [5, 5]


@pytest.mark.parametrize(("method", "engine"), [("cluster_guided", "shards"), ("cluster_guided_full", "bulk"), ("greedy", "shards"), ("dbh", "bulk"), ("adwise", "sequential")])
def test_cover_and_cap(spark, method, engine):
    edges = graph(spark, SF, "nation_planted")
    done = partition(edges, 4, method=method, engine=engine, batches=2)
    cover = metrics.check_exact_cover(edges, done.assignment).first()
    assert (cover["missing"], cover["extra"]) == (0, 0)
    if method != "dbh":
        assert metrics.check_balance(done.assignment, done.cap).first()[0]


def test_edge_cases(spark):
    empty = frame(spark, [])
    assert partition(empty, 2, method="hash_edge").assignment.count() == 0
    assert partition(empty, 2, engine="sequential").assignment.count() == 0
    assert partition(frame(spark, [(0, 1, 2)]), 4, engine="sequential").assignment.count() == 1
    for bad in (dict(k=1), dict(k=2, alpha=0.5), dict(k=2, method="none"), dict(k=2, engine="none"), dict(k=2, terms=())):
        with pytest.raises(ValueError):
            partition(frame(spark, TRIANGLES), **bad)
    with pytest.raises(ValueError):
        degrees.check_known(frame(spark, TRIANGLES), spark.createDataFrame([(1, 2)], "v long, d long"))


def test_normalise(spark):
    raw = spark.createDataFrame([(2, 1, "a"), (1, 2, "b"), (3, 3, "c"), (2**40, 1, "d")], "src long, dst long, w string")
    assert sorted((r["src"], r["dst"]) for r in edge_list.normalise(raw).collect()) == [(1, 2), (1, 2**40)]
    with pytest.raises(Exception, match="null end"):
        edge_list.normalise(spark.createDataFrame([(1, None)], "src long, dst long")).collect()
    with pytest.raises(ValueError):
        edge_list.normalise(spark.createDataFrame([("a", "b")], "src string, dst string"))


def test_formats_round_trip(spark, tmp_path):
    (tmp_path / "e.tsv").write_text("# note\n1\t2\n3 4\n")
    (tmp_path / "adj.txt").write_text("1 2 3\n4\n")
    np.array([[1, 2], [3, 4]], "<u4").tofile(tmp_path / "e.bin")
    got = lambda *a: sorted(map(tuple, edge_list.read_edges(spark, *a).collect()))
    assert got(str(tmp_path / "e.tsv"), "tsv") == [(1, 2), (3, 4)]
    assert got(str(tmp_path / "adj.txt"), "adjacency") == [(1, 2), (1, 3)]
    assert got(str(tmp_path / "e.bin"), "binary") == [(1, 2), (3, 4)]
    for fmt in ("parquet", "orc", "json"):
        getattr(frame(spark, TRIANGLES).select("src", "dst").write, fmt)(str(tmp_path / fmt))
        assert len(got(str(tmp_path / fmt), fmt)) == 7
    done = partition(frame(spark, TRIANGLES), 2, method="hash_edge")
    done.save(str(tmp_path / "out"))
    assert spark.read.parquet(str(tmp_path / "out")).count() == 7


def test_list_scheduling_by_histogram(spark):
    vols = spark.createDataFrame([(i, int(v)) for i, v in enumerate(np.random.default_rng(2).integers(1, 9, 300))], "c long, vol long")
    loads = lambda m: sorted(r[1] for r in m.groupBy("p").agg(F.sum("vol")).collect())
    a, b = cluster_map.assign(vols, 7, "lpt"), cluster_map.by_histogram(vols, 7)
    assert loads(a) == loads(b) and b.count() == 300
    assert cluster_map.assign(vols, 7, "round_robin").count() == 300


def test_components_of_a_path_and_a_star(spark):
    path = [(i, i + 1) for i in range(40)]
    star = [(100, 101 + i) for i in range(30)] + [(500, 500), (None, 3)]
    got = {r["node"]: r["root"] for r in connected_components(spark.createDataFrame(path + star, "a long, b long")).collect()}
    assert all(got[i] == 0 for i in range(41)) and all(got[i] == 100 for i in range(100, 131)) and got[500] == 500


def test_pagerank_sums_and_profile(spark):
    done = partition(frame(spark, TRIANGLES), 2, method="hash_edge")
    ranks = {r["v"]: r["rank"] for r in jobs.pagerank(done.assignment, 12, k=2).collect()}
    assert sum(ranks.values()) == pytest.approx(6.0) and ranks[3] == pytest.approx(ranks[4]) and ranks[3] > ranks[1]
    total = [r for r in jobs.partition_profile(done.assignment).collect() if r["p"] is None][0]
    assert total["edges"] == 7


def test_plans_have_no_product_and_no_single_window_over_edges(spark):
    edges = frame(spark, TRIANGLES)
    text = clustering.one_round(edges, clustering.singletons(degrees.compute(edges)), 8)._jdf.queryExecution().executedPlan().toString()
    assert "CartesianProduct" not in text and "SinglePartition" not in text


def test_live_replica_counts(spark, tmp_path):
    from edgesplit.streaming import live

    frame(spark, TRIANGLES).selectExpr("src", "dst", "cast(pos % 2 as int) as p").coalesce(1).write.parquet(str(tmp_path / "in"))
    stream = spark.readStream.schema("src long, dst long, p int").parquet(str(tmp_path / "in"))
    query = live.replica_counts(stream, 2).writeStream.format("memory").queryName("live_replicas").outputMode("update").option("checkpointLocation", str(tmp_path / "log")).trigger(availableNow=True).start()
    query.awaitTermination()
    got = {r["v"]: r["replicas"] for r in spark.sql("select * from live_replicas").collect()}
    want = {}
    for pos, a, b in TRIANGLES:
        for x in (a, b):
            want.setdefault(x, set()).add(pos % 2)
    assert got == {x: len(p) for x, p in want.items()}


def test_live_clusters_follow_batches(spark, tmp_path):
    from edgesplit.streaming import live

    state = live.LiveClusters(spark, 8, str(tmp_path))
    state.update(frame(spark, TRIANGLES[:3]).select("src", "dst"), 0)
    state.update(frame(spark, TRIANGLES[:3]).select("src", "dst"), 0)  # replayed
    first = {r["v"]: r["d"] for r in state.clusters.collect()}
    state = live.LiveClusters(spark, 8, str(tmp_path))  # restarted
    assert state.version == 0 and {r["v"]: r["d"] for r in state.clusters.collect()} == first
    state.update(frame(spark, TRIANGLES[:3]).select("src", "dst"), 0)
    state.update(frame(spark, TRIANGLES[3:]).select("src", "dst"), 1)
    second = {r["v"]: r["d"] for r in state.clusters.collect()}
    assert first == {1: 2, 2: 2, 3: 2} and second == {1: 2, 2: 2, 3: 3, 4: 3, 5: 2, 6: 2}


def test_a_restarted_stream_goes_on(spark, tmp_path):
    from edgesplit.streaming import live

    folder = str(tmp_path / "in")
    for part in (TRIANGLES[:3], TRIANGLES[3:]):
        frame(spark, part).select("src", "dst").coalesce(1).write.mode("append").parquet(folder)
        state = live.LiveClusters(spark, 8, str(tmp_path / "state"))
        live.run(spark.readStream.schema("src long, dst long").parquet(folder), state).awaitTermination()
    assert {r["v"]: r["d"] for r in state.clusters.collect()} == {1: 2, 2: 2, 3: 3, 4: 3, 5: 2, 6: 2}


def test_nothing_is_ignored_silently(spark):
    for bad in (dict(method="ne"), dict(method="greedy"), dict(method="adwise", engine="shards"), dict(degree_mode="partial"), dict(engine="sequential", clusters=frame(spark, TRIANGLES))):
        with pytest.raises(ValueError):
            partition(frame(spark, TRIANGLES), 2, **bad)


@pytest.mark.parametrize("options", [dict(terms=("cluster",)), dict(terms=("replica",)), dict(try_second=True), {}])
def test_one_shard_is_the_stream(spark, options):
    """With all edges in one shard the fold decides as the sequential engine does, whatever the options."""
    edges = degrees.with_position(graph(spark, SF, "nation_planted"))
    known = partition(edges, 4, engine="sequential", alpha=2.0)
    got = partition(edges, 4, engine="shards", alpha=2.0, clusters=known.clusters, **options).assignment.collect()
    want = partition(edges, 4, engine="sequential", alpha=2.0, **options).assignment.collect()
    assert {(r["src"], r["dst"]): r["p"] for r in got} == {(r["src"], r["dst"]): r["p"] for r in want}


def test_growing_batches_cover_the_stream():
    from edgesplit.operators import placement

    rounds = placement.growing_batches(100_000, 256, 0.5)
    assert rounds[0][0] == 0 and rounds[-1][1] == 100_000 and all(a[1] == b[0] for a, b in zip(rounds, rounds[1:], strict=False)) and all(b - a <= max(256, a) for a, b in rounds) and len(rounds) < 30


def test_histogram_deals_the_largest_volumes_exactly(spark):
    """With a small head the largest volumes go as by exact LPT; only the tail is grouped."""
    large = [(i, 1000 + 37 * i) for i in range(40)]
    vols = spark.createDataFrame(large + [(100 + i, 1 + i % 9) for i in range(30)], "c long, vol long")
    rows = cluster_map.by_histogram(vols, 5, head=40).collect()
    exact, _ = cluster_map.list_schedule([(v, c) for c, v in reversed(large)], 5)
    assert {r["c"]: r["p"] for r in rows if r["c"] < 100} == dict(zip([c for c, _ in reversed(large)], exact, strict=True))
    assert sorted((r["c"], r["vol"]) for r in rows) == sorted((r["c"], r["vol"]) for r in vols.collect())


def test_nearest_rows_by_cosine(spark):
    """Tiles of a block, ties, several blocks and vectors without a direction, against one plain matrix."""
    draw = np.random.default_rng(5)
    x = draw.normal(size=(300, 6)).astype(np.float32)
    x[40:60] = x[7]
    ids = np.arange(300) * 3
    unit = x.astype(float) / np.linalg.norm(x.astype(float), axis=1, keepdims=True)
    cos = np.round(unit @ unit.T, 12)
    np.fill_diagonal(cos, -2)
    best = np.argsort(-cos, axis=1, kind="stable")[:, :8]
    i, j, _ = builders.nearest_of_block(ids, unit, ids, unit, 8, tall=37, wide=41)
    assert sorted(zip(i.tolist(), j.tolist(), strict=True)) == sorted((int(ids[r]), int(ids[c])) for r in range(300) for c in best[r])
    rows = [(int(v), [float(y) for y in row]) for v, row in zip(ids, x, strict=True)]
    odd = [(1, None), (2, [0.0] * 6), (4, [float("nan")] + [1.0] * 5), (5, [float("inf")] + [1.0] * 5), (7, [None] + [1.0] * 5), (None, [1.0] * 6)]
    vectors = spark.createDataFrame(rows + odd, "vec_id long, embedding array<float>")
    got = {(r["src"], r["dst"]) for r in builders.knn(vectors, values=200).collect()}
    assert got == {tuple(sorted((int(ids[r]), int(ids[c])))) for r in range(300) for c in best[r]}


def test_a_block_of_vectors_needs_little_memory():
    import tracemalloc

    x = np.random.default_rng(6).normal(size=(12_000, 8))
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    tracemalloc.start()
    i, _, _ = builders.nearest_of_block(np.arange(12_000), x, np.arange(12_000), x, 8)
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert len(i) == 96_000 and peak < 250e6  # the whole matrix alone has 1,152 MB


def test_a_setting_is_a_task_without_copies_of_the_stream(spark):
    context = spark.sparkContext
    context.setJobGroup("sweep", "")
    rows = workloads.sweep(graph(spark, SF, "nation_planted"), [workloads.setting("hdrf", k) for k in (2, 3, 4, 5, 6)])
    assert len(rows.inputFiles()) == 5  # written by five tasks
    assert [r["k"] for r in rows.orderBy("k").collect()] == [2, 3, 4, 5, 6]
    jobs_run = [context.statusTracker().getJobInfo(i) for i in context.statusTracker().getJobIdsForGroup("sweep")]
    stages = {i for j in jobs_run if j for i in j.stageIds}
    assert 5 in {s.numTasks for s in map(context.statusTracker().getStageInfo, stages) if s}


def test_given_positions_with_gaps_keep_the_order(spark):
    gaps = partition(frame(spark, [(7 * p + 3, u, v) for p, u, v in TRIANGLES]), 2, 1.2, engine="sequential", volume_cap=8)
    want = partition(frame(spark, TRIANGLES), 2, 1.2, engine="sequential", volume_cap=8)
    plain = lambda d: sorted((r["src"], r["dst"], r["p"], r["stage"]) for r in d.assignment.collect())
    assert plain(gaps) == plain(want) and sorted(r["pos"] for r in gaps.assignment.collect()) == [7 * p + 3 for p, _, _ in TRIANGLES]


def test_temporary_tables_go(spark):
    made = []
    with storage.temporary():
        made += storage.materialise(spark.range(3), "a").inputFiles()
        with storage.temporary():
            made += storage.materialise(spark.range(3), "b").inputFiles()
            made += storage.materialise(spark.range(4), "c", keep=True).inputFiles()
        assert storage.exists(spark, made[0]) and storage.exists(spark, made[-1])
    assert not any(storage.exists(spark, x) for x in made)
    with storage.temporary():
        kept = storage.materialise(spark.range(3), "d", keep=True)
    assert kept.count() == 3


def test_hybrid_by_threshold_is_that_of_arrays(spark):
    """Each setting reads the stored edges, of several files, and adds up their positions itself."""
    rows = degrees.with_position(graph(spark, SF, "order_supp")).orderBy("pos").collect()
    src, dst = (np.array([r[c] for r in rows]) for c in ("src", "dst"))
    got = {r["tau"]: (r["rf"], r["scored"]) for r in QUERIES["w_hep_tau"](spark, SF).collect()}
    for tau in (100, 10, 1):
        stream, parts, _ = run_sequential(src, dst, 32, degrees.hard_cap(len(src), 32, 1.05), "hep", dict(seed=0, try_second=False, tau=float(tau), lam=1.1, eps=1.0))
        assert got[tau] == (round(sum(m.bit_count() for m in parts.mask) / stream.n, 6), parts.scored)
    assert len(got) == 3


def test_each_pass_reads_the_stored_edges(spark):
    """As often as the method has passes, from every storage; the result is that of the stream held in one place."""
    edges = degrees.with_position(graph(spark, SF, "cust_part"))
    stored = edges.select("pos", "src", "dst").coalesce(1).sortWithinPartitions("pos").persist()
    for passes in (1, 3):
        got = run_stored(stored, stored.count(), 8, passes=passes).collect()
        want = partition(edges, 8, engine="sequential", passes=passes).assignment.collect()
        assert {(r["pos"], r["p"], r["stage"]) for r in got} == {(r["pos"], r["p"], r["stage"]) for r in want}
        assert {r["passes"] for r in got} == {1 + passes + 2}
    stored.unpersist()
    rows = QUERIES["w_storage"](spark, SF).collect()
    assert [(r["storage"], r["passes"]) for r in rows] == [("cache", 4), ("disk", 4), ("files", 4), ("files_zstd", 4)]


def test_passes_out_of_order_raise():
    pieces = [(np.arange(3), np.arange(3), np.arange(3) + 9), (np.arange(2), np.arange(2), np.arange(2) + 9)]
    stream = seq.PassedStream(iter(pieces))
    with pytest.raises(ValueError, match="not in order"):
        list(stream.chunks())


def test_stored_edges_are_one_piece(spark, monkeypatch):
    """Whatever the session's file splits are."""
    pieces = []
    own = workloads.run_stored
    monkeypatch.setattr(workloads, "run_stored", lambda stored, *rest: (pieces.append(stored.rdd.getNumPartitions()), own(stored, *rest))[1])
    with storage.session_value(spark, "spark.sql.files.maxPartitionBytes", "4096"), storage.session_value(spark, "spark.sql.files.openCostInBytes", "1"):
        workloads.storage_levels(spark, SF)
    assert set(pieces) == {1}
