"""Worked examples, invariants and brute force for the sequential engines."""

from itertools import product

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from edgesplit.functions.hashing import portable_numpy
from edgesplit.operators import sequential as seq
from edgesplit.operators.cluster_map import _deal, list_schedule
from edgesplit.operators.degrees import hard_cap, volume_cap
from edgesplit.operators.placement import least_loaded_turns
from edgesplit.operators.stateless import DIFFERENCE_SETS, grid_shape
from edgesplit.plans.advisor import choose
from edgesplit.plans.api import METHODS, STATELESS, run_sequential, run_stream

OPTIONS = dict(limit=None, passes=1, migration="residual", degree_mode="exact", schedule="lpt", terms=("replica", "cluster"), warm_start=True, try_second=False, seed=0, lam=1.1, eps=1.0, tau=10.0, cache=2, expansion=0.1, min_buffer=10, latency_factor=40.0)
TRIANGLES = np.array([(1, 2), (2, 3), (1, 3), (4, 5), (5, 6), (4, 6), (3, 4)])


def run(edges, k, cap, method="cluster_guided", **changes):
    edges = np.asarray(edges)
    return run_sequential(edges[:, 0], edges[:, 1], k, cap, method, OPTIONS | changes)


def rf(stream, p):
    pairs = {(x, q) for a, b, q in zip(stream.u.tolist(), stream.v.tolist(), p.tolist(), strict=True) for x in (a, b)}
    return len(pairs) / stream.n


def test_two_triangles_and_a_bridge():
    stream, parts, names = run(TRIANGLES, 2, hard_cap(7, 2, 1.2), limit=8)
    assert stream.ids[names].tolist() == [1, 1, 1, 4, 4, 4]
    assert parts.load == [4, 3] and parts.stage.tolist() == [0] * 6 + [1]
    assert rf(stream, parts.p) == pytest.approx(7 / 6)


def test_triangles_with_a_small_cap():
    stream, parts, names = run(TRIANGLES, 2, 4, limit=5)
    _, volumes = seq.cluster(stream, 5)
    assert {int(stream.ids[c]): int(volumes[c]) for c in set(names.tolist())} == {1: 4, 3: 3, 4: 5, 6: 2}
    home = seq.map_clusters(names, volumes, 2)
    assert dict(zip(stream.ids.tolist(), home.tolist(), strict=True)) == {1: 1, 2: 1, 3: 1, 4: 0, 5: 0, 6: 0}
    assert parts.load == [4, 3]


def test_two_cliques_beat_the_edge_hash():
    edges = [(a, b) for block in ((1, 2, 3, 4), (5, 6, 7, 8)) for i, a in enumerate(block) for b in block[i + 1 :]] + [(4, 5), (1, 8)]
    stream, parts, _ = run(edges, 2, 7, limit=15)
    hashed = portable_numpy(np.array([a * 31 + b for a, b in edges])) % 2
    assert rf(stream, parts.p) <= 10 / 8 < rf(stream, hashed)


def test_hub_above_the_cap_stays_alone():
    stream = seq.Stream(np.zeros(10, int), np.arange(1, 11))
    names, _ = seq.cluster(stream, 5)
    assert len(set(names.tolist())) == 11


def test_overflow_goes_to_the_hash_then_the_least_loaded():
    edges = [(a, b) for a in range(5) for b in range(a + 1, 5)]
    _, parts, _ = run(edges, 2, 5, limit=100)
    assert sorted(parts.load) == [5, 5] and set(parts.stage.tolist()) <= {0, 2, 3} and (parts.stage == 0).sum() == 5


@pytest.mark.parametrize("method", [m for m in METHODS if m not in STATELESS])
@pytest.mark.parametrize("k", [2, 5])
def test_every_method_covers_and_keeps_the_cap(method, k):
    draw = np.random.default_rng(3)
    pairs = np.unique(np.sort(draw.integers(0, 60, (400, 2)), axis=1), axis=0)
    pairs = pairs[pairs[:, 0] != pairs[:, 1]]
    draw.shuffle(pairs)
    cap = hard_cap(len(pairs), k, 1.05)
    stream, parts, _ = run(pairs, k, cap, method, limit=volume_cap(len(pairs), k, 1.05))
    assert (parts.p >= 0).all() and np.bincount(parts.p, minlength=k).max() <= cap
    assert 1 <= rf(stream, parts.p) <= min(k, stream.degree.mean())


@pytest.mark.parametrize("method", ["cluster_guided", "hdrf", "ne", "multilevel"])
def test_not_below_the_optimum(method):
    edges = [(0, 1), (1, 2), (0, 2), (3, 4), (4, 5), (3, 5), (2, 3)]
    stream = seq.Stream(*np.array(edges).T)
    cap = hard_cap(len(edges), 2, 1.2)
    best = min(rf(stream, np.array(p)) for p in product((0, 1), repeat=len(edges)) if max(sum(p), len(p) - sum(p)) <= cap)
    assert rf(stream, run(edges, 2, cap, method, limit=8)[1].p) >= best


def test_restreaming_and_order_are_deterministic():
    pairs = np.random.default_rng(1).integers(0, 40, (200, 2))
    pairs = pairs[pairs[:, 0] != pairs[:, 1]]
    a, b = (run(pairs, 4, 60, passes=3, limit=50)[1].p for _ in range(2))
    assert (a == b).all()


@given(st.lists(st.integers(1, 50), min_size=1, max_size=8), st.integers(2, 3))
@settings(max_examples=60, deadline=None)
def test_list_scheduling_bound(jobs, k):
    order = sorted(jobs, reverse=True)
    _, loads = list_schedule([(x, i) for i, x in enumerate(order)], k)
    best = min(max(sum(x for x, q in zip(jobs, where, strict=True) if q == p) for p in range(k)) for where in product(range(k), repeat=len(jobs)))
    assert max(loads) <= 4 / 3 * best and sum(loads) == sum(jobs)


@given(st.lists(st.integers(0, 30), min_size=2, max_size=5), st.integers(1, 9), st.integers(0, 200))
@settings(max_examples=80, deadline=None)
def test_equal_jobs_are_dealt_as_one_by_one(loads, vol, n):
    one = list(loads)
    count = [0] * len(loads)
    for _ in range(n):
        p = min(range(len(one)), key=lambda q: (one[q], q))
        one[p] += vol
        count[p] += 1
    got = _deal(list(loads), vol, n)
    assert sorted(x + vol * m for x, m in zip(loads, got, strict=True)) == sorted(one) and sum(got) == n


@given(st.lists(st.integers(0, 9), min_size=2, max_size=5), st.integers(0, 30))
@settings(max_examples=80, deadline=None)
def test_turns_are_the_least_loaded_rule(loads, n):
    cap = 15
    n = min(n, sum(cap - x for x in loads))
    now, want = list(loads), []
    for _ in range(n):
        p = min(range(len(now)), key=lambda q: (now[q], q))
        now[p] += 1
        want.append(p)
    got = [turn[(i - a) % len(turn)] for a, b, turn in least_loaded_turns(loads, cap, n) for i in range(a, b)]
    assert got == want


def test_difference_sets_and_grid():
    for k, base in DIFFERENCE_SETS.items():
        gaps = sorted((a - b) % k for a in base for b in base if a != b)
        assert gaps == list(range(1, k))
    assert grid_shape(12) == (3, 4) and grid_shape(16) == (4, 4) and grid_shape(7) == (1, 7)


def test_arguments_and_advice():
    with pytest.raises(ValueError):
        hard_cap(10, 1, 1.05)
    with pytest.raises(ValueError):
        hard_cap(10, 2, 0.9)
    assert hard_cap(3, 8, 1.0) == 1
    assert choose(4) == "cluster_guided_full" and choose(256) == "cluster_guided"


def test_quality_trends_on_planted_communities():
    draw = np.random.default_rng(5)
    groups = draw.integers(0, 16, 2000)
    a = draw.integers(0, 20, 2000)
    b = draw.integers(0, 20, 2000)
    pairs = np.unique(np.stack((groups * 20 + np.minimum(a, b), groups * 20 + np.maximum(a, b)), axis=1), axis=0)
    pairs = pairs[pairs[:, 0] != pairs[:, 1]]
    draw.shuffle(pairs)
    k = 8
    cap, limit = hard_cap(len(pairs), k, 1.05), volume_cap(len(pairs), k, 1.05, 0.25)
    got = {m: run(pairs, k, cap, m, limit=limit) for m in ("cluster_guided", "cluster_guided_full", "greedy")}
    stream = got["greedy"][0]
    hashed = portable_numpy(pairs[:, 0] * 1000 + pairs[:, 1]) % k
    assert rf(stream, got["cluster_guided_full"][1].p) <= rf(stream, got["cluster_guided"][1].p) < rf(stream, hashed)
    assert got["cluster_guided"][1].scored == 2 * (got["cluster_guided"][1].stage != 0).sum() or got["cluster_guided"][1].scored <= 2 * len(pairs)


def plain_hdrf(stream, k, cap, lam=1.1, eps=1.0):
    """All k scores of every edge."""
    table, load, out = np.zeros((stream.n, k), bool), np.zeros(k), []
    for u, v in zip(stream.u.tolist(), stream.v.tolist(), strict=True):
        share = stream.degree[u] / (stream.degree[u] + stream.degree[v])
        score = lam * (load.max() - load) / (eps + load.max() - load.min()) + table[u] * (2 - share) + table[v] * (1 + share)
        score[load >= cap] = -1
        p = int(np.round(score, 9).argmax())
        out.append(p)
        load[p] += 1
        table[u, p] = table[v, p] = True
    return out


@pytest.mark.parametrize("lam", [0.0, 1.1, 5.0])
@pytest.mark.parametrize(("k", "alpha"), [(2, 1.0), (9, 1.05), (70, 1.3)])
def test_hdrf_is_the_best_of_all(k, alpha, lam):
    draw = np.random.default_rng(k)
    pairs = np.unique(draw.integers(0, 90, (700, 2)), axis=0)
    draw.shuffle(pairs)
    cap = hard_cap(len(pairs), k, alpha)
    stream, parts, _ = run(pairs, k, cap, "hdrf", lam=lam)
    assert parts.p.tolist() == plain_hdrf(stream, k, cap, lam) and parts.scored == k * len(pairs)


def random_pairs(n, m, seed=0):
    draw = np.random.default_rng(seed)
    pairs = np.unique(draw.integers(0, n, (m, 2)) * 8 + 3, axis=0)
    draw.shuffle(pairs)
    return pairs


def spool(pairs, parts=5, seed=0):
    order = np.random.default_rng(seed).permutation(len(pairs))
    return seq.SpooledStream((c, pairs[c, 0], pairs[c, 1]) for c in np.array_split(order, parts))


@pytest.mark.parametrize("method", [m for m in METHODS if m not in STATELESS])
def test_a_spooled_stream_is_the_stream(method):
    pairs = random_pairs(80, 500)
    cap = hard_cap(len(pairs), 7, 1.05)
    o = OPTIONS | dict(limit=volume_cap(len(pairs), 7, 1.05, 0.25))
    _, want, names = run_sequential(pairs[:, 0], pairs[:, 1], 7, cap, method, o)
    _, got, own = run_stream(spool(pairs), 7, cap, method, o)
    assert (got.p == want.p).all() and (got.stage == want.stage).all() and got.mask == want.mask and (names is None or (names == own).all())
    with pytest.raises(ValueError, match="gapless"):
        seq.SpooledStream([(np.array([0, 2]), np.array([1, 2]), np.array([2, 3]))])


@pytest.mark.parametrize("method", ["cluster_guided", "cluster_guided_full", "hdrf"])
def test_streaming_methods_hold_vertices_not_edges(method):
    import tracemalloc

    pairs = random_pairs(2_000, 200_000)
    stream, k = spool(pairs), 4
    tracemalloc.start()
    run_stream(stream, k, hard_cap(len(pairs), k, 1.05), method, OPTIONS | dict(limit=volume_cap(len(pairs), k, 1.05, 0.25)))
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert peak < 10e6  # lists of both ends alone take 3 MB, their integers 13 MB more


@pytest.mark.parametrize("method", ["ne", "hep"])
def test_expansion_holds_vertices_and_bytes_of_edges(method):
    import tracemalloc

    pairs = random_pairs(10_000, 150_000)
    stream, k = spool(pairs), 4
    tracemalloc.start()
    run_stream(stream, k, hard_cap(len(pairs), k, 1.05), method, OPTIONS)
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert peak < 20e6  # 46 MB with lists of both ends, other ends and edges


def knotted_pairs(seed=0):
    """Hubs, loops and edges that occur twice."""
    draw = np.random.default_rng(seed)
    pairs = np.concatenate((draw.integers(0, 90, (500, 2)), np.stack((np.full(150, 7), draw.integers(0, 90, 150)), axis=1), np.full((3, 2), 7), np.full((2, 2), 50)))
    draw.shuffle(pairs)
    return pairs


@pytest.mark.parametrize("ends", [1, 5, 64, 10**6])
def test_adjacency_in_a_file_is_that_in_memory(ends):
    stream = spool(knotted_pairs())
    offsets, other, edge = stream.neighbours()
    near = seq.SpooledAdjacency(stream, ends)
    assert near.offsets.tolist() == offsets.tolist()
    assert near.rows(0, 2 * stream.m).tolist() == np.stack((other, edge), axis=1).tolist()
    assert near.pairs(3, 9) == list(zip(other[3:9].tolist(), edge[3:9].tolist(), strict=True))


@pytest.mark.parametrize("k", [3, 40, 70])
@pytest.mark.parametrize("tau", [0.5, 1.5, 100.0])
def test_expansion_by_arrays_is_that_one_by_one(k, tau, monkeypatch):
    pairs = knotted_pairs(k)
    cap = hard_cap(len(pairs), k, 1.02)
    _, want, _ = run(pairs, k, cap, "hep", tau=tau)
    assert (want.p >= 0).all() and max(want.load) <= cap and np.bincount(want.p, minlength=k).tolist() == want.load
    masks = [0] * len(want.mask)
    for u, v, p in zip(want._stream.u.tolist(), want._stream.v.tolist(), want.p.tolist(), strict=True):
        masks[u] |= 1 << p
        masks[v] |= 1 << p
    assert list(want.mask) == masks
    # As where vertices are many (masks in plain arrays), all of them hubs, and hubs are read in pieces.
    monkeypatch.setattr(seq._masks, "__defaults__", (0,))
    monkeypatch.setattr(seq.expand, "__defaults__", (*seq.expand.__defaults__[:-2], 0, 3))
    _, got, _ = run_stream(spool(pairs), k, cap, "hep", OPTIONS | dict(tau=tau))
    assert (got.p == want.p).all() and (got.stage == want.stage).all() and list(got.mask) == masks and got.scored == want.scored


@pytest.mark.parametrize("k, alpha, second", [(4, 1.05, False), (32, 1.0, True), (256, 1.0, False)])
def test_two_terms_by_arrays_are_the_score_one_by_one(k, alpha, second, monkeypatch):
    rng = np.random.default_rng(k)
    src, dst = rng.zipf(1.6, 6000) % 300, 300 + rng.integers(0, 500, 6000)
    cap = -(-int(alpha * 6000) // k)
    done = []
    for large in (False, True):
        stream = seq.Stream(src, dst)
        parts = seq.Partitions(stream, k, cap, try_second=second)
        names, volumes = seq.cluster(stream, 3000 // k + 1)
        home = seq.map_clusters(names, volumes, k)
        if large:  # one by one, edge after edge, through first_of_two
            monkeypatch.setattr(seq, "_two_terms", lambda stream, parts, rest, vol, home: _one_by_one(stream, parts, rest, vol, home))
        seq.guided(stream, parts, names, volumes, home)
        done.append((parts.p.tolist(), parts.stage.tolist(), parts.load, list(parts.mask), parts.scored))
    assert done[0] == done[1]
    assert 1 in done[0][1]


def _one_by_one(stream, parts, rest, vol, home):
    for e in np.flatnonzero(rest).tolist():
        u, v = int(stream.u[e]), int(stream.v[e])
        p, q = int(home[u]), int(home[v])
        first = seq.first_of_two(parts.mask[u], parts.mask[v], parts.degree[u], parts.degree[v], int(vol[u]), int(vol[v]), p, q)
        parts.settle(e, u, v, p if first else q, 1, q if first else p)
