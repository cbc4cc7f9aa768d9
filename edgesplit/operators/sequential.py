"""Exact one-edge-at-a-time engines on arrays: reference semantics, in-memory baselines, shard folds.

Ends are dense ids in stream order.  Every function returns a partition for each edge and never
exceeds the cap.  Replica sets are bit masks, one integer for each vertex.  The streaming methods
(guided, HDRF) read edges chunk by chunk, so a spooled stream costs them memory by vertices only,
and two or three bytes an edge for the result; expansion (NE, the hybrid) reads the other ends of a vertex from
a file too and holds at most two bytes an edge more.
"""

from __future__ import annotations

import heapq
import os
import tempfile
from array import array
from collections import defaultdict
from collections.abc import Iterable, Iterator
from functools import cached_property
from typing import IO

import numpy as np

from ..functions.hashing import portable_numpy
from .cluster_map import list_schedule

STAGES = ("prepartition", "scored", "hashed", "least_loaded")


class Stream:
    """Edges of a graph in stream order, with dense ends and degrees."""

    def __init__(self, src: np.ndarray, dst: np.ndarray) -> None:
        self.ids, ends = np.unique(np.concatenate((src, dst)), return_inverse=True)
        self.u, self.v = ends[: len(src)], ends[len(src) :]
        self.n, self.m = len(self.ids), len(src)
        self.degree = np.bincount(ends, minlength=self.n)

    def chunks(self, size: int = 1 << 15) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
        """Number of the first edge and both ends of consecutive edges."""
        for at in range(0, self.m, size):
            yield at, self.u[at : at + size], self.v[at : at + size]

    def neighbours(self) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Offsets, other ends and edge numbers by vertex."""
        ends, other, edge = np.concatenate((self.u, self.v)), np.concatenate((self.v, self.u)), np.tile(np.arange(self.m), 2)
        order = np.argsort(ends, kind="stable")
        return np.concatenate(([0], np.cumsum(self.degree))), other[order], edge[order]

    def adjacency(self) -> Adjacency:
        return Adjacency(*self.neighbours())


class Adjacency:
    """Other ends and edge numbers by vertex, in rows ``offsets[x]`` to ``offsets[x + 1]``."""

    def __init__(self, offsets: np.ndarray, other: np.ndarray, edge: np.ndarray) -> None:
        self.offsets, self._flat = offsets, np.stack((other, edge), axis=1)

    def rows(self, a: int, b: int) -> np.ndarray:
        return self._flat[a:b]

    def pairs(self, a: int, b: int) -> list[tuple[int, int]]:
        flat = self._flat[a:b].ravel().tolist()
        return list(zip(flat[::2], flat[1::2], strict=True))


class SpooledAdjacency(Adjacency):
    """The same in a file of the worker, 8 bytes an end of an edge; ``rows`` and ``pairs`` read what they return.

    Ends are dealt to their bucket's part of the file, with 2 bytes each that name the vertex; then bucket after
    bucket is sorted in memory.  A bucket has at most ``ends`` ends, or one vertex, whose ends are in order as dealt.
    """

    def __init__(self, stream: SpooledStream, ends: int = 1 << 22) -> None:
        offsets = np.zeros(stream.n + 1, np.int32 if 2 * stream.m < 1 << 31 else np.int64)
        np.cumsum(stream.degree, out=offsets[1:])
        self.offsets = offsets
        first = [0]
        while first[-1] < stream.n:
            a = first[-1]
            first.append(min(max(a + 1, int(np.searchsorted(offsets, int(offsets[a]) + ends, "right")) - 1), a + (1 << 16), stream.n))
        self._file = tempfile.TemporaryFile(prefix="adjacency-")
        starts = np.array(first)
        with tempfile.TemporaryFile(prefix="adjacency-vertices-") as vertices:
            self._deal(stream, starts, vertices)
            for a, b in zip(first, first[1:], strict=False):
                at, n = int(offsets[a]), int(offsets[b] - offsets[a])
                if b - a > 1:
                    order = np.argsort(np.frombuffer(_pread(vertices.fileno(), 2 * n, 2 * at), np.uint16), kind="stable")
                    _pwrite(self._file.fileno(), np.ascontiguousarray(self.rows(at, at + n)[order]), 8 * at)

    def _deal(self, stream: SpooledStream, starts: np.ndarray, vertices: IO[bytes]) -> None:
        free = self.offsets[starts].astype(np.int64)
        for side in (0, 1):  # first the edges that leave a vertex, as in ``neighbours``
            for at, *both in stream.chunks(1 << 19):
                own = np.searchsorted(starts, both[side], "right") - 1
                order = np.argsort(own.astype(np.uint16) if len(starts) < 1 << 16 else own, kind="stable")
                names = (both[side] - starts[own])[order].astype(np.uint16)
                rows = np.stack((both[1 - side][order], (at + order).astype(np.int32)), axis=1)
                own = own[order]
                cuts = [0, *(np.flatnonzero(np.diff(own)) + 1).tolist(), len(own)]
                for a, b in zip(cuts, cuts[1:], strict=False):
                    to = int(free[own[a]])
                    _pwrite(self._file.fileno(), rows[a:b], 8 * to)
                    _pwrite(vertices.fileno(), names[a:b], 2 * to)
                    free[own[a]] += b - a

    def rows(self, a: int, b: int) -> np.ndarray:
        return np.frombuffer(_pread(self._file.fileno(), 8 * (b - a), 8 * a), np.int32).reshape(-1, 2)

    def pairs(self, a: int, b: int) -> list[tuple[int, int]]:
        flat = array("i", os.pread(self._file.fileno(), 8 * (b - a), 8 * a))
        return list(zip(flat[::2], flat[1::2], strict=True))


def _pread(file: int, size: int, at: int) -> bytes:
    """All bytes asked for: one call of the system may read fewer."""
    got = os.pread(file, size, at)
    while len(got) < size:
        more = os.pread(file, size - len(got), at + len(got))
        if not more:
            raise EOFError("a file of the stream is too short")
        got += more
    return got


def _pwrite(file: int, values: np.ndarray, at: int) -> None:
    """The whole array: one call of the system may write less."""
    left = memoryview(values).cast("B")
    while left:
        n = os.pwrite(file, left, at)
        left, at = left[n:], at + n


class SpooledStream(Stream):
    """The same over edges that come in batches ``pos, src, dst`` in any order, pos gapless from 0: ends lie in a file of the worker.

    Methods that need the whole graph read ``u`` and ``v`` into memory; the others go by ``chunks`` and ``adjacency``.
    """

    def __init__(self, batches: Iterable[tuple[np.ndarray, np.ndarray, np.ndarray]]) -> None:
        self.m, known, number = 0, np.zeros(0, np.int64), np.zeros(0, np.int32)
        self._file = tempfile.TemporaryFile(prefix="edges-")  # goes with the last reference, or with the worker
        for pos, src, dst in batches:
            found, back = np.unique(np.concatenate((src, dst)), return_inverse=True)
            at = np.searchsorted(known, found)
            fresh = np.ones(len(found), bool)
            fresh[at < len(known)] = known[at[at < len(known)]] != found[at < len(known)]
            number = np.insert(number, at[fresh], np.arange(len(known), len(known) + fresh.sum(), dtype=np.int32))
            known = np.insert(known, at[fresh], found[fresh])
            ends = number[np.searchsorted(known, found)][back].reshape(2, -1).T
            order = np.argsort(pos, kind="stable")
            pos, ends = pos[order], np.ascontiguousarray(ends[order])
            cuts = np.flatnonzero(np.diff(pos) != 1) + 1
            for a, b in zip([0, *cuts.tolist()], [*cuts.tolist(), len(pos)], strict=True):
                os.pwrite(self._file.fileno(), ends[a:b], int(pos[a]) * 8)
            self.m += len(pos)
        if os.fstat(self._file.fileno()).st_size != 8 * self.m:
            raise ValueError("positions are not gapless from 0")
        # Numbers given in order of arrival become ranks of the ids; few methods ask for these, so they wait in a file.
        self.n, self._ids = len(known), tempfile.TemporaryFile(prefix="ids-")
        _pwrite(self._ids.fileno(), known, 0)
        del known
        rank = np.empty(self.n, np.int32)
        rank[number] = np.arange(self.n, dtype=np.int32)
        del number
        self.degree = np.zeros(self.n, np.int32 if 2 * self.m < 1 << 31 else np.int64)
        for at, part in self._read(1 << 20):
            part = rank[part]
            np.add.at(self.degree, part.ravel(), 1)
            os.pwrite(self._file.fileno(), part, at * 8)

    def _read(self, size: int) -> Iterator[tuple[int, np.ndarray]]:
        for at in range(0, self.m, size):
            yield at, np.frombuffer(os.pread(self._file.fileno(), 8 * min(size, self.m - at), 8 * at), np.int32).reshape(-1, 2)

    def chunks(self, size: int = 1 << 15) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
        for at, part in self._read(size):
            yield at, part[:, 0], part[:, 1]

    def _side(self, i: int) -> np.ndarray:
        out = np.empty(self.m, np.int64)
        for at, part in self._read(1 << 20):
            out[at : at + len(part)] = part[:, i]
        return out

    def adjacency(self) -> Adjacency:
        return SpooledAdjacency(self)

    @cached_property
    def ids(self) -> np.ndarray:
        return np.frombuffer(_pread(self._ids.fileno(), 8 * self.n, 0), np.int64)

    @cached_property
    def u(self) -> np.ndarray:
        return self._side(0)

    @cached_property
    def v(self) -> np.ndarray:
        return self._side(1)


class PassedStream(Stream):
    """The same over pieces ``pos, src, dst`` that come in order, all edges anew for each pass: no edge is kept.

    The first pass, for ids and degrees, is read here; each call of ``chunks`` reads the next one.
    """

    def __init__(self, pieces: Iterable[tuple[np.ndarray, np.ndarray, np.ndarray]]) -> None:
        self._pieces, self._next = self._runs(pieces), None
        self.m, self.passes, known, count = 0, 1, np.zeros(0, np.int64), np.zeros(0, np.int64)
        for at, src, dst in self._pieces:
            if at != self.m:
                if at:
                    raise ValueError("positions are not in order")
                self._next = (at, src, dst)
                break
            found, n = np.unique(np.concatenate((src, dst)), return_counts=True)
            at = np.searchsorted(known, found)
            fresh = np.ones(len(found), bool)
            fresh[at < len(known)] = known[at[at < len(known)]] != found[at < len(known)]
            known, count = np.insert(known, at[fresh], found[fresh]), np.insert(count, at[fresh], 0)
            count[np.searchsorted(known, found)] += n
            self.m += len(src)
        self.ids, self.degree, self.n = known, count, len(known)

    @staticmethod
    def _runs(pieces: Iterable[tuple[np.ndarray, np.ndarray, np.ndarray]]) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
        """First position and ends of consecutive edges."""
        for pos, src, dst in pieces:
            cuts = [0, *(np.flatnonzero(np.diff(pos) != 1) + 1).tolist(), len(pos)]
            for a, b in zip(cuts, cuts[1:], strict=False):
                if a < b:
                    yield int(pos[a]), src[a:b], dst[a:b]

    def chunks(self, size: int = 1 << 15) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
        """The next pass."""
        done = 0
        while done < self.m:
            at, src, dst = self._next or next(self._pieces, (-1, None, None))
            self._next = None
            if at != done:
                raise ValueError("a pass has ended early or is not in order")
            done += len(src)
            for a in range(0, len(src), size):
                yield at + a, np.searchsorted(self.ids, src[a : a + size]), np.searchsorted(self.ids, dst[a : a + size])
        self.passes += 1


def _numbers(values: np.ndarray, large: int = 1 << 20) -> list[int] | array:
    """Integers for single reads and writes: a list, or where boxed integers would fill the memory a plain array."""
    return values.tolist() if len(values) < large else array("q", np.ascontiguousarray(values, np.int64).tobytes())


def _masks(n: int, k: int, large: int = 1 << 20) -> list[int] | array:
    """Empty replica masks; a plain array for many vertices, if its words hold k bits."""
    return [0] * n if n < large or k > 64 else array("I" if k <= 32 else "Q", [0]) * n


class Partitions:
    """Loads, replica masks and the chain that settles an edge whose partition is full."""

    def __init__(self, stream: Stream, k: int, cap: int, seed: int = 0, which: str = "max", try_second: bool = False) -> None:
        self.k, self.cap, self.which, self.try_second = k, cap, which, try_second
        self._stream, self._seed = stream, seed
        self.load, self.mask = [0] * k, _masks(stream.n, k)
        self.bits = [1 << p for p in range(k)]
        self.p = np.full(stream.m, -1, np.int8 if k <= 1 << 7 else np.int16 if k <= 1 << 15 else np.int32)
        self.stage = np.zeros(stream.m, np.int8)
        self.scored = 0

    @cached_property
    def hashed(self) -> list[int] | array:
        return _numbers(portable_numpy(self._stream.ids, self._seed) % self.k)

    @cached_property
    def degree(self) -> list[int] | array:
        return _numbers(self._stream.degree)

    def put(self, e: int, u: int, v: int, p: int, stage: int) -> None:
        self.p[e], self.stage[e] = p, stage
        self.load[p] += 1
        self.hold(u, p)
        self.hold(v, p)

    def hold(self, x: int, p: int) -> None:
        """Vertex x lies on p; sets of one partition are one object for all vertices."""
        m, bit = self.mask[x], self.bits[p]
        if not m & bit:
            self.mask[x] = m | bit if m else bit

    def settle(self, e: int, u: int, v: int, p: int, stage: int, second: int | None = None) -> None:
        """Put an edge on p if it has room, else hash its heavier end, else take the least loaded."""
        if self.load[p] < self.cap:
            self.put(e, u, v, p, stage)
            return
        if self.try_second and second is not None and self.load[second] < self.cap:
            self.put(e, u, v, second, stage)
            return
        heavier = self.degree[u] >= self.degree[v] if self.which == "max" else self.degree[u] <= self.degree[v]
        p = self.hashed[u if heavier else v]
        if self.load[p] < self.cap:
            self.put(e, u, v, p, 2)
        else:
            self.put(e, u, v, min(range(self.k), key=self.load.__getitem__), 3)


# ---- the cluster-guided method -------------------------------------------------------------------


def cluster(stream: Stream, cap: int | None, passes: int = 1, migration: str = "residual", degree_mode: str = "exact") -> tuple[np.ndarray, np.ndarray]:
    """Cluster of each vertex, named by its least vertex, and cluster volumes by that name."""
    n = stream.n
    partial = degree_mode == "partial"
    # A vertex not seen yet is a cluster of its own that no other one can join or leave.
    c = _numbers(np.full(n, -1) if partial else np.arange(n))
    d = _numbers(np.zeros(n, np.int64) if partial else stream.degree)
    vol = _numbers(np.zeros(n, np.int64) if partial else stream.degree)
    limit = float("inf") if cap is None else cap
    residual = migration == "residual"
    for turn in range(passes):
        counting = partial and turn == 0
        for _, us, vs in stream.chunks():
            for u, v in zip(us.tolist(), vs.tolist(), strict=True):
                if counting:
                    for x in (u, v):
                        if c[x] < 0:
                            c[x] = x
                        d[x] += 1
                        vol[c[x]] += 1
                a, b = c[u], c[v]
                if a == b:
                    continue
                x, y = vol[a], vol[b]
                if x > limit or y > limit:
                    continue
                du, dv = d[u], d[v]
                if x - du <= y - dv if residual else x <= y:
                    if y + du <= limit:
                        vol[b], vol[a], c[u] = y + du, x - du, b
                elif x + dv <= limit:
                    vol[a], vol[b], c[v] = x + dv, y - dv, a
    found = np.array(c)
    least = np.full(n, n)
    np.minimum.at(least, found, np.arange(n))
    names = least[found]
    volumes = np.bincount(names, weights=stream.degree, minlength=n).astype(np.int64)
    return names, volumes


def map_clusters(names: np.ndarray, volumes: np.ndarray, k: int, policy: str = "lpt", seed: int = 0) -> np.ndarray:
    """Home partition of each vertex."""
    own = np.unique(names)
    placed = np.zeros(len(own), np.int64)
    if policy == "hash":
        placed[:] = portable_numpy(own, seed) % k
    elif policy == "round_robin":
        placed[:] = np.arange(len(own)) % k
    else:
        order = np.argsort(-volumes[own], kind="stable") if policy in ("lpt", "lpt_hist") else np.arange(len(own))
        placed[order] = list_schedule(((vol, 0) for vol in volumes[own][order].tolist()), k)[0]
    return placed[np.searchsorted(own, names)]


def guided(stream: Stream, parts: Partitions, names: np.ndarray, volumes: np.ndarray, home: np.ndarray, terms: tuple[str, ...] = ("replica", "cluster"), warm_start: bool = True, full_scan: tuple[float, float] | None = None) -> None:
    """Pre-partitioning, then the two-candidate score (or, with ``full_scan``, HDRF's over all partitions)."""
    load, inside = parts.load, np.zeros(stream.n, bool)
    for at, us, vs in stream.chunks():
        same = np.flatnonzero(home[us] == home[vs])
        p = home[us[same]]
        counts = np.bincount(p, minlength=parts.k).tolist()
        if all(n + more <= parts.cap for n, more in zip(load, counts, strict=True)):
            parts.p[at + same] = p
            for q, more in enumerate(counts):
                load[q] += more
            inside[us[same]] = inside[vs[same]] = True
        else:  # some partition gets full: one by one
            for e, u, v, q in zip((at + same).tolist(), us[same].tolist(), vs[same].tolist(), p.tolist(), strict=True):
                parts.settle(e, u, v, q, 0)
    rest = parts.p < 0
    if warm_start:
        touched = np.flatnonzero(inside)
        for x, q in zip(touched.tolist(), home[touched].tolist(), strict=True):
            parts.hold(x, q)
    else:
        parts.mask = _masks(stream.n, parts.k)
    if full_scan is not None:
        hdrf(stream, parts, *full_scan, only=rest)
        return
    parts.scored += 2 * int(rest.sum())
    if set(terms) == {"replica", "cluster"} and int(volumes.max()) * int(stream.degree.max()) < 1 << 62:
        _two_terms(stream, parts, rest, volumes[names], home)
        return
    vol, homes, d = _numbers(volumes[names]), _numbers(home), parts.degree
    for e, u, v in _picked(stream, rest):
        p, q = homes[u], homes[v]
        first = first_of_two(parts.mask[u], parts.mask[v], d[u], d[v], vol[u], vol[v], p, q, terms)
        parts.settle(e, u, v, p if first else q, 1, q if first else p)


def _two_terms(stream: Stream, parts: Partitions, rest: np.ndarray, vol: np.ndarray, home: np.ndarray) -> None:
    """The two-candidate score of the edges in ``rest``, as ``first_of_two`` with both terms; what does not depend on replicas is compared by arrays."""
    mask, load, bits, cap = parts.mask, parts.load, parts.bits, parts.cap
    for at, us, vs in stream.chunks():
        i = np.flatnonzero(rest[at : at + len(us)])
        us, vs = us[i], vs[i]
        p, q = home[us], home[vs]
        a, b, du, dv = vol[us].astype(np.int64), vol[vs].astype(np.int64), stream.degree[us].astype(np.int64), stream.degree[vs].astype(np.int64)
        parts.stage[at + i] = 1
        chosen = []
        columns = (x.tolist() for x in (at + i, us, vs, p, q, a * dv >= b * du, a * du >= b * dv, a >= b))
        for e, u, v, p, q, straight, crossed, larger in zip(*columns, strict=True):
            x, y = mask[u], mask[v]
            on_p, on_q = bits[p], bits[q]
            if x & on_p:
                if y & on_p:
                    first = larger if x & on_q and y & on_q else True
                elif x & on_q:
                    first = False if y & on_q else larger
                else:
                    first = straight if y & on_q else True
            elif y & on_p:
                if y & on_q:
                    first = False if x & on_q else larger
                else:
                    first = crossed if x & on_q else True
            else:
                first = False if (x | y) & on_q else larger
            best, second = (p, q) if first else (q, p)
            n = load[best]
            if n < cap:
                load[best] = n + 1
                bit = bits[best]
                if not x & bit:
                    mask[u] = x | bit if x else bit
                y = mask[v]
                if not y & bit:
                    mask[v] = y | bit if y else bit
                chosen.append(best)
            else:
                parts.settle(e, u, v, best, 1, second)
                chosen.append(int(parts.p[e]))
        parts.p[at + i] = chosen


def _picked(stream: Stream, only: np.ndarray | None) -> Iterator[tuple[int, int, int]]:
    """Number and ends of the edges that ``only`` marks, in stream order; of all without it."""
    for at, us, vs in stream.chunks():
        i = np.arange(len(us)) if only is None else np.flatnonzero(only[at : at + len(us)])
        yield from zip((at + i).tolist(), us[i].tolist(), vs[i].tolist(), strict=True)


def first_of_two(mu: int, mv: int, du: int, dv: int, a: int, b: int, p: int, q: int, terms: tuple[str, ...] = ("replica", "cluster")) -> bool:
    """Whether the first end's home p beats the second's q: replica masks, degrees and cluster volumes of both ends; ties go to p."""
    replica, own = "replica" in terms, "cluster" in terms
    if not (replica and own):
        score = lambda x: ((2 - du / (du + dv)) * (mu >> x & 1) + (2 - dv / (du + dv)) * (mv >> x & 1)) * replica + own * ((a if x == p else b) / (a + b))
        return score(p) >= score(q)
    on_p, on_q = (mu >> p & 1) + (mv >> p & 1), (mu >> q & 1) + (mv >> q & 1)
    if on_p != on_q:
        return on_p > on_q
    if on_p == 1 and mu >> p & 1 and mv >> q & 1:
        return a * dv >= b * du
    if on_p == 1 and mv >> p & 1 and mu >> q & 1:
        return du * a >= dv * b
    return a >= b


# ---- stateful baselines --------------------------------------------------------------------------


def hdrf(stream: Stream, parts: Partitions, lam: float = 1.1, eps: float = 1.0, degree_mode: str = "exact", only: np.ndarray | None = None) -> None:
    """Highest degree replicated first: the best of all k partitions for every edge that ``only`` marks.

    Of the partitions without a replica of either end only the least loaded can win: the balance term falls with the
    load, and a replica is worth more than 1.  So the choice among all k (which ``scored`` counts) is computed for the
    ends' replicas and that one partition.  Scores are equal if they agree in 9 digits; the first partition wins.
    """
    k, cap, load, mask, bits, stage = parts.k, parts.cap, parts.load, parts.mask, parts.bits, parts.stage
    seen = _numbers(np.zeros(stream.n, np.int64)) if degree_mode == "partial" else parts.degree
    most, least = max(load), min(load)
    base, levels = least, [0] * (most - least + 1)  # which partitions have a load of base, base + 1, ...
    for p, n in enumerate(load):
        levels[n - base] |= bits[p]
    for e, u, v in _picked(stream, only):
        if degree_mode == "partial":
            seen[u] += 1
            seen[v] += 1
        a, b = mask[u], mask[v]
        bit = levels[least - base]
        bit &= -bit
        best, spread = bit.bit_length() - 1, eps + most - least
        if lam <= 1e-8 * spread:  # a step of the load is lost in rounding: all k
            best, top, share = 0, -1, seen[u] / (seen[u] + seen[v])
            for p, n in enumerate(load):
                if n < cap:
                    score = round((lam * (most - n) / spread + (a >> p & 1) * (2 - share) + (b >> p & 1) * (1 + share)) * 1e9)
                    if score > top:
                        top, best = score, p
        elif a or b:
            both, share = a & b, seen[u] / (seen[u] + seen[v])
            top = -1 if (a | b) & bit else round(lam * (most - least) / spread * 1e9)
            for own, on_u, on_v in ((both, 2 - share, 1 + share), (a ^ both, 2 - share, 0.0), (b ^ both, 0.0, 1 + share)):
                if not own:
                    continue
                # The least loaded of these, the first of several: by load where few loads are in use, else one by one.
                low = cap
                if own.bit_count() > most - least:
                    for low in range(least, most + 1):
                        if found := levels[low - base] & own:
                            p = (found & -found).bit_length() - 1
                            break
                else:
                    while own:
                        q = (own & -own).bit_length() - 1
                        own &= own - 1
                        if load[q] < low:
                            low, p = load[q], q
                if low < cap:
                    score = round((lam * (most - low) / spread + on_u + on_v) * 1e9)
                    if score > top or score == top and p < best:
                        top, best = score, p
        bit = bits[best]
        parts.p[e], stage[e] = best, 1
        n = load[best]
        load[best] = n + 1
        if not a & bit:
            mask[u] = a | bit if a else bit
        b = mask[v]
        if not b & bit:
            mask[v] = b | bit if b else bit
        levels[n - base] ^= bit
        if n == most:
            most = n + 1
            levels.append(bit)
        else:
            levels[n + 1 - base] |= bit
        while not levels[least - base]:
            least += 1
    parts.scored += k * (stream.m if only is None else int(only.sum()))


def greedy(stream: Stream, parts: Partitions) -> None:
    """Four cases by the ends' replica sets; the least loaded partition of the chosen set."""
    left = list(parts.degree)
    everywhere = (1 << parts.k) - 1
    for e, (u, v) in enumerate(zip(stream.u.tolist(), stream.v.tolist(), strict=True)):
        a, b = parts.mask[u], parts.mask[v]
        chosen = a & b or ((a if left[u] >= left[v] else b) if a and b else a | b) or everywhere
        room = [p for p in range(parts.k) if chosen >> p & 1 and parts.load[p] < parts.cap] or [p for p in range(parts.k) if parts.load[p] < parts.cap]
        parts.scored += parts.k
        parts.put(e, u, v, min(room, key=lambda p: (parts.load[p], p)), 1)
        left[u] -= 1
        left[v] -= 1


def adwise(stream: Stream, parts: Partitions, lam: float = 1.1, min_buffer: int = 10, latency_factor: float = 40.0) -> None:
    """A buffer of edges; the best (edge, partition) in it goes first; the buffer adapts to a budget of score evaluations.

    It doubles while gains do not fall and the budget would bear twice its size to the end.
    """
    k, m = parts.k, stream.m
    table, load = np.zeros((stream.n, k), bool), np.zeros(k)
    budget, window, at, last_gain = latency_factor * k * m, min_buffer, 0, 0.0
    held: list[int] = []
    d, us, vs = stream.degree.astype(float), stream.u, stream.v
    seen = np.zeros(stream.n, np.int64)  # how often the buffer holds a vertex
    for done in range(m):
        while len(held) < window and at < m:
            held.append(at)
            seen[us[at]] += 1
            seen[vs[at]] += 1
            at += 1
        e = np.array(held)
        u, v = us[e], vs[e]
        share = (d[u] / (d[u] + d[v]))[:, None]
        most, least = load.max(), load.min()
        close = np.minimum(1.0, (seen[u] + seen[v] - 2) / len(e))[:, None]
        score = lam * (most - load)[None, :] / (1 + most - least) + table[u] * (2 - share) + table[v] * (1 + share) + 0.1 * close * (table[u] | table[v])
        score[:, load >= parts.cap] = -1
        best = int(np.round(score, 9).argmax())
        i, p = divmod(best, k)
        gain = float(score[i, p])
        parts.scored += k * len(e)
        parts.put(int(e[i]), int(u[i]), int(v[i]), p, 1)
        load[p] += 1
        table[u[i], p] = table[v[i], p] = True
        held.pop(i)
        seen[u[i]] -= 1
        seen[v[i]] -= 1
        rate = budget - parts.scored - k * window * (m - done - 1)
        if gain >= last_gain and rate > k * window * (m - done - 1):
            window *= 2
        elif gain < last_gain or rate <= 0:
            window = max(min_buffer, window // 2)
        last_gain = gain


# ---- expansion baselines -------------------------------------------------------------------------


def expand(stream: Stream, parts: Partitions, edges: np.ndarray | None = None, quota: int | None = None, blocked: np.ndarray | None = None, short: int = 64, piece: int = 1 << 16) -> None:
    """Neighbourhood expansion: grow one partition after the other from its boundary.

    ``edges`` marks those that it takes (all without it), ``blocked`` vertices that are never expanded.  Vertices of more
    than ``short`` ends are looked through by arrays, ``piece`` ends at a time.
    """
    near, n, k = stream.adjacency(), stream.n, parts.k
    offsets = memoryview(near.offsets)
    live = bytearray(b"\1") * stream.m if edges is None else bytearray(edges.view(np.uint8))
    is_live = np.frombuffer(live, bool)
    parts.stage[is_live] = 1
    total = int(np.count_nonzero(is_live))
    lefts = _live_degree(stream, is_live) if edges is not None else stream.degree.astype(np.int32 if 2 * stream.m < 1 << 31 else np.int64)
    left = memoryview(lefts)
    # 2p + 1: inside partition p; 2p + 2: expanded there.  Less: neither, whatever it was in earlier ones.
    stamps = np.zeros(n, np.int16 if 2 * k + 2 < 1 << 15 else np.int32)
    stamp, place = memoryview(stamps), memoryview(parts.p)
    quota = quota or -(-total // k)
    stop = blocked.tobytes() if blocked is not None else bytes(n)
    seed = 0
    for p in range(k):
        goal = min(parts.cap - parts.load[p], quota if p < k - 1 else total)
        taken, inside, heap = 0, 2 * p + 1, []
        mask, bit = parts.mask, parts.bits[p]

        def absorb(x: int) -> None:
            """Put x on the boundary and take its live edges into the partition's vertices."""
            nonlocal taken
            stamp[x] = inside
            a, b = offsets[x], offsets[x + 1]
            before = taken
            if b - a <= short:
                for y, e in near.pairs(a, b):
                    if live[e] and stamp[y] >= inside and taken < goal:
                        live[e] = 0
                        left[x] -= 1
                        left[y] -= 1
                        place[e] = p
                        taken += 1
                        m = mask[y]
                        if not m & bit:
                            mask[y] = m | bit if m else bit
            else:
                for at in range(a, b, piece):
                    if taken >= goal:
                        break
                    rows = near.rows(at, min(b, at + piece))
                    own = rows[is_live[rows[:, 1]] & (stamps[rows[:, 0]] >= inside)]
                    if (own[:, 0] == x).any():  # a loop is here twice
                        own = own[np.sort(np.unique(own[:, 1], return_index=True)[1])]
                    own = own[: goal - taken]
                    is_live[own[:, 1]] = False
                    left[x] -= len(own)
                    np.subtract.at(lefts, own[:, 0], 1)
                    parts.p[own[:, 1]] = p
                    taken += len(own)
                    for y in own[:, 0].tolist():
                        parts.hold(y, p)
            if taken > before:
                parts.hold(x, p)
            heapq.heappush(heap, left[x] * n + x)

        while taken < goal and total:
            x = None
            while heap:
                d, y = divmod(heapq.heappop(heap), n)
                if stamp[y] > inside or not left[y] or stop[y]:
                    continue
                if d != left[y]:
                    heapq.heappush(heap, left[y] * n + y)
                    continue
                x = y
                break
            if x is None:
                # No vertex gets live edges back, so those passed over are never seeds again, in later partitions neither.
                while seed < n and (not left[seed] or stop[seed]):
                    seed += 1
                if seed == n:
                    break
                x = seed
                if stamp[x] < inside:
                    absorb(x)
            stamp[x] = inside + 1
            if not left[x]:
                continue
            for at in range(offsets[x], offsets[x + 1], piece):
                b = min(offsets[x + 1], at + piece)
                if b - at > short:
                    rows = near.rows(at, b)
                    rows = rows[is_live[rows[:, 1]] & (stamps[rows[:, 0]] < inside)].tolist()
                else:
                    rows = near.pairs(at, b)
                for y, e in rows:
                    if taken >= goal:
                        break
                    if live[e] and stamp[y] < inside:
                        absorb(y)
        parts.load[p] += taken
        total -= taken
    for e, u, v in _picked(stream, is_live):
        both = parts.mask[u] & parts.mask[v] or parts.mask[u] | parts.mask[v]
        room = [p for p in range(k) if parts.load[p] < parts.cap]
        parts.put(e, u, v, min([p for p in room if both >> p & 1] or room, key=lambda p: (parts.load[p], p)), 1)


def _live_degree(stream: Stream, live: np.ndarray) -> np.ndarray:
    """How often each vertex is an end of an edge that ``live`` marks."""
    out = np.zeros(stream.n, np.int32 if 2 * stream.m < 1 << 31 else np.int64)
    for at, us, vs in stream.chunks(1 << 20):
        own = live[at : at + len(us)]
        np.add.at(out, us[own], 1)
        np.add.at(out, vs[own], 1)
    return out


def expand_stream(stream: Stream, parts: Partitions, cache: int = 2) -> None:
    """Streaming expansion: a cache of ``cache`` edges a vertex is expanded, refilled as edges leave."""
    size = max(parts.k, cache * stream.n)
    for at in range(0, stream.m, size):
        chunk = np.arange(at, min(stream.m, at + size))
        part = Partitions(stream, parts.k, min(parts.cap, -(-len(chunk) * 21 // (20 * parts.k))))
        part.mask = list(parts.mask)
        sub = Stream(stream.ids[stream.u[chunk]], stream.ids[stream.v[chunk]])
        own = Partitions(sub, parts.k, max(part.cap, -(-len(chunk) // parts.k)))
        back = np.searchsorted(stream.ids, sub.ids)
        own.mask = [parts.mask[x] for x in back.tolist()]
        own.load = [0] * parts.k
        own.cap = min(own.cap, max(1, parts.cap - min(parts.load)))
        free = [parts.cap - x for x in parts.load]
        expand(sub, own)
        order = sorted(range(parts.k), key=lambda p: -own.load[p])
        names = _match(own, parts, sub, back, order, free)
        for i, e in enumerate(chunk.tolist()):
            parts.settle(e, int(stream.u[e]), int(stream.v[e]), names[int(own.p[i])], 1)


def _match(own: Partitions, parts: Partitions, sub: Stream, back: np.ndarray, order: list[int], free: list[int]) -> list[int]:
    """Which partition each expanded part of a chunk joins: the one that holds most of its vertices and has room."""
    held = [parts.mask[x] for x in back.tolist()]
    shared = np.zeros((parts.k, parts.k), np.int64)
    members: dict[int, set[int]] = defaultdict(set)
    for e in range(sub.m):
        members[int(own.p[e])].update((int(sub.u[e]), int(sub.v[e])))
    for p, vertices in members.items():
        for x in vertices:
            m = held[x]
            while m:
                low = m & -m
                shared[p, low.bit_length() - 1] += 1
                m ^= low
    names, used = [0] * parts.k, set()
    for p in order:
        names[p] = max((q for q in range(parts.k) if q not in used), key=lambda q: (free[q] >= own.load[p], shared[p, q], free[q], -q))
        used.add(names[p])
    return names


def expand_together(stream: Stream, parts: Partitions, ratio: float = 0.1, seed: int = 0) -> None:
    """All partitions expand at once: each round takes a share of every boundary; claims go to the emptiest partition."""
    offsets, other, edge = (x.tolist() for x in stream.neighbours())
    us, vs = stream.u.tolist(), stream.v.tolist()
    live, left = bytearray(b"\1") * stream.m, list(parts.degree)
    spread = np.random.default_rng(seed).permutation(stream.n).tolist()
    inside: list[set[int]] = [set() for _ in range(parts.k)]
    border: list[set[int]] = [{spread[p]} if p < stream.n else set() for p in range(parts.k)]
    at, rest = parts.k, stream.m
    while rest:
        claims: dict[int, tuple[int, int]] = {}
        for p in sorted(range(parts.k), key=lambda p: (parts.load[p], p)):
            if parts.load[p] >= parts.cap:
                continue
            border[p] = {x for x in border[p] if left[x]}
            if not border[p]:
                while at < stream.n and not left[spread[at]]:
                    at += 1
                fresh = spread[at] if at < stream.n else next((x for x in range(stream.n) if left[x]), None)
                at += at < stream.n
                if fresh is not None:
                    border[p] = {fresh}
            take = sorted(border[p], key=lambda x: (left[x], x))[: max(1, int(ratio * len(border[p])))]
            for x in take:
                inside[p].add(x)
                border[p].discard(x)
                for i in range(offsets[x], offsets[x + 1]):
                    if live[edge[i]]:
                        bid = (parts.load[p], p)
                        if edge[i] not in claims or bid < claims[edge[i]]:
                            claims[edge[i]] = bid
                        border[p].add(other[i])
        for e, (_, p) in sorted(claims.items()):
            if parts.load[p] < parts.cap:
                live[e] = 0
                rest -= 1
                left[us[e]] -= 1
                left[vs[e]] -= 1
                parts.put(e, us[e], vs[e], p, 1)


def hybrid(stream: Stream, parts: Partitions, tau: float = 10.0, lam: float = 1.1, eps: float = 1.0) -> None:
    """Edges with a low-degree end are expanded in memory, those between two high-degree ends are streamed by HDRF."""
    high = stream.degree > tau * stream.degree.mean()
    low = np.empty(stream.m, bool)
    for at, us, vs in stream.chunks(1 << 20):
        low[at : at + len(us)] = ~(high[us] & high[vs])
    if count := int(np.count_nonzero(low)):
        expand(stream, parts, low, quota=-(-count // parts.k), blocked=high)
    if count < stream.m:
        hdrf(stream, parts, lam, eps, only=~low)


# ---- vertex-cut stand-ins ------------------------------------------------------------------------


def _edges_from_vertices(stream: Stream, parts: Partitions, home: np.ndarray) -> None:
    """An edge inside a vertex part goes there, a cut edge to the lighter of its ends' parts."""
    for e, (u, v) in enumerate(zip(stream.u.tolist(), stream.v.tolist(), strict=True)):
        p, q = int(home[u]), int(home[v])
        parts.settle(e, u, v, p if parts.load[p] <= parts.load[q] else q, 1, q if parts.load[p] <= parts.load[q] else p)


def multilevel(stream: Stream, parts: Partitions, seed: int = 0, refine: int = 4) -> None:
    """Heavy-edge matching down to few super-vertices, greedy growth there, refinement on the way back."""
    levels: list[np.ndarray] = []
    u, v, w, weight = stream.u, stream.v, np.ones(stream.m, np.int64), stream.degree.astype(np.int64)
    graphs = [(u, v, w, weight)]
    top = max(1, int(weight.sum() * 1.05 / (3 * parts.k)))
    while len(weight) > 30 * parts.k:
        mate = np.arange(len(weight))
        free = np.ones(len(weight), bool)
        for i in np.lexsort((v, u, -w)).tolist():
            a, b = u[i], v[i]
            if free[a] and free[b] and a != b and weight[a] + weight[b] <= top:
                free[a] = free[b] = False
                mate[max(a, b)] = min(a, b)
        names, parent = np.unique(mate, return_inverse=True)
        if len(names) > 0.95 * len(weight):
            break
        levels.append(parent)
        a, b = np.minimum(parent[u], parent[v]), np.maximum(parent[u], parent[v])
        keep = a != b
        key, back = np.unique(a[keep] * len(names) + b[keep], return_inverse=True)
        w = np.bincount(back, weights=w[keep], minlength=len(key)).astype(np.int64)
        u, v = key // len(names), key % len(names)
        weight = np.bincount(parent, weights=weight, minlength=len(names)).astype(np.int64)
        graphs.append((u, v, w, weight))
    home = _grow(u, v, w, weight, parts.k)
    for level in range(len(graphs) - 1, -1, -1):
        if level < len(levels):
            home = home[levels[level]]
        home = _refine(*graphs[level], home, parts.k, refine)
    _edges_from_vertices(stream, parts, home)


def _grow(u: np.ndarray, v: np.ndarray, w: np.ndarray, weight: np.ndarray, k: int) -> np.ndarray:
    near: dict[int, list[tuple[int, int]]] = defaultdict(list)
    for a, b, c in zip(u.tolist(), v.tolist(), w.tolist(), strict=True):
        near[a].append((b, c))
        near[b].append((a, c))
    home, goal = np.full(len(weight), -1), weight.sum() / k
    order = np.argsort(-weight, kind="stable").tolist()
    for p in range(k):
        load, gain = 0, {}
        while load < goal or p == k - 1:
            x = max(gain, key=lambda y: (gain[y], -y)) if gain else next((y for y in order if home[y] < 0), None)
            if x is None:
                break
            gain.pop(x, None)
            home[x] = p
            load += weight[x]
            for y, c in near[x]:
                if home[y] < 0:
                    gain[y] = gain.get(y, 0) + c
    home[home < 0] = k - 1
    return home


def _refine(u: np.ndarray, v: np.ndarray, w: np.ndarray, weight: np.ndarray, home: np.ndarray, k: int, rounds: int) -> np.ndarray:
    """Move boundary vertices to the part that they are tied to most, while it stays within its share."""
    home = home.copy()
    most = 1.1 * weight.sum() / k + weight.max()
    for _ in range(rounds):
        ends, others, ties = np.concatenate((u, v)), np.concatenate((v, u)), np.concatenate((w, w))
        key, back = np.unique(ends * k + home[others], return_inverse=True)
        pull = np.bincount(back, weights=ties)
        owner, to = key // k, key % k
        own = np.zeros(len(weight))
        same = home[owner] == to
        own[owner[same]] = pull[same]
        gain = pull - own[owner]
        load = np.bincount(home, weights=weight, minlength=k)
        moved = 0
        for i in np.argsort(-gain, kind="stable").tolist():
            if gain[i] <= 0:
                break
            x, p = owner[i], to[i]
            if home[x] != p and load[p] + weight[x] <= most and (x % 2 == _ % 2):
                load[home[x]] -= weight[x]
                load[p] += weight[x]
                home[x] = p
                moved += 1
        if not moved:
            break
    return home


def label_propagation(stream: Stream, parts: Partitions, rounds: int = 8, seed: int = 0) -> None:
    """Size-capped label propagation from hashed labels; edges follow their ends."""
    home = portable_numpy(stream.ids, seed) % parts.k
    home = _refine(stream.u, stream.v, np.ones(stream.m, np.int64), stream.degree.astype(np.int64), home, parts.k, rounds)
    _edges_from_vertices(stream, parts, home)
