"""Hierarchical packing of documents into sequences of several context sizes.

A document is cut into whole windows of the longest size; what remains is routed to the smallest
tier (a power of two) that holds it.  Tiers are packed from the longest down: a remainder opens a
window of its tier, shorter documents fill the gap, the largest that fits first, and the last gap is
closed with a piece cut from a document.  A sequence is full at its tier's size, a power of two, so
it needs no padding.  Sequences of every tier are dealt evenly to step groups.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

WINDOW = 2048
SMALLEST = 256
LEAST_TAIL = 64
STEP_TOKENS = 64 * WINDOW
_CHUNK = 2_000_000
_SCHEMA = pa.schema(
    [
        ("row", pa.int64()), ("start", pa.int64()), ("length", pa.int64()), ("ids", pa.binary()), ("doc_tokens", pa.int64()),
        ("sequence_id", pa.int64()), ("offset", pa.int64()), ("window", pa.int32()), ("step_group", pa.int64()),
    ]
)


class Packer:
    """Packs pieces ``(document, start, length)`` into windows; what fills no window waits for more."""

    def __init__(self, window: int = WINDOW, smallest: int = SMALLEST) -> None:
        if window & (window - 1) or smallest & (smallest - 1) or not 0 < smallest <= window:
            raise ValueError("window and smallest must be powers of two, smallest at most window")
        self.window = window
        self.tiers = [1 << k for k in range(smallest.bit_length() - 1, window.bit_length())]
        self._waiting: list[list[tuple[int, int]]] = [[] for _ in range(window)]
        self._lengths = 0  # bit n is set if a piece of length n waits

    def add(self, doc: int, tokens: int) -> list[tuple[int, list[tuple[int, int, int]]]]:
        """Whole windows of a document at once; its remainder waits."""
        whole = tokens // self.window
        if tokens % self.window:
            self._put(doc, whole * self.window, tokens % self.window)
        return [(self.window, [(doc, i * self.window, self.window)]) for i in range(whole)]

    def _put(self, doc: int, start: int, n: int) -> None:
        self._waiting[n].append((doc, start))
        self._lengths |= 1 << n

    def _get(self, n: int) -> tuple[int, int]:
        piece = self._waiting[n].pop()
        if not self._waiting[n]:
            self._lengths &= ~(1 << n)
        return piece

    def fill(self) -> Iterator[tuple[int, list[tuple[int, int, int]]]]:
        """Windows of all tiers, longest first, as long as there is enough to fill them."""
        for tier in reversed(self.tiers):
            floor = tier // 2 if tier > self.tiers[0] else 0
            while (longest := self._lengths.bit_length() - 1) > floor:
                if not longest or longest > tier:
                    break
                pieces, gap = [], tier
                while gap:
                    fits = (self._lengths & ((1 << (gap + 1)) - 1)).bit_length() - 1
                    if fits > 0:
                        pieces.append((*self._get(fits), fits))
                        gap -= fits
                    elif self._lengths:
                        n = (self._lengths & -self._lengths).bit_length() - 1
                        doc, start = self._get(n)
                        pieces.append((doc, start, gap))
                        self._put(doc, start + gap, n - gap)
                        gap = 0
                    else:
                        break
                if gap:
                    for piece in pieces:
                        self._put(*piece)
                    return
                yield tier, pieces

    def rest(self, least: int = LEAST_TAIL) -> Iterator[tuple[int, list[tuple[int, int, int]]]]:
        """What waits at the end: full windows of ever smaller powers of two, and one last padded sequence."""
        pieces = [(d, s, n) for n in range(self.window - 1, 0, -1) for d, s in self._waiting[n]]
        left = sum(n for _, _, n in pieces)
        while left:
            size = self.window if left >= self.window else 1 << (left.bit_length() - 1)
            if size < least:
                size = left
            taken, room = [], size
            while room:
                d, s, n = pieces.pop(0)
                if n > room:
                    pieces.insert(0, (d, s + room, n - room))
                    n = room
                taken.append((d, s, n))
                room -= n
            left -= size
            yield (size if size & (size - 1) == 0 else self.window), taken
        self._waiting, self._lengths = [[] for _ in range(self.window)], 0


def pack(docs: DataFrame, paths: tuple[str, str], pattern: str, window: int = WINDOW, smallest: int = SMALLEST, end_id: int = 1) -> DataFrame:
    """A row for each piece: the columns of ``docs`` but its text, then ``start, length, ids,
    doc_tokens, sequence_id, offset, window, step_group``.

    ``paths`` are the vocabulary's rank file and its ``tokenizers`` file.  ``ids`` holds the piece's
    ids as little-endian unsigned 32-bit integers.  Every id of every row lies in one piece; a null
    or empty text is its end id alone; repeated rows are packed each; an empty table gives an empty
    result.  Each input partition is packed on its own as it streams by, so nothing is shuffled and
    memory is bounded by a chunk of texts; at most one sequence of a partition is padded.  Sequence
    ids follow from the partition, so a task that runs again gives the same rows.  Columns with the
    names of results are replaced.
    """
    results = _SCHEMA.names[1:]
    kept = [c for c in docs.columns if c not in (*results, "text")]
    renamed = docs.select(*[F.col(f"`{c}`").alias(f"c{i}") for i, c in enumerate(kept)], F.coalesce(F.col("text"), F.lit("")).alias("__text"))
    names = [f"c{i}" for i in range(len(kept))]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from .bpe import Encoder

        encoder, packer = Encoder(*paths, pattern), Packer(window, smallest)
        store: dict[int, tuple[pa.RecordBatch, int, np.ndarray]] = {}
        serial = [TaskContext.get().partitionId() << 40, 0, 0]

        def emit(found: list[tuple[int, list[tuple[int, int, int]]]]) -> Iterator[pa.RecordBatch]:
            for i in range(0, len(found), 512):
                part = found[i : i + 512]
                if out := _rows(part, store, serial, names):
                    yield out

        for texts, batch, at in _chunks(batches):
            ids, bounds = encoder.encode(texts)
            found = []
            for k in range(len(texts)):
                doc = serial[1]
                serial[1] += 1
                own = np.append(ids[bounds[k] : bounds[k + 1]], np.uint32(end_id)).astype("<u4")
                store[doc] = (batch, at + k, own)
                found += packer.add(doc, len(own))
            found += packer.fill()
            yield from emit(_dealt(found, serial))
            waiting = {d for x in packer._waiting for d, _ in x}
            store = {d: store[d] for d in waiting}
        yield from emit(_dealt(list(packer.rest()), serial))

    schema = ", ".join([f"{n} {t}" for n, t in renamed.dtypes if n != "__text"] + [f"r_{n} {t}" for n, t in zip(results, ("long", "long", "binary", "long", "long", "long", "int", "long"), strict=True)])
    done = renamed.mapInArrow(run, schema)
    return done.select(*[F.col(f"c{i}").alias(c) for i, c in enumerate(kept)], *[F.col(f"r_{n}").alias(n) for n in results])


def _chunks(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[list[str], pa.RecordBatch, int]]:
    for batch in batches:
        sizes = np.diff(np.frombuffer(batch.column("__text").buffers()[1], np.int32)[batch.column("__text").offset :][: batch.num_rows + 1]) if batch.num_rows else []
        at = 0
        while at < batch.num_rows:
            end, total = at, 0
            while end < batch.num_rows and (end == at or total + sizes[end] <= _CHUNK):
                total += int(sizes[end])
                end += 1
            yield batch.column("__text").slice(at, end - at).to_pylist(), batch, at
            at = end


def _dealt(found: list, serial: list[int]) -> list[tuple[int, list, int]]:
    """Each sequence with its step group: every group gets its share of each tier."""
    groups = max(1, sum(n for _, pieces in found for _, _, n in pieces) // STEP_TOKENS) if found else 0
    by_tier: dict[int, list] = {}
    for x in found:
        by_tier.setdefault(x[0], []).append(x)
    first = (serial[0] >> 40 << 40) + serial[2]
    serial[2] += groups
    return [(tier, pieces, first + i * groups // len(own)) for tier, own in by_tier.items() for i, (_, pieces) in enumerate(own)]


def _rows(found: list[tuple[int, list[tuple[int, int, int]], int]], store: dict, serial: list[int], names: list[str]) -> pa.RecordBatch | None:
    out: dict[str, list] = {n: [] for n in _SCHEMA.names[1:]}
    rows: list[tuple[pa.RecordBatch, int]] = []
    for tier, pieces, group in found:
        offset = 0
        for doc, start, n in pieces:
            batch, at, ids = store[doc]
            rows.append((batch, at))
            for name, x in zip(out, (start, n, ids[start : start + n].tobytes(), len(ids), serial[0], offset, tier, group), strict=True):
                out[name].append(x)
            offset += n
        serial[0] += 1
    if not rows:
        return None
    arrays = []
    for name in names:
        values = {id(b): b.column(name).to_pylist() for b in {id(b): b for b, _ in rows}.values()}
        arrays.append(pa.array([values[id(b)][i] for b, i in rows], rows[0][0].schema.field(name).type))
    arrays += [pa.array(out[n], _SCHEMA.field(n).type) for n in out]
    return pa.RecordBatch.from_arrays(arrays, names=[*names, *(f"r_{n}" for n in out)])
