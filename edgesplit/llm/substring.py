"""Substring dedup over difference-cover anchors.

Words at positions whose remainder modulo a period lies in a difference cover start an anchor: a
short window that is hashed.  Whatever the shift between two occurrences of a passage, some position
of the cover is aligned in both, so every match of anchor + period - 1 words shares an anchor.  The
first round finds anchors that several documents share; only around those does the second round hash
whole windows and find which window starts in an earlier document too.  Both rounds send hashes
packed by bucket, after each task has merged its own repeats: a passage that every document holds
costs one entry for each chunk of texts.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import zstandard
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..plans.storage import materialise
from . import words as W
from .columns import Packed, text_key
from .mixing import word_count

WINDOW = 13
# A perfect difference cover; every remainder modulo 7 is a difference of two members.
PERIOD, COVER = 7, (0, 1, 3)
_CHUNK = 2 << 20
_BUCKET_BYTES = 16 << 20
_LEAST_BUCKETS = 64


# ---- packed entries ------------------------------------------------------------------------------


def _pack(ids: np.ndarray, low: np.ndarray, high: np.ndarray) -> bytes:
    """Entries sorted by id: the ids, how many entries each has, and the entries' hashes."""
    new = np.flatnonzero(np.diff(ids, prepend=ids[:1] - 1))
    counts = np.diff(np.append(new, len(ids))).astype(np.uint32)
    squeeze = zstandard.ZstdCompressor(level=1).compress
    gaps = np.diff(ids[new], prepend=0)
    table = squeeze(gaps.tobytes() + counts.tobytes())
    head = np.array([len(new), len(ids), len(table), high.itemsize], np.int64).tobytes()
    return head + table + low.astype(np.uint32).tobytes() + high.tobytes()


def _unpack(blob: bytes) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    n_ids, n, n_table, width = np.frombuffer(blob, np.int64, 4)
    table = zstandard.ZstdDecompressor().decompress(blob[32 : 32 + n_table])
    ids = np.cumsum(np.frombuffer(table, np.int64, n_ids))
    counts = np.frombuffer(table, np.uint32, n_ids, int(n_ids) * 8)
    low = np.frombuffer(blob, np.uint32, n, 32 + int(n_table))
    high = np.frombuffer(blob, {2: np.uint16, 4: np.uint32, 8: np.uint64}[int(width)], n, 32 + int(n_table) + 4 * int(n))
    return np.repeat(ids, counts), low, high


def _by_bucket(ids: np.ndarray, keys: np.ndarray, high: np.ndarray, buckets: int) -> Iterator[tuple[int, bytes]]:
    """Packed entries of each bucket; the bucket is a range of the key's upper half, its lower half and ``high`` are sent."""
    bucket = ((keys >> np.uint64(32)) * np.uint64(buckets)) >> np.uint64(32)
    order = np.lexsort((ids, bucket))
    bucket, ids, keys, high = bucket[order], ids[order], keys[order], high[order]
    cuts = np.flatnonzero(np.diff(bucket)) + 1
    for a, b in zip(np.concatenate(([0], cuts)).tolist(), np.concatenate((cuts, [len(bucket)])).tolist(), strict=True):
        if a < b:
            yield int(bucket[a]), _pack(ids[a:b], keys[a:b] & np.uint64(0xFFFFFFFF), high[a:b])


def _groups(order_by: tuple[np.ndarray, ...]) -> tuple[np.ndarray, np.ndarray]:
    """Sort by the last key first; the order, and where each group of equal keys (all but the first) begins."""
    order = np.lexsort(order_by)
    differ = np.zeros(len(order), bool)
    differ[:1] = True
    for key in order_by[1:]:
        k = key[order]
        differ[1:] |= k[1:] != k[:-1]
    return order, np.flatnonzero(differ)


def _marks(ids: np.ndarray, values: np.ndarray) -> Iterator[tuple[int, bytes]]:
    """Values of each id, as bytes."""
    order = np.argsort(ids, kind="stable")
    ids, values = ids[order], values[order]
    cuts = np.flatnonzero(np.diff(ids)) + 1
    for a, b in zip(np.concatenate(([0], cuts)).tolist(), np.concatenate((cuts, [len(ids)])).tolist(), strict=True):
        if a < b:
            yield int(ids[a]), np.unique(values[a:b]).tobytes()


# ---- windows of a chunk of texts -----------------------------------------------------------------


class _Chunk:
    """Word hashes of some texts, and which windows of a size lie in one text."""

    def __init__(self, texts: pa.Array) -> None:
        self.words = W.split(texts)
        self.hashed = W.hashes(self.words)
        self.doc = np.repeat(np.arange(len(texts)), self.words.counts)
        self.place = np.arange(len(self.doc)) - self.words.first[:-1][self.doc] if len(self.doc) else self.doc

    def starts(self, size: int) -> np.ndarray:
        n = len(self.doc) - size + 1
        return np.flatnonzero(self.doc[:n] == self.doc[size - 1 :]) if n > 0 else np.zeros(0, np.int64)

    def anchors(self, size: int) -> tuple[np.ndarray, np.ndarray]:
        """Anchor positions and their hashes."""
        at = self.starts(size)
        cover = np.zeros(PERIOD, bool)
        cover[list(COVER)] = True
        at = at[cover[self.place[at] % PERIOD]]
        return at, W.window_hashes(self.hashed, size)[at]

    def second_hashes(self, size: int) -> np.ndarray:
        return W.window_hashes(W.hashes(self.words, 1), size, 1)


_ROUND = "bucket int, doc_id long, body binary"


def _round_rows(rows: list[tuple[int, int | None, bytes]]) -> pa.RecordBatch:
    b, d, x = zip(*rows, strict=True)
    return pa.RecordBatch.from_arrays([pa.array(b, pa.int32()), pa.array(d, pa.int64()), pa.array(x, pa.binary())], names=["bucket", "doc_id", "body"])


def _first_round(docs: DataFrame, window: int, buckets: int) -> DataFrame:
    """Packed anchors for each bucket (null doc_id), and marks of anchors that documents of one chunk share (with doc_id)."""
    size = window - PERIOD + 1

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            own_ids, own_texts = batch.column("doc_id"), batch.column("text")
            for a, b in W.documents(own_texts, _CHUNK):
                ids = np.asarray(own_ids.slice(a, b - a))
                chunk = _Chunk(own_texts.slice(a, b - a))
                at, keys = chunk.anchors(size)
                if not len(at):
                    continue
                who = ids[chunk.doc[at]]
                order, begin = _groups((who, keys))
                who, keys = who[order], keys[order]
                least, most = who[begin], np.append(who[begin[1:] - 1], who[-1])
                shared = np.repeat(least != most, np.diff(np.append(begin, len(who))))
                rows = [(bucket, None, body) for bucket, body in _by_bucket(least, keys[begin], (keys[begin] >> np.uint64(32)).astype(np.uint16), buckets)]
                rows += [(doc % buckets, doc, body) for doc, body in _marks(who[shared], (keys[shared] & np.uint64(0xFFFFFFFF)).astype(np.uint32))]
                yield _round_rows(rows)

    return docs.mapInArrow(run, _ROUND)


def _second_round(matched: DataFrame, window: int, buckets: int) -> DataFrame:
    """Packed windows around marked anchors for each bucket, and marks of windows to remove that a chunk settles itself."""
    size = window - PERIOD + 1

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            own_ids, own_texts, own_marks = (batch.column(c) for c in ("doc_id", "text", "marks"))
            for a, b in W.documents(own_texts, _CHUNK):
                ids = np.asarray(own_ids.slice(a, b - a))
                chunk = _Chunk(own_texts.slice(a, b - a))
                at, keys = chunk.anchors(size)
                if not len(at):
                    continue
                marked = _member(chunk.doc[at], (keys & np.uint64(0xFFFFFFFF)).astype(np.uint32), own_marks.slice(a, b - a), np.uint32)
                touched = np.zeros(len(chunk.doc) + 1, np.int64)
                hit = at[marked]
                np.add.at(touched, np.maximum(hit - (PERIOD - 1), chunk.words.first[chunk.doc[hit]]), 1)
                np.add.at(touched, hit + 1, -1)
                starts = chunk.starts(window)
                starts = starts[np.cumsum(touched)[starts] > 0]
                if not len(starts):
                    continue
                keys, high = W.window_hashes(chunk.hashed, window)[starts], chunk.second_hashes(window)[starts]
                who = ids[chunk.doc[starts]]
                order, begin = _groups((who, high, keys))
                who, keys, high = who[order], keys[order], high[order]
                least = np.repeat(who[begin], np.diff(np.append(begin, len(who))))
                rows = [(bucket, None, body) for bucket, body in _by_bucket(who[begin], keys[begin], high[begin], buckets)]
                rows += [(doc % buckets, doc, body) for doc, body in _marks(who[who > least], high[who > least])]
                yield _round_rows(rows)

    return matched.mapInArrow(run, _ROUND)


def _member(docs: np.ndarray, values: np.ndarray, marks: pa.Array, kind: type) -> np.ndarray:
    """Which values are among the marks of their document (an array of byte strings for each)."""
    lists = [np.concatenate([np.frombuffer(x, kind) for x in m]) if m else np.zeros(0, kind) for m in marks.to_pylist()]
    out = np.zeros(len(values), bool)
    cuts = np.searchsorted(docs, np.arange(len(lists) + 1))
    for i, own in enumerate(lists):
        if len(own) and cuts[i] < cuts[i + 1]:
            out[cuts[i] : cuts[i + 1]] = np.isin(values[cuts[i] : cuts[i + 1]], own)
    return out


def _settle(rounds: DataFrame, all_sharing: bool) -> DataFrame:
    """Marks of both kinds: those that chunks found, and those of entries whose bucket holds another document's.

    With ``all_sharing`` every document of a shared entry is marked, else all but the smallest.
    """

    def run(table: pa.Table) -> pa.Table:
        packed = pc.is_null(table.column("doc_id"))
        found = table.filter(pc.invert(packed)).select(["doc_id", "body"])
        parts = [_unpack(x.as_py()) for x in table.filter(packed).column("body")]
        if not parts:
            return found
        ids, low, high = (np.concatenate([p[i] for p in parts]) for i in range(3))
        order, begin = _groups((ids, high, low))
        ids, high, low = ids[order], high[order], low[order]
        counts = np.diff(np.append(begin, len(ids)))
        least, most = np.repeat(ids[begin], counts), np.repeat(np.append(ids[begin[1:] - 1], ids[-1:]), counts)
        chosen = least != most if all_sharing else ids > least
        rows = list(_marks(ids[chosen], low[chosen] if all_sharing else high[chosen]))
        return pa.concat_tables([found, pa.Table.from_arrays([pa.array([r[0] for r in rows], pa.int64()), pa.array([r[1] for r in rows], pa.binary())], names=["doc_id", "body"])])

    return rounds.groupBy("bucket").applyInArrow(run, "doc_id long, body binary")


# ---- the operator --------------------------------------------------------------------------------


def _kept(texts: pa.Array, marks: pa.Array, window: int) -> tuple[np.ndarray, list[str], np.ndarray]:
    """Words of each text, what is left of it, and how many words went."""
    chunk = _Chunk(texts)
    starts = chunk.starts(window)
    cover = np.zeros(len(chunk.doc) + 1, np.int64)
    if len(starts):
        gone = starts[_member(chunk.doc[starts], chunk.second_hashes(window)[starts], marks, np.uint64)]
        np.add.at(cover, gone, 1)
        np.add.at(cover, gone + window, -1)
    removed = np.cumsum(cover)[:-1] > 0
    data, begins, ends = W.normalised(chunk.words, lower=False)
    raw, first = data.tobytes(), chunk.words.first
    gone_before = np.concatenate(([0], np.cumsum(removed)))
    n_removed = gone_before[first[1:]] - gone_before[first[:-1]]
    left = []
    for i, n in enumerate(n_removed.tolist()):
        a, b = int(first[i]), int(first[i + 1])
        if a == b or n == b - a:
            left.append("")
        elif not n:
            left.append(raw[begins[a] : ends[b - 1]].decode())
        else:
            keep = np.flatnonzero(~removed[a:b]) + a
            runs = np.split(keep, np.flatnonzero(np.diff(keep) > 1) + 1)
            left.append(b" ".join(raw[begins[r[0]] : ends[r[-1]]] for r in runs).decode())
    return chunk.words.counts, left, n_removed


def whole_words(text: Column) -> Column:
    """All words of a text joined by one space."""
    return F.trim(F.regexp_replace(F.coalesce(text, F.lit("")), r"[\x20\x09-\x0D]+", " "))


def removals(docs: DataFrame, window: int = WINDOW) -> DataFrame:
    """``doc_id, text_key, kept_text, n_words, n_removed`` of each text that loses words, once for each doc_id."""
    if window < PERIOD:
        raise ValueError(f"window must be at least {PERIOD}")
    narrow = docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string"))
    # A document that cannot hold a window takes no part.
    eligible = narrow.where(F.col("doc_id").isNotNull() & (F.octet_length("text") >= 2 * window - 1))
    size = eligible.agg(F.sum(F.octet_length("text").cast("long"))).first()[0] or 0
    buckets = max(_LEAST_BUCKETS, -(-size // _BUCKET_BYTES))

    marks = _settle(_first_round(eligible, window, buckets), True).groupBy("doc_id").agg(F.collect_list("body").alias("marks"))
    matched = materialise(eligible.join(marks, "doc_id"), "substring-matched")
    gone = _settle(_second_round(matched, window, buckets), False).groupBy("doc_id").agg(F.collect_list("body").alias("gone"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = batch.column("text")
            for a, b in W.documents(texts, _CHUNK):
                n_words, left, n_removed = _kept(texts.slice(a, b - a), batch.column("gone").slice(a, b - a), window)
                arrays = [batch.column(n).slice(a, b - a) for n in ("doc_id", "text_key")] + [pa.array(left, pa.string()), pa.array(n_words, pa.int64()), pa.array(n_removed, pa.int64())]
                yield pa.RecordBatch.from_arrays(arrays, names=["doc_id", "text_key", "kept_text", "n_words", "n_removed"])

    losing = matched.select("doc_id", "text").join(gone, "doc_id").withColumn("text_key", text_key(F.col("text")))
    cut = losing.mapInArrow(run, "doc_id long, text_key long, kept_text string, n_words long, n_removed long").where("n_removed > 0")
    return cut.dropDuplicates(["doc_id", "text_key"])


def remove_repeats(docs: DataFrame, window: int = WINDOW) -> DataFrame:
    """``docs`` with ``kept_text, n_words, n_removed`` instead of ``text``; every row stays.

    A word goes if it is covered by a window of ``window`` words whose sequence also starts in a
    document with a smaller doc_id.  Kept words are joined by one space.  A null text has no words; a
    row with a null doc_id is before or after no other, so it is kept whole and removes nothing;
    rows with one doc_id are one document to others, each keeps its own text; an empty table gives
    an empty result.  Columns with the names of results are replaced.
    """
    return _joined(docs, whole_words, removals(docs, window), "kept_text", "kept_text")


def cut_repeats(docs: DataFrame, window: int = WINDOW) -> DataFrame:
    """As ``remove_repeats``, but with what is left as ``text``: a text that loses nothing stays as it is, blanks and null too."""
    return _joined(docs, lambda text: text, removals(docs, window), "kept_text", "text")


def repeat_digests(docs: DataFrame, window: int = WINDOW) -> DataFrame:
    """As ``remove_repeats``, with ``kept_sha256`` instead of the text, so that no text is shuffled for it."""
    cut = removals(docs, window).withColumn("kept_sha256", F.sha2("kept_text", 256)).drop("kept_text")
    return _joined(docs, lambda text: F.sha2(whole_words(text), 256), cut, "kept_sha256", "kept_sha256")


def _joined(docs: DataFrame, whole: Callable[[Column], Column], cut: DataFrame, left: str, result: str) -> DataFrame:
    own, text = Packed(docs, {result, "n_words", "n_removed"} - {"text"}, ("doc_id", "text")), F.col("text")
    rows = own.rows.select("row", "doc_id", text_key(text).alias("key"), whole(text).alias("whole"), word_count(text).alias("words"))
    cut = cut.select(F.col("doc_id").alias("cut_doc"), F.col("text_key").alias("cut_key"), F.col(left).alias("left_over"), F.col("n_removed").alias("gone"))
    both = rows.join(cut, (F.col("doc_id") == F.col("cut_doc")) & (F.col("key") == F.col("cut_key")), "left")
    return both.select(*own.back("text"), F.coalesce("left_over", "whole").alias(result), F.col("words").alias("n_words"), F.coalesce("gone", F.lit(0)).cast("long").alias("n_removed"))
