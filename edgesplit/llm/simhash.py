"""SimHash near-duplicates by pivot distance tables.

A fingerprint's table holds its Hamming distances to many reference fingerprints.  No distance may
differ by more than a link's bits, so pairs whose tables differ more in any coordinate are discarded,
and survivors are verified.  Which pairs are looked at follows from references too: those of a group
differ from a zero reference within one group of bits only, so their distances say what a fingerprint's
bits there are.  Fingerprints that differ in few bits agree in most groups; a bucket holds those that
agree in all groups but a choice of as many as a link may change, and no link is lost.  A bucket with too
many members is dealt again, by groups of the bits that its members may differ in, until few are left.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators.components import connected_components
from ..plans.storage import materialise
from . import words as W
from .columns import Packed, text_key

BITS = 64
#: Members of a bucket that are compared pair by pair.
MAX_PAIRED = 48
_CHUNK = 1 << 20


# ---- fingerprints --------------------------------------------------------------------------------


def fingerprints_of(texts: pa.Array, shingle: int) -> np.ndarray:
    """Unsigned 64-bit fingerprints: a bit is set if over half of the text's shingles have it set."""
    hashed, n = shingle_hashes(texts, shingle)
    return _majority(hashed, n)


def shingle_hashes(texts: pa.Array, shingle: int) -> tuple[np.ndarray, np.ndarray]:
    """XXH64 (seed 42) of all shingles of all texts in a row, and how many each text has."""
    import xxhash

    w = W.split(texts)
    data, begins, ends = W.normalised(w, lower=True)
    counts = w.counts
    n = np.where(counts >= shingle, counts - shingle + 1, (counts > 0).astype(np.int64))
    shift = np.repeat(w.first[:-1] - np.concatenate(([0], np.cumsum(n)[:-1])), n) if len(n) else np.zeros(0, np.int64)
    at = np.arange(int(n.sum())) + shift
    last = np.minimum(at + shingle - 1, np.repeat(w.first[1:], n) - 1)
    raw, digest = data.tobytes(), xxhash.xxh64_intdigest
    hashed = np.array([digest(raw[i:j], 42) for i, j in zip(begins[at].tolist(), ends[last].tolist(), strict=True)], dtype=np.uint64)
    return hashed, n


def _majority(hashed: np.ndarray, n: np.ndarray) -> np.ndarray:
    out = np.zeros(len(n), np.uint64)
    full = np.flatnonzero(n)
    if len(full):
        starts = np.concatenate(([0], np.cumsum(n)))[full]
        for bit in range(BITS):
            ones = np.add.reduceat(((hashed >> np.uint64(bit)) & np.uint64(1)).astype(np.int32), starts)
            out[full] |= (2 * ones > n[full]).astype(np.uint64) << np.uint64(bit)
    return out


def fingerprints(docs: DataFrame, shingle: int = 3) -> DataFrame:
    """``doc_id, fp`` for every row (``fp`` as a signed long)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids, texts = batch.column("doc_id"), batch.column("text")
            for a, b in W.documents(texts, _CHUNK):
                found = fingerprints_of(texts.slice(a, b - a), shingle)
                yield pa.RecordBatch.from_arrays([ids.slice(a, b - a), pa.array(found.view(np.int64))], names=["doc_id", "fp"])

    return docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).mapInArrow(run, "doc_id long, fp long")


# ---- pivot tables --------------------------------------------------------------------------------


class Pivots:
    """Reference fingerprints, the buckets that distances to groups of them give, and the far table that discards pairs."""

    def __init__(self, max_bits: int, far: int = 16, seed: int = 11) -> None:
        self.max_bits, self.groups = max_bits, max_bits + 3
        self.far = np.random.default_rng(seed).integers(0, 1 << 64, far, dtype=np.uint64)

    def far_table(self, fps: np.ndarray) -> np.ndarray:
        return np.bitwise_count(fps[:, None] ^ self.far[None, :]).astype(np.int16)

    def freed(self, free: int) -> list[int]:
        """For each choice of groups that may differ: their bits.  ``free`` has the bits that members of a bucket may differ in."""
        bits = [x for x in range(BITS) if free >> x & 1]
        edges = [round(i * len(bits) / self.groups) for i in range(self.groups + 1)]
        masks = [sum(1 << x for x in bits[i:j]) for i, j in zip(edges, edges[1:], strict=False)]
        return sorted({sum(c) for c in combinations(masks, self.max_bits)})

    def group_table(self, fps: np.ndarray, bits: int) -> np.ndarray:
        """Distances to the references of the given bits, one prefix of them each, less that to the zero reference."""
        prefixes = np.bitwise_or.accumulate(np.array([1 << x for x in range(BITS) if bits >> x & 1], np.uint64))
        return np.bitwise_count(fps[:, None] ^ prefixes[None, :]).astype(np.int16) - np.bitwise_count(fps)[:, None].astype(np.int16)

    def keys(self, fps: np.ndarray, free: int) -> Iterator[tuple[int, np.ndarray]]:
        """The bits that each choice frees, and each fingerprint's key: a hash of what its group tables say of all others.

        Neighbours in a group table differ by one, up or down as the bit is: it holds the same as the bits.
        """
        for bits in self.freed(free):
            yield bits, W.mix(W.mix(fps & ~np.uint64(bits)) ^ W.mix(np.full(1, bits, np.uint64) + np.uint64(1)))


def _within(fps: np.ndarray, far: np.ndarray, max_bits: int) -> tuple[np.ndarray, np.ndarray, int]:
    """Pairs of a small bucket: discarded by the largest coordinate difference (how many), then verified."""
    i, j = np.triu_indices(len(fps), 1)
    close = np.abs(far[i] - far[j]).max(axis=1) <= max_bits
    discarded = len(i) - int(close.sum())
    i, j = i[close], j[close]
    same = np.bitwise_count(fps[i] ^ fps[j]) <= max_bits
    return i[same], j[same], discarded


def _spanning(n: int, i: np.ndarray, j: np.ndarray) -> list[tuple[int, int]]:
    """Edges of a forest with the same components."""
    up = list(range(n))

    def root(x: int) -> int:
        while up[x] != x:
            up[x] = up[up[x]]
            x = up[x]
        return x

    out = []
    for a, b in zip(i.tolist(), j.tolist(), strict=True):
        x, y = root(a), root(b)
        if x != y:
            up[max(x, y)] = min(x, y)
            out.append((a, b))
    return out


_LINKS = "a long, b long, free long, pairs long, discarded long, survivors long"


def link_edges(distinct: DataFrame, max_bits: int = 2, max_paired: int = MAX_PAIRED) -> DataFrame:
    """``a, b``: fingerprints that link directly, enough of them to span every component.

    ``distinct`` has one row for each fingerprint ``fp``; ``max_paired`` is 2 to the power of ``max_bits`` at least.
    """
    return compared_buckets(distinct, max_bits, max_paired).where("b is not null").select("a", "b").distinct()


def pivot_counts(distinct: DataFrame, max_bits: int = 2, max_paired: int = MAX_PAIRED) -> DataFrame:
    """``pairs, discarded, survivors``: pairs of members of buckets, those that the far table discarded, and the rest, which were verified."""
    return compared_buckets(distinct, max_bits, max_paired).agg(*[F.coalesce(F.sum(c), F.lit(0)).alias(c) for c in ("pairs", "discarded", "survivors")])


def compared_buckets(distinct: DataFrame, max_bits: int = 2, max_paired: int = MAX_PAIRED) -> DataFrame:
    """Links (``a, b``) and counts (``pairs, discarded, survivors``) of all buckets, each with up to ``max_paired`` members."""
    pivots = Pivots(max_bits)
    if max_paired < 1 << max_bits:
        raise ValueError("max_paired must hold all fingerprints that differ in max_bits given bits")

    def keyed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            fps, free = (np.asarray(batch.column(c)).view(np.uint64) for c in ("fp", "free"))
            for own_free in np.unique(free).tolist():
                own = fps[free == own_free]
                for bits, keys in pivots.keys(own, own_free):
                    freed = np.full(len(own), bits, np.uint64)
                    yield pa.RecordBatch.from_arrays([pa.array(x.view(np.int64)) for x in (keys, own, freed)], names=["key", "fp", "free"])

    def bucketed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        run_key, free, held, large = None, 0, [], False
        counts = np.zeros(3, np.int64)

        def close() -> Iterator[pa.RecordBatch]:
            if not large and len(held) > 1:
                fps = np.array(held, np.int64).view(np.uint64)
                i, j, discarded = _within(fps, pivots.far_table(fps), max_bits)
                pairs = len(fps) * (len(fps) - 1) // 2
                counts[:] += (pairs, discarded, pairs - discarded)
                tree = _spanning(len(fps), i, j)
                if tree:
                    ends = fps.view(np.int64)[np.array(tree)]
                    yield _links(ends[:, 0], ends[:, 1])

        for batch in batches:
            keys, frees, fps = (np.asarray(batch.column(c)) for c in ("key", "free", "fp"))
            cuts = np.flatnonzero(np.diff(keys)) + 1
            for a, b in zip([0, *cuts.tolist()], [*cuts.tolist(), len(keys)], strict=True):
                if a == b:
                    continue
                if keys[a] != run_key:
                    yield from close()
                    run_key, free, held, large = keys[a], frees[a], [], False
                own = fps[a:b]
                if not large and len(held) + len(own) <= max_paired:
                    held += own.tolist()
                    continue
                members = np.concatenate((np.array(held, np.int64), own))
                held, large = [], True
                yield _links(members, None, np.full(len(members), free))
        yield from close()
        yield _links(np.zeros(0, np.int64), None, np.zeros(0, np.int64), counts)

    rows, out = distinct.select("fp", F.lit(-1).cast("long").alias("free")), None
    while True:
        found = rows.mapInArrow(keyed, "key long, fp long, free long").repartition("key").sortWithinPartitions("key", "fp").mapInArrow(bucketed, _LINKS)
        found = materialise(found, "simhash-links")
        told = found.where("b is not null or pairs is not null")
        out = told if out is None else out.union(told)
        rows = found.where("free is not null").select(F.col("a").alias("fp"), "free").distinct()
        if rows.isEmpty():  # freed bits get fewer with every deal: in the end a bucket's members differ in max_bits bits only
            return out


def _links(a: np.ndarray, b: np.ndarray | None, free: np.ndarray | None = None, counts: np.ndarray | None = None) -> pa.RecordBatch:
    """Links, members of a large bucket with its free bits, or one row of counts."""
    n = 1 if counts is not None else len(a)
    column = lambda x: pa.array(x.astype(np.int64)) if x is not None and len(x) == n else pa.nulls(n, pa.int64())
    tallies = [pa.array([int(x)]) for x in counts] if counts is not None else [pa.nulls(n, pa.int64())] * 3
    return pa.RecordBatch.from_arrays([column(a), column(b), column(free), *tallies], names=[c.split()[0] for c in _LINKS.split(", ")])


def near_duplicates(docs: DataFrame, shingle: int = 3, max_bits: int = 2) -> DataFrame:
    """``doc_id, fp, component_id`` for every row of ``docs``.

    Fingerprints link at ``max_bits`` differing bits or fewer; ``component_id`` is the smallest
    doc_id that a row reaches, its own included.  A null text or one without words has fingerprint
    zero and links like any other; rows with equal fingerprints are one class and are never paired;
    repeated rows stay; a null doc_id belongs to its class but never names it; an empty table gives
    an empty result.  Other columns are left out.
    """
    prints = materialise(fingerprints(docs, shingle), "simhash-prints")
    classes = prints.groupBy("fp").agg(F.min("doc_id").alias("least"))
    roots = connected_components(link_edges(classes, max_bits))
    named = classes.join(roots, classes["fp"] == roots["node"], "left").select("fp", "least", F.coalesce("root", "fp").alias("root"))
    heads = named.groupBy("root").agg(F.min("least").alias("component_id"))
    final = named.join(heads, "root").select("fp", "component_id")
    return prints.join(final, "fp").select("doc_id", "fp", "component_id")


# ---- near copies by shingle similarity -----------------------------------------------------------

SHINGLE, SIMILARITY = 5, 0.8
#: Keys of a set, least hashes in a key, and bits (of 128) that two fingerprints may differ in.  Sets of
#: Jaccard similarity 0.8 share no key with a chance of (1 - 0.8^5)^20 = 0.0004, whatever the size of the
#: corpus; their fingerprints differ in 19.4 to 19.9 bits on average, and in more than the reach with a
#: chance of 0.0001.  Majorities of few shingles tie too often for that: smaller sets are never discarded.
TABLES, LEAST_HASHES, REACH, FEW = 20, 5, 36, 16
_GOLDEN = np.uint64(0x9E3779B97F4A7C15)


def _distinct(hashed: np.ndarray, n: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of each text sorted and once each, and how many each text has."""
    who = np.repeat(np.arange(len(n)), n)
    order = np.lexsort((hashed, who))
    hashed, who = hashed[order], who[order]
    new = np.ones(len(hashed), bool)
    new[1:] = (hashed[1:] != hashed[:-1]) | (who[1:] != who[:-1])
    return hashed[new], np.bincount(who[new], minlength=len(n))


def _set_digests(hashed: np.ndarray, n: np.ndarray) -> np.ndarray:
    """One value for each set of distinct hashes, equal for equal sets."""
    sums = np.concatenate((np.zeros(1, np.uint64), np.cumsum(W.mix(hashed ^ _GOLDEN), dtype=np.uint64)))
    ends = np.cumsum(n)
    return W.mix((sums[ends] - sums[ends - n]) ^ (n.astype(np.uint64) * _GOLDEN))


def _set_keys(hashed: np.ndarray, n: np.ndarray, tables: int) -> np.ndarray:
    """Keys of each set: a row of ``tables`` values, each of ``LEAST_HASHES`` least values under hashes of its own."""
    full = np.flatnonzero(n)
    out = np.zeros((len(n), tables), np.uint64)
    if len(full):
        starts = (np.cumsum(n) - n)[full]
        draw = np.random.default_rng(23).integers(0, 1 << 64, (tables, LEAST_HASHES), dtype=np.uint64)
        for t in range(tables):
            key = np.full(len(full), t, np.uint64)
            for salt in draw[t]:
                key = W.mix((key * _GOLDEN) ^ np.minimum.reduceat(W.mix(hashed ^ salt), starts))
            out[full, t] = key
    return out


def _set_prints(docs: DataFrame, shingle: int) -> DataFrame:
    """``doc_id, text_key, node, fp, fp2, few, keys`` of each text and its shingle set: its digest, two fingerprints, if it is under ``FEW``, and its packed keys (null without words)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = batch.column("text")
            for a, b in W.documents(texts, _CHUNK):
                hashed, n = _distinct(*shingle_hashes(texts.slice(a, b - a), shingle))
                values = [_set_digests(hashed, n), _majority(hashed, n), _majority(W.mix(hashed * _GOLDEN), n)]
                keys = pa.array([k.tobytes() if m else None for k, m in zip(_set_keys(hashed, n, TABLES), n.tolist(), strict=True)], pa.binary())
                own = [batch.column(c).slice(a, b - a) for c in ("doc_id", "text_key")]
                yield pa.RecordBatch.from_arrays([*own, *(pa.array(x.view(np.int64)) for x in values), pa.array(n < FEW), keys], names=["doc_id", "text_key", "node", "fp", "fp2", "few", "keys"])

    return docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string"), text_key(F.col("text")).alias("text_key")).mapInArrow(run, "doc_id long, text_key long, node long, fp long, fp2 long, few boolean, keys binary")


def _bits_apart(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    return np.bitwise_count(a[:, 0] ^ b[:, 0]).astype(np.int16) + np.bitwise_count(a[:, 1] ^ b[:, 1])


def candidate_pairs(classes: DataFrame, reach: int = REACH) -> tuple[DataFrame, DataFrame]:
    """``a, b``: classes that share a key and whose two fingerprints differ in ``reach`` bits together or fewer, unless
    one is of a set under ``FEW``; and ``key, node``: the members of large buckets.

    Buckets of up to ``_WHOLE`` classes are compared whole.  In a larger one a centre, the class nearest
    to the bucket's majority, meets all within reach of it, then the rest chooses a centre of its own.
    That joins most of the bucket cheaply; ``links_between`` compares what it leaves apart.
    """
    far = np.random.default_rng(29).integers(0, 1 << 64, 8, dtype=np.uint64)

    def keyed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, 4096):
                part = batch.slice(at, 4096)
                keys = np.frombuffer(b"".join(part.column("keys").to_pylist()), np.int64).reshape(part.num_rows, -1)
                for t in range(keys.shape[1]):
                    yield pa.RecordBatch.from_arrays([pa.array(keys[:, t]), part.column("node"), part.column("fp"), part.column("fp2"), part.column("few")], names=["key", "node", "fp", "fp2", "few"])

    def met(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[str, np.ndarray] | None = None
        large_key = None
        for batch in batches:
            own = {c: batch.column(c).to_numpy(zero_copy_only=False) for c in ("key", "node", "fp", "fp2", "few")}
            if not batch.num_rows:
                continue
            if held is not None:
                own = {c: np.concatenate((held[c], own[c])) for c in own}
            sizes = np.unique(own["key"], return_inverse=True, return_counts=True)
            # Standing rows of a large bucket were told already; telling them again does no harm.
            large = (sizes[2] > _WHOLE)[sizes[1]] | (own["key"] == large_key if large_key is not None else False)
            large_key = own["key"][-1] if large[-1] else None
            yield _found(own["node"][large], None, own["key"][large])
            pairs, open_rows = _meet(own)
            x, y = own["node"][pairs[0]], own["node"][pairs[1]]
            found = np.unique(np.stack((np.minimum(x, y), np.maximum(x, y)), axis=1)[x != y], axis=0)
            yield _found(found[:, 0], found[:, 1], None)
            held = {c: own[c][open_rows] for c in own}

    def _meet(own: dict[str, np.ndarray]) -> tuple[tuple[np.ndarray, np.ndarray], np.ndarray]:
        """Pairs of rows within reach, and the rows of the last bucket that stand for it if it goes on."""
        key, n = own["key"], len(own["key"])
        if not n:
            return (np.zeros(0, np.int64), np.zeros(0, np.int64)), np.zeros(0, np.int64)
        begin = np.flatnonzero(np.diff(key, prepend=key[:1] - 1))
        sizes = np.diff(np.append(begin, n))
        small = np.repeat(sizes <= _WHOLE, sizes)
        left, right = [], []
        for k in range(1, min(_WHOLE, n)):
            i = np.flatnonzero((key[:-k] == key[k:]) & small[:-k])
            left.append(i)
            right.append(i + k)
        prints = np.stack((own["fp"].view(np.uint64), own["fp2"].view(np.uint64)), axis=1)
        standing = np.arange(begin[-1], n) if sizes[-1] <= _WHOLE else begin[-1:]
        for at, size in zip(begin[sizes > _WHOLE].tolist(), sizes[sizes > _WHOLE].tolist(), strict=True):
            i, j, centres = _stars(prints, np.arange(at, at + size), reach)
            left.append(i)
            right.append(j)
            if at == begin[-1]:
                standing = centres[:_WHOLE]
        a, b = (np.concatenate(x) if x else np.zeros(0, np.int64) for x in (left, right))
        table = np.bitwise_count(prints[:, 0][:, None] ^ far[None, :]).astype(np.int16)
        few = own["few"][a] | own["few"][b]
        close = (np.abs(table[a] - table[b]).max(axis=1, initial=0) <= reach) | few
        a, b, few = a[close], b[close], few[close]
        near = (_bits_apart(prints[a], prints[b]) <= reach) | few
        return (a[near], b[near]), standing

    parts = int(classes.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    rows = classes.where("keys is not null").select("node", "fp", "fp2", "few", "keys").mapInArrow(keyed, "key long, node long, fp long, fp2 long, few boolean")
    rows = rows.repartition(parts, "key").sortWithinPartitions("key", "fp", "fp2", "node").mapInArrow(met, "a long, b long, key long")
    found = materialise(rows, "near-met")
    return found.where("b is not null").select("a", "b").distinct(), found.where("b is null").select("key", F.col("a").alias("node")).distinct()


def _found(a: np.ndarray, b: np.ndarray | None, key: np.ndarray | None) -> pa.RecordBatch:
    rest = [pa.nulls(len(a), pa.int64()) if x is None else pa.array(x) for x in (b, key)]
    return pa.RecordBatch.from_arrays([pa.array(a), *rest], names=["a", "b", "key"])


#: Buckets up to this size are compared whole; classes in a block of a larger one.
_WHOLE, _BLOCK = 16, 256


def _stars(prints: np.ndarray, rows: np.ndarray, reach: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Pairs of a large bucket's rows with centres that cover it, and the centres."""
    left, right, centres = [], [], []
    while len(rows) > _WHOLE:
        bits = np.unpackbits(prints[rows].view(np.uint8), axis=1)
        majority = np.packbits(2 * bits.sum(axis=0) > len(rows)).view(np.uint64)
        centre = rows[np.argmin(_bits_apart(prints[rows], majority[None, :]))]
        inside = _bits_apart(prints[rows], prints[centre][None, :]) <= reach
        left.append(rows[inside])
        right.append(np.full(int(inside.sum()), centre))
        centres.append(centre)
        rows = rows[~inside]
    i, j = np.triu_indices(len(rows), 1)
    return np.concatenate((*left, rows[i])), np.concatenate((*right, rows[j])), np.array(centres, np.int64)


def _apart(members: DataFrame, roots: DataFrame) -> DataFrame:
    """``key, node, root, other``: members of buckets with several components; ``other`` marks those outside the bucket's largest."""
    rooted = members.join(roots, "node", "left").select("key", "node", F.coalesce("root", "node").alias("root"))
    rooted = materialise(rooted, "near-rooted")
    per = rooted.groupBy("key", "root").count()
    main = per.groupBy("key").agg(F.count("*").alias("roots"), F.max_by("root", F.struct("count", "root")).alias("main")).where("roots > 1")
    # Buckets with the same members are compared once.
    same = rooted.groupBy("key").agg(F.sum(F.xxhash64("node").cast("decimal(38,0)")).alias("s"), F.sum(F.xxhash64("node", F.lit(1)).cast("decimal(38,0)")).alias("t"), F.count("*").alias("n"))
    chosen = same.join(main, "key").groupBy("s", "t", "n").agg(F.min_by(F.struct("key", "main"), "key").alias("own")).select("own.*")
    return materialise(rooted.join(chosen, "key").select("key", "node", "root", (F.col("root") != F.col("main")).alias("other")), "near-apart")


def links_between(apart: DataFrame, bodies: DataFrame, similarity: float) -> DataFrame:
    """``a, b``: links between different components of a bucket, enough to join what links; every such pair is compared.

    The members outside a bucket's largest component meet all its members block against block, on whole sets.
    """
    sizes = apart.groupBy("key").agg(F.ceil(F.count("*") / _BLOCK).cast("int").alias("blocks"), F.ceil(F.sum(F.col("other").cast("int")) / _BLOCK).cast("int").alias("others"))
    # Both are tables when they are joined, so that rows of a large bucket are not gathered for it and are dealt by blocks after.
    sizes = materialise(sizes, "near-sizes")
    block = lambda n, salt: F.pmod(F.xxhash64("node", F.lit(salt)), F.col(n)).cast("int")
    dealt = materialise(apart.join(sizes, "key"), "near-dealt")
    left = dealt.where("other").select("key", "node", "root", block("others", 5).alias("x"), F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)).alias("y"), F.lit(0).alias("side"))
    right = dealt.select("key", "node", "root", F.explode(F.sequence(F.lit(0), F.col("others") - 1)).alias("x"), block("blocks", 7).alias("y"), F.lit(1).alias("side"))

    def compare(table: pa.Table) -> pa.Table:
        side, node, root = (table.column(c).to_numpy() for c in ("side", "node", "root"))
        sets = [np.frombuffer(x, np.uint32) for x in table.column("body").to_pylist()]
        rows, columns = np.flatnonzero(side == 0), np.flatnonzero(side == 1)
        i, j = _similar(sets, rows, columns, similarity)
        a, b = rows[i], columns[j]
        apart = root[a] != root[b]
        a, b = a[apart], b[apart]
        named, at = np.unique(root, return_inverse=True)
        first = {}
        for x, y in zip(a.tolist(), b.tolist(), strict=True):
            first.setdefault((int(at[x]), int(at[y])), (x, y))
        keys = list(first)
        tree = _spanning(len(named), np.array([k[0] for k in keys], np.int64), np.array([k[1] for k in keys], np.int64))
        ends = [first[k] for k in tree]
        return pa.Table.from_arrays([pa.array([int(node[e[k]]) for e in ends], pa.int64()) for k in (0, 1)], names=["a", "b"])

    return left.union(right).join(bodies, "node").groupBy("key", "x", "y").applyInArrow(compare, "a long, b long").distinct()


def _similar(sets: list[np.ndarray], rows: np.ndarray, columns: np.ndarray, similarity: float) -> tuple[np.ndarray, np.ndarray]:
    """Positions in ``rows`` and ``columns`` of all pairs of sets with at least this Jaccard similarity."""
    lengths = np.array([len(x) for x in sets], np.int64)
    shared = np.zeros((len(rows), len(columns)), np.float32)
    if not shared.size or not lengths.sum():
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    values, at = np.unique(np.concatenate(sets), return_inverse=True)
    order = np.argsort(at, kind="stable")
    who, at = np.repeat(np.arange(len(sets)), lengths)[order], at[order]
    for low in range(0, len(values), 4096):
        own = slice(*np.searchsorted(at, (low, low + 4096)))
        holds = np.zeros((len(sets), min(4096, len(values) - low)), np.float32)
        holds[who[own], at[own] - low] = 1
        shared += holds[rows] @ holds[columns].T
    total = lengths[rows][:, None] + lengths[columns][None, :]
    return np.nonzero((shared > 0) & (shared >= similarity * (total - shared)))


def similar_documents(docs: DataFrame, shingle: int = SHINGLE, similarity: float = SIMILARITY) -> DataFrame:
    """``doc_id, text_key, root, component_id`` for every row: documents whose shingle sets have at least this Jaccard similarity link.

    Candidates share a key of their shingle sets and have fingerprints within reach; links are verified
    on whole sets.  Rows with equal sets are one class.  Texts that are null or without words are one
    class; a null doc_id never names a component, but its text links as any other; repeated rows stay; an empty table gives an empty result.
    ``root`` tells components apart, with a doc_id or without; ``text_key`` tells rows of one doc_id apart.
    """
    prints = materialise(_set_prints(docs, shingle), "near-prints")
    firsts = F.min_by(F.struct("fp", "fp2", "few", "keys"), F.struct("fp", "fp2")).alias("own")
    classes = materialise(prints.groupBy("node").agg(F.min("doc_id").alias("least"), F.min("text_key").alias("text_key"), firsts).select("node", "least", "text_key", "own.*"), "near-classes")
    pairs, members = candidate_pairs(classes)
    pairs = materialise(pairs, "near-candidates")

    # One text stands for a class; only classes in a candidate pair or a large bucket have their sets made.
    involved = pairs.select(F.explode(F.array("a", "b")).alias("node")).union(members.select("node")).distinct()
    heads = classes.join(involved, "node").select("node", F.col("least").alias("doc_id"), "text_key")

    def sets(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = batch.column("text")
            for a, b in W.documents(texts, _CHUNK):
                hashed, n = _distinct(*shingle_hashes(texts.slice(a, b - a), shingle))
                bounds = np.concatenate(([0], np.cumsum(n)))
                bodies = [np.unique(hashed[i:j].astype(np.uint32)).tobytes() for i, j in zip(bounds[:-1].tolist(), bounds[1:].tolist(), strict=True)]
                nodes = batch.column("node").slice(a, b - a)
                # Another text of the same doc_id is not the one that stands for the class.
                own = np.asarray(nodes) == _set_digests(hashed, n).view(np.int64)
                yield pa.RecordBatch.from_arrays([nodes, pa.array(bodies, pa.binary())], names=["node", "body"]).filter(pa.array(own))

    texts = docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string"))
    chosen = texts.join(heads.where("doc_id is not null").select("node", "doc_id"), "doc_id").select("node", "text")
    # A class in which no row has a doc_id is found by its text.
    unnamed = texts.where("doc_id is null").select("text", text_key(F.col("text")).alias("text_key"))
    unnamed = unnamed.join(heads.where("doc_id is null").select("node", "text_key"), "text_key").dropDuplicates(["node"])
    chosen = chosen.union(unnamed.select("node", "text"))
    bodies = materialise(chosen.mapInArrow(sets, "node long, body binary").dropDuplicates(["node"]), "near-sets")

    def verify(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            good = []
            for x, y in zip(batch.column("x").to_pylist(), batch.column("y").to_pylist(), strict=True):
                one, two = np.frombuffer(x, np.uint32), np.frombuffer(y, np.uint32)
                low, high = sorted((len(one), len(two)))
                both = len(np.intersect1d(one, two, assume_unique=True)) if low >= similarity * high else 0
                good.append(bool(both) and both >= similarity * (low + high - both))
            yield batch.select(["a", "b"]).filter(pa.array(good, pa.bool_()))

    left = bodies.select(F.col("node").alias("a"), F.col("body").alias("x"))
    right = bodies.select(F.col("node").alias("b"), F.col("body").alias("y"))
    links = pairs.join(left, "a").join(right, "b").select("a", "b", "x", "y").mapInArrow(verify, "a long, b long")
    links = materialise(links, "near-links")
    roots = connected_components(links)
    apart = _apart(members, roots)
    if not apart.isEmpty():
        roots = connected_components(links.union(links_between(apart, bodies, similarity)))
    named = classes.join(roots, "node", "left").select("node", "least", F.coalesce("root", "node").alias("root"))
    least = named.groupBy("root").agg(F.min("least").alias("component_id"))
    final = named.join(least, "root").select("node", "root", "component_id")
    return prints.join(final, "node").select("doc_id", "text_key", "root", "component_id")


def keep_one(docs: DataFrame, components: DataFrame) -> DataFrame:
    """One row of ``docs`` for each component: that of the smallest doc_id (of several with it, of the smallest text key).

    A row without a doc_id stays only for a component in which none has one.  Rows that share a doc_id
    but not their text belong to the components of their texts.
    """
    first = F.min(F.struct(F.col("doc_id").isNull().alias("unnamed"), "doc_id", "text_key")).alias("first")
    heads = components.groupBy("root").agg(first).select(F.col("first.doc_id").alias("head"), F.col("first.text_key").alias("head_key"))
    own = Packed(docs, apart=("doc_id",), extra=[text_key(F.col("text")).alias("text_key")])
    kept = own.rows.join(heads, (F.col("text_key") == F.col("head_key")) & F.col("doc_id").cast("long").eqNullSafe(F.col("head")), "left_semi")
    return kept.dropDuplicates(["doc_id", "text_key"]).select(*own.back())
