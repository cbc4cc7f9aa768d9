"""Embedding near-dedup by sorted projection passes.

A pass gives every vector a key, the concatenated signs of random projections, sorts each label's
vectors by it, and compares each with the next few.  Links of all passes are united.  Vectors are
centred on their label's mean first, and how many passes a label takes follows from how far its
vectors lie from that mean: where they share a direction, signs through the origin would not tell them
apart.  Passes ship 16-bit sketches with a proven error, which settle nearly all pairs; the rest are
verified on the vectors themselves.  Vectors that agree on the leading signs that a pass counts on, in
longer runs than the window, are compared block against block.  How many others a vector links with
is then counted inside its component: a component in which every vector is within half the allowed
angle of its first one is complete, and any other is counted block against block.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators.components import connected_components
from ..plans.storage import materialise
from .simhash import _spanning
from .vectors import matrix, usable

THRESHOLD = 0.93
#: Places that two compared neighbours may be apart, and how many vectors an even run of leading signs holds.
WINDOW, RUN = 256, 64
BITS = 63
BLOCK = 512
#: Chance that a pair at the threshold is missed; passes at least and at most.  A label that would need more passes
#: counts on fewer leading signs, and its runs, longer then, are compared block against block.
MISS, LEAST_PASSES, MOST_PASSES = 0.01, 6, 48
_RUN_KEY = ["pass", "label", "size", "run"]
_KEYS = "pass int, label long, size int, run long, key long, node long, sketch binary"
_PAIRS = "a long, b long, sure boolean"


def plan_label(rows: int, spread: float, threshold: float = THRESHOLD) -> tuple[int, int]:
    """Passes of a label, and the leading signs that a pair must share in one of them to be compared.

    ``spread`` is the mean squared distance of its unit vectors from their mean (1: spread evenly).  A
    pair at the threshold, seen from the mean, then agrees in a sign with a chance of 1 - angle / pi.
    """
    agree = 1 - math.acos(max(-1.0, 1 - (1 - threshold) / max(spread, 1e-9))) / math.pi
    wanted = max(0, math.ceil(math.log2(max(1, rows) / RUN)))
    bearable = math.floor(math.log(1 - MISS ** (1 / MOST_PASSES)) / math.log(agree)) if 0 < agree < 1 else 0
    leading = min(wanted, bearable, BITS)
    if not leading:
        return 1, 0
    return min(MOST_PASSES, max(LEAST_PASSES, math.ceil(math.log(MISS) / math.log(1 - agree**leading)))), leading


# ---- sketches ------------------------------------------------------------------------------------


def sketches(unit: np.ndarray) -> list[bytes]:
    """Each unit vector as 16-bit integers behind their scale and the distance of what they stand for."""
    scale = np.maximum(np.abs(unit).max(axis=1, keepdims=True), 1e-300) / 32767
    rounded = np.rint(unit / scale).astype(np.int16)
    error = np.sqrt(((unit - rounded * scale) ** 2).sum(axis=1))
    head = np.stack((scale[:, 0], error), axis=1)
    return [h.tobytes() + r.tobytes() for h, r in zip(head, rounded, strict=True)]


def read_sketches(column: pa.Array | pa.ChunkedArray) -> tuple[np.ndarray, np.ndarray]:
    """Vectors of one length that sketches stand for, and a bound on how far the true ones are."""
    raw = column.to_pylist()
    head = np.array([np.frombuffer(x, np.float64, 2) for x in raw])
    return np.array([np.frombuffer(x, np.int16, offset=16) for x in raw]) * head[:, :1], head[:, 1] + 1e-9


def _sorted_pairs(unit: np.ndarray, error: np.ndarray, old: int, threshold: float, window: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Pairs of places at most ``window`` apart, the later one from ``old`` on, that may link; and whether they surely do."""
    left, right, sure = [], [], []
    for at in range(old, len(unit), window):
        low, high = max(0, at - window), min(len(unit), at + window)
        cosine = unit[low:high] @ unit[at:high].T
        i, j = np.nonzero(cosine + error[low:high, None] + error[None, at:high] * (1 + error.max()) >= threshold)
        apart = (at + j) - (low + i)
        near = (apart > 0) & (apart <= window)
        i, j = i[near], j[near]
        left.append(low + i)
        right.append(at + j)
        sure.append(cosine[i, j] - error[low + i] - error[at + j] * (1 + error.max()) >= threshold)
    empty = np.zeros(0, np.int64)
    return (np.concatenate(left), np.concatenate(right), np.concatenate(sure)) if left else (empty, empty, np.zeros(0, bool))


def _told(node: np.ndarray, i: np.ndarray, j: np.ndarray, sure: np.ndarray) -> pa.RecordBatch:
    """Sure pairs enough to span what they join, and the unsure ones between what these leave apart."""
    tree = np.array(_spanning(len(node), i[sure], j[sure]), np.int64).reshape(-1, 2)
    up = np.arange(len(node))
    for a, b in tree.tolist():
        x, y = up[a], up[b]
        up[up == max(x, y)] = min(x, y)
    i, j = i[~sure], j[~sure]
    open_ones = up[i] != up[j]
    a, b = np.concatenate((tree[:, 0], i[open_ones])), np.concatenate((tree[:, 1], j[open_ones]))
    return pa.RecordBatch.from_arrays([pa.array(node[a]), pa.array(node[b]), pa.array(np.arange(len(a)) < len(tree))], names=["a", "b", "sure"])


# ---- the operator --------------------------------------------------------------------------------


def near_duplicate_vectors(rows: DataFrame, threshold: float = THRESHOLD, window: int = WINDOW) -> DataFrame:
    """``vec_id, n_links, component_id, kept`` for every row of ``rows`` (vec_id, embedding, label).

    Rows link if their labels are equal and not null and their cosine is at least ``threshold``.  A
    vector that is null, empty, zero or holds null or non-finite components links with nothing, nor
    do vectors of different lengths.  Equal vectors of one label are one class: they link with each
    other and are never paired.  A repeated row is a vector of its own; a null vec_id is counted as a
    link but never names a component; an empty table gives an empty result.  Other columns are left
    out.
    """
    base = rows.select(F.col("vec_id").cast("long"), F.col("embedding").cast("array<double>").alias("embedding"), F.col("label").cast("long"))
    takes_part = F.col("label").isNotNull() & usable(F.col("embedding"))
    digest = F.concat(*[F.lpad(F.hex(F.xxhash64(F.lit(i), "label", "embedding")), 16, "0") for i in (0, 1)])
    keyed = materialise(base.withColumn("class", F.when(takes_part, digest)), "vectors")
    classes = keyed.where("class is not null").groupBy("class").agg(F.min("vec_id").alias("least"), F.count("*").alias("n"), F.first("label").alias("label"), F.first("embedding").alias("embedding"))
    # A class's node is a hash of its content: it stays the same whichever task computes it.
    classes = materialise(classes.withColumns({"node": F.xxhash64("class"), "size": F.size("embedding")}), "vector-classes")
    keys = materialise(_keys(classes, threshold), "vector-keys")
    # Runs longer than a window: most of them are dense groups, others come about by chance.
    long_runs = materialise(keys.groupBy(*_RUN_KEY).count().where(F.col("count") > window + 1).select(*_RUN_KEY), "vector-long")
    found = materialise(_window_pairs(keys, long_runs, threshold, window), "vector-pairs")
    roots = connected_components(found.where("sure"))
    apart = _apart(keys, long_runs, roots)
    if not apart.isEmpty():
        found = found.union(materialise(_between(apart, threshold), "vector-between"))
    roots = _joined(roots, found, classes, threshold)
    members = classes.join(roots, classes["node"] == roots["node"], "left").select(classes["node"], "class", "least", "n", "embedding", F.coalesce("root", classes["node"]).alias("root"))
    members = materialise(members, "vector-members")
    counted = _counts(members, threshold)
    heads = members.groupBy("root").agg(F.min("least").alias("component_id"))
    facts = members.select("class", "node", "root").join(counted, "node").join(heads, "root").select("class", "n_links", "component_id")
    out = keyed.select("vec_id", "class").join(facts, "class", "left")
    component = F.coalesce("component_id", "vec_id")
    return out.select("vec_id", F.coalesce("n_links", F.lit(0)).cast("long").alias("n_links"), component.alias("component_id"), F.coalesce(F.col("vec_id") == component, F.lit(False)).alias("kept"))


def _label_facts(classes: DataFrame, threshold: float) -> DataFrame:
    """``label, size, mean, passes, leading`` for each label and length of vectors; summed before they are shuffled."""

    def partial(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[tuple[int, int], tuple[int, np.ndarray]] = {}

        def told() -> pa.RecordBatch:
            keys = list(held)
            arrays = [pa.array([k[0] for k in keys], pa.int64()), pa.array([k[1] for k in keys], pa.int32()), pa.array([held[k][0] for k in keys], pa.int64()), pa.array([held[k][1] for k in keys], pa.list_(pa.float64()))]
            return pa.RecordBatch.from_arrays(arrays, names=["label", "size", "n", "sums"])

        for batch in batches:
            labels, sizes = np.asarray(batch.column("label")), np.asarray(batch.column("size"))
            for size in np.unique(sizes).tolist():
                own = sizes == size
                unit, which = _unit(matrix(batch.column("embedding").filter(pa.array(own)))), labels[own]
                for label in np.unique(which).tolist():
                    n, total = held.get((label, size), (0, 0.0))
                    part = unit[which == label]
                    held[label, size] = n + len(part), total + part.sum(axis=0)
            if len(held) > 4096:
                yield told()
                held = {}
        yield told()

    sums = classes.select("label", "size", "embedding").mapInArrow(partial, "label long, size int, n long, sums array<double>")
    per_place = sums.select("label", "size", "n", F.posexplode("sums").alias("i", "x")).groupBy("label", "size", "i").agg(F.sum("n").alias("n"), F.sum("x").alias("x"))
    per = per_place.groupBy("label", "size").agg(F.max("n").alias("n"), F.array_sort(F.collect_list(F.struct("i", (F.col("x") / F.col("n")).alias("x")))).alias("mean"))

    def plan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            means = [np.array(x, np.float32).astype(float) for x in batch.column("mean").to_pylist()]
            plans = [plan_label(n, 1 - float(m @ m), threshold) for n, m in zip(batch.column("n").to_pylist(), means, strict=True)]
            yield pa.RecordBatch.from_arrays(
                [batch.column("label"), batch.column("size"), pa.array([m.tolist() for m in means], pa.list_(pa.float64())), *(pa.array([p[k] for p in plans], pa.int32()) for k in (0, 1))],
                names=["label", "size", "mean", "passes", "leading"],
            )

    return per.select("label", "size", "n", F.transform("mean", lambda x: x["x"]).alias("mean")).mapInArrow(plan, "label long, size int, mean array<double>, passes int, leading int")


def _planes(dimension: int) -> np.ndarray:
    return np.random.default_rng([31, dimension]).normal(size=(MOST_PASSES, dimension, BITS))


def _keys(classes: DataFrame, threshold: float) -> DataFrame:
    """A row for each class and pass of its label: its signs, the run of leading ones, its sketch."""
    facts = materialise(_label_facts(classes, threshold), "vector-labels")

    def keyed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        planes: dict[int, np.ndarray] = {}
        powers = np.int64(1) << np.arange(BITS - 1, -1, -1, dtype=np.int64)
        for batch in batches:
            sizes = np.asarray(batch.column("size"))
            for size in np.unique(sizes).tolist():
                whole = batch.filter(pa.array(sizes == size))
                if size not in planes:
                    planes = {size: _planes(size)}
                for at in range(0, whole.num_rows, 2048):
                    part = whole.slice(at, 2048)
                    unit = _unit(matrix(part.column("embedding")))
                    centred, passes, leading = unit - matrix(part.column("mean")), np.asarray(part.column("passes")), np.asarray(part.column("leading"))
                    sketch = pa.array(sketches(unit), pa.binary())
                    for p in range(int(passes.max())):
                        own = np.flatnonzero(passes > p)
                        key = ((centred[own] @ planes[size][p]) > 0).astype(np.int64) @ powers
                        take = pa.array(own)
                        yield pa.RecordBatch.from_arrays(
                            [pa.array(np.full(len(own), p, np.int32)), part.column("label").take(take), part.column("size").take(take), pa.array(key >> (BITS - leading[own])), pa.array(key), part.column("node").take(take), sketch.take(take)],
                            names=["pass", "label", "size", "run", "key", "node", "sketch"],
                        )

    return classes.select("label", "size", "node", "embedding").join(facts, ["label", "size"]).mapInArrow(keyed, _KEYS)


def _window_pairs(keys: DataFrame, long_runs: DataFrame, threshold: float, window: int) -> DataFrame:
    """Pairs of neighbours of a pass, in one run of leading signs."""

    def compared(rows: pa.Table | pa.RecordBatch, old: int) -> pa.RecordBatch:
        unit, error = read_sketches(rows.column("sketch"))
        node = rows.column("node").to_numpy()
        return _told(node, *_sorted_pairs(unit, error, old, threshold, window))

    def in_order(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: pa.Table | None = None
        current: tuple | None = None
        first: tuple | None = None
        head: list[pa.Table] = []
        for batch in batches:
            facts = np.stack([np.asarray(batch.column(c)).astype(np.int64) for c in _RUN_KEY], axis=1)
            cuts = np.flatnonzero((facts[1:] != facts[:-1]).any(axis=1)) + 1
            for a, b in zip([0, *cuts.tolist()], [*cuts.tolist(), len(facts)], strict=True):
                for at in range(a, b, 8 * window):
                    part = pa.Table.from_batches([batch.slice(at, min(8 * window, b - at))])
                    run = tuple(facts[at].tolist())
                    first = first or run
                    held = held if run == current else None
                    if run == first and sum(map(len, head)) < window:
                        head.append(part.slice(0, window - sum(map(len, head))))
                    old = held.num_rows if held is not None else 0
                    part = pa.concat_tables([held, part]) if held is not None else part
                    if part.num_rows > 1:
                        yield _pair_rows(compared(part, old))
                    held, current = part.slice(max(0, part.num_rows - window)), run
        # Runs may go on in another partition: both ends of this one meet what borders on them once more.
        here = TaskContext.get().partitionId()
        for end, border in ((pa.concat_tables(head) if head else None, here), (held, here + 1)):
            for batch in end.combine_chunks().to_batches() if end is not None else ():
                yield batch.append_column("border", pa.array(np.full(batch.num_rows, border, np.int32)))

    def _pair_rows(pairs: pa.RecordBatch) -> pa.RecordBatch:
        n = pairs.num_rows
        nulls = {"pass": pa.int32(), "label": pa.int64(), "size": pa.int32(), "run": pa.int64(), "key": pa.int64(), "node": pa.int64(), "sketch": pa.binary()}
        return pa.RecordBatch.from_arrays([pa.nulls(n, t) for t in nulls.values()] + [pa.nulls(n, pa.int32()), *pairs.columns], names=[*nulls, "border", "a", "b", "sure"])

    def told(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for out in in_order(batches):
            if "a" not in out.schema.names:
                n = out.num_rows
                out = pa.RecordBatch.from_arrays([*out.columns, pa.nulls(n, pa.int64()), pa.nulls(n, pa.int64()), pa.nulls(n, pa.bool_())], names=[*out.schema.names, "a", "b", "sure"])
            yield out

    order = ["pass", "label", "size", "key", "node"]
    parts = max(1, int(keys.sparkSession.conf.get("spark.sql.shuffle.partitions")))
    ordered = keys.repartitionByRange(parts, *order).sortWithinPartitions(*order)
    found = materialise(ordered.mapInArrow(told, f"{_KEYS}, border int, {_PAIRS}"), "vector-windows")

    def across(rows: pa.Table) -> pa.Table:
        rows = rows.sort_by([("key", "ascending"), ("node", "ascending")])
        node = rows.column("node").to_numpy()
        rows = rows.filter(pa.array(np.append(True, node[1:] != node[:-1])))
        return pa.Table.from_batches([compared(rows, 0)])

    # A run of at most a window's rows meets as a whole, a longer one border by border: two windows of rows at most.
    # (Where it crosses a partition shorter than a window, the comparison of long runs block by block has the rest.)
    ends = found.where("a is null").select(*_RUN_KEY, "key", "node", "sketch", "border")
    marked = ends.join(long_runs.withColumn("long", F.lit(True)), _RUN_KEY, "left").withColumn("border", F.when(F.col("long"), F.col("border")).otherwise(-1))
    cut = materialise(marked, "vector-ends").groupBy(*_RUN_KEY, "border").applyInArrow(across, _PAIRS)
    return found.where("a is not null").select("a", "b", "sure").union(cut).groupBy("a", "b").agg(F.max("sure").alias("sure"))


def _apart(keys: DataFrame, long_runs: DataFrame, roots: DataFrame) -> DataFrame:
    """``pass, label, size, run, node, root, other, sketch, blocks, others``: members of long runs with several components.

    ``other`` marks those outside the run's largest component; ``blocks`` and ``others`` are how many blocks all and
    those are dealt to.
    """
    rows = keys.select(*_RUN_KEY, "node", "sketch").join(long_runs, _RUN_KEY, "left_semi")
    rooted = materialise(rows.join(roots, "node", "left").select(*_RUN_KEY, "node", F.coalesce("root", "node").alias("root"), "sketch"), "vector-runs")
    per = rooted.groupBy(*_RUN_KEY, "root").count()
    blocks = lambda n: F.ceil(n / BLOCK).cast("int")
    runs = per.groupBy(*_RUN_KEY).agg(F.count("*").alias("roots"), F.sum("count").alias("n"), F.max("count").alias("largest"), F.max_by("root", F.struct("count", "root")).alias("main"))
    runs = runs.where("roots > 1").select(*_RUN_KEY, "main", blocks(F.col("n")).alias("blocks"), blocks(F.col("n") - F.col("largest")).alias("others"))
    marked = rooted.join(materialise(runs, "vector-run-facts"), _RUN_KEY).select(*_RUN_KEY, "node", "root", (F.col("root") != F.col("main")).alias("other"), "sketch", "blocks", "others")
    return materialise(marked, "vector-apart")


def _between(apart: DataFrame, threshold: float) -> DataFrame:
    """Pairs of different components of a run, enough to join what links; every such pair of vectors is compared."""
    block = lambda n, salt: F.pmod(F.xxhash64("node", F.lit(salt)), F.col(n)).cast("int")
    kept = [*_RUN_KEY, "node", "root", "sketch"]
    left = apart.where("other").select(*kept, block("others", 5).alias("x"), F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)).alias("y"), F.lit(0).alias("side"))
    right = apart.select(*kept, F.explode(F.sequence(F.lit(0), F.col("others") - 1)).alias("x"), block("blocks", 7).alias("y"), F.lit(1).alias("side"))

    def compare(table: pa.Table) -> pa.Table:
        side, node, root = (table.column(c).to_numpy() for c in ("side", "node", "root"))
        unit, error = read_sketches(table.column("sketch"))
        rows, columns = np.flatnonzero(side == 0), np.flatnonzero(side == 1)
        cosine, bound = unit[rows] @ unit[columns].T, error[rows][:, None] + error[columns][None, :] * (1 + error.max())
        differ = root[rows][:, None] != root[columns][None, :]
        named, at = np.unique(root, return_inverse=True)
        i, j = np.nonzero((cosine - bound >= threshold) & differ)
        # One pair of vectors for each pair of components.
        joined, first = np.unique(at[rows[i]] * np.int64(len(named)) + at[columns[j]], return_index=True)
        tree = set(_spanning(len(named), joined // len(named), joined % len(named)))
        chosen = np.array([k for k, pair in zip(first.tolist(), joined.tolist(), strict=True) if divmod(pair, len(named)) in tree], np.int64)
        k, m = np.nonzero((cosine + bound >= threshold) & (cosine - bound < threshold) & differ)
        a, b = np.concatenate((rows[i[chosen]], rows[k])), np.concatenate((columns[j[chosen]], columns[m]))
        return pa.Table.from_arrays([pa.array(node[a]), pa.array(node[b]), pa.array(np.arange(len(a)) < len(chosen))], names=["a", "b", "sure"])

    return left.union(right).groupBy(*_RUN_KEY, "x", "y").applyInArrow(compare, _PAIRS).distinct()


def _joined(roots: DataFrame, pairs: DataFrame, classes: DataFrame, threshold: float) -> DataFrame:
    """``node, root`` after the pairs that ``roots`` leave apart: sure ones, and those whose vectors' cosine says so."""
    of_a, of_b = (roots.select(F.col("node").alias(x), F.col("root").alias(f"root_{x}")) for x in "ab")
    left = pairs.join(of_a, "a", "left").join(of_b, "b", "left").withColumns({f"root_{x}": F.coalesce(f"root_{x}", x) for x in "ab"}).where("root_a <> root_b")
    left = materialise(left.select("a", "b", "sure", "root_a", "root_b"), "vector-open")
    if left.isEmpty():
        return roots
    one, two = (classes.select(F.col("node").alias(x), F.col("embedding").alias(f"v_{x}")) for x in "ab")
    checked = left.where("not sure").join(one, "a").join(two, "b")

    def verify(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            good = [float(_unit(np.array([x])) @ _unit(np.array([y])).T) >= threshold for x, y in zip(batch.column("v_a").to_pylist(), batch.column("v_b").to_pylist(), strict=True)]
            yield batch.select(["root_a", "root_b"]).filter(pa.array(good, pa.bool_()))

    edges = left.where("sure").select("root_a", "root_b").union(checked.select("root_a", "root_b", "v_a", "v_b").mapInArrow(verify, "root_a long, root_b long"))
    above = connected_components(materialise(edges.distinct(), "vector-edges"), "root_a", "root_b").select(F.col("node").alias("low"), F.col("root").alias("high"))
    whole = roots.join(above, roots["root"] == above["low"], "full_outer").select(F.coalesce("node", "low").alias("node"), F.coalesce("high", "root").alias("root"))
    return materialise(whole, "vector-roots")


def _unit(x: np.ndarray) -> np.ndarray:
    return x / np.maximum(np.sqrt((x * x).sum(axis=1, keepdims=True)), 1e-300)


def _counts(members: DataFrame, threshold: float) -> DataFrame:
    """``node, n_links``: exact counts inside each component, the other rows of the class included."""
    sizes = materialise(members.groupBy("root").agg(F.count("*").alias("classes"), F.sum("n").alias("total")), "vector-sizes")
    centre = members.where("node = root").select("root", F.col("embedding").alias("centre"))
    alone = members.join(sizes.where("classes = 1"), "root").select("node", (F.col("n") - 1).alias("n_links"))
    # Joins by component end in tables: a large component's rows are split among tasks there, and dealt by blocks after.
    several = materialise(members.select("root", "node", "n", "embedding").join(sizes.where("classes > 1"), "root").join(centre, "root"), "vector-several")
    dot = lambda x, y: F.aggregate(F.zip_with(x, y, lambda a, b: a * b), F.lit(0.0), lambda s, v: s + v)
    cosine = dot("embedding", "centre") / F.sqrt(dot("embedding", "embedding") * dot("centre", "centre"))
    # Angles add up at most: within half the allowed angle of one vector, all pairs link.
    widest = several.groupBy("root").agg(F.max(F.acos(F.least(F.lit(1.0), F.greatest(F.lit(-1.0), cosine)))).alias("widest"))
    tight = materialise(widest.where(2 * F.col("widest") <= math.acos(threshold) - 1e-9).select("root"), "vector-tight")
    settled = several.join(tight, "root", "left_semi").select("node", (F.col("total") - 1).alias("n_links"))
    blocks = F.ceil(F.col("classes") / BLOCK).cast("int")
    loose = several.join(tight, "root", "left_anti")
    dealt = loose.select("root", "node", "n", "embedding", blocks.alias("blocks"), F.pmod(F.xxhash64("node", F.lit(3)), blocks).cast("int").alias("block"))
    # Every block meets every other: the row goes once to each pair of blocks that holds its own.
    paired = dealt.select("*", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)).alias("other"))
    paired = materialise(paired.select("root", "node", "n", "embedding", "block", F.least("block", "other").alias("low"), F.greatest("block", "other").alias("high")), "vector-paired")

    def count(table: pa.Table) -> pa.Table:
        unit, node, n, block = _unit(matrix(table.column("embedding"))), table.column("node").to_numpy(), table.column("n").to_numpy(), table.column("block").to_numpy()
        out_node, out_n = [], []
        sides = np.unique(block)
        pairs = [(s, t) for s in sides for t in sides if s != t] if len(sides) > 1 else ([(sides[0], sides[0])] if table.column("low")[0].as_py() == table.column("high")[0].as_py() else [])
        for s, t in pairs:
            rows, columns = np.flatnonzero(block == s), np.flatnonzero(block == t)
            linked = (unit[rows] @ unit[columns].T) >= threshold
            if s == t:
                np.fill_diagonal(linked, True)
            out_node.append(node[rows])
            out_n.append(linked @ n[columns] - (1 if s == t else 0))
        if not out_node:
            return pa.Table.from_arrays([pa.array([], pa.int64())] * 2, names=["node", "n_links"])
        return pa.Table.from_arrays([pa.array(np.concatenate(out_node)), pa.array(np.concatenate(out_n).astype(np.int64))], names=["node", "n_links"])

    parts = paired.groupBy("root", "low", "high").applyInArrow(count, "node long, n_links long")
    return parts.groupBy("node").agg(F.sum("n_links").alias("n_links")).union(settled).union(alone)
