"""Quality classifier: random Fourier features over document statistics, ridge, isotonic calibration.

Cosines of random projections approximate a Gaussian kernel, so kernel ridge regression becomes a
linear one: each task sums its share of the normal equations, the sums meet row by row, and only a
matrix of fixed size reaches the driver.  Folds 1 to 3 of the labelled rows fit the weights, fold 4
calibrates them to probabilities by pooled adjacent violators over fixed score bins; fold 0 is held
out from both.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..plans.storage import materialise
from . import words as W

FEATURES = 14
COSINES = 384
RIDGE = 1e-4
BINS = 400
THRESHOLD = 0.3
_CHUNK = 1 << 20

_KIND = np.zeros(256, np.int8)
_KIND[np.arange(ord("a"), ord("z") + 1)] = 1
_KIND[np.arange(ord("A"), ord("Z") + 1)] = 2
_KIND[np.arange(ord("0"), ord("9") + 1)] = 3
_KIND[[ord(x) for x in ".,;:'\"()-"]] = 4
_KIND[[ord(x) for x in "!?"]] = 5
_KIND[[ord(x) for x in "#$%&*+/<=>@[\\]^_`{|}~"]] = 6
_KIND[0x80:] = 7
_KIND[[0x0A, 0x0D]] = 8


def statistics(texts: pa.Array) -> np.ndarray:
    """A row of statistics for each text; zeros for a text without words."""
    w = W.split(texts)
    n, first, counts = len(texts), w.first, w.counts
    doc = np.repeat(np.arange(n), counts)
    sizes = (w.ends - w.begins).astype(np.float64)
    texts = texts.fill_null("") if texts.null_count else texts
    large = texts.cast(pa.large_string())
    bounds = np.frombuffer(large.buffers()[1], np.int64)[large.offset : large.offset + n + 1]
    bounds = bounds - bounds[0]
    kinds = _KIND[w.data]
    at = np.concatenate((np.zeros((9, 1), np.int64), np.stack([np.cumsum(kinds == k) for k in range(9)])), axis=1)
    per = (at[:, bounds[1:]] - at[:, bounds[:-1]]).astype(np.float64)
    length = np.maximum(np.diff(bounds), 1).astype(np.float64)
    letters = np.maximum(per[1] + per[2], 1)
    own = np.maximum(counts, 1).astype(np.float64)
    sum_of = lambda x: np.bincount(doc, weights=x, minlength=n)
    hashed = W.hashes(w)
    repeat = np.zeros(len(hashed), bool)
    repeat[1:] = (hashed[1:] == hashed[:-1]) & (doc[1:] == doc[:-1])
    order = np.lexsort((hashed, doc))
    new = np.ones(len(order), bool)
    new[1:] = (hashed[order][1:] != hashed[order][:-1]) | (doc[order][1:] != doc[order][:-1])
    runs = np.flatnonzero(new)
    run_sizes = np.diff(np.append(runs, len(order))).astype(np.float64)
    most = np.zeros(n)
    np.maximum.at(most, doc[order][runs], run_sizes)
    three = W.window_hashes(hashed, 3)
    inside = np.flatnonzero(doc[: len(three)] == doc[2:]) if len(three) else np.zeros(0, np.int64)
    three, doc3 = three[inside], doc[inside]
    order3 = np.lexsort((three, doc3))
    new3 = np.ones(len(order3), bool)
    new3[1:] = (three[order3][1:] != three[order3][:-1]) | (doc3[order3][1:] != doc3[order3][:-1])
    distinct3 = np.bincount(doc3[order3][new3], minlength=n)
    symbol = np.concatenate(([0], np.cumsum((kinds == 6) | (kinds == 5))))
    marked = (symbol[w.ends] - symbol[w.begins]) > 0
    mean = sum_of(sizes) / own
    out = np.stack(
        [
            np.log1p(counts), mean, np.sqrt(np.maximum(sum_of(sizes**2) / own - mean**2, 0)), per[2] / letters, per[3] / length, per[4] / length, per[5] / length, per[6] / length,
            per[8] / own, sum_of(marked.astype(float)) / own, sum_of(repeat.astype(float)) / own, np.bincount(doc[order][new], minlength=n) / own, most / own,
            distinct3 / np.maximum(counts - 2, 1),
        ],
        axis=1,
    )
    out[counts == 0] = 0
    return out


def _projections(features: int, cosines: int, seed: int = 5) -> tuple[np.ndarray, np.ndarray]:
    draw = np.random.default_rng(seed)
    return draw.normal(0, 1 / np.sqrt(features), (features, cosines)), draw.uniform(0, 2 * np.pi, cosines)


def fourier(stats: np.ndarray, mean: np.ndarray, spread: np.ndarray, cosines: int) -> np.ndarray:
    """Random Fourier features of standardised statistics, and a constant."""
    weights, phases = _projections(stats.shape[1], cosines)
    scaled = np.clip((stats - mean) / spread, -6, 6)
    return np.concatenate((np.sqrt(2 / cosines) * np.cos(scaled @ weights + phases), np.ones((len(stats), 1))), axis=1)


def fold(key: Column) -> Column:
    """Remainder modulo 5 of the key's CRC-32 as text; null for a null key."""
    return F.crc32(key.cast("string").cast("binary")) % 5


def with_statistics(docs: DataFrame) -> DataFrame:
    """``doc_id, stats`` for every row."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids, texts = batch.column("doc_id"), batch.column("text")
            for a, b in W.documents(texts, _CHUNK):
                found = statistics(texts.slice(a, b - a))
                yield pa.RecordBatch.from_arrays([ids.slice(a, b - a), pa.array(found.tolist(), pa.list_(pa.float64()))], names=["doc_id", "stats"])

    return docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).mapInArrow(run, "doc_id long, stats array<double>")


def _matrix(column: pa.Array) -> np.ndarray:
    return column.flatten().to_numpy(zero_copy_only=False).reshape(len(column), -1)


class Model:
    """Fitted weights and calibration; small and of fixed size."""

    def __init__(self, mean: np.ndarray, spread: np.ndarray, weights: np.ndarray) -> None:
        self.mean, self.spread, self.weights = mean, spread, weights
        self.knots, self.values = np.array([0.0, 1.0]), np.array([0.0, 1.0])

    def raw(self, stats: np.ndarray) -> np.ndarray:
        return fourier(stats, self.mean, self.spread, len(self.weights) - 1) @ self.weights

    def score(self, stats: np.ndarray) -> np.ndarray:
        return np.clip(np.interp(self.raw(stats), self.knots, self.values), 0.0, 1.0)


def isotonic(x: np.ndarray, y: np.ndarray, n: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Pooled adjacent violators: block centres in x and their non-decreasing means."""
    blocks: list[list[float]] = []
    for a, b, c in zip(x.tolist(), y.tolist(), n.tolist(), strict=True):
        blocks.append([a * c, b, c])
        while len(blocks) > 1 and blocks[-2][1] / blocks[-2][2] >= blocks[-1][1] / blocks[-1][2]:
            last = blocks.pop()
            blocks[-1] = [p + q for p, q in zip(blocks[-1], last, strict=True)]
    return np.array([b[0] / b[2] for b in blocks]), np.array([b[1] / b[2] for b in blocks])


def fit(stats: DataFrame, labels: DataFrame, cosines: int = COSINES, ridge: float = RIDGE) -> Model:
    """Fit on all labelled rows outside fold 0; ``stats`` has doc_id and stats, ``labels`` doc_id and quality."""
    known = labels.where("quality is not null and doc_id is not null").select(F.col("doc_id").alias("__id"), F.col("quality").cast("double").alias("y"))
    rows = stats.join(known, stats["doc_id"] == known["__id"]).select(fold(F.col("doc_id")).alias("fold"), "stats", "y").where("fold <> 0")
    rows = materialise(rows, "quality-labelled")
    moments = [m for i in range(FEATURES) for m in (F.avg(F.col("stats")[i]), F.stddev_pop(F.col("stats")[i]))]
    found = rows.where("fold < 4").agg(F.count("*"), *moments).first()
    if not found[0]:
        return Model(np.zeros(FEATURES), np.ones(FEATURES), np.append(np.zeros(cosines), 1.0))
    mean, spread = np.array(found[1::2], float), np.maximum(np.array(found[2::2], float), 1e-6)

    def sums(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros((cosines + 1, cosines + 2))
        for batch in batches:
            if batch.num_rows:
                z = fourier(_matrix(batch.column("stats")), mean, spread, cosines)
                total += z.T @ np.column_stack((z, batch.column("y").to_numpy()))
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(cosines + 1, dtype=np.int32)), pa.array([r.tobytes() for r in total], pa.binary())], names=["row", "part"])

    def add(table: pa.Table) -> pa.Table:
        whole = np.sum([np.frombuffer(x.as_py()) for x in table.column("part")], axis=0)
        return pa.Table.from_arrays([table.column("row").combine_chunks().slice(0, 1), pa.array([whole.tobytes()], pa.binary())], names=["row", "part"])

    parts = rows.where("fold < 4").mapInArrow(sums, "row int, part binary").groupBy("row").applyInArrow(add, "row int, part binary")
    system = np.stack([np.frombuffer(r["part"]) for r in sorted(parts.collect(), key=lambda r: r["row"])])
    n = system[-1, -2]
    weights = np.linalg.solve(system[:, :-1] + ridge * n * np.eye(cosines + 1), system[:, -1])
    model = Model(mean, spread, weights)

    def binned(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows:
                at = np.clip(np.floor((model.raw(_matrix(batch.column("stats"))) + 0.5) / 2 * BINS), 0, BINS - 1).astype(np.int32)
                yield pa.RecordBatch.from_arrays([pa.array(at), batch.column("y")], names=["bin", "y"])

    table = rows.where("fold = 4").mapInArrow(binned, "bin int, y double").groupBy("bin").agg(F.sum("y").alias("y"), F.count("*").alias("n")).orderBy("bin").collect()
    if table:
        x = (np.array([r["bin"] for r in table]) + 0.5) / BINS * 2 - 0.5
        model.knots, model.values = isotonic(x, np.array([r["y"] for r in table], float), np.array([r["n"] for r in table], float))
    return model


def score_documents(docs: DataFrame, labels: DataFrame, threshold: float = THRESHOLD) -> DataFrame:
    """``doc_id, held_out, score, predicted`` for every row of ``docs``.

    Statistics come from whole texts alone.  Without labelled rows every score is 1.  A null or
    empty text has zero statistics and is scored like any other; a null doc_id is in no fold, so it
    is not held out; repeated rows are scored each; an empty table gives an empty result.
    """
    stats = materialise(with_statistics(docs), "quality-stats")
    model = fit(stats, labels)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows:
                found = model.score(_matrix(batch.column("stats")))
                yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(found)], names=["doc_id", "score"])

    scored = stats.mapInArrow(run, "doc_id long, score double")
    return scored.select("doc_id", F.coalesce(fold(F.col("doc_id")) == 0, F.lit(False)).alias("held_out"), "score", (F.col("score") >= threshold).cast("int").alias("predicted"))


def keep_good(docs: DataFrame, labels: DataFrame, threshold: float = THRESHOLD) -> DataFrame:
    """Rows of ``docs`` that the classifier does not reject, with all their columns.

    The fitted model is small, so rows are scored and filtered where they are read.
    """
    model = fit(materialise(with_statistics(docs), "quality-stats"), labels)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = batch.column("text")
            for a, b in W.documents(texts, _CHUNK):
                good = model.score(statistics(texts.slice(a, b - a))) >= threshold
                yield batch.slice(a, b - a).filter(pa.array(good))

    return docs.mapInArrow(run, docs.schema)
